"""A memo of what each distinct word maps to, bounded, for work that repeats by word."""

from __future__ import annotations


class WordMemo(dict):
    """word -> value; `fill(words)` computes many at once. Emptied when it holds `most` words,
    so its memory is bounded; that changes time, never results."""

    def __init__(self, fill, most: int = 400_000):
        super().__init__()
        self._fill, self._most = fill, most

    def learn(self, words) -> None:
        new = [w for w in words if w not in self]
        if len(self) + len(new) > self._most:
            self.clear()
            new = list(words)
        if new:
            self.update(zip(new, self._fill(new), strict=True))


class LazyMemo(dict):
    """word -> value, computed where it is missing; bounded in the same way."""

    def __init__(self, of, most: int = 800_000):
        super().__init__()
        self._of, self._most = of, most

    def __missing__(self, word):
        if len(self) >= self._most:
            self.clear()
        value = self[word] = self._of(word)
        return value
