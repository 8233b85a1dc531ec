"""SentencePiece encoding, decoding and token counts.

Texts are normalised and cut where no piece can span (before runs of the space mark), and each
distinct unit of a batch is segmented once:

* encoding indexes the concatenated units in a suffix array (sorted to the longest piece's
  length), narrows every piece to its range of suffixes by binary search, sorts the edges by
  position and relaxes them: by score for unigram models, by merge rank for BPE models, where
  a best path over scores would not give the model's ids;
* counting walks an Aho-Corasick automaton of the pieces and carries only the best score and its
  piece count, by the unigram rules: of equal scores the earliest start of the last piece wins,
  a character without a piece of its own costs the least score less ten and counts its bytes.

Scores add exactly (the usual implementation rounds to 32 bits, so texts whose scores pass 2**24
may break ties differently there).

Defined results: null and empty texts have no ids; repeated rows are alike; an empty table
gives an empty result; very long units are segmented whole; extra columns are ignored, or kept where named.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import WordMemo

MARK, END = "▁", 0x110000
UNITS = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
CHUNK, SHORT = 400_000, 48


def fields(data: bytes) -> Iterator[tuple[int, int, int, int]]:
    """(number, wire type, begin, end) of a message's fields."""

    def varint(at: int) -> tuple[int, int]:
        n = shift = 0
        while True:
            b = data[at]
            n, shift, at = n | (b & 127) << shift, shift + 7, at + 1
            if b < 128:
                return n, at

    at = 0
    while at < len(data):
        key, at = varint(at)
        begin = at
        if key & 7 == 2:
            size, begin = varint(at)
            at = begin + size
        elif key & 7 == 0:
            _, at = varint(at)
        else:
            at += 8 if key & 7 == 1 else 4
        yield key >> 3, key & 7, begin, at


def is_bpe(data: bytes) -> bool:
    for number, _, a, b in fields(data):
        if number == 2:
            spec = data[a:b]
            return any(n == 3 and spec[x] == 2 for n, _, x, _ in fields(spec))
    return False


class Vocabulary:
    """Pieces, scores and rules of a model file."""

    def __init__(self, path: str):
        from sentencepiece import SentencePieceProcessor

        with open(path, "rb") as f:
            data = f.read()
        m = self.model = SentencePieceProcessor(model_proto=data)
        n = m.vocab_size()
        self.bpe = is_bpe(data)
        self.piece = [m.id_to_piece(i) for i in range(n)]
        special = [m.is_control(i) or m.is_unknown(i) or m.is_byte(i) for i in range(n)]
        self.score = np.array([m.get_score(i) for i in range(n)], float)
        self.normal = [i for i in range(n) if not special[i] and not m.is_unused(i)]
        self.byte = {int(self.piece[i][3:5], 16): i for i in range(n) if m.is_byte(i)}
        self.unknown = m.unk_id()
        self.unknown_score = min((self.score[i] for i in self.normal), default=0.0) - 10
        self.longest = max((len(self.piece[i]) for i in self.normal), default=1)
        self.cut = not any(MARK in self.piece[i].lstrip(MARK) for i in self.normal)
        self.plain = m.normalize(" a  ﬁ\né ") == f"{MARK}{MARK}a{MARK}{MARK}ﬁ\né{MARK}"
        self.dtype = np.dtype("<u2" if n <= 65536 else "<u4")
        self.bytes_of = [b"" if m.is_control(i) else bytes([int(self.piece[i][3:5], 16)]) if m.is_byte(i) else " ⁇ ".encode() if m.is_unknown(i) else self.piece[i].replace(MARK, " ").encode() for i in range(n)]

    def units(self, text: str) -> list[str]:
        if not text:
            return []
        t = MARK + text.replace(" ", MARK) if self.plain else self.model.normalize(text)
        return UNITS.findall(t) if self.cut else [t]

    def spell(self, char: str) -> list[int]:
        """Ids of a character without a piece."""
        return [self.byte[b] for b in char.encode("utf-8", "replace")] if self.byte else [self.unknown]

    def decode(self, ids) -> str:
        out = b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")
        return out[1:] if out[:1] == " " else out


class PieceTree:
    """The pieces' prefixes by depth: parents, characters, and which piece ends there."""

    def __init__(self, v: Vocabulary):
        node: dict[str, int] = {"": 0}
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        ends = {v.piece[i]: i for i in reversed(v.normal)}
        for depth in range(1, v.longest + 1):
            new = sorted({p[:depth] for p in ends if len(p) >= depth})
            place = {p: k for k, p in enumerate(new)}
            self.levels.append((np.array([node[p[:-1]] for p in new]), np.array([ord(p[-1]) for p in new], np.int64), np.array([ends.get(p, -1) for p in new])))
            node = place


def suffixes(codes: np.ndarray, depth: int) -> np.ndarray:
    """Places in order of the text that begins there, compared over depth characters at least:
    as many characters as fit in one word first, then twice as many each time."""
    n = len(codes)
    seen = np.zeros(int(codes.max(initial=0)) + 1, bool)
    seen[codes] = True
    rank = (np.cumsum(seen))[codes].astype(np.int64)  # from 1; 0 is past the end
    bits = int(rank.max(initial=1)).bit_length()
    k = max(1, min(depth, 63 // bits))
    key = np.zeros(n, np.int64)
    for d in range(min(k, n)):
        key[: n - d] |= rank[d:] << (bits * (k - 1 - d))
    while True:
        order = np.argsort(key, kind="stable")
        if k >= depth or k >= n:
            return order
        step = np.empty(n, np.int64)
        step[0], step[1:] = 0, np.diff(key[order]) != 0
        rank[order] = np.cumsum(step)
        after = np.zeros(n, np.int64)
        after[: n - k] = rank[k:] + 1
        key = rank * (n + 2) + after
        k *= 2


def occurrences(tree: PieceTree, codes: np.ndarray, depth: int) -> np.ndarray:
    """Table (place, length) -> piece id or -1: all edges, by position."""
    n = len(codes)
    order = suffixes(codes, depth)
    padded = np.concatenate([codes, np.full(depth + 1, -1)])
    lo, hi = np.array([0]), np.array([n])
    table = np.full((n, depth + 1), -1, np.int32)
    at_all, len_all, id_all = [], [], []
    for d, (parent, char, ends) in enumerate(tree.levels):
        a, b = lo[parent], hi[parent]
        bounds = []
        for right in (False, True):
            x, y = a.copy(), b.copy()
            live = np.nonzero(x < y)[0]
            while len(live):
                mid = (x[live] + y[live]) // 2
                got = padded[order[mid] + d]
                up = got <= char[live] if right else got < char[live]
                x[live] = np.where(up, mid + 1, x[live])
                y[live] = np.where(up, y[live], mid)
                live = live[x[live] < y[live]]
            bounds.append(x)
        lo, hi = bounds
        own = np.nonzero((ends >= 0) & (lo < hi))[0]
        if len(own):
            size = hi[own] - lo[own]
            start = np.repeat(lo[own], size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            at_all.append(order[start]), len_all.append(np.full(size.sum(), d + 1)), id_all.append(np.repeat(ends[own], size))
    if at_all:
        at, length, ids = map(np.concatenate, (at_all, len_all, id_all))
        by = np.argsort(at, kind="stable")
        table[at[by], length[by]] = ids[by]
    return table


def relax_scores(v: Vocabulary, table: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best paths over all units at once: where tokens begin and end, by place."""
    score = np.append(v.score, -np.inf)
    best = np.full(len(table) + 1, -np.inf)
    back = np.zeros(len(table) + 1, np.int64)
    # Units lie apart by one separator, whose place takes the value at the unit's end.
    best[start] = 0
    for t in range(1, int(size.max(initial=0)) + 1):
        p = start[size >= t] + t
        top, take = np.full(len(p), -np.inf), np.zeros(len(p), np.int64)
        for length in range(min(t, v.longest), 0, -1):
            ids = table[p - length, length]
            c = best[p - length] + (np.where(ids < 0, v.unknown_score, score[ids]) if length == 1 else score[ids])
            win = c > top
            top, take = np.where(win, c, top), np.where(win, length, take)
        best[p], back[p] = top, take
    ends, begins, p, low = [], [], start + size, start
    while len(p):
        live = p > low
        p, low = p[live], low[live]
        ends.append(p)
        p = p - back[p]
        begins.append(p)
    begin, end = np.concatenate(begins), np.concatenate(ends)
    order = np.argsort(begin, kind="stable")
    return begin[order], end[order]


def merge_one(v: Vocabulary, table: np.ndarray, s: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """BPE of one long unit: best score first, leftmost of equals."""
    nxt, prv, size = list(range(1, n + 1)), list(range(-1, n - 1)), [1] * n
    score, deep = v.score, table.shape[1]

    def pair(i: int):
        j = nxt[i]
        if j < n and size[i] + size[j] < deep and (k := table[s + i, size[i] + size[j]]) >= 0:
            return -score[k], i, size[i] + size[j]
        return None

    heap = [x for i in range(n) if (x := pair(i))]
    heapify(heap)
    while heap:
        _, i, total = heappop(heap)
        j = nxt[i] if size[i] else n
        if j >= n or size[i] + size[j] != total:
            continue
        size[i], size[j], nxt[i] = total, 0, nxt[j]
        if nxt[i] < n:
            prv[nxt[i]] = i
        for k in (i, prv[i]):
            if k >= 0 and (x := pair(k)):
                heappush(heap, x)
    begin = np.nonzero(size)[0] + s
    return begin, begin + np.array(size)[begin - s]


def merge_ranks(v: Vocabulary, table: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """BPE of all short units at once, a merge for each unit in each round; long units one by one."""
    done = [merge_one(v, table, int(start[u]), int(size[u])) for u in np.nonzero(size > SHORT)[0]]
    short = np.nonzero(size <= SHORT)[0]
    n = size[short]
    unit = np.repeat(np.arange(len(short)), n)
    begin = np.repeat(start[short], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    end, score, deep = begin + 1, np.append(v.score, -np.inf), table.shape[1]
    while len(unit):
        width = np.zeros(len(unit), np.int64)
        width[:-1] = np.where(unit[1:] == unit[:-1], end[1:] - begin[:-1], 0)
        s = score[table[begin, np.where(width < deep, width, 0)]]  # no piece has length 0
        first = np.nonzero(np.concatenate([[True], unit[1:] != unit[:-1]]))[0]
        top = np.repeat(np.maximum.reduceat(s, first), np.diff(np.append(first, len(unit))))
        live = top > -np.inf
        if not live.all():
            done.append((begin[~live], end[~live]))
        pick = np.minimum.reduceat(np.where((s == top) & live, np.arange(len(unit)), len(unit)), first)
        pick = pick[pick < len(unit)]
        end[pick] = end[pick + 1]
        live[pick + 1] = False
        unit, begin, end = unit[live], begin[live], end[live]
    begin, end = (np.concatenate(x) for x in zip(*done, strict=True)) if done else (np.zeros(0, np.int64),) * 2
    order = np.argsort(begin, kind="stable")
    return begin[order], end[order]


class Encoder:
    """Ids of texts, by units that are segmented once."""

    def __init__(self, path: str, algorithm: str | None = None):
        self.v = Vocabulary(path)
        self.tree = PieceTree(self.v)
        self.relax = merge_ranks if (algorithm or ("bpe" if self.v.bpe else "unigram")) == "bpe" else relax_scores
        self.memo = WordMemo(self._fill, 500_000)

    def _fill(self, units: list[str]) -> list[bytes]:
        out, k = [], 0
        while k < len(units):
            held, j = 0, k
            while j < len(units) and (held == 0 or held + len(units[j]) < CHUNK):
                held, j = held + len(units[j]) + 1, j + 1
            out += self._segment(units[k:j])
            k = j
        return out

    def _segment(self, units: list[str]) -> list[bytes]:
        size = np.array([len(u) for u in units])
        start = np.cumsum(size + 1) - size - 1
        codes = np.full(int(size.sum()) + len(units), END, np.int64)
        inside = np.ones(len(codes), bool)
        inside[start + size] = False
        codes[inside] = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), "<u4")
        table = occurrences(self.tree, codes, self.v.longest)
        begin, end = self.relax(self.v, table, start, size)
        ids = table[begin, end - begin]
        first, wide = np.append(np.searchsorted(begin, start), len(begin)), self.v.dtype.itemsize
        data, cuts = ids.astype(self.v.dtype).tobytes(), (first * wide).tolist()
        out = [data[a:b] for a, b in zip(cuts, cuts[1:])]
        for k in np.unique(np.searchsorted(start, begin[ids < 0], side="right") - 1).tolist():  # with characters to spell
            own = [x for i, p in zip(ids[first[k] : first[k + 1]].tolist(), begin[first[k] : first[k + 1]].tolist()) for x in ([i] if i >= 0 else self.v.spell(units[k][p - start[k]]))]
            out[k] = np.array(own, self.v.dtype).tobytes()
        return out

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        out = []
        for k in range(0, len(texts), 200):  # as many units as these texts have lie in memory at once
            part = [self.v.units(t) for t in texts[k : k + 200]]
            self.memo.learn(dict.fromkeys(x for u in part for x in u))
            out += [np.frombuffer(b"".join(map(self.memo.__getitem__, u)), self.v.dtype) for u in part]
        return out


@lru_cache(maxsize=2)
def encoder(path: str, algorithm: str | None) -> Encoder:
    """A worker process keeps its encoder, and the units that it knows, from task to task."""
    return Encoder(path, algorithm)


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text: str = "text", algorithm: str | None = None) -> DataFrame:
    """(doc_id, text, ids array<int>, n_tokens, ids_crc32 of little-endian unsigned 32-bit ids)"""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(model_path, algorithm)
        for b in batches:
            for k in range(0, b.num_rows, 1000):
                r = b.slice(k, 1000)
                ids = [x.astype("<u4") for x in enc.encode([t or "" for t in r.column(1).to_pylist()])]
                n = np.array([len(x) for x in ids], np.int64)
                flat = np.concatenate(ids).astype(np.int32) if ids else np.zeros(0, np.int32)
                arr = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]), pa.int32()), pa.array(flat))
                yield pa.RecordBatch.from_arrays([r.column(0), r.column(1), arr, pa.array(n), pa.array([zlib.crc32(x.tobytes()) for x in ids], pa.int64())], ["doc", "text", "ids", "n_tokens", "ids_crc32"])

    d = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text).alias("text"))
    out = d.mapInArrow(run, "doc long, text string, ids array<int>, n_tokens long, ids_crc32 long")
    return out.withColumnsRenamed({"doc": id_col, "text": text} if text != "text" else {"doc": id_col})


def decode(coded: DataFrame, model_path: str, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """coded with the texts of its ids."""
    names = coded.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = Vocabulary(model_path)
        for b in batches:
            col = b.column(names.index(ids))
            texts = [None if x is None else v.decode(x) for x in (y.values.to_numpy(zero_copy_only=False).tolist() if y.is_valid else None for y in col)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(texts, pa.string())], [*names, out])

    return coded.mapInArrow(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in coded.schema) + f", `{out}` string")


class Counter:
    """Best score and piece count of units, by an automaton of the pieces."""

    def __init__(self, path: str):
        import ahocorasick

        self.v = Vocabulary(path)
        self.machine = ahocorasick.Automaton()
        for i in reversed(self.v.normal):
            self.machine.add_word(self.v.piece[i], (len(self.v.piece[i]), float(self.v.score[i])))
        self.machine.make_automaton()
        self.memo = WordMemo(lambda us: [self.count(u) for u in us], 300_000)

    def count(self, unit: str) -> tuple[int, float]:
        n, unknown = len(unit), float(self.v.unknown_score)
        best, count, at, single = [0.0] + [-np.inf] * n, [0] * (n + 1), 0, False

        def close(t: int) -> None:
            """The character before t has no piece of its own."""
            if best[t - 1] + unknown > best[t]:
                best[t] = best[t - 1] + unknown
                count[t] = count[t - 1] + (len(unit[t - 1].encode("utf-8", "replace")) if self.v.byte else 1)

        for end, (size, score) in self.machine.iter(unit):  # by end, the longest first
            t = end + 1
            if t != at:
                if at and not single:
                    close(at)
                for k in range(at + 1, t):
                    close(k)
                at, single = t, False
            s = best[t - size] + score
            if s > best[t]:
                best[t], count[t] = s, count[t - size] + 1
            single |= size == 1
        if at and not single:
            close(at)
        for k in range(at + 1, n + 1):
            close(k)
        return count[n], best[n]


def token_counts(docs: DataFrame, model_path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_tokens, score) under the vocabulary's unigram rules."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = Counter(model_path)
        get = c.memo.__getitem__
        for b in batches:
            for k in range(0, b.num_rows, 200):
                r = b.slice(k, 200)
                units = [c.v.units(t or "") for t in r.column(1).to_pylist()]
                c.memo.learn(dict.fromkeys(x for u in units for x in u))
                got = [list(map(get, u)) for u in units]
                yield pa.RecordBatch.from_arrays([r.column(0), pa.array([sum(x[0] for x in g) for g in got], pa.int64()), pa.array([float(sum(x[1] for x in g)) for g in got])], ["doc", "n_tokens", "score"])

    d = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text).alias("text"))
    return d.mapInArrow(run, "doc long, n_tokens long, score double").withColumnRenamed("doc", id_col)
