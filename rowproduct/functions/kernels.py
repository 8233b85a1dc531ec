"""Row accumulators as such, for one block of rows in a task: they count what they do.

Scale belongs to the declarative lowerings, whose aggregates are the engine's own hash and sort
accumulators; these show the methods themselves, with their probes, memory and phases.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from heapq import heapify, heappop, heapreplace

import numpy as np

#: Odd multiplier that spreads ids over a table.
SPREAD = 0x9E3779B1


def table_capacity(max_work: int, ncols: int) -> int:
    """The least power of two above what a row can hold, so that one slot stays free."""
    return 1 << int(min(max_work, ncols)).bit_length()


def slot(col: int, capacity: int, spread: int = SPREAD) -> int:
    return (col * spread) & (capacity - 1)


@dataclass
class Tally:
    """ops: finds or inserts; probes: slots or chunks looked at; peak: the accumulator's entries."""

    ops: int = 0
    probes: int = 0
    peak: int = 0


class HashTable:
    """Open addressing, linear steps; the table serves all rows of a block and only touched slots are cleared."""

    def __init__(self, capacity: int):
        self.mask, self.keys, self.vals, self.used = capacity - 1, [-1] * capacity, [0] * capacity, []
        self.tally = Tally(peak=capacity)

    def find(self, col: int) -> int:
        keys, mask, t = self.keys, self.mask, self.tally
        p = (col * SPREAD) & mask
        t.ops += 1
        t.probes += 1
        while keys[p] != col:
            if keys[p] < 0:
                keys[p] = col
                self.used.append(p)
                break
            p = (p + 1) & mask
            t.probes += 1
        return p

    def add(self, col: int, val) -> None:
        self.vals[self.find(col)] += val

    def take(self) -> list[tuple]:
        out = [(self.keys[p], self.vals[p]) for p in self.used]
        for p in self.used:
            self.keys[p], self.vals[p] = -1, 0
        self.used = []
        return out


def bits(equal: np.ndarray) -> int:
    """The mask of a comparison of all lanes: bit k for lane k."""
    return int.from_bytes(np.packbits(equal, bitorder="little").tobytes(), "little")


def first_lane(mask: int) -> int:
    """Trailing zeros of a mask."""
    return (mask & -mask).bit_length() - 1


class ChunkTable:
    """Chunks of `lanes` keys, compared with a key as a whole: the mask's lowest bit is its lane. A new key takes the first
    lane that equals the empty key, and a full chunk sends on to the next."""

    EMPTY = -1

    def __init__(self, capacity: int, lanes: int):
        n = 1 << max(0, (max(1, capacity // lanes) - 1).bit_length())
        self.mask, self.keys, self.vals, self.used = n - 1, np.full((n, lanes), self.EMPTY, np.int64), [[0] * lanes for _ in range(n)], []
        self.tally = Tally(peak=n * lanes)

    def find(self, col: int) -> tuple[int, int]:
        t = self.tally
        p = (col * SPREAD) & self.mask
        t.ops += 1
        while True:
            t.probes += 1
            hit = bits(self.keys[p] == col)
            if hit:
                return p, first_lane(hit)
            free = bits(self.keys[p] == self.EMPTY)
            if free:
                lane = first_lane(free)
                self.keys[p, lane] = col
                self.used.append((p, lane))
                return p, lane
            p = (p + 1) & self.mask

    def add(self, col: int, val) -> None:
        p, lane = self.find(col)
        self.vals[p][lane] += val

    def take(self) -> list[tuple]:
        out = [(int(self.keys[p, lane]), self.vals[p][lane]) for p, lane in self.used]
        for p, lane in self.used:
            self.keys[p, lane], self.vals[p][lane] = self.EMPTY, 0
        self.used = []
        return out


class PooledTable:
    """Chained buckets over a fixed pool. When a new column finds it full, `add` hands out all entries as partial sums and the pool
    starts anew, so that it never holds more than `pool`; whoever takes them adds them up."""

    def __init__(self, pool: int):
        self.pool, self.heads, self.held = pool, {}, 0
        self.tally = Tally(peak=0)

    def add(self, col: int, val) -> list[tuple]:
        t, b = self.tally, (col * SPREAD) & 255
        t.ops += 1
        out: list[tuple] = []
        for e in self.heads.get(b, ()):
            t.probes += 1
            if e[0] == col:
                e[1] += val
                return out
        t.probes += 1
        if self.held >= self.pool:
            out = self.take()
        self.heads.setdefault(b, []).append([col, val])
        self.held += 1
        t.peak = max(t.peak, self.held)
        return out

    def take(self) -> list[tuple]:
        out = [tuple(e) for c in self.heads.values() for e in c]
        self.heads, self.held = {}, 0
        return out


def heap_row(parts: list[tuple[list, list, object]], tally: Tally) -> list[tuple]:
    """Merge of sorted rows through a heap of one cursor each; columns come out rising."""
    heap = [(cols[0], n, 0) for n, (cols, _, _) in enumerate(parts) if cols]
    heapify(heap)
    tally.peak = max(tally.peak, len(heap))
    out: list[list] = []
    while heap:
        col, n, at = heap[0]
        cols, vals, scale = parts[n]
        tally.ops += 1
        tally.probes += max(1, len(heap).bit_length())
        if out and out[-1][0] == col:
            out[-1][1] += scale * vals[at]
        else:
            out.append([col, scale * vals[at]])
        if at + 1 < len(cols):
            heapreplace(heap, (cols[at + 1], n, at + 1))
        else:
            heappop(heap)
    return [tuple(x) for x in out]


def dense_row(parts: list[tuple[list, list, object]], place: dict, acc: np.ndarray, tally: Tally) -> list[tuple]:
    """A value for every column of the block, a list of touched ones."""
    touched: dict[int, int] = {}
    for cols, vals, scale in parts:
        for c, v in zip(cols, vals, strict=True):
            p = place[c]
            touched.setdefault(c, p)
            acc[p] += scale * v
            tally.ops += 1
            tally.probes += 1
    out = [(c, acc[p].item()) for c, p in touched.items()]
    acc[list(touched.values())] = 0
    return out


def multiply_block(a: Iterable[tuple], b: dict, ncols: int, accumulator: str = "hash", lanes: int = 8, phases: int = 2, order: str = "unsorted", pool: int = 1024) -> tuple[Iterator[tuple], Tally]:
    """a: rows (i, [(k, value)]); b: k -> (columns, values), rising if the heap is to merge them.
    Gives (i, [(column, value)]) row by row, and the tally that fills meanwhile. The pooled table gives a row in parts, whose
    values the caller adds up."""
    a = list(a)
    work = {i: sum(len(b[k][0]) for k, _ in row if k in b) for i, row in a}
    cap = table_capacity(max(work.values(), default=0), ncols)
    table = {"hash": lambda: HashTable(cap), "chunk": lambda: ChunkTable(cap, lanes), "pooled": lambda: PooledTable(pool)}.get(accumulator, lambda: None)()
    tally = table.tally if table else Tally()
    place, acc = {}, None
    if accumulator == "dense":
        every = sorted({c for cols, _ in b.values() for c in cols})
        place = {c: n for n, c in enumerate(every)}
        acc = np.zeros(len(every), np.float64 if any(isinstance(v, float) for _, vals in b.values() for v in vals[:1]) else np.int64)
        tally.peak = len(every)

    def rows() -> Iterator[tuple]:
        for i, row in a:
            parts = [(*b[k], v) for k, v in row if k in b]
            expected = None
            if table is not None and phases == 2 and accumulator != "pooled":
                for cols, _, _ in parts:  # symbolic: sizes only
                    for c in cols:
                        table.find(c)
                expected = len(table.take())
            if accumulator == "heap":
                out = heap_row(parts, tally)
            elif accumulator == "dense":
                out = dense_row(parts, place, acc, tally)
            else:
                for cols, vals, v in parts:
                    for c, w in zip(cols, vals, strict=True):
                        part = table.add(c, v * w)
                        if part:
                            yield i, part
                out = table.take()
            if expected is not None and expected != len(out):
                raise AssertionError("symbolic and numeric sizes differ")
            if order == "sorted" and accumulator != "heap":
                out.sort()
            yield i, out

    return rows(), tally
