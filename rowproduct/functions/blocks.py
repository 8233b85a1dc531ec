"""Blocks of a product in NumPy: rows of A as entry arrays, the rows of B that they need beside them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Products that are laid out at once, and places that may be marked for each of them before sorting is cheaper.
LAID_OUT, MARKS = 1 << 20, 16
#: A column of two blocks whose products are more than this share of the places goes into dense arrays, so many columns at once.
DENSE, WIDE = 1 / 128, 512
#: What a squeezed block holds as steps from the one before.
STEPS = ("ids", "cols")


def _slices(i: np.ndarray, count: np.ndarray) -> Iterator[tuple[np.ndarray, int, int]]:
    """(first entries of the rows, lo, hi): runs of whole rows that hold LAID_OUT products, one row at least."""
    first = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
    ends = np.r_[first[1:], len(i)]
    done = np.r_[0, np.cumsum(count)]
    lo = 0
    while lo < len(first):
        hi = max(lo + 1, int(np.searchsorted(done[ends], done[first[lo]] + LAID_OUT, "right")))
        yield first[lo:hi], int(first[lo]), int(ends[hi - 1])
        lo = hi


def row_sizes(i: np.ndarray, k: np.ndarray, inner: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the product that have any entry, and how many each has, from places (i, k) of A and (inner, j) of B."""
    order = np.argsort(inner)
    held, start, length = np.unique(inner[order], return_index=True, return_counts=True)
    wide, col = np.unique(j, return_inverse=True)
    col, n = col[order], len(wide)
    order = np.argsort(i, kind="stable")
    i, k = i[order], k[order]
    at = np.minimum(np.searchsorted(held, k), max(0, len(held) - 1))
    meets = held[at] == k if len(held) else np.zeros(len(k), bool)
    i, at = i[meets], at[meets]
    if not len(i):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    start, length = start[at], length[at]
    rows, sizes = _distinct(i, start, length, col, n)
    return i[rows], sizes


def _distinct(i: np.ndarray, start: np.ndarray, length: np.ndarray, col: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(first entries of the rows, distinct columns of each): entries by rising row i, each meeting length columns of n, in col from start on."""
    rows, sizes = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
    for first, lo, hi in _slices(i, length) if len(i) else ():
        local = np.repeat(np.arange(len(first)), np.diff(np.r_[first, hi]))
        total = int(length[lo:hi].sum())
        marked = len(first) * n <= MARKS * total or len(first) == 1
        seen = np.zeros(len(first) * n, bool) if marked else None
        for p, q in _pieces(length, lo, hi, marked):
            m = length[p:q]
            key = np.repeat(local[p - lo : q - lo] * n, m) + col[_runs(start[p:q], m)]
            if marked:
                seen[key] = True
        if not marked:
            key.sort()
            key = key[np.r_[True, key[1:] != key[:-1]]]
        rows.append(first)
        sizes.append(seen.reshape(len(first), n).sum(1) if marked else np.bincount(key // n, minlength=len(first)))
    return np.concatenate(rows), np.concatenate(sizes).astype(np.int64)


def _pieces(length: np.ndarray, lo: int, hi: int, split: bool) -> Iterator[tuple[int, int]]:
    """Entries lo to hi whole, or so that a heavy row alone is laid out piece by piece."""
    cuts = [lo, *(lo + np.flatnonzero(np.diff(np.cumsum(length[lo:hi]) // LAID_OUT)) + 1), hi] if split else [lo, hi]
    return zip(cuts, cuts[1:], strict=False)


def _tiles(big: np.ndarray, small: np.ndarray) -> tuple[np.ndarray, dict[tuple[int, int], slice]]:
    """The entries' order by (big, small), and where each pair's entries lie in it."""
    order = np.lexsort((small, big))
    big, small = big[order], small[order]
    if not len(big):
        return order, {}
    first = np.flatnonzero(np.r_[True, (big[1:] != big[:-1]) | (small[1:] != small[:-1])])
    return order, {(int(big[p]), int(small[p])): slice(p, q) for p, q in zip(first, np.r_[first[1:], len(big)], strict=True)}


def dense_rows(i, k, v, inner, j, w, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entries of one block row of the product, from those of A's block row and of B, by dense blocks of `size` a side."""
    oa, at = _tiles(k // size, k // size)
    i, k, v = i[oa], k[oa] % size, v[oa].astype(float)
    ob, bt = _tiles(j // size, inner // size)
    inner, j, w = inner[ob] % size, j[ob] % size, w[ob].astype(float)
    base = int(i[0]) // size * size if len(i) else 0
    out, c, wide = [], None, None

    def leave() -> None:
        r, s = np.nonzero(c)
        out.append((r + base, s + wide * size, np.rint(c[r, s]).astype(np.int64)))

    for (column, row), sb in bt.items():  # by column of blocks: one block of the product is open at a time
        sa = at.get((row, row))
        if sa is None:
            continue
        if column != wide:
            if c is not None:
                leave()
            c, wide = np.zeros((size, size)), column
        x, y = np.zeros((size, size)), np.zeros((size, size))
        x[i[sa] - base, k[sa]] = v[sa]
        y[inner[sb], j[sb]] = w[sb]
        c += x @ y
    if c is not None:
        leave()
    return tuple(np.concatenate([o[n] for o in out]) if out else np.empty(0, np.int64) for n in range(3))


def packed(i: np.ndarray, k: np.ndarray, v: np.ndarray) -> dict[str, np.ndarray]:
    """A block of rows by column: its row ids, its columns, where each begins, and the rows (by place) and values in them."""
    ids, rows = np.unique(i, return_inverse=True)
    order = np.lexsort((rows, k))
    cols, starts = np.unique(k[order], return_index=True)
    return {"ids": ids, "cols": cols, "starts": np.r_[starts, len(k)].astype(np.int32), "rows": rows[order].astype(np.int32), "vals": v[order]}


def _narrow(x: np.ndarray) -> np.ndarray:
    """Whole numbers in the narrowest type that holds them all."""
    if x.dtype.kind != "f" and len(x):
        for kind in (np.uint8, np.int8, np.uint16, np.int16, np.uint32, np.int32):
            if np.iinfo(kind).min <= x.min() and x.max() <= np.iinfo(kind).max:
                return x.astype(kind)
    return x


def squeezed(block: dict[str, np.ndarray]) -> bytes:
    """A packed block in few bytes: ids and columns as steps from the one before, whole numbers narrow, all of it compressed."""
    batch = pa.RecordBatch.from_pydict({c: pa.array([_narrow(np.diff(x, prepend=0) if c in STEPS else x)]) for c, x in block.items()})
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(batch)
    return out.getvalue().to_pybytes()


def opened(block: bytes | pa.Buffer) -> dict[str, np.ndarray]:
    """The packed block that squeezed was given; its rows and values stay narrow."""
    batch = pa.ipc.open_stream(block).read_next_batch()
    out = {c: batch[c][0].values.to_numpy() for c in batch.schema.names}
    return out | {c: np.cumsum(out[c], dtype=np.int64) for c in STEPS} | {"starts": out["starts"].astype(np.int64)}


def _runs(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each run, one after another."""
    return np.arange(length.sum()) + np.repeat(start - (np.cumsum(length) - length), length)


def row_dots(a: dict[str, np.ndarray], b: dict[str, np.ndarray]) -> np.ndarray:
    """Products of the rows of two packed blocks: integers exactly, in doubles as long as these hold every partial sum."""
    _, p, q = np.intersect1d(a["cols"], b["cols"], assume_unique=True, return_indices=True)
    na, nb = len(a["ids"]), len(b["ids"])
    x, y = a["vals"], b["vals"]
    if x.dtype.kind != "f" and len(x) and len(y):
        bound = np.bincount(a["rows"], np.abs(x.astype(float)), na).max() * np.abs(y.astype(float)).max()
        x, y = (z.astype(float if bound < 1 << 52 else np.int64 if bound < 1 << 62 else object) for z in (x, y))
    (sa, la), (sb, lb) = ((m["starts"][at].astype(np.int64), np.diff(m["starts"]).astype(np.int64)[at]) for m, at in ((a, p), (b, q)))
    c = np.zeros((na, nb), x.dtype)
    full = np.flatnonzero(la * lb >= DENSE * na * nb)
    for at in np.split(full, range(WIDE, len(full), WIDE)):
        sides = []
        for m, z, s, n, size in ((a, x, sa[at], la[at], na), (b, y, sb[at], lb[at], nb)):
            e = _runs(s, n)
            t = np.zeros((size, len(at)), z.dtype)
            np.add.at(t, (m["rows"][e], np.repeat(np.arange(len(at)), n)), z[e])
            sides.append(t)
        c += sides[0] @ sides[1].T
    thin = np.flatnonzero(la * lb < DENSE * na * nb)
    e, s, n = _runs(sa[thin], la[thin]), np.repeat(sb[thin], la[thin]), np.repeat(lb[thin], la[thin])
    cuts = [0, *(np.flatnonzero(np.diff(np.cumsum(n) // LAID_OUT)) + 1), len(e)]
    flat = c.reshape(-1)
    for lo, hi in zip(cuts, cuts[1:], strict=False):
        m = n[lo:hi]
        f = _runs(s[lo:hi], m)
        np.add.at(flat, np.repeat(a["rows"][e[lo:hi]].astype(np.int64) * nb, m) + b["rows"][f], np.repeat(x[e[lo:hi]], m) * y[f])
    return c


def near_rows(a: dict[str, np.ndarray], b: dict[str, np.ndarray], least, same: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(smaller id, larger id, product) of the blocks' pairs of rows that share a column and reach `least`; within one block each pair once."""
    c = row_dots(a, b)
    hit = c >= least
    if least <= 0:  # else rows without a common column fall short by themselves
        ones = ({**m, "vals": np.ones(len(m["vals"]))} for m in (a, b))
        hit &= row_dots(*ones) > 0
    up = a["ids"][:, None] < b["ids"]
    out = []
    for x, y, z, m in ((a, b, c, hit & up), (b, a, c.T, (hit & ~up).T))[: 1 if same else 2]:  # each run of pairs under one smaller id
        r, s = np.nonzero(m)
        out.append((x["ids"][r], y["ids"][s], z[m]))
    i, j, dot = (np.concatenate(z) for z in zip(*out, strict=True))
    return i, j, dot if a["vals"].dtype.kind == "f" else np.rint(dot).astype(np.int64) if dot.dtype.kind == "f" else dot.astype(np.int64)


def closed_paths(i: np.ndarray, k: np.ndarray, inner: np.ndarray, j: np.ndarray) -> int:
    """How many paths i, k, j end where the same row has an entry: places (i, k) of a block's whole rows, and (inner, j) of the rows they need."""
    wide = np.unique(k)
    n = len(wide)
    if not n or not len(j):
        return 0
    col = np.minimum(np.searchsorted(wide, j), n - 1)
    ends = wide[col] == j  # other ends close nothing
    inner, col = inner[ends], col[ends]
    order = np.argsort(inner, kind="stable")
    held, start, length = np.unique(inner[order], return_index=True, return_counts=True)
    col = col[order]
    order = np.lexsort((k, i))
    i, k = i[order], k[order]
    own = np.searchsorted(wide, k)
    if not len(held):
        return 0
    at = np.minimum(np.searchsorted(held, k), len(held) - 1)
    length, start = np.where(held[at] == k, length[at], 0), start[at]
    found = 0
    for first, lo, hi in _slices(i, length):
        local = np.repeat(np.arange(len(first)), np.diff(np.r_[first, hi])) * n
        keys = local + own[lo:hi]
        seen = None
        if len(first) * n <= MARKS * int(length[lo:hi].sum()) or len(first) == 1:
            seen = np.zeros(len(first) * n, bool)
            seen[keys] = True
        # A heavy row alone is laid out piece by piece.
        for p, q in zip(cuts := [lo, *(lo + np.flatnonzero(np.diff(np.cumsum(length[lo:hi]) // LAID_OUT)) + 1), hi], cuts[1:], strict=False):
            m = length[p:q]
            key = np.repeat(local[p - lo : q - lo], m) + col[_runs(start[p:q], m)]
            found += int(np.count_nonzero(seen[key] if seen is not None else keys[np.minimum(np.searchsorted(keys, key), len(keys) - 1)] == key))
    return found


def _met(a: dict[str, np.ndarray], b: dict[str, np.ndarray]) -> tuple[np.ndarray, ...]:
    """Of a block of A's rows, packed by row, and one of B's columns, packed by inner id: A's entries that meet any of B's,
    the rows of these (by place), where B's entries begin for each, and how many they are."""
    at = np.minimum(np.searchsorted(b["cols"], a["ids"]), max(0, len(b["cols"]) - 1))
    if not len(b["cols"]) or not len(a["ids"]):
        return (np.empty(0, np.int64),) * 4
    length = np.where(b["cols"][at] == a["ids"], np.diff(b["starts"])[at], 0)[a["rows"]]
    e = np.flatnonzero(length)
    return e, np.repeat(np.arange(len(a["cols"])), np.diff(a["starts"]))[e], b["starts"][at][a["rows"][e]], length[e]


def pair_counts(a: dict[str, np.ndarray], b: dict[str, np.ndarray]) -> tuple[np.ndarray, ...]:
    """(i, work, na, nc) of the rows of two blocks' product that have any entry: multiplications and entries here, and the whole row's entries of A."""
    e, row, start, length = _met(a, b)
    first, nc = _distinct(row, start, length, b["rows"], len(b["ids"]))
    work = np.add.reduceat(length, first) if len(first) else length
    return a["cols"][row[first]], work, np.diff(a["starts"])[row[first]], nc


def pair_products(a: dict[str, np.ndarray], b: dict[str, np.ndarray], ones: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, v) of two blocks' product, a run of rows at a time; ones counts products. Integers are exact, in doubles as long as these hold every partial sum."""
    e, row, start, length = _met(a, b)
    if not len(e):
        return
    x, y, col, n = a["vals"][e], b["vals"], b["rows"], len(b["ids"])
    whole = ones or "f" not in (x.dtype.kind, y.dtype.kind)
    if whole and not ones:
        bound = np.bincount(row, np.abs(x.astype(float)) * length).max() * np.abs(y.astype(float)).max()
        x, y = (z.astype(float if bound < 1 << 52 else np.int64 if bound < 1 << 62 else object) for z in (x, y))
    for first, lo, hi in _slices(row, length):
        local = np.repeat(np.arange(len(first)) * n, np.diff(np.r_[first, hi]))
        marked = len(first) * n <= MARKS * int(length[lo:hi].sum()) or len(first) == 1
        seen, c = (np.zeros(len(first) * n, t) for t in (bool, float if ones else np.result_type(x, y))) if marked else (None, None)
        for p, q in _pieces(length, lo, hi, marked):
            m = length[p:q]
            place = _runs(start[p:q], m)
            key = np.repeat(local[p - lo : q - lo], m) + col[place]
            v = np.ones(len(key)) if ones else np.repeat(x[p:q], m) * y[place]
            if not marked:
                by = np.argsort(key, kind="stable")
                key = key[by]
                new = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
                key, c = key[new], np.add.reduceat(v[by], new)
                continue
            seen[key] = True
            if v.dtype.kind == "f":
                c += np.bincount(key, v, len(c))
            else:
                np.add.at(c, key, v)
        if marked:
            key = np.flatnonzero(seen)
            c = c[key]
        r = key // n
        yield a["cols"][row[first]][r], b["ids"][key - r * n], (np.rint(c) if c.dtype.kind == "f" else c).astype(np.int64) if whole else c


def dense_products(a: dict[str, np.ndarray], b: dict[str, np.ndarray], size: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, v) of two blocks' product by dense blocks of `size` a side, of which three are open at a time."""
    i, inner = (np.repeat(m["cols"], np.diff(m["starts"])) for m in (a, b))
    k, j = a["ids"][a["rows"]], b["ids"][b["rows"]]
    (oa, at), (ob, bt) = _tiles(i // size, k // size), _tiles(j // size, inner // size)
    i, k, v = i[oa] % size, k[oa] % size, a["vals"][oa].astype(float)
    inner, j, w = inner[ob] % size, j[ob] % size, b["vals"][ob].astype(float)
    down, across = {}, {}
    for tiles, out in ((at, down), (bt, across)):
        for (one, middle), entries in tiles.items():
            out.setdefault(one, {})[middle] = entries
    for r, row in down.items():
        for s, col in across.items():
            c = None
            for middle in row.keys() & col.keys():
                x, y = np.zeros((size, size)), np.zeros((size, size))
                p, q = row[middle], col[middle]
                x[i[p], k[p]] = v[p]
                y[inner[q], j[q]] = w[q]
                c = x @ y if c is None else c + x @ y
            if c is not None:
                at_i, at_j = np.nonzero(c)
                yield at_i + r * size, at_j + s * size, np.rint(c[at_i, at_j]).astype(np.int64)
