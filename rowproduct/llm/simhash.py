"""Near-duplicate groups from SimHash fingerprints, paired exactly through vantage-point trees.

A shared tree deals all fingerprints to shards; it is grown on the driver from a sample of POINTS fingerprints for each shard to come
(at least SAMPLE, at most MOST_SAMPLE):
those within a vantage point's radius go left, the rest go right, and the ones of the left
whose distance lies within `bits` of the radius are copied to the right. By the triangle
inequality every pair within `bits` then shares a shard. Inside a shard the tree goes on
the same way until its leaves are small or the radius prunes nothing; shards above a bound
are compared block by block, each pair of blocks in a task of its own. A task returns
no pairs but one star for each group it finds, so a group of thousands adds no square of links.

Defined results: null text is empty text; texts without words have fingerprint zero and link
like any other; fewer words than a shingle make one shingle; a null id is never a
component's least id unless all are null, and such a component has a null component_id;
repeated rows share a component; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .scratch import stored

SAMPLE, MOST_SAMPLE, POINTS, LEAF, BLOCK = 4096, 1 << 20, 64, 32768, 65536
LAST_ID = (1 << 63) - 1


def fingerprint(text: str, shingle: int, seeds) -> tuple[int, list[int]]:
    """(shingles, a 64-bit fingerprint for each seed)"""
    w = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII case and white space only
    if not w:
        return 0, [0] * len(seeds)
    parts = [b" ".join(w)] if len(w) < shingle else list(map(b" ".join, zip(*(w[k:] for k in range(shingle)))))
    out, digest = [], xxhash.xxh64_intdigest
    for seed in seeds:
        count = np.zeros(64, np.int64)
        for k in range(0, len(parts), 16384):
            h = np.array([digest(s, seed) for s in parts[k : k + 16384]], "<u8")
            count += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out.append(int(np.packbits(2 * count > len(parts), bitorder="little").view("<u8")[0]))
    return len(parts), out


def fingerprints(docs: DataFrame, shingle: int = 3, seeds=(42,), id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc, th, n, f0, f1, ...): th is a hash of the text, n its shingles, f the fingerprints as signed longs."""
    lanes = [f"f{k}" for k in range(len(seeds))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [fingerprint(t or "", shingle, seeds) for t in (x.as_py() for x in b.column(2))]
            f = np.array([x[1] for x in got], np.uint64).reshape(-1, len(seeds)).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([x[0] for x in got], pa.int64()), *(pa.array(np.ascontiguousarray(f[:, k])) for k in range(len(seeds)))], ["doc", "th", "n", *lanes])

    d = docs.select(F.col(id_col).cast("long").alias("doc"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("th"), F.col(text).alias("text"))
    return d.mapInArrow(run, "doc long, th long, n long, " + ", ".join(f"{x} long" for x in lanes))


def distance(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Differing bits between rows of lanes, broadcast."""
    out = np.bitwise_count(x[..., 0] ^ y[..., 0])
    for k in range(1, x.shape[-1]):
        out = out + np.bitwise_count(x[..., k] ^ y[..., k])
    return out


def best_split(points: np.ndarray, bits: int):
    """(vantage, radius) that leaves least to compare, or None where that is over nine tenths of everything."""
    n, best = len(points), (0.9, None)
    size = 64 * points.shape[1]
    for v in points[:: max(1, n // 6)][:6]:
        upto = np.cumsum(np.bincount(distance(points, v[None]), minlength=size + 1)).astype(float) / n
        below = np.concatenate([np.zeros(bits), upto[:-bits]]) if bits else upto
        right = 1 - below if bits else 1 - upto
        cost = upto**2 + right**2
        m = int(np.argmin(cost))
        if cost[m] < best[0] and 0 < upto[m] < 1:
            best = cost[m], (v, m)
    return best[1]


def grow(points: np.ndarray, bits: int, scale: float, leaf: int = LEAF):
    """A tree over a sample that stands for scale times as many: nested (vantage, radius, left, right), leaves are numbers."""
    made = [0]

    def node(p: np.ndarray):
        split = best_split(p, bits) if len(p) * scale > leaf and len(p) >= 32 else None
        if split is None:
            made[0] += 1
            return made[0] - 1
        d = distance(p, split[0][None])
        return (*split, node(p[d <= split[1]]), node(p[d > split[1] - bits]))

    return node(points) if len(points) else 0


def route(tree, points: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, leaf) for every shard that a row belongs to."""
    rows, leaves, todo = [], [], [(tree, np.arange(len(points)))]
    while todo:
        t, idx = todo.pop()
        if isinstance(t, int):
            rows.append(idx), leaves.append(np.full(len(idx), t))
            continue
        d = distance(points[idx], t[0][None])
        todo += [(t[2], idx[d <= t[1]]), (t[3], idx[d > t[1] - bits])]
    return np.concatenate(rows), np.concatenate(leaves)


def contract(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least reachable row of each of n rows."""
    lab = np.arange(n)
    while True:
        lo, hi = np.minimum(lab[a], lab[b]), np.maximum(lab[a], lab[b])
        go = lo != hi
        if not go.any():
            return lab
        np.minimum.at(lab, hi[go], lo[go])
        while True:
            nxt = lab[lab]
            if (nxt == lab).all():
                break
            lab = nxt


def groups_within(points: np.ndarray, side: np.ndarray | None, bits: int, leaf: int = 256) -> np.ndarray:
    """Least row of each row's group over pairs within bits; with side, only pairs across sides count."""
    n = len(points)
    a_all, b_all, held = [np.arange(0)], [np.arange(0)], 0
    todo = [np.arange(n)]
    while todo:
        idx = todo.pop()
        split = best_split(points[idx[:: max(1, len(idx) // 2048)]], bits) if len(idx) > leaf else None
        if split is not None:
            d = distance(points[idx], split[0][None])
            left, right = idx[d <= split[1]], idx[d > split[1] - bits]
            if max(len(left), len(right)) < len(idx):
                todo += [left, right]
                continue
        x, y = (idx, idx) if side is None else (idx[side[idx] == 0], idx[side[idx] == 1])
        if not len(x) or not len(y):
            continue
        step, q = max(1, (1 << 19) // len(y)), points[y][None]
        for k in range(0, len(x), step):
            near = distance(points[x[k : k + step]][:, None], q) <= bits
            if near.any():
                i, j = np.nonzero(near)
                i, j = x[k : k + step][i], y[j]
                i, j = (i[i < j], j[i < j]) if side is None else (i, j)
                a_all.append(i), b_all.append(j)
                held += len(i)
                if held > 2_000_000:
                    lab = contract(n, np.concatenate(a_all), np.concatenate(b_all))
                    i = np.nonzero(lab != np.arange(n))[0]
                    a_all, b_all, held = [i], [lab[i]], 0
    return contract(n, np.concatenate(a_all), np.concatenate(b_all))


def links(prints: DataFrame, bits: int, lanes: int, ratio: float | None = None, leaf: int = LEAF, block: int = BLOCK) -> DataFrame:
    """prints (node struct<rep, f...>, n) of distinct fingerprints -> links (a, b) between nodes that
    connect all that are within bits. ratio: pairs whose shingle counts differ by more than
    that factor are left apart (needed for a set similarity of that much)."""
    names = [f"f{k}" for k in range(lanes)]
    node = "struct<rep:long, " + ", ".join(f"{x}:long" for x in names) + ">"
    matrix = lambda t: np.stack([t.column(x).to_numpy().view(np.uint64) for x in names], axis=1)
    flat = prints.select("node.*", "n")
    total = flat.count()
    want = min(MOST_SAMPLE, max(SAMPLE, POINTS * total // leaf))
    # By a share of all hashes: nothing is sorted, and twice as many as wanted can hardly come.
    sample = flat.where(F.pmod(F.xxhash64(*names), F.lit(max(1, total // want))) == 0).limit(2 * want).select(*names).orderBy(*names).toPandas()
    points = np.stack([sample[x].to_numpy(np.int64).view(np.uint64) for x in names], axis=1) if len(sample) else np.zeros((0, lanes), np.uint64)
    tree = grow(points, bits, total / max(1, len(points)), leaf)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                rows, leaves = route(tree, matrix(b), bits)
                yield pa.RecordBatch.from_arrays([*(c.take(pa.array(rows)) for c in b.columns), pa.array(leaves, pa.int64())], [*b.schema.names, "leaf"])

    dealt = flat.mapInArrow(deal, "rep long, " + ", ".join(f"{x} long" for x in names) + ", n long, leaf long")
    if ratio is None:
        dealt = dealt.withColumn("band", F.lit(0))
    else:  # a band meets itself and the next one
        band = F.floor(F.log(F.greatest("n", F.lit(1)) + 0.0) / F.log(F.lit(1 / ratio))).cast("int")
        dealt = dealt.withColumn("band", F.explode(F.array(band, band - 1)))
    dealt = stored(dealt, "shards")
    # Shards above the bound are cut in blocks by hash; every pair of blocks meets once.
    sizes = F.broadcast(dealt.groupBy("leaf", "band").agg(F.ceil(F.count("*") / F.lit(block)).cast("int").alias("cuts")))  # one row a leaf and band
    dealt = dealt.join(sizes, ["leaf", "band"]).withColumn("own", F.pmod(F.xxhash64(*names), F.col("cuts")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("cuts") - 1)))
    dealt = dealt.withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other"))

    def meet(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        side = None if i == j else (table.column("own").to_numpy() == j).astype(np.int8)
        lab = groups_within(matrix(table), side, bits)
        a = np.nonzero(lab != np.arange(len(lab)))[0]
        ends = [table.select(["rep", *names]).take(pa.array(x)).combine_chunks() for x in (a, lab[a])]
        typ = [pa.field("rep", pa.int64()), *(pa.field(x, pa.int64()) for x in names)]
        return pa.table({k: pa.StructArray.from_arrays([c.chunk(0) if c.num_chunks else pa.array([], pa.int64()) for c in e.columns], fields=typ) for k, e in zip("ab", ends, strict=True)})

    return dealt.groupBy("leaf", "band", "i", "j").applyInArrow(meet, f"a {node}, b {node}")


def near_duplicates(docs: DataFrame, shingle: int = 3, bits: int = 3, seeds=(42,), ratio: float | None = None, id_col: str = "doc_id", text: str = "text",
                    leaf: int = LEAF, block: int = BLOCK) -> DataFrame:
    """doc_id, th, fingerprint (hex of every lane), component_id: the least doc_id reachable over
    fingerprints that differ in at most bits."""
    lanes = [f"f{k}" for k in range(len(seeds))]
    prints = stored(fingerprints(docs, shingle, seeds, id_col, text), "prints")
    # Of equal fingerprints with different counts the sizes can differ: the count is part of the node only where it decides.
    keys = lanes + (["n"] if ratio else [])
    u = prints.groupBy(*keys).agg(F.coalesce(F.min("doc"), F.lit(LAST_ID)).alias("rep"), *([] if ratio else [F.min("n").alias("n")]))
    u = stored(u.select(F.struct("rep", *lanes).alias("node"), "n", *lanes), "nodes")
    comp = connected_components(links(u, bits, len(seeds), ratio, leaf, block))
    named = u.join(comp, "node", "left").select(*keys, F.coalesce("root.rep", "node.rep").alias("c"))
    hexes = F.concat(*[F.lower(F.lpad(F.hex(x), 16, "0")) for x in lanes])
    return prints.join(named, keys).select(F.col("doc").alias(id_col), "th", hexes.alias("fingerprint"), F.when(F.col("c") != LAST_ID, F.col("c")).alias("component_id"))


def keep_one(docs: DataFrame, groups: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """The document with the least id of each group (of equal ids, that with the least text hash), once; columns may have any name."""
    # A group without any id is known by its fingerprint.
    group = [F.col("component_id"), F.when(F.col("component_id").isNull(), F.col("fingerprint")).alias("_fp")]
    first = groups.groupBy(*group).agg(F.min(F.struct(F.coalesce(F.col(id_col), F.lit(LAST_ID)).alias("_id"), F.col("th").alias("_th"))).alias("k")).select("k.*").distinct()
    # The row travels as one value, so that its columns can have any name.
    keyed = docs.select(F.struct("*").alias("row"), F.coalesce(F.col(id_col).cast("long"), F.lit(LAST_ID)).alias("_id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("_th"))
    return keyed.join(first, ["_id", "_th"], "left_semi").dropDuplicates(["_id", "_th"]).select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
