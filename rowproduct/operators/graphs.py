"""Searches, triangles, clustering, similarity: what products are used for."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.blocks import closed_paths, near_rows, opened, packed, squeezed
from ..functions.semiring import PLUS_PAIR
from ..matrix import SparseMatrix
from ..plans import lowering as low
from ..plans.cut import cut, dropped, freed_twice, held, stored
from ..plans.schedule import balanced, block_starts, place_of
from ..plans.work import checked_broadcast, number_rows
from .algebra import column_subset
from .product import multiply


# Tall and skinny

def random_columns(m: SparseMatrix, k: int, seed: int = 1) -> SparseMatrix:
    """k of M's occurring columns, those whose md5 of seed and id comes first, relabelled 0 to k-1."""
    h = m.df.select("j").distinct().withColumn("h", F.md5(F.concat(F.lit(f"{seed}:"), F.col("j").cast("string"))))
    first = h.orderBy("h", "j").limit(k)  # k rows
    cols = first.select("j", (F.row_number().over(W.orderBy("h", "j")) - 1).cast("bigint").alias("to"))
    return column_subset(m, cols)


def tall_skinny(m: SparseMatrix, k: int, seed: int = 1, **o) -> SparseMatrix:
    return multiply(m, random_columns(m, k, seed), **o)


def frontier_step(edges: DataFrame, frontier: DataFrame, seen: DataFrame) -> DataFrame:
    """frontier, seen (search, vertex) -> vertices that the frontiers' edges reach first."""
    new = frontier.join(edges.select(F.col("i").alias("vertex"), F.col("j").alias("to")), "vertex").select("search", F.col("to").alias("vertex")).distinct()
    return new.join(seen.select("search", "vertex"), ["search", "vertex"], "left_anti")


def msbfs(m: SparseMatrix, sources: list[int], max_level: int | None = None) -> DataFrame:
    """(search, vertex, level) of searches from each source: all frontiers are one tall, skinny factor."""
    at = m.spark.createDataFrame([(k, s, 0) for k, s in enumerate(sources)], "search int, vertex bigint, level int")
    seen, level = at, 0
    while max_level is None or level < max_level:
        level += 1
        new = cut(frontier_step(m.df, at.select("search", "vertex"), seen).withColumn("level", F.lit(level)))
        if not new.limit(1).count():
            break
        at, seen = new, seen.unionByName(new)
    return seen


def shortest_path_counts(m: SparseMatrix, sources: list[int], max_level: int | None = None) -> DataFrame:
    """(search, vertex, level, paths), until no search finds a new vertex where max_level is None."""
    at = m.spark.createDataFrame([(k, s, 0, 1) for k, s in enumerate(sources)], "search int, vertex bigint, level int, paths bigint")
    seen, level = at, 0
    while max_level is None or level < max_level:
        level += 1
        e = m.df.select(F.col("i").alias("vertex"), F.col("j").alias("to"))
        new = at.join(e, "vertex").groupBy("search", F.col("to").alias("vertex")).agg(F.sum("paths").cast("bigint").alias("paths"))
        at = cut(new.join(seen.select("search", "vertex"), ["search", "vertex"], "left_anti").select("search", "vertex", F.lit(level).alias("level"), "paths"))
        if not at.limit(1).count():
            break
        seen = seen.unionByName(at)
    return seen


def betweenness(m: SparseMatrix, sources: list[int], max_level: int | None = None) -> DataFrame:
    """(vertex, score): dependencies of the given sources, passed back level by level; end points not counted.
    max_level cuts the searches and so changes scores; None runs them to the end."""
    p = cut(shortest_path_counts(m, sources, max_level))
    deepest = p.agg(F.max("level")).first()[0] or 0
    e = m.df.select(F.col("i").alias("vertex"), F.col("j").alias("to"))
    dep = p.select("search", "vertex", "level", "paths", F.lit(0.0).alias("d"))
    for level in range(deepest - 1, 0, -1):
        below = dep.where(F.col("level") == level + 1).select("search", F.col("vertex").alias("to"), ((1 + F.col("d")) / F.col("paths")).alias("g"))
        add = dep.where(F.col("level") == level).select("search", "vertex", "paths").join(e, "vertex").join(below, ["search", "to"]).groupBy("search", "vertex").agg(F.sum(F.col("paths") * F.col("g")).alias("a"))
        dep = cut(dep.join(add, ["search", "vertex"], "left").select("search", "vertex", "level", "paths", F.when(F.col("level") == level, F.coalesce("a", F.lit(0.0))).otherwise(F.col("d")).alias("d")))
    return dep.where("level > 0").groupBy("vertex").agg(F.sum("d").alias("score"))


# Triangles

def degrees(m: SparseMatrix) -> DataFrame:
    return m.df.groupBy("i").agg(F.count("*").alias("d"))


def reorder(m: SparseMatrix) -> SparseMatrix:
    """Rows and columns renamed by rising row size, ties by id."""
    rank = number_rows(degrees(m), ["d", "i"], "r").select("i", "r")
    d = m.df.join(rank, "i").join(rank.select(F.col("i").alias("j"), F.col("r").alias("s")), "j").select(F.col("r").alias("i"), F.col("s").alias("j"), "v")
    return m.with_df(d)


def split(m: SparseMatrix) -> tuple[SparseMatrix, SparseMatrix]:
    return m.with_df(m.df.where("j < i")), m.with_df(m.df.where("j > i"))


def by_degree(m: SparseMatrix) -> tuple[SparseMatrix, SparseMatrix]:
    """The same two triangles without ranks: ends compared as (size, id), so nothing is sorted over all rows."""
    d = degrees(m)
    e = m.df.join(d, "i").join(d.select(F.col("i").alias("j"), F.col("d").alias("e")), "j")
    low = F.struct(F.col("e"), F.col("j")) < F.struct(F.col("d"), F.col("i"))
    return m.with_df(e.where(low).select("i", "j", "v")), m.with_df(e.where(~low).select("i", "j", "v"))


def wedges(m: SparseMatrix, **o) -> SparseMatrix:
    """L U with counts: paths over a smaller vertex."""
    low, up = by_degree(m)
    return multiply(low, up, **({"semiring": PLUS_PAIR} | o))


def closed_wedges(m: SparseMatrix, **o) -> DataFrame:
    """Wedges whose ends are joined, each triangle twice; the mask goes below the count."""
    low, up = by_degree(m)
    return multiply(low, up, semiring=PLUS_PAIR, mask=m.df.select("i", "j"), **o).df


def rising_rows(edges: DataFrame, d: DataFrame) -> DataFrame:
    """(i, cols): every vertex' neighbours of more edges (equal ones: of larger id), from each edge once and the vertices' edges (i, d). Stored by ranges of i."""
    small = checked_broadcast(d)
    d = d if small is None else small
    e = edges.select("i", "j").join(d, "i").join(d.select(F.col("i").alias("j"), F.col("d").alias("e")), "j")
    rises = F.struct(F.col("d"), F.col("i")) < F.struct(F.col("e"), F.col("j"))
    up = e.select(F.when(rises, F.col("i")).otherwise(F.col("j")).alias("i"), F.when(rises, F.col("j")).otherwise(F.col("i")).alias("j"))
    n = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return stored(up.repartitionByRange(n, "i").groupBy("i").agg(F.collect_list("j").alias("cols")))


def triangles_by_block(m: SparseMatrix, edges: DataFrame, d: DataFrame) -> DataFrame:
    """(n) of each block of rows of U, which has an edge from its end of fewer edges: U U where U has an entry itself. Blocks fetch packed rows;
    a block's own rows are factor and mask, and no path is exchanged."""
    rows = rising_rows(edges, d)
    sizes = rows.select(F.col("i").alias("k"), F.size("cols").alias("n"))
    small = checked_broadcast(sizes)
    ends = rows.select("i", F.explode("cols").alias("k"))
    work = stored(ends.join(sizes if small is None else small, "k").groupBy("i").agg(F.sum("n").cast("bigint").alias("work")))
    starts, n = block_starts(work, m.nrows, max(1, m.spark.sparkContext.defaultParallelism), low.BLOCK_WORK)
    place = place_of(starts or [0]) if starts is not None else None
    x = rows.withColumn("bucket", place) if place is not None else rows.join(balanced(work, n).select("i", "bucket"), "i")
    needs = x.select(F.explode("cols").alias("k"), "bucket").groupBy("k").agg(F.collect_set("bucket").alias("owns"))
    y = needs.join(rows.select(F.col("i").alias("k"), F.col("cols").alias("to")), "k").select(F.explode("owns").alias("own"), "k", "to")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        flat = []
        for t, key, to in ((left, "i", "cols"), (right, "k", "to")):
            c = t[to].combine_chunks()
            flat += [np.repeat(t[key].to_numpy(), pc.list_value_length(c).to_numpy()), c.flatten().to_numpy()]
        return pa.table({"n": pa.array([closed_paths(*flat)], pa.int64())})

    return x.groupBy("bucket").cogroup(y.groupBy("own")).applyInArrow(run, "n bigint")


def triangle_count(m: SparseMatrix, **o) -> DataFrame:
    """(triangles). Beyond BLOCK_WORK paths each is counted in blocks, once, from edges stored once."""
    if not o:
        edges = stored(m.df.where("i < j").select("i", "j"))
        d = stored(edges.select(F.explode(F.array("i", "j")).alias("i")).groupBy("i").agg(F.count("*").alias("d")))
        if (d.agg(F.sum(F.col("d") * F.col("d"))).first()[0] or 0) > low.BLOCK_WORK:
            got = triangles_by_block(m, edges, d).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("triangles"))
            return m.spark.createDataFrame([tuple(r) for r in got.collect()], got.schema)  # one row
    return closed_wedges(m, **o).agg((F.coalesce(F.sum("v"), F.lit(0)) / 2).cast("bigint").alias("triangles"))


def triangles_by_vertex(m: SparseMatrix) -> DataFrame:
    """(vertex, tri): triangles at each vertex that has any, over directed edges from smaller to larger."""
    _, up = by_degree(m)
    e = up.df
    t = (e.select(F.col("i").alias("a"), F.col("j").alias("b")).join(e.select(F.col("i").alias("a"), F.col("j").alias("c")), "a")
         .join(e.select(F.col("i").alias("b"), F.col("j").alias("c")), ["b", "c"]))
    return t.select(F.explode(F.array("a", "b", "c")).alias("vertex")).groupBy("vertex").agg(F.count("*").alias("tri"))


def clustering_coefficient(m: SparseMatrix) -> DataFrame:
    """(vertex, tri, wedges): the coefficient is their ratio."""
    d = degrees(m).select(F.col("i").alias("vertex"), (F.col("d") * (F.col("d") - 1) / 2).cast("bigint").alias("wedges"))
    return d.join(triangles_by_vertex(m), "vertex", "left").select("vertex", F.coalesce("tri", F.lit(0)).cast("bigint").alias("tri"), "wedges")


# Clustering

def column_stochastic(m: SparseMatrix) -> SparseMatrix:
    """Self loops of the column's largest value, then columns that sum to 1."""
    m, = held(m)  # its own makers would run for every count and side of the products to come
    loops = m.df.groupBy("j").agg(F.max("v").alias("v")).select(F.col("j").alias("i"), "j", "v")
    d = m.df.where("i <> j").unionByName(loops)
    t = d.groupBy("j").agg(F.sum("v").alias("t"))
    return held(m.with_df(d.join(t, "j").select("i", "j", (F.col("v").cast("double") / F.col("t")).alias("v"))))[0]


def column_heads(d: DataFrame, keep: int, most: int = 1 << 22) -> DataFrame:
    """d (i, j, p) without what `keep` entries of the same column and partition surpass: of larger p, or as large and of smaller i. A task holds `most`
    entries at most, and lets go of all of them beyond; batches with nulls or NaN pass whole."""
    def pruned(t: pa.Table) -> pa.Table:
        i, j, p = (t[c].to_numpy() for c in "ijp")
        by = np.lexsort((i, -p, j))
        j = j[by]
        first = np.flatnonzero(np.r_[True, j[1:] != j[:-1]])
        rank = np.arange(len(j)) - np.repeat(first, np.diff(np.r_[first, len(j)]))
        return t.take(by[rank < keep])

    def run(batches):
        kept, new, n = None, [], 0
        for b in batches:
            if any(c.null_count for c in b.columns) or np.isnan(b["p"].to_numpy()).any():
                yield b
                continue
            new.append(b)
            n += len(b)
            if n >= max(most // 4, len(kept) if kept else 0):
                kept, new, n = pruned(pa.Table.from_batches([*(kept.to_batches() if kept else []), *new])), [], 0
                if len(kept) > most:
                    yield from kept.to_batches(max(1, most // 64))
                    kept = None
        if kept or n:
            yield from pruned(pa.Table.from_batches([*(kept.to_batches() if kept else []), *new])).to_batches(max(1, most // 64))

    return d.mapInArrow(run, "i bigint, j bigint, p double")


def inflate(m: SparseMatrix, r: float, keep: int) -> SparseMatrix:
    """Powers of the values, the keep largest of a column, columns again of sum 1. M is made once; of a column no more than the keep largest of each task is exchanged."""
    w = W.partitionBy("j").orderBy(F.desc("p"), "i")
    d = column_heads(m.df.select("i", "j", F.round(F.pow("v", F.lit(r)), 12).alias("p")), keep)
    d = d.withColumn("n", F.row_number().over(w)).where(F.col("n") <= keep)
    return m.with_df(d.select("i", "j", (F.col("p") / F.sum("p").over(W.partitionBy("j"))).alias("v")))


def markov_round(m: SparseMatrix, r: float = 2.0, keep: int = 20) -> SparseMatrix:
    return inflate(multiply(m, m), r, keep)


def markov_clusters(m: SparseMatrix, rounds: int = 20, r: float = 2.0, keep: int = 20) -> DataFrame:
    """(vertex, cluster): the row with the largest value of each column at the end."""
    x = column_stochastic(m)
    for _ in range(rounds):
        x, = held(markov_round(x, r, keep))
    return x.df.groupBy(F.col("j").alias("vertex")).agg(F.max_by("i", F.struct("v", -F.col("i"))).alias("cluster"))


def subset_expand(m: SparseMatrix, columns: int, batch: int, seed: int = 1):
    """M times batches of its first `columns` random columns: one tall, skinny product after another."""
    for k in range(0, columns, batch):
        yield tall_skinny(m, min(batch, columns - k), seed + k)


def label_step(m: SparseMatrix, labels: DataFrame) -> DataFrame:
    """labels (vertex, label): each vertex takes its neighbours' heaviest label, the least of equals."""
    votes = m.df.join(labels.select(F.col("vertex").alias("j"), "label"), "j").groupBy("i", "label").agg(F.sum("v").alias("n"))
    w = W.partitionBy("i").orderBy(F.desc("n"), "label")
    return votes.withColumn("r", F.row_number().over(w)).where("r = 1").select(F.col("i").alias("vertex"), "label")


def peer_step(m: SparseMatrix, assigned: DataFrame) -> DataFrame:
    """assigned (vertex, cluster): as label_step, a vertex' votes shared over its edges (in exact decimals)."""
    d = m.df.groupBy(F.col("j")).agg(F.count("*").alias("d"))
    share = (F.lit(1).cast("decimal(20,12)") / F.col("d").cast("decimal(10,0)")).cast("decimal(20,12)")
    votes = m.df.join(d, "j").join(assigned.select(F.col("vertex").alias("j"), "cluster"), "j").groupBy("i", "cluster").agg(F.sum(share).alias("n"))
    w = W.partitionBy("i").orderBy(F.desc("n"), "cluster")
    return votes.withColumn("r", F.row_number().over(w)).where("r = 1").select(F.col("i").alias("vertex"), "cluster")


# Similarity

#: Rows and entries that a block of a comparison of all pairs should hold, at most about.
PAIR_ROWS, PAIR_ENTRIES = 1024, 1 << 19


def block_pairs(m: SparseMatrix, min_dot, rows: int, entries: int) -> DataFrame:
    """(i, j, dot) as cosine_pairs: rows are packed in blocks, stored, and every two blocks multiplied in NumPy in one task, which
    reads both: nothing of a pair is exchanged. On disk a block is one binary, a few bytes an entry."""
    spark, kind = m.spark, m.value_type
    n = max(1, -(-rows // PAIR_ROWS), -(-entries // PAIR_ENTRIES))

    def pack(batches):
        t = pa.Table.from_batches(list(batches))
        if len(t):
            block = squeezed(packed(*(t[c].to_numpy() for c in ("i", "j", "v"))))
            yield pa.RecordBatch.from_pydict({"bucket": t["bucket"].combine_chunks()[:1], "block": pa.array([block], pa.binary())})

    def compare(batches):
        for t in batches:
            for at in range(len(t)):
                a, b = (opened(t[f"{side}_block"][at].as_buffer()) for side in "ab")
                i, j, dot = near_rows(a, b, min_dot, t["a_bucket"][at] == t["b_bucket"][at])
                yield pa.RecordBatch.from_pydict({"i": i, "j": j, "dot": dot})

    freed_twice(spark)  # else the shuffles that made m lie beside those of its blocks, and these beside those of the pairs
    dealt = m.df.withColumn("bucket", F.pmod(F.xxhash64("i"), F.lit(n)).cast("int")).repartitionById(n, "bucket")
    blocks = stored(dealt.mapInArrow(pack, "bucket int, block binary"))
    del dealt
    freed_twice(spark)
    a, b = (blocks.repartitionById(n, "bucket").toDF(f"{side}_bucket", f"{side}_block") for side in "ab")
    return a.join(b.hint("shuffle_replicate_nl"), F.col("a_bucket") <= F.col("b_bucket")).mapInArrow(compare, f"i bigint, j bigint, dot {kind}")


def cosine_pairs(m: SparseMatrix, min_dot, drop_columns_over: int | None = None) -> DataFrame:
    """(i, j, dot), i < j, of rows whose product is min_dot at least. Pairs are made by column, one of each two; beyond BLOCK_WORK, where
    columns make as many products as there are pairs of rows, by comparing blocks of rows.
    drop_columns_over leaves out columns of more rows than that, and so changes the products; None keeps all."""
    d = m.df
    if drop_columns_over:
        d = d.join(d.groupBy("j").count().where(F.col("count") <= drop_columns_over).select("j"), "j", "left_semi")
    if m.value_type in ("bigint", "double"):
        m, = held(m.with_df(d.where("i is not null and j is not null and v is not null")))
        d = m.df
        made = d.groupBy("j").agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * F.col("n")), F.sum("n")).first()
        if (made[0] or 0) > 2 * low.BLOCK_WORK:
            rows = d.select("i").distinct().count()
            if made[0] >= rows * rows:
                pairs = block_pairs(m, min_dot, rows, made[1])
                dropped(d)  # the blocks hold it all
                return pairs
    x, y = d.select("i", F.col("j").alias("k"), F.col("v").alias("x")), d.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("v").alias("y"))
    p = x.join(y, "k").where(F.col("i") < F.col("j"))
    return p.groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("dot")).where(F.col("dot") >= min_dot)


def common_neighbours(m: SparseMatrix) -> DataFrame:
    """(i, j, n), i < j: columns that two rows share; beyond a broadcast's size pairs are counted in blocks of rows, and not exchanged."""
    m, = held(m)
    return multiply(m, m.transpose(), semiring=PLUS_PAIR, where=F.col("i") < F.col("j")).df.withColumnRenamed("v", "n")
