"""Physical forms of a product. Each gives the same matrix.

joinagg   join on the inner id, partial sums, one exchange of products on (i, j)
rowlocal  B to every executor (of checked size), A by row: products are never exchanged
rowfetch  blocks of rows fetch the B rows they need, each once a block; products stay in their block
splithub  inner ids of hub rows are salted and partial rows added: a row may then be shared
kernel    rowfetch whose blocks run an accumulator as such, with its counters
pairs     blocks of A's rows and of B's columns, packed and stored, meet by twos in NumPy: nothing of a pair is exchanged
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.blocks import opened, packed, pair_counts, pair_products, row_sizes as block_row_sizes, squeezed
from ..functions.kernels import multiply_block
from ..functions.semiring import Semiring
from ..matrix import SparseMatrix
from .cut import freed_twice, stored
from .work import checked_broadcast, row_work, total_work

#: Multiplications that a block should hold: of the engine's own aggregates, and of Python kernels.
BLOCK_WORK, KERNEL_WORK = 30_000_000, 1_000_000
#: Entries of B that blocks of rows may fetch in all; where it could be more, packed blocks of so many entries meet by twos.
FETCHED, PAIR_ENTRIES = 50_000_000, 1 << 20


def sides(a: SparseMatrix, b: SparseMatrix) -> tuple[DataFrame, DataFrame]:
    """Renamed apart, so that A times A is no ambiguous join."""
    return a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x")), b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))


def reduce_products(products: DataFrame, s: Semiring, vtype: str, keys=("i", "j")) -> DataFrame:
    return products.groupBy(*keys).agg(s.reduce(s.combine(F.col("x"), F.col("y"))).alias("v")).select("i", "j", F.col("v").cast(vtype).alias("v"))


def result_type(a: SparseMatrix, b: SparseMatrix) -> str:
    types = {a.value_type, b.value_type}
    if "double" in types:
        return "double"
    if any(t.startswith("decimal") for t in types):
        scale = sum(int(t.split(",")[1].rstrip(")")) for t in (a.value_type, b.value_type) if t.startswith("decimal"))
        return f"decimal(38,{min(scale, 12)})"
    return "bigint"


def joinagg(a: SparseMatrix, b: SparseMatrix, s: Semiring, mask: DataFrame | None = None, hint: str | None = None, where: Column | None = None) -> DataFrame:
    x, y = sides(a, b)
    p = x.join(y.hint(hint) if hint else y, "k")
    p = p.where(where) if where is not None else p
    p = p.join(mask, ["i", "j"], "left_semi") if mask is not None else p
    return reduce_products(p, s, result_type(a, b))


def rowlocal(a: SparseMatrix, b: SparseMatrix, s: Semiring, blocks: int, mask: DataFrame | None = None, order: str = "unsorted", b_rows: int | None = None, where: Column | None = None) -> DataFrame | None:
    """None where B is too large to broadcast."""
    x, y = sides(a, b)
    small = checked_broadcast(y, b_rows)
    if small is None:
        return None
    p = x.repartition(blocks, "i").join(small, "k")
    p = p.where(where) if where is not None else p
    if mask is not None:
        p = p.join(mask.repartition(blocks, "i"), ["i", "j"], "left_semi")
    if order == "sorted":
        p = p.sortWithinPartitions("i", "j")
    return reduce_products(p, s, result_type(a, b))


def bucketed(a: SparseMatrix, blocks: int, buckets: Column | DataFrame | None) -> DataFrame:
    """A's triples with the block of their row: an expression of i, scheduled (i, bucket), or hashed."""
    x = a.df.select("i", F.col("j").alias("k"), F.col("v").alias("x"))
    if buckets is None:
        buckets = F.pmod(F.xxhash64("i"), F.lit(blocks)).cast("int")
    if isinstance(buckets, Column):
        return x.withColumn("bucket", buckets)
    return x.join(buckets.select("i", "bucket"), "i")


def fetched(x: DataFrame, b: SparseMatrix) -> DataFrame:
    """(bucket, k, j, y): each B row once for every block that needs it. Needs are dealt by k, where they
    lose their repeats and meet B, in one exchange."""
    y = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    return x.select("bucket", "k").repartition("k").distinct().join(y, "k")


def rowfetch(a: SparseMatrix, b: SparseMatrix, s: Semiring, blocks: int, buckets: Column | DataFrame | None = None, mask: DataFrame | None = None, where: Column | None = None) -> DataFrame:
    """A block is a partition of its own number: hashing the numbers would put several in one. A block's rows of A,
    never more than its work, are the hashed side; a broadcast would undo the dealing and exchange products."""
    x = bucketed(a, blocks, buckets)
    y = fetched(x, b).select(F.col("bucket").alias("own"), F.col("k").alias("inner"), "j", "y")  # renamed apart from A: Spark would rename it, but not inside the search for a block
    p = y.repartitionById(blocks, "own").join(x.repartitionById(blocks, "bucket").hint("shuffle_hash"), (F.col("own") == F.col("bucket")) & (F.col("inner") == F.col("k")))
    p = p.where(where) if where is not None else p
    p = p.join(mask, ["i", "j"], "left_semi") if mask is not None else p
    return reduce_products(p, s, result_type(a, b), ("bucket", "i", "j"))


def splithub(a: SparseMatrix, b: SparseMatrix, s: Semiring, target: int = KERNEL_WORK, mask: DataFrame | None = None) -> DataFrame:
    """Rows of more than `target` multiplications are dealt over as many salts as they hold targets; each
    salt adds up its own partial row first."""
    x, y = sides(a, b)
    hubs = row_work(a, b, all_rows=False).select("i", F.ceil(F.col("work") / F.lit(target)).cast("int").alias("cuts")).where("cuts > 1")
    x = x.join(hubs, "i", "left").withColumn("salt", F.when(F.col("cuts") > 1, F.pmod(F.xxhash64("k"), F.col("cuts"))).otherwise(F.lit(0)).cast("int"))
    p = x.join(y, "k")
    p = p.join(mask, ["i", "j"], "left_semi") if mask is not None else p
    part = p.groupBy("i", "salt", "j").agg(s.reduce(s.combine(F.col("x"), F.col("y"))).alias("v"))
    # Counts are added up; every other reduction applies to its own results again.
    again = F.sum if s.name == "plus_pair" else s.reduce
    return part.groupBy("i", "j").agg(again(F.col("v")).alias("v")).select("i", "j", F.col("v").cast(result_type(a, b)).alias("v"))


def sizes(a: SparseMatrix, b: SparseMatrix, blocks: int, buckets: Column | DataFrame | None = None) -> DataFrame:
    """(i, nnz) of the product's rows that have any entry: blocks fetch the places of B that they need, as in rowfetch, and count
    distinct ones; no product is exchanged."""
    x = bucketed(a, blocks, buckets).select("bucket", "i", "k")
    y = fetched(x, b).select(F.col("bucket").alias("own"), F.col("k").alias("inner"), "j")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        i, nnz = block_row_sizes(*(t[c].to_numpy() for t, c in ((left, "i"), (left, "k"), (right, "inner"), (right, "j"))))
        return pa.table({"i": i, "nnz": nnz})

    return x.groupBy("bucket").cogroup(y.groupBy("own")).applyInArrow(run, "i bigint, nnz bigint")


def by_twos(a: SparseMatrix, b: SparseMatrix, work: int, blocks: int | None = None) -> bool:
    """Whether blocks of rows (by work, unless given) that need rows of B from everywhere would fetch more than FETCHED entries, and packed blocks can hold both."""
    if min(work, (blocks or -(-work // BLOCK_WORK)) * b.nnz()) <= FETCHED or not {a.value_type, b.value_type} <= {"bigint", "double"}:
        return False
    return not any(m.df.where("i is null or j is null or v is null").limit(1).count() for m in (a, b))


def block_table(m: SparseMatrix, by: str, n: int, valued: bool, unit: int = 1) -> DataFrame:
    """(bucket, block), stored: M's entries in n packed blocks of whole rows (by 'i') or columns ('j'), a few bytes an entry; ids are dealt by
    hash, `unit` neighbours together, so that blocks are alike wherever entries lie."""
    def pack(batches):
        got = list(batches)
        if sum(x.num_rows for x in got):
            t = pa.Table.from_batches(got)
            v = t["v"].to_numpy() if valued else np.zeros(len(t), np.int8)
            block = squeezed(packed(t["j"].to_numpy(), t["i"].to_numpy(), v))
            yield pa.RecordBatch.from_pydict({"bucket": t["bucket"].combine_chunks()[:1], "block": pa.array([block], pa.binary())})

    dealt = m.df.select("i", "j", *["v"] * valued, F.pmod(F.xxhash64(F.col(by) if unit == 1 else F.floor(F.col(by) / unit)), F.lit(n)).cast("int").alias("bucket")).repartitionById(n, "bucket")
    out = stored(dealt.mapInArrow(pack, "bucket int, block binary"))
    del dealt
    freed_twice(m.spark)
    return out


def met_by_twos(a: SparseMatrix, b: SparseMatrix, work: int, run: Callable, schema: str, valued: bool, unit: int = 1) -> DataFrame:
    """What run(block of A's rows, block of B's columns) yields for every two of them; a task reads both from where they lie."""
    n, m = (max(1, -(-x.nnz() // PAIR_ENTRIES)) for x in (a, b))
    grow = max(1.0, math.sqrt(max(work / BLOCK_WORK, 3 * a.spark.sparkContext.defaultParallelism) / (n * m)))
    n, m = math.ceil(n * grow), math.ceil(m * grow)

    def each(batches):
        for t in batches:
            for at in range(len(t)):
                for out in run(*(opened(t[f"{side}_block"][at].as_buffer()) for side in "ab")):
                    if len(out[0]):
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in out], names)

    names = [x.split()[0] for x in schema.split(", ")]
    left, right = (block_table(x, by, k, valued, unit).repartitionById(k, "bucket").toDF(f"{side}_bucket", f"{side}_block") for x, by, k, side in ((a, "i", n, "a"), (b, "j", m, "b")))
    return left.crossJoin(right.hint("shuffle_replicate_nl")).mapInArrow(each, schema)


def pairs(a: SparseMatrix, b: SparseMatrix, s: Semiring, work: int, where: Column | None = None) -> DataFrame:
    """The product, for sums of products and counts of pairs: each two blocks make their part of it whole."""
    count = s.name == "plus_pair"
    kind = result_type(a, b)
    real = kind == "double"

    def run(x, y):
        for i, j, v in pair_products(x, y, count):
            yield i, j, v.astype(float) if real else v

    out = met_by_twos(a, b, work, run, f"i bigint, j bigint, v {kind}", not count)
    return out if where is None else out.where(where)


def pair_costs(a: SparseMatrix, b: SparseMatrix, work: int) -> DataFrame:
    """(i, work, na, nc) of the product's rows that have any entry, counted by twos of blocks and added up."""
    got = met_by_twos(a, b, work, lambda x, y: [pair_counts(x, y)], "i bigint, work bigint, na bigint, nc bigint", False)
    return got.groupBy("i").agg(F.sum("work").alias("work"), F.max("na").alias("na"), F.sum("nc").alias("nc"))


def kernel_blocks(a: SparseMatrix, b: SparseMatrix, least: int) -> int:
    """As many blocks as hold KERNEL_WORK multiplications each, `least` at least."""
    return max(least, -(-total_work(a, b) // KERNEL_WORK))


def kernel(a: SparseMatrix, b: SparseMatrix, blocks: int, accumulator: str, buckets: Column | DataFrame | None = None, lanes: int = 8, phases: int = 2, order: str = "unsorted", pool: int = 1024, stats: bool = False) -> DataFrame:
    """Blocks through an accumulator: triples, or with stats (bucket, ops, probes, peak) of each block."""
    x = bucketed(a, blocks, buckets)
    y = fetched(x, b)
    vtype = result_type(a, b)
    if vtype.startswith("decimal"):
        raise TypeError("kernels take integers and doubles; decimals go through the aggregates")
    ncols = b.ncols

    def run(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        ad = left.select(["i", "k", "x"]).sort_by([("i", "ascending"), ("k", "ascending")]).to_pydict()
        bd = right.select(["inner", "j", "y"]).sort_by([("inner", "ascending"), ("j", "ascending")]).to_pydict()
        rows: dict[int, list] = {}
        for i, k, v in zip(ad["i"], ad["k"], ad["x"], strict=True):
            rows.setdefault(i, []).append((k, v))
        bs: dict[int, tuple[list, list]] = {}
        for k, j, v in zip(bd["inner"], bd["j"], bd["y"], strict=True):
            r = bs.setdefault(k, ([], []))
            r[0].append(j), r[1].append(v)
        out, tally = multiply_block(rows.items(), bs, ncols, accumulator, lanes, phases, order, pool)
        ci, cj, cv = [], [], []
        for i, row in out:
            ci += [i] * len(row)
            cj += [c for c, _ in row]
            cv += [v for _, v in row]
        if stats:
            return pa.table({"bucket": [key[0].as_py()], "ops": [tally.ops], "probes": [tally.probes], "peak": [tally.peak]}, schema=pa.schema([("bucket", pa.int32()), ("ops", pa.int64()), ("probes", pa.int64()), ("peak", pa.int64())]))
        return pa.table({"i": pa.array(ci, pa.int64()), "j": pa.array(cj, pa.int64()), "v": pa.array(cv, pa.float64() if vtype == "double" else pa.int64())})

    schema = "bucket int, ops bigint, probes bigint, peak bigint" if stats else f"i bigint, j bigint, v {vtype}"
    y = y.select(F.col("bucket").alias("own"), F.col("k").alias("inner"), "j", "y")  # renamed apart from A, which it came from
    out = x.groupBy("bucket").cogroup(y.groupBy("own")).applyInArrow(run, schema)
    if accumulator == "pooled" and not stats:  # partial sums left the pool: added up here
        out = out.groupBy("i", "j").agg(F.sum("v").alias("v"))
    return out


__all__ = ["bucketed", "fetched", "joinagg", "kernel", "pair_costs", "pairs", "rowfetch", "rowlocal", "splithub"]
