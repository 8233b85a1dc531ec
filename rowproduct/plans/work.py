"""Work counts, prefix sums over all rows, and dense numbering, without a one-task window."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..matrix import SparseMatrix
from .cut import cut

#: Rows that a broadcast may have; beyond it a plan takes its shuffled form.
BROADCAST_ROWS = 2_000_000


def row_sizes(m: SparseMatrix) -> DataFrame:
    return m.df.groupBy("i").agg(F.count("*").alias("nnz"))


def row_work(a: SparseMatrix, b: SparseMatrix, all_rows: bool = True) -> DataFrame:
    """(i, work, na): multiplications of each row and its nonzeros, from ids and row sizes alone."""
    if a.ncols != b.nrows:
        raise ValueError(f"inner dimensions differ: {a.ncols} and {b.nrows}")
    sizes = row_sizes(b).withColumnRenamed("i", "j")
    w = a.df.select("i", "j").join(sizes, "j", "left").groupBy("i").agg(F.sum(F.coalesce("nnz", F.lit(0))).cast("bigint").alias("work"), F.count("*").alias("na"))
    if not all_rows:
        return w
    every = a.spark.range(a.nrows).withColumnRenamed("id", "i")
    return every.join(w, "i", "left").select("i", F.coalesce("work", F.lit(0).cast("bigint")).alias("work"), F.coalesce("na", F.lit(0).cast("bigint")).alias("na"))


def total_work(a: SparseMatrix, b: SparseMatrix) -> int:
    """Sum over inner ids of column size times row size: no row is needed."""
    ca = a.df.groupBy("j").agg(F.count("*").alias("x"))
    got = ca.join(row_sizes(b), ca.j == F.col("i")).agg(F.sum(F.col("x") * F.col("nnz"))).first()[0]
    return int(got or 0)


def prefix_sum(df: DataFrame, order: list[str], value: str, out: str = "before", parts: int | None = None) -> DataFrame:
    """df with the exclusive running sum of value in the given order, in two levels: inside range
    partitions, then over the partitions' totals, of which there is one each."""
    n = parts or max(1, df.sparkSession.sparkContext.defaultParallelism)
    ranged = df.repartitionByRange(n, *order).withColumn("_p", F.spark_partition_id())
    ranged = cut(ranged)  # the range bounds are sampled: all that follows must see one dealing
    inside = W.partitionBy("_p").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    totals = ranged.groupBy("_p").agg(F.sum(value).alias("_t"))
    ahead = totals.select("_p", (F.sum("_t").over(W.partitionBy(F.lit(0)).orderBy("_p")) - F.col("_t")).alias("_a"))  # as many rows as partitions
    return (ranged.withColumn("_s", F.coalesce(F.sum(value).over(inside), F.lit(0))).join(F.broadcast(ahead), "_p")
            .withColumn(out, (F.col("_a") + F.col("_s")).cast("bigint")).drop("_p", "_a", "_s"))


def number_rows(df: DataFrame, order: list[str], out: str = "id") -> DataFrame:
    """df with dense numbers from 0 in the given order."""
    return prefix_sum(df.withColumn("_one", F.lit(1)), order, "_one", out).drop("_one")


def global_lead(df: DataFrame, order: list[str], value: str, out: str) -> DataFrame:
    """df with the next row's value in the given order over all rows: inside range partitions, and over
    their borders through each partition's first row."""
    n = max(1, df.sparkSession.sparkContext.defaultParallelism)
    ranged = df.repartitionByRange(n, *order).withColumn("_p", F.spark_partition_id())
    ranged = cut(ranged)
    w = W.partitionBy("_p").orderBy(*order)
    first = ranged.groupBy("_p").agg(F.min_by(value, F.struct(*order)).alias("_f"))
    after = first.select("_p", F.lead("_f").over(W.partitionBy(F.lit(0)).orderBy("_p")).alias("_n"))  # as many rows as partitions
    own = ranged.withColumn("_l", F.lead(value).over(w)).withColumn("_last", F.lead(F.lit(1)).over(w).isNull())
    return own.join(F.broadcast(after), "_p").withColumn(out, F.when(F.col("_last"), F.col("_n")).otherwise(F.col("_l"))).drop("_p", "_l", "_last", "_n")


def lower_bound(prefix: DataFrame, key: str, before: str, values: list[int]) -> DataFrame:
    """(value, key): the least key whose prefix is at least each value; null if none is. values: as many as blocks."""
    v = prefix.sparkSession.createDataFrame([(int(x),) for x in values], "value bigint")
    hit = prefix.join(F.broadcast(v), F.col(before) >= F.col("value")).groupBy("value").agg(F.min(key).alias(key))
    return v.join(hit, "value", "left")


def checked_broadcast(df: DataFrame, rows: int | None = None, most: int = BROADCAST_ROWS) -> DataFrame | None:
    """df marked for broadcast if it has at most `most` rows, else None."""
    n = df.limit(most + 1).count() if rows is None else rows
    return F.broadcast(df) if n <= most else None
