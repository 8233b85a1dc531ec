"""Costs and measures of products, as DataFrames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..matrix import SparseMatrix
from .cut import freed_twice, held
from .work import row_work, total_work


def row_costs(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(i, work, na, nc) of rows that have any product; where packed blocks meet by twos all are counted at once."""
    from ..operators.product import symbolic
    from .lowering import by_twos, pair_costs

    a, b = held(a, b)
    if by_twos(a, b, work := total_work(a, b)):
        return pair_costs(a, b, work)
    return row_work(a, b, all_rows=False).join(symbolic(a, b).withColumnRenamed("nnz", "nc"), "i")


def heap_cost(floor_log: int = 0) -> Column:
    """Sum of work times log2 of the row's nonzeros; floor_log=1 charges rows of one nonzero too."""
    log = F.log2(F.col("na"))
    return F.sum(F.col("work") * (F.greatest(log, F.lit(1.0)) if floor_log else log))


def sort_cost() -> Column:
    return F.sum(F.col("nc") * F.log2(F.col("nc")))


def costs(a: SparseMatrix, b: SparseMatrix, c: float = 1.0, floor_log: int = 0) -> DataFrame:
    """One row: work, nnz of C, compression, and the cost of heap, hash with sorted and with unsorted rows."""
    spark, (a, b) = a.spark, held(a, b)  # read once for every count
    r = row_costs(a, b)
    s = r.agg(F.coalesce(F.sum("work"), F.lit(0)).cast("bigint").alias("work"), F.coalesce(F.sum("nc"), F.lit(0)).cast("bigint").alias("nnz_c"), F.coalesce(heap_cost(floor_log), F.lit(0.0)).alias("t_heap"), F.coalesce(sort_cost(), F.lit(0.0)).alias("_s"))
    unsorted = F.col("work") * F.lit(float(c))
    out = s.select("work", "nnz_c", (F.col("work") / F.col("nnz_c")).alias("cr"), F.round("t_heap", 3).alias("t_heap"), F.round(unsorted + F.col("_s"), 3).alias("t_hash_sorted"), F.round(unsorted, 3).alias("t_hash_unsorted"))
    got, schema = [tuple(x) for x in out.collect()], out.schema  # one row: nothing is counted again for whoever reads it
    del r, s, out
    freed_twice(spark)
    return spark.createDataFrame(got, schema)


def accumulator_memory(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """Most entries that one row's accumulator holds: heap, hash, dense."""
    return row_work(a, b, all_rows=False).agg(F.max("na").alias("heap"), F.max("work").alias("hash"), F.lit(b.ncols).cast("bigint").alias("dense"))


def row_profile(m: SparseMatrix) -> DataFrame:
    """Distribution of row sizes over rows with entries."""
    r = m.df.groupBy("i").agg(F.count("*").alias("n"))
    return r.agg(F.count("*").alias("rows"), F.sum("n").cast("bigint").alias("nnz"), F.max("n").alias("max_n"), F.expr("percentile(n, 0.5)").alias("median_n"), F.round(F.stddev_pop("n"), 6).alias("sd_n"), F.round(F.skewness("n"), 6).alias("skew_n"))


def skew_class(m: SparseMatrix, limit: float = 1.0) -> str:
    """'skewed' where the row sizes' deviation exceeds `limit` means, else 'uniform'; empty rows count."""
    got = m.df.groupBy("i").agg(F.count("*").alias("n")).agg(F.sum("n").alias("s"), F.sum(F.col("n") * F.col("n")).alias("q")).first()
    if not got[0]:
        return "uniform"
    mean = got[0] / m.nrows
    return "skewed" if max(0.0, got[1] / m.nrows - mean * mean) ** 0.5 > limit * mean else "uniform"


def stanza_profile(a: SparseMatrix, b: SparseMatrix, entry_bytes: int = 12) -> DataFrame:
    """(run_len, run_bytes, reads): how often a product reads a run of that many entries of B."""
    reads = a.df.groupBy("j").agg(F.count("*").alias("reads"))
    runs = b.df.groupBy("i").agg(F.count("*").alias("run_len"))
    return reads.join(runs, F.col("j") == F.col("i")).groupBy("run_len").agg(F.sum("reads").cast("bigint").alias("reads")).select("run_len", (F.col("run_len") * entry_bytes).alias("run_bytes"), "reads")


def probe_stats(a: SparseMatrix, b: SparseMatrix, accumulators=(("hash", 8), ("chunk", 8), ("chunk", 16)), blocks: int = 8) -> DataFrame:
    """(method, ops, probes, collision): mean looks at a slot or chunk for each find or insert."""
    from .lowering import kernel, kernel_blocks

    out, blocks = None, kernel_blocks(a, b, blocks)
    for name, lanes in accumulators:
        s = kernel(a, b, blocks, name, None, lanes, phases=1, stats=True)
        one = s.agg(F.sum("ops").cast("bigint").alias("ops"), F.sum("probes").cast("bigint").alias("probes")).select(F.lit(name if name != "chunk" else f"chunk{lanes}").alias("method"), "ops", "probes", (F.col("probes") / F.col("ops")).alias("collision"))
        out = one if out is None else out.unionByName(one)
    return out


# Measures over (problem, method, cost)

def scores(times: DataFrame) -> DataFrame:
    """Cost over the best cost on the problem."""
    return times.withColumn("score", F.col("cost") / F.min("cost").over(W.partitionBy("problem")))


def performance_profile(times: DataFrame, taus) -> DataFrame:
    """(method, tau, share): share of problems on which a method is within tau of the best."""
    t = F.broadcast(times.sparkSession.createDataFrame([(float(x),) for x in taus], "tau double"))
    n = times.select("problem").distinct().agg(F.count("*").alias("n"))
    hit = scores(times).crossJoin(t).groupBy("method", "tau").agg(F.sum((F.col("score") <= F.col("tau")).cast("bigint")).alias("hits"))
    return hit.crossJoin(n).select("method", "tau", (F.col("hits") / F.col("n")).alias("share"))


def win_share(times: DataFrame) -> DataFrame:
    """(method, wins, problems, worst): problems where a method is best, and its worst score."""
    return scores(times).groupBy("method").agg(F.sum((F.col("score") == 1).cast("bigint")).alias("wins"), F.count("*").alias("problems"), F.round(F.max("score"), 6).alias("worst"))


def harmonic_mean(df: DataFrame, value: str) -> DataFrame:
    return df.agg((F.count(value) / F.sum(1 / F.col(value))).alias("harmonic_mean"))


def trend(df: DataFrame, x: str, y: str, by: str) -> DataFrame:
    """Straight line of y on x by group."""
    return df.groupBy(by).agg(F.round(F.regr_slope(y, x), 6).alias("slope"), F.round(F.regr_intercept(y, x), 6).alias("intercept"))
