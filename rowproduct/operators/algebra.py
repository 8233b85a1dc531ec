"""Element-wise operators, reshapes, and products with vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.semiring import PLUS_TIMES, Semiring
from ..matrix import SparseMatrix
from ..plans.cut import held
from ..plans.work import total_work
from .product import multiply


def ewise_add(a: SparseMatrix, b: SparseMatrix, sign: int = 1) -> SparseMatrix:
    """A + B or A - B: a union and one sum, so a place is exchanged once."""
    d = a.df.unionByName(b.df.select("i", "j", (F.col("v") * sign).alias("v"))).groupBy("i", "j").agg(F.sum("v").alias("v"))
    return a.with_df(d)


def ewise_mult(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    d = a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"]).select("i", "j", (F.col("v") * F.col("w")).alias("v"))
    return a.with_df(d)


def apply(m: SparseMatrix, f) -> SparseMatrix:
    return m.with_df(m.df.select("i", "j", f(F.col("v")).alias("v")), row_order=m.row_order)


def prune_below(m: SparseMatrix, least) -> SparseMatrix:
    return m.with_df(m.df.where(F.col("v") >= least), row_order=m.row_order)


def strip_diagonal(m: SparseMatrix) -> SparseMatrix:
    return m.with_df(m.df.where("i <> j"), row_order=m.row_order)


def slice_rows(m: SparseMatrix, lo: int, hi: int) -> SparseMatrix:
    return m.with_df(m.df.where((F.col("i") >= lo) & (F.col("i") < hi)), row_order=m.row_order)


def column_subset(m: SparseMatrix, cols: DataFrame) -> SparseMatrix:
    """cols (j, to): those columns, relabelled."""
    n = cols.count()
    return m.with_df(m.df.join(F.broadcast(cols) if n <= 1_000_000 else cols, "j").select("i", F.col("to").alias("j"), "v"), ncols=n)


def scale_rows(m: SparseMatrix, d: DataFrame) -> SparseMatrix:
    """d (i, d): diagonal matrix times M."""
    return m.with_df(m.df.join(d, "i").select("i", "j", (F.col("d") * F.col("v")).alias("v")))


def normalise(m: SparseMatrix, by: str) -> DataFrame:
    """(i, j, v, total, share): each value over its row's (by='i') or column's (by='j') sum."""
    t = m.df.groupBy(by).agg(F.sum("v").alias("total"))
    return m.df.join(t, by).select("i", "j", "v", "total", (F.col("v") / F.col("total")).alias("share"))


def spmv(m: SparseMatrix, x: DataFrame) -> DataFrame:
    """x (j, x) -> (i, y)"""
    return m.df.join(x, "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("y"))


def vecmat(x: DataFrame, m: SparseMatrix) -> DataFrame:
    """x (i, x) -> (j, y)"""
    return m.df.join(x, "i").groupBy("j").agg(F.sum(F.col("v") * F.col("x")).alias("y"))


def gram_rows(m: SparseMatrix, **o) -> SparseMatrix:
    return multiply(m, m.transpose(), **o)


def gram_cols(m: SparseMatrix, **o) -> SparseMatrix:
    return multiply(m.transpose(), m, **o)


def chain(a: SparseMatrix, b: SparseMatrix, c: SparseMatrix, **o) -> SparseMatrix:
    """A B C, from the side whose first product needs fewer multiplications."""
    if total_work(a, b) <= total_work(b, c):
        return multiply(multiply(a, b, **o), c, **o)
    return multiply(a, multiply(b, c, **o), **o)


def galerkin(p: SparseMatrix, a: SparseMatrix, **o) -> SparseMatrix:
    """P' A P"""
    return chain(p.transpose(), a, p, **o)


def power(m: SparseMatrix, n: int, semiring: Semiring | None = None, **o) -> SparseMatrix:
    """M**n by repeated squaring; factors are stored, and in the plain product the later square, the denser one, stands left, whose rows move once."""
    if n < 1:
        raise ValueError("power from 1")
    m, = held(m)
    o = o | ({"semiring": semiring} if semiring else {})
    out, sq = None, m
    while n:
        if n & 1:
            out = sq if out is None else multiply(sq, out, **o) if semiring in (None, PLUS_TIMES) else multiply(out, sq, **o)  # there powers of M commute
        n >>= 1
        if n:
            sq, = held(multiply(sq, sq, **o))
            out = held(out)[0] if out is not None else None
    return out


def kron(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Every block of A times B; for a small B, which goes to every executor."""
    y = b.df.select(F.col("i").alias("bi"), F.col("j").alias("bj"), F.col("v").alias("w"))
    d = a.df.crossJoin(F.broadcast(y)).select((F.col("i") * b.nrows + F.col("bi")).alias("i"), (F.col("j") * b.ncols + F.col("bj")).alias("j"), (F.col("v") * F.col("w")).alias("v"))
    return SparseMatrix(d, a.nrows * b.nrows, a.ncols * b.ncols)


def topk_per_row(m: SparseMatrix, k: int) -> SparseMatrix:
    """Each row's k largest values; ties to smaller columns."""
    w = W.partitionBy("i").orderBy(F.desc("v"), "j")
    return m.with_df(m.df.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).select("i", "j", "v"))


def row_pointers(m: SparseMatrix) -> DataFrame:
    """(i, nnz, ptr) of every row, empty ones too."""
    from ..plans.work import prefix_sum, row_sizes

    every = m.spark.range(m.nrows).withColumnRenamed("id", "i").join(row_sizes(m), "i", "left").select("i", F.coalesce("nnz", F.lit(0)).cast("bigint").alias("nnz"))
    return prefix_sum(every, ["i"], "nnz", "ptr")
