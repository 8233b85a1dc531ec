"""What the methods are compared with."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.blocks import dense_products, dense_rows
from ..functions.semiring import PLUS_TIMES
from ..matrix import SparseMatrix
from ..plans import lowering as low
from ..plans.cut import held
from ..plans.work import total_work


def plain(a: SparseMatrix, b: SparseMatrix, order: str = "unsorted") -> DataFrame:
    """Library-style product: a join and a sum as they come; the sorted mode sorts all of it."""
    c = low.joinagg(a, b, PLUS_TIMES)
    return c.orderBy("i", "j") if order == "sorted" else c


def expand_sort(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """All products written out, sorted by place, runs added."""
    x, y = low.sides(a, b)
    p = x.join(y, "k").select("i", "j", (F.col("x") * F.col("y")).alias("p"))
    return p.repartition("i").sortWithinPartitions("i", "j").groupBy("i", "j").agg(F.sum("p").alias("v"))


def pooled(a: SparseMatrix, b: SparseMatrix, pool: int = 1024, blocks: int = 8) -> DataFrame:
    """Bounded memory: chained buckets over a fixed pool, partial sums passed on when it is full; `blocks` at least, more where the work asks for it."""
    return low.kernel(a, b, low.kernel_blocks(a, b, blocks), "pooled", None, pool=pool)


def blocks(a: SparseMatrix, b: SparseMatrix, size: int = 256) -> DataFrame:
    """Dense blocks: a task holds `size` rows of A and the rows of B that they need as triples, and fills and multiplies one
    pair of blocks at a time; where these could fetch too much, packed blocks of several times `size` rows or columns meet by twos. Sums are doubles, exact for integers up to 2**53; zeros are left out."""
    a, b = held(a, b)
    work = total_work(a, b)
    if low.by_twos(a, b, work, -(-a.nrows // size)):
        return low.met_by_twos(a, b, work, lambda x, y: dense_products(x, y, size), "i bigint, j bigint, v bigint", True, size)
    x = low.bucketed(a, -(-a.nrows // size), F.floor(F.col("i") / size).cast("int"))
    y = low.fetched(x, b).select(F.col("bucket").alias("own"), F.col("k").alias("inner"), "j", "y")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        i, k, v = (left[c].to_numpy() for c in ("i", "k", "x"))
        inner, j, w = (right[c].to_numpy() for c in ("inner", "j", "y"))
        i, j, v = dense_rows(i, k, v, inner, j, w, size)
        return pa.table({"i": i, "j": j, "v": v})

    return x.groupBy("bucket").cogroup(y.groupBy("own")).applyInArrow(run, "i bigint, j bigint, v bigint")
