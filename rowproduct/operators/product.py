"""The product C = A B, row by row, and its phases."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.semiring import PLUS_PAIR, PLUS_TIMES, Semiring
from ..matrix import SparseMatrix
from ..plans import lowering as low
from ..plans.cut import cut, held
from ..plans.schedule import balanced, block_starts, place_of, static_block
from ..plans.work import row_work, total_work

ACCUMULATORS = ("auto", "advised", "engine", "sortagg", "hash", "chunk", "heap", "dense", "pooled")
LOWERINGS = ("auto", "joinagg", "rowlocal", "rowfetch", "splithub", "kernel", "pairs")


@dataclass(frozen=True)
class ProductOptions:
    """A valid combination: the heap needs sorted input, gives sorted rows and works in one phase."""

    accumulator: str = "auto"
    phases: int | str = "auto"
    order: str = "unsorted"
    schedule: str = "balanced"
    lowering: str = "auto"
    blocks: int | None = None
    lanes: int = 8

    def __post_init__(self):
        for name, value, allowed in (("accumulator", self.accumulator, ACCUMULATORS), ("lowering", self.lowering, LOWERINGS), ("order", self.order, ("sorted", "unsorted")), ("schedule", self.schedule, ("static", "balanced", "hashed"))):
            if value not in allowed:
                raise ValueError(f"{name}: {value} is none of {', '.join(allowed)}")
        if self.accumulator == "heap" and self.phases == 2:
            raise ValueError("the heap works in one phase")


def dealing(a: SparseMatrix, b: SparseMatrix, schedule: str, least: int, target: int | None):
    """What gives a row its block, and how many blocks: more than `least` where `target` work each asks for it."""
    if schedule == "balanced":
        rows = row_work(a, b, all_rows=False)
        starts, n = block_starts(rows, a.nrows, least, target)
        if starts is None:  # too many blocks for a literal: a table of rows is joined
            return balanced(rows, n), n
        return place_of(starts or [0]), n
    n = max(least, -(-total_work(a, b) // target)) if target else least
    return (static_block(a.nrows, n) if schedule == "static" else None), n


def multiply(a: SparseMatrix, b: SparseMatrix, *, accumulator: str = "auto", phases: int | str = "auto", order: str = "unsorted", schedule: str = "balanced", lowering: str = "auto",
             semiring: Semiring = PLUS_TIMES, mask: DataFrame | None = None, where: Column | None = None, blocks: int | None = None, lanes: int = 8, op: str = "AxA", source: str = "real") -> SparseMatrix:
    """C = A B.

    accumulator: 'engine' (hash aggregate), 'sortagg' (sorted products, merged), a kernel by name, or 'advised': counts of the
    product, taken first, choose by the published rules for `op` and `source` (by cost, where they have no cell).
    lowering: 'rowlocal' fetches rows by block where B is too large to broadcast.
    mask: (i, j) of places to keep, pushed below the aggregate; where: the same by a condition on i and j. 'auto' broadcasts B where its size
    allows, else fetches rows by block where that ships less than the products (or has packed blocks meet by twos, where it could ship too much), else joins.
    """
    o = ProductOptions(accumulator, phases, order, schedule, lowering, blocks, lanes)
    if a.ncols != b.nrows:
        raise ValueError(f"inner dimensions differ: {a.ncols} and {b.nrows}")
    if accumulator == "advised":
        from ..plans.advisor import advise, stats_of

        if semiring is not PLUS_TIMES or mask is not None or where is not None or lowering != "auto":
            raise ValueError("the rules are for the plain product")
        method = advise(stats_of(a, b), op, source, order).method
        if method == "inspector":
            c = Inspector(a, b).execute(a, b)
            return c.sorted_rows(blocks) if order == "sorted" else c
        return multiply(a, b, accumulator=method, order=order, schedule=schedule, blocks=blocks, lanes=lanes)
    spark = a.spark
    n = blocks or max(1, spark.sparkContext.defaultParallelism) * 3
    kernels = ("hash", "chunk", "heap", "dense", "pooled")
    mask = mask.select("i", "j").distinct() if mask is not None else None
    if accumulator in kernels:
        if semiring is not PLUS_TIMES or mask is not None or where is not None or lowering not in ("auto", "kernel"):
            raise ValueError("kernels compute the plain product")
        assigned, n = dealing(a, b, schedule, n, None if blocks else low.KERNEL_WORK)
        two = 1 if accumulator == "heap" else 2 if phases == "auto" else phases
        out = low.kernel(a, b, n, accumulator, assigned, lanes, two, order)
        # A kernel's rows leave in its own order; Spark promises none to a reader but by a sort.
        c = SparseMatrix(out, a.nrows, b.ncols)
        return c.sorted_rows(n) if order == "sorted" or accumulator == "heap" else c
    out = None
    if lowering in ("auto", "rowlocal"):
        out = low.rowlocal(a, b, semiring, n, mask, "sorted" if accumulator == "sortagg" else "unsorted", where=where)
        if out is None and lowering == "rowlocal":  # each block gets the rows of B that it needs in place of all
            lowering = "rowfetch"
    if out is None and lowering == "auto":
        work = total_work(a, b)
        lowering = "rowfetch" if work > 4 * b.nnz() else "joinagg"
        if lowering == "rowfetch" and work > low.FETCHED and mask is None and blocks is None and accumulator != "sortagg" and semiring in (PLUS_TIMES, PLUS_PAIR):
            a, b = held(a, b)
            lowering = "pairs" if low.by_twos(a, b, work) else lowering
    if out is None:
        if lowering == "pairs":
            if semiring not in (PLUS_TIMES, PLUS_PAIR) or mask is not None:
                raise ValueError("pairs of blocks sum products or count pairs, without a mask")
            a, b = held(a, b)
            out = low.pairs(a, b, semiring, total_work(a, b), where)
        elif lowering == "rowfetch":
            assigned, n = dealing(a, b, schedule, n, None if blocks else low.BLOCK_WORK)
            out = low.rowfetch(a, b, semiring, n, assigned, mask, where)
        elif lowering == "splithub":
            if where is not None:
                raise ValueError("splithub takes no condition")
            out = low.splithub(a, b, semiring, low.BLOCK_WORK, mask)
        else:
            out = low.joinagg(a, b, semiring, mask, where=where)
    c = SparseMatrix(out, a.nrows, b.ncols)
    if order == "sorted":
        # Rows lie whole in partitions already where nothing was exchanged on (i, j).
        c = c.with_df(out.sortWithinPartitions("i", "j"), row_order="sorted") if accumulator == "sortagg" and lowering != "pairs" else c.sorted_rows(n)
    return c


def symbolic(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(i, nnz): sizes of C's rows, from ids alone. Beyond BLOCK_WORK multiplications places are counted by block, and not exchanged."""
    a, b = held(a, b)
    work = total_work(a, b)
    if low.by_twos(a, b, work):
        return low.pair_costs(a, b, work).select("i", F.col("nc").alias("nnz"))
    if work > low.BLOCK_WORK:
        assigned, n = dealing(a, b, "balanced", max(1, a.spark.sparkContext.defaultParallelism) * 3, low.BLOCK_WORK)
        return low.sizes(a, b, n, assigned)
    x, y = low.sides(a, b)
    return x.select("i", "k").join(y.select("k", "j"), "k").select("i", "j").distinct().groupBy("i").agg(F.count("*").alias("nnz"))


def symbolic_approx(a: SparseMatrix, b: SparseMatrix, error: float = 0.05) -> DataFrame:
    """Sizes of C's rows by distinct-count sketches: one pass, no exchange of products."""
    x, y = low.sides(a, b)
    return x.select("i", "k").join(y.select("k", "j"), "k").groupBy("i").agg(F.approx_count_distinct("j", error).alias("nnz"))


def numeric(a: SparseMatrix, b: SparseMatrix, structure: DataFrame) -> DataFrame:
    """Values in the places of a structure (i, j); places whose values are missing are 0."""
    c = low.joinagg(a, b, PLUS_TIMES)
    return structure.select("i", "j").join(c, ["i", "j"], "left").select("i", "j", F.coalesce("v", F.lit(0)).cast(low.result_type(a, b)).alias("v"))


class Inspector:
    """Inspects two patterns once and multiplies any values that have them: the pairing of entries
    with places of the product is kept."""

    def __init__(self, a: SparseMatrix, b: SparseMatrix):
        x, y = low.sides(a, b)
        self.shape = a.nrows, b.ncols
        self.pairs = cut(x.select("i", "k").join(y.select("k", "j"), "k"))
        self.structure = cut(self.pairs.select("i", "j").distinct())

    def execute(self, a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
        x, y = low.sides(a, b)
        p = self.pairs.join(x, ["i", "k"]).join(y, ["k", "j"])
        return SparseMatrix(low.reduce_products(p, PLUS_TIMES, low.result_type(a, b)), *self.shape)


def explain_product(a: SparseMatrix, b: SparseMatrix, **options) -> str:
    """Counts, the advisor's choice and the plan of a product."""
    from ..plans.advisor import advise, stats_of

    s = stats_of(a, b)
    c = multiply(a, b, **options)
    plan = c.df._jdf.queryExecution().explainString(a.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    return f"{s}\n{advise(s, op='AxA', source='real', order=options.get('order', 'unsorted'))}\n{plan}"
