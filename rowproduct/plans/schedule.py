"""Which block of work a row belongs to, and how even the blocks are."""

from __future__ import annotations

from heapq import heapify, heapreplace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import table_capacity
from ..matrix import SparseMatrix
from .work import prefix_sum, row_work


def static_block(nrows: int, blocks: int) -> Column:
    """The block of row i among blocks of equal numbers of rows."""
    return F.floor(F.col("i") * blocks / F.lit(nrows)).cast("int") if nrows * blocks < 1 << 52 else F.expr(f"cast(floor(cast(i as decimal(38,0)) * {blocks} / {nrows}) as int)")


def static(rows: DataFrame, nrows: int, blocks: int) -> DataFrame:
    """Equal numbers of rows."""
    return rows.withColumn("bucket", static_block(nrows, blocks))


def place_of(starts: list[int], column: str = "i") -> Column:
    """How many of the ascending starts lie at or under the column, less one: which block holds it. A search by
    halves in an array literal, so that no join attaches blocks to rows."""
    n = len(starts)
    held = F.split(F.lit(",".join(map(str, starts))), ",").cast("array<bigint>")  # folded into one literal
    steps = F.array(*[F.lit(1 << k) for k in reversed(range(max(1, n.bit_length())))])
    found = F.aggregate(steps, F.lit(0), lambda at, step: F.when(F.get(held, at + step - 1) <= F.col(column), at + step).otherwise(at))
    return (F.coalesce(found, F.lit(0)) - F.lit(1)).cast("int")  # never null: a filter would search again


def block_starts(rows: DataFrame, nrows: int, least: int, target: int | None = None, bins: int = 1 << 15, most: int = 1 << 16) -> tuple[list[int] | None, int]:
    """First rows of contiguous blocks of nearly equal work (None beyond `most` blocks), and how many: `least`, or as
    many as hold `target` work each where that is more. Work is counted by ranges of rows, at most `bins` of them, in
    one job; ranges heavier than an eighth of a block are opened again, down to single rows. No block exceeds
    the mean by more than that eighth or its heaviest row."""
    width = 1 << max(0, (-(-nrows // bins) - 1).bit_length())

    def count(df: DataFrame, w: int) -> dict[int, tuple[int, int]]:
        lo = (F.col("i") - F.col("i") % F.lit(w)).alias("lo")
        return {r[0]: (int(r[1] or 0), w) for r in df.groupBy(lo).agg(F.sum("work")).collect()}

    held = count(rows, width)
    total = sum(w for w, _ in held.values())
    n = max(least, -(-total // target)) if target else least
    if n > most:
        return None, n
    while width > 1:
        heavy = [lo for lo, (w, wide) in held.items() if wide == width and w * 8 * n > total]
        if not heavy:
            break
        opened = F.broadcast(rows.sparkSession.createDataFrame([(lo,) for lo in heavy], "open bigint"))  # at most 8 n
        inside = rows.join(opened, F.col("i") - F.col("i") % F.lit(width) == F.col("open"), "left_semi")
        for lo in heavy:
            del held[lo]
        width = max(1, width >> 6)
        held |= count(inside, width)
    starts, before, last = [], 0, -1
    for lo in sorted(held):
        block = min(n - 1, before * n // total) if total else 0
        if block > last:
            starts.append(lo)
            last = block
        before += held[lo][0]
    return starts, n


def balanced(rows: DataFrame, blocks: int, work: str = "work") -> DataFrame:
    """Contiguous blocks of equal work. The block of a row is how many block boundaries lie at or under the
    work before it, which is one division instead of a search for each boundary."""
    p = prefix_sum(rows, ["i"], work)
    total = rows.agg(F.coalesce(F.sum(work), F.lit(0)).cast("decimal(38,0)").alias("_w"))
    share = F.expr(f"least({blocks - 1}, cast((cast(before as decimal(38,0)) * {blocks}) div _w as int))")
    return p.crossJoin(F.broadcast(total)).withColumn("bucket", F.when(F.col("_w") > 0, share).otherwise(F.lit(0)).cast("int")).drop("_w")


def chunks(nrows: int, blocks: int, policy: str, chunk: int = 1) -> list[tuple[int, int, int]]:
    """(number, first row, end) that workers take one by one: equal ones (dynamic), or an equal share of what
    is left each time (guided, at least `chunk`)."""
    out, lo = [], 0
    while lo < nrows:
        n = chunk if policy == "dynamic" else max(chunk, -(-(nrows - lo) // blocks))
        out.append((len(out), lo, min(nrows, lo + n)))
        lo += n
    return out


def chunk_work(rows: DataFrame, table: list[tuple[int, int, int]]) -> DataFrame:
    """Work of each chunk: a row finds its chunk by halving, then chunks meet their ends by number."""
    t = rows.sparkSession.createDataFrame(table, "chunk int, row_lo bigint, row_hi bigint")
    if not table:
        return t.withColumn("work", F.lit(0).cast("bigint"))
    sums = rows.withColumn("chunk", place_of([lo for _, lo, _ in table])).groupBy("chunk").agg(F.sum("work").cast("bigint").alias("work"))
    return t.join(sums, "chunk").select("chunk", "row_lo", "row_hi", "work")


def simulate(works: list[int], blocks: int) -> list[int]:
    """Load of each worker when the free one (the least loaded, then the first) takes the next chunk."""
    heap = [(0, k) for k in range(blocks)]
    heapify(heap)
    load = [0] * blocks
    for w in works:
        have, k = heap[0]
        load[k] = have + w
        heapreplace(heap, (have + w, k))
    return load


def block_table(assigned: DataFrame) -> DataFrame:
    """(bucket, row_lo, row_hi, work, max_work, max_na): row_hi is the last row."""
    return assigned.groupBy("bucket").agg(F.min("i").alias("row_lo"), F.max("i").alias("row_hi"), F.sum("work").cast("bigint").alias("work"), F.max("work").alias("max_work"), F.max("na").alias("max_na"))


def imbalance(loads: DataFrame, blocks: int) -> DataFrame:
    """Largest block's work over the mean of all blocks."""
    return loads.agg(F.max("work").alias("max_work"), F.sum("work").cast("bigint").alias("total"), (F.max("work") * F.lit(blocks) / F.sum("work")).alias("imbalance"))


def buffer_plan(a: SparseMatrix, b: SparseMatrix, blocks: int) -> DataFrame:
    """Memory of each balanced block: table slots, heap cursors, one-phase buffer (its work) and two-phase buffer (its output)."""
    from ..operators.product import symbolic

    assigned = balanced(row_work(a, b), blocks)
    sizes = symbolic(a, b)
    plan = assigned.join(sizes, "i", "left").groupBy("bucket").agg(
        F.min("i").alias("row_lo"), F.max("i").alias("row_hi"), F.sum("work").cast("bigint").alias("work"), F.max("work").alias("max_work"), F.max("na").alias("heap"), F.coalesce(F.sum("nnz"), F.lit(0)).cast("bigint").alias("exact"))
    most = f"least(max_work, cast({b.ncols} as bigint))"
    return plan.withColumn("capacity", F.expr(f"case when {most} > 0 then shiftleft(cast(1 as bigint), length(bin({most}))) else cast(1 as bigint) end"))


__all__ = ["balanced", "block_starts", "block_table", "buffer_plan", "chunk_work", "chunks", "imbalance", "place_of", "simulate", "static", "static_block", "table_capacity"]
