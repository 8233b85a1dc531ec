"""Experiments on time: they report, and are no oracle's business."""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .functions.kernels import multiply_block
from .matrix import SparseMatrix
from .operators.product import multiply
from .plans.schedule import balanced, chunks, simulate, static
from .plans.work import row_work


def timed(make: Callable[[], DataFrame], runs: int = 10, warm: int = 1) -> float:
    """Mean seconds of writing a plan to nowhere."""
    took = []
    for k in range(runs + warm):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return float(np.mean(took[warm:]))


def rate(work: int, seconds: float) -> float:
    """Multiplications a second."""
    return work / seconds


def schedule_probe(rows: DataFrame, policy: str, workers: int) -> float:
    """Seconds for an empty loop over the rows of a table (one bigint column), cut by a policy, a task for each chunk."""
    iterations = rows.count()
    n = workers if policy == "static" else len(chunks(iterations, workers, policy, max(1, iterations // 256)))
    return timed(lambda: rows.repartition(max(1, n)).where("spark_partition_id() < 0"), 3)


def alloc_probe(rows: DataFrame, tasks: int) -> DataFrame:
    """(task, bytes, touch_s, free_s): the values of a table's bigint column in one buffer of one task, or in private ones of
    several, each filled by its task and let go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        parts = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
        t, at = time.perf_counter(), 0
        x = np.empty(sum(map(len, parts)), np.int64)
        for p in parts:
            x[at : at + len(p)] = p
            at += len(p)
        u, size = time.perf_counter(), x.nbytes
        del x
        yield pa.RecordBatch.from_pylist([{"task": TaskContext.get().partitionId(), "bytes": size, "touch_s": u - t, "free_s": time.perf_counter() - u}])

    return rows.repartition(tasks).mapInArrow(run, "task bigint, bytes bigint, touch_s double, free_s double")


def stanza_probe(spark: SparkSession, run_bytes: int, total_bytes: int = 1 << 26, seed: int = 1) -> DataFrame:
    """(run_bytes, gb_per_s) of reading runs at random places of an array, in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _ in batches:
            x = np.ones(total_bytes // 8)
            n = max(1, run_bytes // 8)
            at = np.random.default_rng(seed).permutation(len(x) // n)[: (1 << 22) // n + 1]
            t = time.perf_counter()
            x.reshape(-1, n)[at].sum() if len(x) % n == 0 else x[: len(x) // n * n].reshape(-1, n)[at].sum()
            s = time.perf_counter() - t
            yield pa.RecordBatch.from_pylist([{"run_bytes": run_bytes, "gb_per_s": len(at) * n * 8 / s / 1e9}])

    return spark.range(0, 1, 1, 1).mapInArrow(run, "run_bytes bigint, gb_per_s double")


def strong_scaling(script: str, cores: list[int], timeout: int = 600) -> dict[int, float]:
    """Seconds under local[k] for each k, each in a process of its own: the number, or the JSON line's "value", that a
    script prints last."""
    out = {}
    for k in cores:
        got = subprocess.run([sys.executable, script], capture_output=True, text=True, timeout=timeout, env={**os.environ, "BENCH_CPUS": str(k)})
        last = json.loads(got.stdout.strip().splitlines()[-1])
        out[k] = float(last["value"] if isinstance(last, dict) else last)
    return out


def heap_ablation(a: SparseMatrix, blocks: int) -> list[tuple[str, float]]:
    """(setting, imbalance): largest load over the mean for static, dynamic, guided and balanced rows of the heap
    product, and balanced rows with private buffers, which share the balanced loads."""
    w = row_work(a, a)
    work = [r.work for r in w.orderBy("i").collect()] if a.nrows <= 1 << 20 else None  # a study's input, of bounded size
    if work is None:
        raise ValueError("a study of up to 2**20 rows")
    total = max(1, sum(work)) / blocks
    by = {"static": [r[1] for r in static(w, a.nrows, blocks).groupBy("bucket").sum("work").collect()],
          "balanced": [r[1] for r in balanced(w, blocks).groupBy("bucket").sum("work").collect()]}
    for policy in ("dynamic", "guided"):
        by[policy] = simulate([sum(work[lo:hi]) for _, lo, hi in chunks(a.nrows, blocks, policy)], blocks)
    by["balanced_private"] = by["balanced"]
    return [(k, max(v) / total) for k, v in by.items()]


def storage_modes(a: SparseMatrix, runs: int = 3) -> dict[str, float]:
    """Seconds of squaring from files, from memory and from local disk: the nearest thing to memory modes here."""
    from pyspark import StorageLevel

    out = {"files": timed(lambda: multiply(a, a).df, runs)}
    for name, level in (("memory", StorageLevel.MEMORY_ONLY), ("disk", StorageLevel.DISK_ONLY)):
        held = a.with_df(a.df.persist(level))
        held.df.count()
        out[name] = timed(lambda: multiply(held, held).df, runs)
        held.df.unpersist()
    return out


def kernel_times(rows, b, ncols: int, runs: int = 3) -> dict[str, float]:
    """Seconds of one block's product by each accumulator."""
    out = {}
    for name, lanes in (("hash", 8), ("chunk", 8), ("chunk", 16), ("heap", 8), ("dense", 8)):
        t = time.perf_counter()
        for _ in range(runs):
            for _ in multiply_block(rows, b, ncols, name, lanes, 1)[0]:
                pass
        out[name if name != "chunk" else f"chunk{lanes}"] = (time.perf_counter() - t) / runs
    return out
