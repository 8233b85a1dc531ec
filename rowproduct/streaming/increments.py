"""Products and counts over streams of edges. Files arrive, `availableNow` drains them, what was
written is read back; the batch aggregate over the same rows is what each must equal."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import SparseMatrix
from ..plans.cut import new_path, remove

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream; watermarks take zoned times only."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(df: DataFrame, mode: str) -> DataFrame:
    """Runs a stream to its end and gives what it wrote: files in the folder that all executors share, since a memory table
    is the driver's. A complete batch takes the place of those before."""
    spark, out, batches = df.sparkSession, new_path(df.sparkSession, "out"), []

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{n}")
        if mode == "complete":
            for old in set(batches) - {n}:
                remove(spark, f"{out}/{old}")
            batches.clear()
        batches.append(n)

    w = df.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", new_path(spark, "state"))
    w.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(*[f"{out}/{n}" for n in sorted(set(batches))]) if batches else spark.createDataFrame([], df.schema)


def product_increment(edges: DataFrame, b: SparseMatrix) -> DataFrame:
    """C grows by dA B as edges (i, j, v) arrive: a stream-static join and a running sum."""
    y = b.df.select(F.col("i").alias("k"), F.col("j").alias("to"), F.col("v").alias("w"))
    return edges.join(y, F.col("j") == F.col("k")).groupBy("i", F.col("to").alias("j")).agg(F.sum(F.col("v") * F.col("w")).alias("v"))


def tumbling(s: DataFrame, size: str = "1 day") -> DataFrame:
    w = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", size), "user_id", "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "user_id", "event_type", "n")


def sliding(s: DataFrame, size: str = "1 day", step: str = "12 hours") -> DataFrame:
    w = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", size, step), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(s: DataFrame, gap: str = "1 hour") -> DataFrame:
    w = s.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedup_edges(s: DataFrame, keys: list[str], late: str = "30 days") -> DataFrame:
    """First sight of each key; the state lives as long as rows may be late."""
    return s.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def stateful_rows(edges: DataFrame) -> DataFrame:
    """Running row sums kept in state of our own: (i, n, total) after each batch of a row's edges."""

    def step(key, frames: Iterator[pd.DataFrame], state):
        n, total = state.get if state.exists else (0, 0)
        for f in frames:
            n, total = n + len(f), total + int(f["v"].sum())
        state.update((n, total))
        yield pd.DataFrame({"i": [key[0]], "n": [n], "total": [total]})

    return edges.groupBy("i").applyInPandasWithState(step, "i bigint, n bigint, total bigint", "n bigint, total bigint", "update", "NoTimeout")
