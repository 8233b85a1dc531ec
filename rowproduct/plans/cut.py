"""Cutting lineage in the folder that all executors share."""

from __future__ import annotations

import atexit
import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession

_WRITTEN: list[tuple[SparkSession, str]] = []


def _shared(spark: SparkSession) -> str:
    """The checkpoint folder, set where nobody has."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="rowproduct-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in spark.checkpoint.dir; a local folder only where that is unset and all runs in one process (tests)."""
    _shared(df.sparkSession)
    return df.checkpoint(eager=True)


def new_path(spark: SparkSession, name: str) -> str:
    """A place in the same folder, deleted when the driver's Python ends."""
    path = f"{_shared(spark)}/rowproduct-{uuid.uuid4().hex}/{name}"
    _WRITTEN.append((spark, path))
    return path


def stored(df: DataFrame) -> DataFrame:
    """As cut, in Parquet, which takes a fraction of a checkpoint's room; what led there is let go at once."""
    path = new_path(df.sparkSession, "table")
    df.write.parquet(path)
    spark, schema = df.sparkSession, df.schema
    del df
    freed(spark)
    out = spark.read.schema(schema).parquet(path)
    out._stored = path
    return out


def held(*matrices):
    """The matrices with their triples stored, each once; those that are stored already as they are."""
    done = {}
    for m in matrices:
        if id(m) not in done:
            done[id(m)] = m if getattr(m.df, "_stored", False) else m.with_df(stored(m.df), row_order=m.row_order)
    return tuple(done[id(m)] for m in matrices)


def freed(spark: SparkSession) -> None:
    """Has the driver's JVM look for shuffles that nothing can reach, whose files Spark then deletes."""
    spark.sparkContext._jvm.System.gc()


def freed_twice(spark: SparkSession) -> None:
    """As freed, also of what Python's cycles hold, or the JVM until it has looked once: a shuffle that is done often goes only then."""
    gc.collect()
    freed(spark)
    time.sleep(0.3)
    freed(spark)


def dropped(df: DataFrame) -> None:
    """Deletes the files of a stored table that nothing reads any more."""
    remove(df.sparkSession, df._stored)


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for spark, path in _WRITTEN:
        try:
            remove(spark, path.rsplit("/", 1)[0])
        except Exception:  # the JVM may have ended first
            return
