"""Triples in files: columnar, line-based and coordinate text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import SparseMatrix

SCHEMA = "i bigint, j bigint, v bigint"


def write_triples(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    df.select("i", "j", "v").write.mode("overwrite").format(fmt).save(path)


def read_triples(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = SCHEMA) -> DataFrame:
    return spark.read.format(fmt).schema(schema).load(path)


def write_row_blocks(assigned: DataFrame, path: str) -> None:
    """Triples with their block, a folder for each block: a reader of some blocks reads no others."""
    assigned.select("i", "j", "v", "bucket").repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed by row, so that products on i find their rows together."""
    df.select("i", "j", "v").write.mode("overwrite").bucketBy(buckets, "i").sortBy("i", "j").saveAsTable(name)


def write_coordinate_text(m: SparseMatrix, path: str) -> None:
    """Coordinate text: a comment line, one line of sizes, then places from 1. Parts are read back in any order."""
    head = m.spark.createDataFrame([("%%MatrixMarket matrix coordinate integer general",), (f"{m.nrows} {m.ncols} {m.nnz()}",)], "value string").coalesce(1)
    lines = m.df.select(F.concat_ws(" ", F.col("i") + 1, F.col("j") + 1, "v").alias("value"))
    head.write.mode("overwrite").text(f"{path}/head")
    lines.write.mode("overwrite").text(f"{path}/entries")


def read_coordinate_text(spark: SparkSession, head: str, entries: str) -> SparseMatrix:
    """Also single files: give the same path twice; the size line is then the first that is no comment."""
    sizes = spark.read.text(head).where("value not like '\\%%' and value <> ''").first()[0].split()
    own = spark.read.text(entries).where("value not like '\\%%' and value <> ''")
    own = own.where(F.col("value") != " ".join(sizes)) if head == entries else own
    p = F.split("value", r"\s+")
    d = own.select((p[0].cast("bigint") - 1).alias("i"), (p[1].cast("bigint") - 1).alias("j"), F.coalesce(F.get(p, F.lit(2)).cast("bigint"), F.lit(1)).cast("bigint").alias("v"))
    return SparseMatrix(d, int(sizes[0]), int(sizes[1]))
