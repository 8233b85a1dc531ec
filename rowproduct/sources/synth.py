"""Generated matrices: 2**scale rows and columns, edge_factor draws a row.

Each draw walks down `scale` levels and takes a quadrant at each, uniform or skewed. A draw is the first
seven hexadecimal digits of md5(edge:level), so any engine makes the same matrix; equal places are summed.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..matrix import SparseMatrix

# Chances of the four quadrants (upper left, upper right, lower left, lower right).
KINDS = {"uniform": (0.25, 0.25, 0.25, 0.25), "skewed": (0.57, 0.19, 0.19, 0.05)}
DRAWS = 16**7


def synth(spark: SparkSession, scale: int, edge_factor: int, kind: str, seed: str = "") -> SparseMatrix:
    return placed(spark.range((1 << scale) * edge_factor), scale, kind, seed)


def events_drawn(spark: SparkSession, sf_dir: str, scale: int, kind: str) -> SparseMatrix:
    """Every event is a draw: as many edges as the table has rows."""
    return placed(spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("id")), scale, kind)


def placed(edges: DataFrame, scale: int, kind: str, seed: str = "") -> SparseMatrix:
    """edges (id): the matrix of their places."""
    a, b, c, _ = KINDS[kind]
    row, col = F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    for level in range(scale):
        u = F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.col("id").cast("string"), F.lit(f":{level}"))), 1, 7), 16, 10).cast("bigint") / F.lit(float(DRAWS))
        edges = edges.withColumn(f"u{level}", u)
        low = (F.col(f"u{level}") >= a + b).cast("bigint")
        right = (((F.col(f"u{level}") >= a) & (F.col(f"u{level}") < a + b)) | (F.col(f"u{level}") >= a + b + c)).cast("bigint")
        row, col = row * 2 + low, col * 2 + right
    n = 1 << scale
    return SparseMatrix(edges.select(row.alias("i"), col.alias("j")).groupBy("i", "j").agg(F.count("*").alias("v")), n, n)


def place(e: int, scale: int, chance: tuple) -> tuple[int, int]:
    """Where edge e falls, in plain Python."""
    a, b, c, _ = chance
    i = j = 0
    for level in range(scale):
        u = int(hashlib.md5(f"{e}:{level}".encode()).hexdigest()[:7], 16) / DRAWS
        i, j = 2 * i + (u >= a + b), 2 * j + (a <= u < a + b or u >= a + b + c)
    return i, j


class _Share(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.ef = int(options["scale"]), int(options["edgefactor"] if "edgefactor" in options else options["edgeFactor"])
        self.chance, self.parts = KINDS[options.get("kind", "uniform")], int(options.get("partitions", 8))

    def partitions(self):
        n = (1 << self.scale) * self.ef
        return [_Share(n * k // self.parts, n * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition):
        for e in range(partition.lo, partition.hi):
            yield place(e, self.scale, self.chance)


class QuadrantSource(DataSource):
    """spark.read.format('quadrants').options(scale=, edgeFactor=, kind=): the drawn places, repeats included."""

    @classmethod
    def name(cls):
        return "quadrants"

    def schema(self):
        return "i bigint, j bigint"

    def reader(self, schema):
        return _Reader(self.options)


def scan_synth(spark: SparkSession, scale: int, edge_factor: int, kind: str) -> DataFrame:
    spark.dataSource.register(QuadrantSource)
    raw = spark.read.format("quadrants").options(scale=scale, edgeFactor=edge_factor, kind=kind).load()
    return raw.groupBy("i", "j").agg(F.count("*").alias("v"))


def scan_drawn(edges: DataFrame, scale: int, kind: str) -> DataFrame:
    """edges (id): the same matrix as `placed` gives, each edge placed by the Python reader's own code as it is scanned."""
    chance = KINDS[kind]

    def run(batches):
        for b in batches:
            at = [place(e, scale, chance) for e in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_pydict({"i": pa.array([x for x, _ in at], pa.int64()), "j": pa.array([y for _, y in at], pa.int64())})

    return edges.mapInArrow(run, "i bigint, j bigint").groupBy("i", "j").agg(F.count("*").alias("v"))
