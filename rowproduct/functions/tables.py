"""Functions that SQL can call: slots, row merges, row expansion, generated edges."""

from __future__ import annotations


import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernels import SPREAD


def _pairs(a: str, b: str) -> T.StructType:
    """Types as objects: DDL text needs a session, and this module is imported before there is one."""
    return T.StructType([T.StructField(a, T.LongType()), T.StructField(b, T.LongType())])


@F.pandas_udf(T.LongType())
def slot_udf(cols: pd.Series, capacity: pd.Series) -> pd.Series:
    return (cols.astype("uint64") * SPREAD & (capacity.astype("uint64") - 1)).astype("int64")


def slot(col, capacity):
    """The same inside the engine: ids under 2**31 times the multiplier stay within 63 bits."""
    return (F.col(col) * F.lit(SPREAD)).bitwiseAND(F.col(capacity) - 1)


@F.pandas_udf(T.LongType())
def merge_rows(vals: pd.Series) -> int:
    """Grouped sum, as a Python aggregate."""
    return int(vals.sum())


@F.udtf(returnType=_pairs("j", "v"))
class ExpandRow:
    """A packed row as its entries."""

    def eval(self, cols: list[int], vals: list[int]):
        yield from zip(cols, vals, strict=True)


@F.udtf(returnType=_pairs("i", "j"))
class SynthEdges:
    """Drawn places of a generated matrix, serially: for small scales in SQL."""

    def eval(self, scale: int, edge_factor: int, kind: str):
        from ..sources.synth import _Reader, _Share

        r = _Reader({"scale": scale, "edgefactor": edge_factor, "kind": kind})
        yield from r.read(_Share(0, (1 << scale) * edge_factor))


def register(spark: SparkSession) -> None:
    spark.udtf.register("expand_row", ExpandRow)
    spark.udtf.register("synth_edges", SynthEdges)
    spark.udf.register("table_slot", slot_udf)


def sql_product(spark: SparkSession, a: str, b: str):
    """The product of two views of triples, as SQL."""
    return spark.sql(f"select x.i, y.j, sum(x.v * y.v) as v from {a} x join {b} y on x.j = y.i group by x.i, y.j")


__all__ = ["ExpandRow", "SynthEdges", "merge_rows", "register", "slot", "slot_udf", "sql_product"]
