"""Scalar operations of a product: how a pair combines, how a place's pairs reduce."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    name: str
    combine: Callable[[Column, Column], Column]
    reduce: Callable[[Column], Column]


PLUS_TIMES = Semiring("plus_times", lambda a, b: a * b, F.sum)
OR_AND = Semiring("or_and", lambda a, b: F.lit(1).cast("bigint"), F.max)
PLUS_PAIR = Semiring("plus_pair", lambda a, b: F.lit(1).cast("bigint"), F.sum)
MIN_PLUS = Semiring("min_plus", lambda a, b: a + b, F.min)
MAX_TIMES = Semiring("max_times", lambda a, b: a * b, F.max)
