"""Sparse matrix products over DataFrames: methods, schedules, costs, advice and workloads."""

from .matrix import SparseMatrix
from .operators.product import multiply
from .plans.advisor import advise

__all__ = ["SparseMatrix", "advise", "multiply"]
