"""Which method for which product: the published rules as data, and the cost formulas beside them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..matrix import SparseMatrix
from .cost import costs, skew_class
from .cut import held
from .work import row_work

# Fixed values: (source, operation, row order, class, skew, method). Classes part at a compression
# ratio of 2 for real data and at 8 entries a row for synthetic data; both bounds belong to the lower class.
RECIPE = (
    ("real", "AxA", "sorted", "high", "any", "hash"),
    ("real", "AxA", "sorted", "low", "any", "hash"),
    ("real", "AxA", "unsorted", "high", "any", "inspector"),
    ("real", "AxA", "unsorted", "low", "any", "hash"),
    ("real", "LxU", "sorted", "high", "any", "hash"),
    ("real", "LxU", "sorted", "low", "any", "heap"),
    ("synthetic", "AxA", "sorted", "sparse", "uniform", "heap"),
    ("synthetic", "AxA", "sorted", "sparse", "skewed", "heap"),
    ("synthetic", "AxA", "sorted", "dense", "uniform", "heap"),
    ("synthetic", "AxA", "sorted", "dense", "skewed", "hash"),
    ("synthetic", "AxA", "unsorted", "sparse", "uniform", "chunk"),
    ("synthetic", "AxA", "unsorted", "sparse", "skewed", "chunk"),
    ("synthetic", "AxA", "unsorted", "dense", "uniform", "chunk"),
    ("synthetic", "AxA", "unsorted", "dense", "skewed", "hash"),
    ("synthetic", "tall", "sorted", "sparse", "skewed", "hash"),
    ("synthetic", "tall", "sorted", "dense", "skewed", "chunk"),
    ("synthetic", "tall", "unsorted", "sparse", "skewed", "hash"),
    ("synthetic", "tall", "unsorted", "dense", "skewed", "hash"),
)
CR_LIMIT, EF_LIMIT = 2.0, 8.0


@dataclass(frozen=True)
class ProductStats:
    nnz_a: int
    nnz_b: int
    work: int
    nnz_c: int
    cr: float
    edge_factor: float
    skew: str
    max_work: int
    t_heap: float
    t_hash_sorted: float
    t_hash_unsorted: float


@dataclass(frozen=True)
class Choice:
    """recipe_choice is None where the rules have no cell; `method` is the recipe's where there is one."""

    recipe_choice: str | None
    cost_choice: str
    basis: str
    method: str
    reason: str


def stats_of(a: SparseMatrix, b: SparseMatrix) -> ProductStats:
    a, b = held(a, b)
    c = costs(a, b).first()
    most = row_work(a, b, all_rows=False).agg({"work": "max"}).first()[0] or 0
    na = a.nnz()
    return ProductStats(na, b.nnz(), c.work, c.nnz_c, c.cr or 1.0, na / max(1, a.nrows), skew_class(a), most, c.t_heap, c.t_hash_sorted, c.t_hash_unsorted)


def advise(s: ProductStats, op: str = "AxA", source: str = "real", order: str = "unsorted", edge_factor: float | None = None) -> Choice:
    """op: 'AxA', 'LxU' or 'tall'. Synthetic data are judged by their nominal edge factor where it is given."""
    ef = edge_factor if edge_factor is not None else s.edge_factor
    cls = ("low" if s.cr <= CR_LIMIT else "high") if source == "real" else ("sparse" if ef <= EF_LIMIT else "dense")
    cell = next((r[5] for r in RECIPE if r[:4] == (source, op, order, cls) and r[4] in ("any", s.skew)), None)
    hash_cost = s.t_hash_sorted if order == "sorted" else s.t_hash_unsorted
    by_cost = "heap" if s.t_heap < hash_cost else "hash"
    reason = f"{op} {order}, {cls} ({'ratio %.3g' % s.cr if source == 'real' else 'edge factor %.3g' % ef}), {s.skew} rows; heap {s.t_heap:.0f}, hash {hash_cost:.0f}"
    return Choice(cell, by_cost, "recipe" if cell else "cost", cell or by_cost, reason)


def recipe_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(RECIPE), "source string, op string, row_order string, class string, skew string, method string")
