"""Sparse matrices as DataFrames of triples (i, j, v), unique by place."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SparseMatrix:
    """df(i BIGINT, j BIGINT, v) with its shape; row_order says whether each row lies by rising column.

    Dimensions are part of the value and never inferred from ids, so empty rows and columns count."""

    df: DataFrame
    nrows: int
    ncols: int
    row_order: str = "unsorted"

    @property
    def spark(self):
        return self.df.sparkSession

    @property
    def value_type(self) -> str:
        return dict(self.df.dtypes)["v"]

    def with_df(self, df: DataFrame, **changes) -> "SparseMatrix":
        return replace(self, **({"df": df, "row_order": "unsorted"} | changes))

    def transpose(self) -> "SparseMatrix":
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.ncols, self.nrows)

    def nnz(self) -> int:
        return self.df.count()

    def sorted_rows(self, blocks: int | None = None) -> "SparseMatrix":
        """Rows whole in a partition, each by rising column."""
        parts = self.df.repartition(blocks, "i") if blocks else self.df.repartition("i")
        return self.with_df(parts.sortWithinPartitions("i", "j"), row_order="sorted")


def clean(df: DataFrame, keep_zeros: bool = True) -> DataFrame:
    """Triples without nulls; several values of a place are summed. keep_zeros=False drops zeros that were
    stored as such; zeros that a product makes by cancelling always stay."""
    d = df.where("i is not null and j is not null and v is not null").groupBy("i", "j").agg(F.sum("v").alias("v"))
    return d if keep_zeros else d.where("v <> 0")


def to_rows(m: SparseMatrix, order: str = "sorted") -> DataFrame:
    """(i, cols, vals): a row each, its columns rising if order is 'sorted'."""
    packed = F.collect_list(F.struct("j", "v"))
    packed = F.array_sort(packed) if order == "sorted" else packed
    return m.df.groupBy("i").agg(packed.alias("r")).select("i", F.col("r.j").alias("cols"), F.col("r.v").alias("vals"))


def to_triples(rows: DataFrame) -> DataFrame:
    return rows.select("i", F.inline(F.arrays_zip("cols", "vals"))).toDF("i", "j", "v")


def to_map_rows(m: SparseMatrix) -> DataFrame:
    return m.df.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("j", "v"))).alias("row"))


def map_row_add(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sum of two matrices of map rows."""
    add = lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0))
    empty = F.map_from_arrays(F.array().cast("array<bigint>"), F.array().cast("array<bigint>"))
    both = a.withColumnRenamed("row", "x").join(b.withColumnRenamed("row", "y"), "i", "full")
    return both.select("i", F.map_zip_with(F.coalesce("x", empty), F.coalesce("y", empty), add).alias("row"))


def densify(m: SparseMatrix) -> DataFrame:
    """(i, row): dense arrays of ncols values, for matrices of few columns."""
    at = F.map_from_entries(F.collect_list(F.struct("j", "v")))
    got = m.df.groupBy("i").agg(at.alias("m"))
    cells = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(m.ncols - 1).cast("bigint")), lambda j: F.coalesce(F.element_at("m", j), F.lit(0)))
    return m.spark.range(m.nrows).withColumnRenamed("id", "i").join(got, "i", "left").select("i", F.when(F.col("m").isNull(), F.array_repeat(F.lit(0).cast(m.value_type), m.ncols)).otherwise(cells).alias("row"))


def permute_columns(m: SparseMatrix, seed: int) -> SparseMatrix:
    """Columns relabelled at random: their ranks by md5 of seed and id. Only occurring columns move."""
    from .plans.work import number_rows

    cols = m.df.select("j").distinct()
    ranked = number_rows(cols.withColumn("h", F.md5(F.concat(F.lit(f"{seed}:"), F.col("j").cast("string")))), ["h", "j"], "to")
    home = number_rows(cols.withColumnRenamed("j", "label"), ["label"], "to")
    pairs = ranked.join(home, "to").select("j", "label")
    return m.with_df(m.df.join(pairs, "j").select("i", F.col("label").alias("j"), "v"))


def shuffle_within_rows(rows: DataFrame, seed: int) -> DataFrame:
    """Packed rows in another column order, the same for equal seeds."""
    r = F.array_sort(F.transform(F.arrays_zip("cols", "vals"), lambda x: F.struct(F.xxhash64(x["cols"], F.lit(seed)).alias("h"), x["cols"].alias("c"), x["vals"].alias("v"))))
    return rows.select("i", r.alias("r")).select("i", F.col("r.c").alias("cols"), F.col("r.v").alias("vals"))


def require_sorted(rows: DataFrame) -> DataFrame:
    """The packed rows, or an error at the first whose columns do not rise."""
    ok = F.col("cols") == F.array_sort("cols")
    return rows.withColumn("cols", F.when(ok, F.col("cols")).otherwise(F.raise_error(F.concat(F.lit("row is not sorted: "), F.col("i").cast("string")))))


def dot_packed(a_cols, a_vals, b_cols, b_vals) -> Column:
    """Product of two packed rows of equal columns."""
    return F.aggregate(F.zip_with(a_vals, b_vals, lambda x, y: x * y), F.lit(0).cast("bigint"), lambda s, x: s + x)


def same_product(a: DataFrame, b: DataFrame) -> bool:
    """Equality of two matrices, either way round."""
    x, y = a.select("i", "j", "v"), b.select("i", "j", "v")
    return not x.exceptAll(y).limit(1).count() and not y.exceptAll(x).limit(1).count()
