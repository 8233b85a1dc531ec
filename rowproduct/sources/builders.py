"""Matrices over the given tables. Dimensions come from key domains, not from the entries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import SparseMatrix
from ..plans.work import global_lead


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def key_id(c: Column) -> Column:
    """A 60-bit id of a string: no dictionary, no order."""
    return F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("bigint")


HASHED = 1 << 60


def _count(spark, sf_dir, name, key) -> int:
    return int(table(spark, sf_dir, name).agg(F.max(key)).first()[0] or 0) + 1


def _lines(spark, sf_dir, *cols) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(*cols)


def order_part(spark, sf_dir) -> SparseMatrix:
    d = _lines(spark, sf_dir, F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_quantity").cast("bigint").alias("v"))
    return SparseMatrix(d.groupBy("i", "j").agg(F.sum("v").alias("v")), _count(spark, sf_dir, "orders", "o_orderkey"), _count(spark, sf_dir, "part", "p_partkey"))


def part_supp(spark, sf_dir) -> SparseMatrix:
    d = _lines(spark, sf_dir, F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j"), F.col("l_quantity").cast("bigint").alias("v"))
    return SparseMatrix(d.groupBy("i", "j").agg(F.sum("v").alias("v")), _count(spark, sf_dir, "part", "p_partkey"), _count(spark, sf_dir, "supplier", "s_suppkey"))


def cust_part(spark, sf_dir) -> SparseMatrix:
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("i"))
    d = _lines(spark, sf_dir, "l_orderkey", F.col("l_partkey").alias("j"), F.col("l_quantity").cast("bigint").alias("v"))
    d = d.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return SparseMatrix(d.groupBy("i", "j").agg(F.sum("v").alias("v")), _count(spark, sf_dir, "customer", "c_custkey"), _count(spark, sf_dir, "part", "p_partkey"))


def _follow(spark, sf_dir, key: str) -> DataFrame:
    a = _lines(spark, sf_dir, F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("n"), F.col(key).alias("i"), F.col("l_quantity").cast("bigint").alias("q"))
    b = _lines(spark, sf_dir, F.col("l_orderkey").alias("o"), (F.col("l_linenumber") - 1).alias("n"), F.col(key).alias("j"))
    return a.join(b, ["o", "n"]).where("i <> j")


def part_follow(spark, sf_dir) -> SparseMatrix:
    n = _count(spark, sf_dir, "part", "p_partkey")
    return SparseMatrix(_follow(spark, sf_dir, "l_partkey").groupBy("i", "j").agg(F.sum("q").alias("v")), n, n)


def supplier_follow(spark, sf_dir) -> SparseMatrix:
    n = _count(spark, sf_dir, "supplier", "s_suppkey")
    return SparseMatrix(_follow(spark, sf_dir, "l_suppkey").groupBy("i", "j").agg(F.count("*").alias("v")), n, n)


def copurchase(spark, sf_dir) -> SparseMatrix:
    n = _count(spark, sf_dir, "part", "p_partkey")
    parts = _lines(spark, sf_dir, "l_orderkey", "l_partkey").where("l_orderkey is not null").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("p"))  # dealt once, where a join deals each side
    p = parts.select(F.explode("p").alias("i"), "p").select("i", F.explode("p").alias("j")).where("i <> j")
    return SparseMatrix(p.distinct().withColumn("v", F.lit(1).cast("bigint")), n, n)


def symmetric(m: SparseMatrix) -> SparseMatrix:
    """Undirected pattern: both directions, no loops, ones."""
    both = F.inline(F.array(F.struct("i", "j"), F.struct(F.col("j").alias("i"), F.col("i").alias("j"))))  # M is made once, not once each way
    d = m.df.where("i <> j").select(both).distinct()
    return m.with_df(d.withColumn("v", F.lit(1).cast("bigint")))


def follow_sym(spark, sf_dir) -> SparseMatrix:
    return symmetric(part_follow(spark, sf_dir))


def user_next(spark, sf_dir) -> SparseMatrix:
    e = table(spark, sf_dir, "events").select("ts", "event_id", F.col("user_id").alias("i"))
    n = _count(spark, sf_dir, "events", "user_id")
    d = global_lead(e, ["ts", "event_id"], "i", "j").where("j is not null")
    return SparseMatrix(d.groupBy("i", "j").agg(F.count("*").alias("v")), n, n)


# The event types, in id order.
EVENT_TYPES = ("click", "purchase", "refund", "signup", "view")


def event_type_id(c: str = "event_type") -> Column:
    out = F.lit(None).cast("bigint")
    for k, t in enumerate(EVENT_TYPES):
        out = F.when(F.col(c) == t, F.lit(k).cast("bigint")).otherwise(out)
    return out


def user_type(spark, sf_dir) -> SparseMatrix:
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("i"), event_type_id().alias("j")).where("j is not null")
    return SparseMatrix(e.groupBy("i", "j").agg(F.count("*").alias("v")), _count(spark, sf_dir, "events", "user_id"), len(EVENT_TYPES))


def tokens(text: str = "text") -> Column:
    return F.filter(F.regexp_extract_all(F.lower(F.col(text)), F.lit("[a-z]+"), F.lit(0)), lambda x: F.length(x) > 2)


def doc_terms(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("i"), F.explode(tokens()).alias("term"))
    return d.groupBy("i", "term").agg(F.count("*").alias("v"))


def doc_term(spark, sf_dir) -> SparseMatrix:
    d = doc_terms(spark, sf_dir).select("i", key_id(F.col("term")).alias("j"), "v")
    return SparseMatrix(d, _count(spark, sf_dir, "documents", "doc_id"), HASHED)


def term_bigram(spark, sf_dir) -> SparseMatrix:
    t = table(spark, sf_dir, "documents").where("lang = 'en'").select(tokens().alias("w"))
    pairs = F.arrays_zip(F.col("w").alias("a"), F.slice("w", 2, F.greatest(F.size("w"), F.lit(1))).alias("b"))
    d = t.select(F.explode(pairs).alias("p")).select(F.col("p.a").alias("a"), F.col("p.b").alias("b")).where("b is not null")
    d = d.groupBy("a", "b").agg(F.count("*").alias("v"))
    return SparseMatrix(d.select(key_id(F.col("a")).alias("i"), key_id(F.col("b")).alias("j"), "v"), HASHED, HASHED)


def page_anchor(spark, sf_dir) -> SparseMatrix:
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("i"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("h"))
    d = p.groupBy("i", "h").agg(F.count("*").alias("v")).select("i", key_id(F.col("h")).alias("j"), "v")
    return SparseMatrix(d, _count(spark, sf_dir, "pages", "page_id"), HASHED)


def embed_rows(spark, sf_dir, least: float | None = None) -> SparseMatrix:
    """Values in millionths, so that sums are exact in any order."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("i"), F.posexplode("embedding").alias("j", "x"))
    e = e.select("i", F.col("j").cast("bigint").alias("j"), F.floor(F.col("x").cast("double") * 1000000 + 0.5).cast("bigint").alias("v"))
    e = e if least is None else e.where(F.abs("v") >= int(least * 1000000))
    return SparseMatrix(e, _count(spark, sf_dir, "embeddings", "vec_id"), 64)


def _incidence(spark, sf_dir, name: str, i: str, j: str, other: str, okey: str) -> SparseMatrix:
    d = table(spark, sf_dir, name).select(F.col(i).cast("bigint").alias("i"), F.col(j).cast("bigint").alias("j"), F.lit(1).cast("bigint").alias("v"))
    return SparseMatrix(d, _count(spark, sf_dir, name, i), _count(spark, sf_dir, other, okey))


def nation_region(spark, sf_dir) -> SparseMatrix:
    return _incidence(spark, sf_dir, "nation", "n_nationkey", "n_regionkey", "region", "r_regionkey")


def cust_nation(spark, sf_dir) -> SparseMatrix:
    return _incidence(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "nation", "n_nationkey")


def supp_nation(spark, sf_dir) -> SparseMatrix:
    return _incidence(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey", "nation", "n_nationkey")


def cust_month(spark, sf_dir) -> SparseMatrix:
    """Orders by customer and month since 1992."""
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("i"), ((F.year("o_orderdate") - 1992) * 12 + F.month("o_orderdate") - 1).cast("bigint").alias("j"))
    return SparseMatrix(o.groupBy("i", "j").agg(F.count("*").alias("v")), _count(spark, sf_dir, "customer", "c_custkey"), 12 * 20)


def user_propkey(spark, sf_dir) -> SparseMatrix:
    """Events by user and the number that their JSON holds under k."""
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("bigint").alias("j")).where("j is not null")
    return SparseMatrix(e.groupBy("i", "j").agg(F.count("*").alias("v")), _count(spark, sf_dir, "events", "user_id"), 1 << 31)


BUILDERS: dict[str, Callable] = {f.__name__: f for f in (order_part, part_supp, cust_part, part_follow, supplier_follow, copurchase, follow_sym, user_next, user_type, doc_term, term_bigram, page_anchor, embed_rows, nation_region, cust_nation, supp_nation, cust_month, user_propkey)}
