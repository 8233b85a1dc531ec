"""Connected components over links, by alternating star contraction.

Nodes are any orderable column type. Each round is two grouped minima, combined before they move, and two
joins that send only what changes; both are dealt by a salt beside the node, so that no hub's links meet in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import cut

SALTS = 16


def _everywhere(df: DataFrame) -> DataFrame:
    return df.withColumn("z", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def connected_components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """links(a, b) -> (node, root): root is the least node reachable. Nodes without links
    do not appear; null ends and loops are ignored; empty links give an empty result."""
    e = links.select("a", "b").where("a is not null and b is not null and a <> b")
    e = cut(e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    for _ in range(max_rounds):
        # large star: whoever points to b points to the least of b's neighbourhood, where that is less than b
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        less = both.groupBy("a").agg(F.min("b").alias("m")).where("m < a").select(F.col("a").alias("b"), "m")
        salted = e.withColumn("z", F.pmod(F.xxhash64("a"), F.lit(SALTS)).cast("int"))
        large = salted.join(_everywhere(less), ["b", "z"], "left").select("a", F.coalesce("m", "b").alias("b")).distinct()
        # small star: a node and its smaller neighbours point to the least of them
        low = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("c"))
        several = _everywhere(low.where("c > 1").select("a", "m"))
        dealt = large.withColumn("z", F.pmod(F.xxhash64("b"), F.lit(SALTS)).cast("int"))
        moved = dealt.join(several, ["a", "z"]).where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        small = cut(low.select("a", F.col("m").alias("b")).unionByName(moved).distinct())
        # a forest of stars: nobody is both a child and a root, and each child has one root
        loose = small.join(small.select(F.col("b").alias("a")).distinct(), "a", "left_semi").limit(1).count()
        many = 0 if loose else small.groupBy("a").count().where("count > 1").limit(1).count()
        e = small
        if not loose and not many:
            break
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(
        e.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
