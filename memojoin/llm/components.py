"""Connected components of a link table, by alternating star contractions.

Each round links every node's larger neighbours to its smallest one, then its smaller neighbours likewise, and
writes the links to the shared folder; it ends when the links are stars. Smallest neighbours are aggregates
(combined before the shuffle), and the joins that bring them back are sort-merge joins, whose hot keys Spark may
split. No links reach the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import materialise

MAX_ROUNDS = 60


def _both(e: DataFrame) -> DataFrame:
    return e.select(F.explode(F.array(F.struct(F.col("a").alias("u"), F.col("b").alias("v")), F.struct(F.col("b").alias("u"), F.col("a").alias("v")))).alias("e")).select("e.u", "e.v")


def _large_star(e: DataFrame) -> DataFrame:
    n = _both(e)
    low = n.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return n.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(e: DataFrame) -> DataFrame:
    n = e.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    low = n.groupBy("u").agg(F.min("v").alias("m"))
    linked = n.join(low, "u")
    return linked.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(linked.select(F.col("u").alias("a"), F.col("m").alias("b"))).where("a <> b").distinct()


def _settled(e: DataFrame) -> bool:
    """Whether the links are stars already: every node hangs on one other, and none on a node that hangs itself."""
    ends = e.select(F.explode(F.array(F.struct(F.col("a").alias("u"), F.lit(1).alias("low")), F.struct(F.col("b").alias("u"), F.lit(0).alias("low")))).alias("x")).select("x.*")
    roles = ends.groupBy("u").agg(F.sum("low").alias("below"), F.min("low").alias("top"))
    return not roles.where("below > 1 OR (below = 1 AND top = 0)").take(1)


def components(links: DataFrame) -> DataFrame:
    """node, component (its smallest reachable node) for every node of links (a, b); links to oneself count not."""
    e = links.select("a", "b").where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    e = materialise(e, "links")
    for _ in range(MAX_ROUNDS):
        if _settled(e):
            break
        e = materialise(_small_star(_large_star(e)), "links")
    else:
        raise RuntimeError("components did not settle")
    return e.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("component")).unionByName(e.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
