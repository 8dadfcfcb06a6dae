"""Measures over results and data: skew, hit rates, independence, spill."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def skew_profile(df: DataFrame, column: str) -> DataFrame:
    """values, rows, max_count, avg_count, p50_count, second_moment_share (1/values if even, 1 if all equal)."""
    c = df.groupBy(column).agg(F.count(F.lit(1)).alias("c"))
    return c.agg(
        F.count(F.lit(1)).alias("values"), F.coalesce(F.sum("c"), F.lit(0)).alias("rows"), F.max("c").alias("max_count"), F.avg("c").alias("avg_count"), F.percentile_approx("c", 0.5).alias("p50_count"),
        (F.sum((F.col("c") * F.col("c")).cast("double")) / F.pow(F.sum("c").cast("double"), F.lit(2.0))).alias("second_moment_share"),
    )


def heavy_hitters(df: DataFrame, column: str, k: int = 10) -> DataFrame:
    """The k most frequent values: a top-k report."""
    return df.groupBy(column).agg(F.count(F.lit(1)).alias("c")).orderBy(F.desc("c"), column).limit(k)


def hit_account(frontier: DataFrame, adhesion: list[str]) -> DataFrame:
    """entries, misses, hits that demanding the adhesion of every row of a frontier gives an unbounded memo."""
    total = frontier.groupBy(*adhesion).agg(F.count(F.lit(1)).alias("c"))
    return total.agg(F.coalesce(F.sum("c"), F.lit(0)).cast("long").alias("entries"), F.count(F.lit(1)).alias("misses"), F.coalesce(F.sum(F.col("c") - 1), F.lit(0)).cast("long").alias("hits"))


def hit_curve(frontier: DataFrame, adhesion: list[str], buckets: int = 100) -> DataFrame:
    """How hits grow with the number of cached keys, the most demanded first, in buckets of equally many keys."""
    c = frontier.groupBy(*adhesion).agg(F.count(F.lit(1)).alias("c"))
    by_count = c.groupBy("c").agg(F.count(F.lit(1)).alias("keys"))  # few rows: one for each multiplicity
    w = Window.orderBy(F.desc("c")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return by_count.select(F.sum("keys").over(w).alias("cached_keys"), F.sum(F.col("keys") * (F.col("c") - 1)).over(w).alias("hits"))


def check_mvd(result: DataFrame, adhesion: list[str], inside: list[str]) -> bool:
    """Whether, for each value of the adhesion, the subtree's variables are independent of the others."""
    rest = [c for c in result.columns if c not in adhesion and c not in inside]
    pack = lambda cs: F.struct(*[F.col(c) for c in cs]) if cs else F.lit(1)
    g = result.groupBy(*adhesion) if adhesion else result.groupBy()
    bad = g.agg(F.countDistinct(pack(inside)).alias("a"), F.countDistinct(pack(rest)).alias("b"), F.count(F.lit(1)).alias("n")).where("a * b <> n")
    return not bad.take(1)
