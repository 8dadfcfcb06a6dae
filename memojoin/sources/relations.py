"""Relations over the given tables: graphs of different skew, bipartite cast tables, words, and a star schema.

Only integers enter keys, so every engine gets the same rows. All relations are sets.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from memojoin.functions import scalars as S


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def g_flat(spark, d) -> DataFrame:
    """A user's purchase and the next user's, in time: small and balanced.

    Rows are ordered within each hour; the last of an hour is followed by the first of the next hour that has some,
    so that no task orders the whole table.
    """
    e = load(spark, d, "events").where("event_type = 'purchase'").select("ts", "event_id", "user_id", F.date_trunc("hour", "ts").alias("hour"))
    own = Window.partitionBy("hour").orderBy("ts", "event_id")
    follow = e.select("hour", F.col("user_id").alias("s"), F.lead(F.struct("user_id")).over(own).alias("next"))
    firsts = e.groupBy("hour").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("f"))  # a row for each hour
    after = firsts.select("hour", F.lead(F.struct("f.user_id")).over(Window.orderBy("hour")).alias("first"))
    return follow.join(after, "hour").select("s", F.coalesce("next", "first").getField("user_id").alias("t")).dropna().distinct()


def _lines(spark, d, where: str) -> DataFrame:
    return load(spark, d, "lineitem").where(where)


def _side(spark, d, table: str, share: int, least: int) -> int:
    """How many numbers keys are mapped onto: a share of the table's rows; cubes of it stay within 64 bits."""
    return min(max(load(spark, d, table).count() // share, least), 1_000_000)


def g_skew(spark, d, power: int = 3) -> DataFrame:
    """Part and order of some returned lines, both crowded towards small numbers by an integer power; the range of the
    numbers grows with the table of parts."""
    n = _side(spark, d, "part", 100, 200)
    x = _lines(spark, d, "l_returnflag = 'R' AND l_linestatus = 'F' AND l_quantity <= 10").select("l_partkey", "l_orderkey")
    return x.select(S.skew_map(F.col("l_partkey"), n, power).alias("s"), S.skew_map(F.col("l_orderkey"), n, power).alias("t")).distinct()


def g_clustered(spark, d) -> DataFrame:
    """Different parts of one order: symmetric, with many triangles."""
    x = _lines(spark, d, "l_returnflag = 'R' AND l_linestatus = 'F'").select("l_orderkey", "l_partkey").distinct()
    return x.join(x.withColumnRenamed("l_partkey", "q"), "l_orderkey").where("l_partkey <> q").select(F.col("l_partkey").alias("s"), F.col("q").alias("t")).distinct()


def g_parts(spark, d) -> DataFrame:
    """Consecutive parts of an order, crowded towards small numbers."""
    n = load(spark, d, "part").count()
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    x = load(spark, d, "lineitem").select(F.col("l_partkey").alias("p"), F.lead("l_partkey").over(w).alias("q")).dropna()
    square = lambda c: S.int_div(F.col(c) * F.col(c), F.lit(n).cast("long"))
    return x.select(square("p").alias("s"), square("q").alias("t")).distinct()


def g_words(spark, d) -> DataFrame:
    """Consecutive words of English documents: large and heavily skewed, with string keys."""
    return S.bigrams(load(spark, d, "documents").where("lang = 'en'").select("text")).distinct()


def _cast(spark, d, status: str) -> DataFrame:
    lines = _lines(spark, d, f"l_returnflag = 'R' AND l_linestatus = '{status}'").select("l_orderkey", "l_partkey")
    orders = load(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return lines.join(orders, "l_orderkey").select(S.skew_map(F.col("o_custkey"), _side(spark, d, "customer", 50, 300), 3).alias("p"), F.col("l_partkey").alias("m")).distinct()


def cast_a(spark, d) -> DataFrame:
    """Persons (skewed) and movies (flat), first half."""
    return _cast(spark, d, "O")


def cast_b(spark, d) -> DataFrame:
    return _cast(spark, d, "F")


def doc_word(spark, d) -> DataFrame:
    x = load(spark, d, "documents").where("lang = 'en'")
    return x.select(F.col("doc_id").alias("s"), F.explode(S.words(x)).alias("t")).distinct()


def user_k(spark, d) -> DataFrame:
    return S.user_k(load(spark, d, "events")).select(F.col("user_id").alias("s"), F.col("k").alias("t"))


def page_href(spark, d) -> DataFrame:
    paths = F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))
    return load(spark, d, "pages").select(F.col("page_id").alias("s"), F.explode(paths).alias("t")).distinct()


def part_supp(spark, d) -> DataFrame:
    return load(spark, d, "lineitem").select(F.col("l_partkey").alias("s"), F.col("l_suppkey").alias("t")).distinct()


def star(spark, d) -> dict[str, DataFrame]:
    """L(o,p,s), O(o,c), C(c,n), S(s,n), N(n,r)."""
    t = lambda name, *c: load(spark, d, name).select(*c)
    return {
        "L": t("lineitem", "l_orderkey", "l_partkey", "l_suppkey"), "LS": t("lineitem", "l_orderkey", "l_suppkey"), "O": t("orders", "o_orderkey", "o_custkey"),
        "C": t("customer", "c_custkey", "c_nationkey"), "S": t("supplier", "s_suppkey", "s_nationkey"), "N": t("nation", "n_nationkey", "n_regionkey"),
    }


GRAPHS = {"g_flat": g_flat, "g_skew": g_skew, "g_clustered": g_clustered, "g_parts": g_parts, "g_words": g_words}

#: The same relations in SQL.
SQL = {
    "g_flat": "SELECT DISTINCT s, t FROM (SELECT user_id AS s, lead(user_id) OVER (ORDER BY ts, event_id) AS t FROM events WHERE event_type = 'purchase') WHERE s IS NOT NULL AND t IS NOT NULL",
    "g_clustered": "SELECT DISTINCT a.l_partkey AS s, b.l_partkey AS t FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_returnflag = 'R' AND a.l_linestatus = 'F' AND b.l_returnflag = 'R' AND b.l_linestatus = 'F' AND a.l_partkey <> b.l_partkey",
    "g_parts": "SELECT DISTINCT p * p // n AS s, q * q // n AS t FROM (SELECT l_partkey AS p, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS q FROM lineitem), (SELECT count(*) AS n FROM part) WHERE p IS NOT NULL AND q IS NOT NULL",
    "g_words": "SELECT DISTINCT w[k] AS s, w[k + 1] AS t FROM (SELECT w, unnest(range(1, len(w))) AS k FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents WHERE lang = 'en'))",
    "doc_word": "SELECT DISTINCT s, t FROM (SELECT doc_id AS s, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS t FROM documents WHERE lang = 'en')",
    "user_k": "SELECT DISTINCT user_id AS s, CAST(json_extract_string(props, '$.k') AS BIGINT) AS t FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL",
    "page_href": "SELECT DISTINCT s, t FROM (SELECT page_id AS s, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS t FROM pages)",
    "part_supp": "SELECT DISTINCT l_partkey AS s, l_suppkey AS t FROM lineitem",
}


def skew_sql(power: int) -> str:
    f = lambda c: f"(({c} % n) ** {power})::BIGINT // (n ** {power - 1})::BIGINT"
    return f"SELECT DISTINCT {f('l_partkey')} AS s, {f('l_orderkey')} AS t FROM lineitem, (SELECT least(greatest(count(*) // 100, 200), 1000000) AS n FROM part) WHERE l_returnflag = 'R' AND l_linestatus = 'F' AND l_quantity <= 10"


def cast_sql(status: str) -> str:
    return f"SELECT DISTINCT ((o_custkey % n) ** 3)::BIGINT // (n * n) AS p, l_partkey AS m FROM lineitem JOIN orders ON l_orderkey = o_orderkey, (SELECT least(greatest(count(*) // 50, 300), 1000000) AS n FROM customer) WHERE l_returnflag = 'R' AND l_linestatus = '{status}'"


SQL |= {"g_skew": skew_sql(3), "cast_a": cast_sql("O"), "cast_b": cast_sql("F")}
