"""Mixing sources to target weights by repeating documents.

Sizes are counted in words, summed for each source, and a total budget is shared by weight; no source may be
repeated more than ``max_repeats`` times, and what a capped source leaves is shared again among the others. A
document of a source with repetition rate r is then emitted floor(r) times, and once more if a hash of its id,
read as a number in [0, 1), lies below the fraction of r. Nothing is drawn at random, so reruns and retried
tasks agree.

Defined cases: a null text has size 0; null is a source of its own, ordered last; a source without words has
target 0; repeated rows of one id share their hash and so their fate; a null id is hashed by its text; an
empty table gives an empty result; extra columns are carried by ``mix`` and ignored by ``plan_documents``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from memojoin.llm.common import discard, materialise, native_words, read

WEIGHTS = (1, 2, 3)
MAX_REPEATS = 3
#: Up to so many sources and bytes of their names are planned on the driver and broadcast; more stay a table.
MAX_SOURCES, MAX_NAME_BYTES = 100_000, 16 << 20
#: Parts into which each source is cut for the join with a table of sources, so that no task gets a whole one.
SALTS = 32
SEED = "mix-1"


def share_out(sizes: list[int], weights: list[int], total: int, max_repeats: int = MAX_REPEATS) -> list[float]:
    """Targets that share total by weight, none above max_repeats times its size (exact integer comparisons)."""
    order = sorted(range(len(sizes)), key=lambda k: (sizes[k] / weights[k], k))
    left, weight, targets = total, sum(weights), [0.0] * len(sizes)
    for at, k in enumerate(order):
        if max_repeats * sizes[k] * weight > weights[k] * left:
            for j in order[at:]:
                targets[j] = weights[j] * left / weight
            break
        targets[k] = float(max_repeats * sizes[k])
        left -= max_repeats * sizes[k]
        weight -= weights[k]
    return targets


SCHEMA = T.StructType([T.StructField("__source", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType())])


def source_plan(sized: DataFrame, weights=WEIGHTS, max_repeats=MAX_REPEATS) -> tuple[DataFrame, bool]:
    """One row for each source (__source, source_size, target), and whether it is small enough to broadcast."""
    sums = sized.groupBy("__source").agg(F.sum("size").alias("source_size"))
    sums = materialise(sums, "mix-sources")
    n, wide = sums.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("__source")), F.lit(0))).first()
    if n > MAX_SOURCES or wide > MAX_NAME_BYTES:
        return _planned_as_table(sums, weights, max_repeats), False
    rows = sorted(sums.collect(), key=lambda r: (r[0] is None, r[0] or ""))  # Python orders strings by code point
    discard(sums)
    sizes = [r[1] for r in rows]
    targets = share_out(sizes, [weights[k % len(weights)] for k in range(len(rows))], sum(sizes), max_repeats)
    return sized.sparkSession.createDataFrame([(r[0], s, t) for r, s, t in zip(rows, sizes, targets)], SCHEMA), True


def _planned_as_table(sums: DataFrame, weights, max_repeats) -> DataFrame:
    """The same for any number of sources: capped sources are found in rounds, as a level that rises."""
    ranked = sums.orderBy(F.col("__source").asc_nulls_last()).withColumn("__id", F.monotonically_increasing_id())
    ranked = materialise(ranked, "mix-ranked")
    part = F.shiftright("__id", 33)
    before, offsets = 0, []
    for p, n in sorted(map(tuple, ranked.groupBy(part).count().collect())):  # a row for each partition
        offsets.append((p, before))
        before += n
    offsets = sums.sparkSession.createDataFrame(offsets, "__p long, __before long")
    rank = F.col("__before") + F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(rank, F.lit(len(weights))) + 1).cast("int")).cast("decimal(38,0)")
    size = F.col("source_size").cast("decimal(38,0)")
    rows = ranked.join(F.broadcast(offsets), part == F.col("__p")).select("__source", "source_size", weight.alias("__w"))
    rows = materialise(rows, "mix-weighted")
    total, heavy = rows.agg(F.sum(size), F.sum("__w")).first()
    left, weight_left = total, heavy
    while True:
        capped = F.lit(int(max_repeats)).cast("decimal(38,0)") * size * F.lit(weight_left) <= F.col("__w") * F.lit(left)
        got = rows.where(capped).agg(F.sum(size), F.sum("__w")).first()
        now = total - max_repeats * (got[0] or 0), heavy - (got[1] or 0)
        if now == (left, weight_left) or not now[1]:
            break
        left, weight_left = now
    share = F.col("__w").cast("double") * F.lit(float(left)) / F.lit(float(weight_left))
    return rows.select("__source", "source_size", F.when(capped, (F.lit(max_repeats) * F.col("source_size")).cast("double")).otherwise(share).alias("target"))


def _uniform(key: Column) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(SEED + "|"), key).cast("binary")), 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def _planned(docs: DataFrame, keep: Column, weights, max_repeats) -> DataFrame:
    """keep as __row (a struct, so that no column of docs can clash), size, source_size, target and copies."""
    size = F.size(native_words(F.col("text"))).cast("long").alias("size")
    sized = docs.select(
        keep.alias("__row"), F.col("source").alias("__source"), size,
        _uniform(F.coalesce(F.col("doc_id").cast("string"), F.md5(F.col("text").cast("binary")), F.lit(""))).alias("__u"),
    )
    plan, small = source_plan(docs.select(F.col("source").alias("__source"), size), weights, max_repeats)
    plan = plan.withColumnRenamed("__source", "__s")
    same = F.col("__source").eqNullSafe(F.col("__s"))
    if small:
        joined = sized.join(F.broadcast(plan), same, "inner")
    else:
        salted = sized.withColumn("__salt", F.floor(F.col("__u") * SALTS).cast("int"))
        copies = plan.withColumn("__part", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = salted.join(copies, same & (F.col("__salt") == F.col("__part")), "inner").drop("__salt", "__part")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    joined = joined.withColumn("__rate", rate)
    whole = F.floor("__rate")
    copies = whole + F.when(F.col("__u") < F.col("__rate") - whole, 1).otherwise(0)
    return joined.withColumn("copies", copies.cast("long")).drop("__source", "__s", "__u", "__rate")


def plan_documents(docs: DataFrame, weights=WEIGHTS, max_repeats=MAX_REPEATS) -> DataFrame:
    """doc_id with size, source_size, target and copies; texts are measured where they lie and go nowhere."""
    return _planned(docs, F.struct("doc_id"), weights, max_repeats).select(F.col("__row.doc_id").alias("doc_id"), "size", "source_size", "target", "copies")


def mix(docs: DataFrame, weights=WEIGHTS, max_repeats=MAX_REPEATS) -> DataFrame:
    """The mixed corpus: every row of docs as often as its rate says, with the columns of docs."""
    copies = F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    return _planned(docs, row, weights, max_repeats).where("copies > 0").select("__row", copies.alias("__copy")).select("__row.*")


def op7_mixing(spark, sf_dir: str) -> DataFrame:
    out = plan_documents(read(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


OP7_SQL = f"""
WITH d AS (
  SELECT doc_id, source, text,
         len(list_filter(string_split(translate(coalesce(text, ''), chr(9)||chr(10)||chr(11)||chr(12)||chr(13), '     '), ' '), lambda x: x <> ''))::BIGINT AS size
  FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT source, source_size, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::BIGINT AS w FROM s),
o AS (SELECT *, row_number() OVER (ORDER BY source_size::DOUBLE / w, source NULLS LAST) AS k FROM w),
p AS (SELECT *, (sum(source_size) OVER ())::BIGINT - coalesce(sum(3 * source_size) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS rem,
             (sum(w) OVER ())::BIGINT - coalesce(sum(w) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS ws
      FROM o),
f AS (SELECT min(k) AS k FROM p WHERE 3 * source_size * ws > w * rem),
t AS (SELECT p.source, p.source_size,
             CASE WHEN f.k IS NULL OR p.k < f.k THEN (3 * p.source_size)::DOUBLE
                  ELSE (p.w * g.rem)::DOUBLE / g.ws::DOUBLE END AS target
      FROM p CROSS JOIN f LEFT JOIN p g ON g.k = f.k),
r AS (SELECT d.doc_id, d.size, t.source_size, t.target,
             CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0 END AS rate,
             ('0x' || substr(md5('{SEED}|' || coalesce(d.doc_id::VARCHAR, md5(d.text), '')), 1, 13))::BIGINT::DOUBLE / 4503599627370496.0 AS u
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       (size * (floor(rate)::BIGINT + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM r"""
