"""Quality rules: a table of thresholds compiled into one Spark projection, without user functions.

Each rule names a measure and the range it must stay in. The measures are ratios over whole texts: lengths,
symbols, stop words, lines, repeated word windows. Everything is built from Spark's own expressions and needs
no shuffle, so a hot source or a long text stays within its own row.

Repeated windows are found per text by sorting (window hash, position) pairs: n log n in the words of a text,
and only for texts that have a repeated hash at all. Hashes are 64 bits wide.

Defined cases: a null text counts as empty, has no words and fails the base rule; ratios of an empty text are 0
(so that only the base rule decides); repeated rows and ties give equal results; an empty table gives an empty
result; extra columns are ignored by ``measure`` and carried by ``keep_good``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import ASCII_SPACE, read

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: The characters that count as symbols.
SYMBOLS = "#*$%&|<>"
#: Frequent function words of the languages at hand.
STOP_WORDS = (
    "the of and to in is that for with was on are as by an this from or be it at he a not "
    "der die und in den von zu mit das ist im auf dem nicht ein eine als auch es an er sie "
    "de la le les des et en un une du que est pour dans qui par sur au pas plus ce il avec "
    "el los las y del se por con para como su al lo una"
).split()
#: measure, least, most: the verdict keeps a text whose measures all lie in their ranges (percent, or characters).
RULES = (
    ("chars_per_word", 2.0, 12.0),
    ("symbol_percent_of_words", 0.0, 10.0),
    ("exclaimed_percent_of_words", 0.0, 30.0),
    ("upper_percent_of_letters", 0.0, 50.0),
    ("stop_word_percent", 4.0, 100.0),
    ("duplicate_line_percent", 0.0, 50.0),
    ("repeated_word_percent", 0.0, 40.0),
)


def _let(value: Column, body) -> Column:
    """body(value) with value computed once for each row."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _repeat_words(words: Column) -> Column:
    """Words that lie in a window of three words found twice or more."""

    def windows(w):
        return F.transform(F.slice(w, 1, F.greatest(F.size(w) - 2, F.lit(0))), lambda x, i: F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2)))

    def covered(h):
        ranked = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def repeated(s):
            same = lambda e, k: (k >= 0) & (F.get(s, k)["h"] == e["h"])
            return F.filter(s, lambda e, k: F.coalesce(same(e, k - 1), F.lit(False)) | F.coalesce(same(e, k + 1), F.lit(False)))

        at = F.sort_array(F.transform(_let(ranked, repeated), lambda e: e["i"].cast("long")))
        start = F.struct(F.lit(-3).cast("long").alias("last"), F.lit(0).cast("long").alias("n"))
        return F.aggregate(at, start, lambda a, x: F.struct(x.alias("last"), (a["n"] + F.least(F.lit(3).cast("long"), x - a["last"])).alias("n")), lambda a: a["n"])

    return _let(_let(words, windows), lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(covered(h)))


def measure(docs: DataFrame) -> DataFrame:
    """doc_id with the counts of the base rules and the measures of the rule table."""
    long = lambda c: c.cast("long")
    cut = lambda c, chars: F.translate(c, chars, "")
    text = F.coalesce(F.col("text"), F.lit(""))
    one = docs.select("doc_id", text.alias("__t"), F.array_remove(F.split(F.translate(text, ASCII_SPACE[:-1], " " * 5), " "), "").alias("__w"))
    lines = F.filter(F.split(F.col("__t"), "\n"), lambda x: F.length(cut(x, ASCII_SPACE)) > 0)
    two = one.select(
        "doc_id",
        long(F.size("__w")).alias("n_words"),
        long(F.length(cut(F.col("__t"), ASCII_SPACE))).alias("word_chars"),
        long(F.length("__t") - F.length(cut(F.col("__t"), SYMBOLS))).alias("n_symbols"),
        lines.alias("__lines"),
        long(_repeat_words(F.col("__w"))).alias("n_repeat_words"),
        long(F.size(F.filter("__w", lambda x: F.lower(x).isin(*sorted(set(STOP_WORDS)))))).alias("__stop"),
        long(F.length("__t") - F.length(cut(F.col("__t"), "!"))).alias("__bangs"),
        long(F.length(F.regexp_replace("__t", r"\P{Lu}+", ""))).alias("__upper"),
        long(F.length(F.regexp_replace("__t", r"\P{L}+", ""))).alias("__letters"),
    )
    three = two.withColumn("n_lines", long(F.size("__lines"))).withColumn("n_dup_lines", long(F.size("__lines") - F.size(F.array_distinct("__lines"))))
    ratio = lambda n, d, by=1.0: F.when(d > 0, n * F.lit(by) / d).otherwise(F.lit(0.0))
    words = F.col("n_words")
    return three.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        ratio(F.col("word_chars"), words).alias("chars_per_word"),
        ratio(F.col("n_symbols"), words, 100.0).alias("symbol_percent_of_words"),
        ratio(F.col("__bangs"), words, 100.0).alias("exclaimed_percent_of_words"),
        ratio(F.col("__upper"), F.col("__letters"), 100.0).alias("upper_percent_of_letters"),
        ratio(F.col("__stop"), words, 100.0).alias("stop_word_percent"),
        ratio(F.col("n_dup_lines"), F.col("n_lines"), 100.0).alias("duplicate_line_percent"),
        ratio(F.col("n_repeat_words"), words, 100.0).alias("repeated_word_percent"),
    )


def judge(docs: DataFrame, rules=RULES) -> DataFrame:
    """measure() with base_failed and kept."""
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    good = F.lit(True)
    for name, least, most in rules:
        good = good & F.col(name).between(least, most)
    return measure(docs).withColumn("base_failed", base).withColumn("kept", ~F.col("base_failed") & good)


def op4_quality_rules(spark, sf_dir: str) -> DataFrame:
    return judge(read(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _sql() -> str:
    stops = ", ".join(f"'{w}'" for w in sorted(set(STOP_WORDS)))
    rules = " AND ".join(f"{name} BETWEEN {least} AND {most}" for name, least, most in RULES)
    spaces = "chr(9)||chr(10)||chr(11)||chr(12)||chr(13)"
    r = lambda n, d, by="1.0": f"CASE WHEN {d} > 0 THEN {n} * {by}::DOUBLE / {d} ELSE 0.0 END"
    return f"""
WITH d AS (
  SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS t,
         list_filter(string_split(translate(coalesce(text, ''), {spaces}, '     '), ' '), lambda x: x <> '') AS w FROM documents),
e AS (SELECT k, unnest(w) AS x, generate_subscripts(w, 1) AS i FROM d),
s AS (SELECT k, i, x, lead(x, 1) OVER v AS y, lead(x, 2) OVER v AS z FROM e WINDOW v AS (PARTITION BY k ORDER BY i)),
n AS (SELECT k, i, count(*) OVER (PARTITION BY k, x, y, z) AS n FROM s WHERE z IS NOT NULL),
c AS (SELECT k, count(DISTINCT i + o)::BIGINT AS n_repeat_words FROM n, (VALUES (0), (1), (2)) q(o) WHERE n > 1 GROUP BY k),
b AS (
  SELECT d.k, doc_id, len(w)::BIGINT AS n_words, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
         length(regexp_replace(t, '[\\x20\\x09-\\x0D]', '', 'g'))::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS l,
         len(list_filter(w, lambda x: lower(x) IN ({stops})))::BIGINT AS st,
         length(regexp_replace(t, '[^!]', '', 'g'))::BIGINT AS bangs,
         length(regexp_replace(t, '\\P{{Lu}}', '', 'g'))::BIGINT AS up,
         length(regexp_replace(t, '\\P{{L}}', '', 'g'))::BIGINT AS letters
  FROM d LEFT JOIN c USING (k)),
m AS (
  SELECT *, len(l) AS n_lines, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines FROM b),
q AS (
  SELECT *, {r('word_chars', 'n_words')} AS chars_per_word, {r('n_symbols', 'n_words', '100.0')} AS symbol_percent_of_words,
         {r('bangs', 'n_words', '100.0')} AS exclaimed_percent_of_words, {r('up', 'letters', '100.0')} AS upper_percent_of_letters,
         {r('st', 'n_words', '100.0')} AS stop_word_percent, {r('n_dup_lines', 'n_lines', '100.0')} AS duplicate_line_percent,
         {r('n_repeat_words', 'n_words', '100.0')} AS repeated_word_percent,
         (n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words) AS base_failed
  FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       (NOT base_failed AND {rules}) AS kept
FROM q"""


OP4_SQL = _sql()
