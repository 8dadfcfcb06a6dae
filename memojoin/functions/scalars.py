"""Column expressions that the joins need around them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def key(column: Column, kind: T.DataType) -> Column:
    """A join key: one zero, no NaN (it becomes null and so never joins); nested types are refused."""
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return F.when(~F.isnan(column), column + F.lit(0.0).cast(kind))
    if isinstance(kind, (T.ArrayType, T.MapType, T.StructType)):
        raise TypeError(f"{kind.simpleString()} cannot be a join key")
    return column


OVERFLOW = "ARITHMETIC_OVERFLOW: count beyond 64 bits"


def _checked(value: Column, there: Column) -> Column:
    """value, or an error where it is null though there holds: overflow, whatever the session's ANSI mode."""
    return F.when(there & value.isNull(), F.raise_error(F.lit(OVERFLOW)).cast("bigint")).otherwise(value)


def product(columns: list[Column], decimal: bool = False) -> Column:
    """The product of counts as bigint, which raises on overflow, or as decimal(38,0)."""
    if not columns:
        return F.lit(1).cast(count_type(decimal))
    if decimal:
        return reduce(lambda a, b: (a * b).cast("decimal(38,0)"), [c.cast("decimal(38,0)") for c in columns])
    if len(columns) == 1:
        return columns[0]
    return _checked(reduce(F.try_multiply, columns), reduce(lambda a, b: a & b, [c.isNotNull() for c in columns]))


def count_type(decimal: bool) -> str:
    return "decimal(38,0)" if decimal else "bigint"


def sum_product(columns: list[Column], decimal: bool = False) -> Column:
    """Sum over rows of the product of counts, as bigint or, for counts beyond 2**63, decimal(38,0)."""
    if decimal:
        return F.sum(product(columns, True)).cast("decimal(38,0)")
    return _checked(F.try_sum(product(columns)), F.count(columns[0]) > 0)


def cheapest(degrees: list[Column]) -> Column:
    """The number of the smallest degree (the first of equals)."""
    low = F.least(*degrees) if len(degrees) > 1 else degrees[0]
    out = F.lit(len(degrees) - 1)
    for k in reversed(range(len(degrees) - 1)):
        out = F.when(degrees[k] == low, F.lit(k)).otherwise(out)
    return out


def _under(own: Column, share: int):
    return lambda c: F.transform(own, lambda o: c * F.lit(share) + o)


def cell_ids(variables: list[str], have: list[str], shares: dict[str, int]) -> Column:
    """All hypercube cells that a tuple with the variables in have belongs to, as an array of cell numbers."""
    cells = F.array(F.lit(0).cast("long"))
    for v in variables:
        p = shares.get(v, 1)
        if p == 1:
            continue
        own = F.array(F.pmod(F.xxhash64(F.lit(v), F.col(v)), F.lit(p))) if v in have else F.sequence(F.lit(0).cast("long"), F.lit(p - 1).cast("long"))
        cells = F.flatten(F.transform(cells, _under(own, p)))
    return cells


def words(df: DataFrame, text: str = "text") -> Column:
    """Lower-case ASCII words of a text."""
    return F.regexp_extract_all(F.lower(F.col(text)), F.lit("([a-z]+)"), F.lit(1))


def bigrams(df: DataFrame, text: str = "text") -> DataFrame:
    """s, t: consecutive words, once for each place."""
    w = df.select(words(df, text).alias("w"))
    at = F.explode(F.when(F.size("w") > 1, F.sequence(F.lit(1), F.size("w") - 1)).otherwise(F.array().cast("array<int>")))
    return w.select("w", at.alias("k")).select(F.element_at("w", F.col("k")).alias("s"), F.element_at("w", F.col("k") + 1).alias("t"))


def skew_map(column: Column, n: int, power: int) -> Column:
    """An integer map of [0, n) into itself that crowds small values the more, the higher the power."""
    x = F.pmod(column.cast("long"), F.lit(n).cast("long"))
    return int_div(_power(x, power), F.lit(n ** (power - 1)).cast("long"))


def _power(x: Column, power: int) -> Column:
    return reduce(lambda a, _: a * x, range(power - 1), x)


def int_div(a: Column, b: Column) -> Column:
    """Integer division, exact beyond the range of doubles."""
    return F.call_function("div", a, b)


def user_bucket(events: DataFrame, step: str = "hour") -> DataFrame:
    """user_id and its time bucket."""
    return events.select("user_id", F.date_trunc(step, "ts").alias("bucket")).distinct()


def user_k(events: DataFrame) -> DataFrame:
    """user_id and the number k of its JSON attributes."""
    return events.select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k IS NOT NULL").distinct()


def result_hash(df: DataFrame) -> DataFrame:
    """rows, hash: independent of the order of rows."""
    h = F.xxhash64(*[F.col(c) for c in sorted(df.columns)])
    return df.select(h.alias("h")).agg(F.count(F.lit(1)).alias("rows"), F.sum(F.col("h").cast("decimal(38,0)")).alias("hash"))


def second_moment(column: str) -> Column:
    return F.sum(F.col(column) * F.col(column))
