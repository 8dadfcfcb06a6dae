"""Aggregates over all results without producing them: the memoised count in other semirings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from memojoin.operators.catalog import Catalog, empty_row
from memojoin.operators.frontier import _options, check_plan
from memojoin.plans.decomp import OrderedTD
from memojoin.plans.query import ConjunctiveQuery

#: name: (addition, multiplication, one)
SEMIRINGS = {
    "sum_product": (F.sum, lambda a, b: a * b, 1),
    "min_plus": (F.min, lambda a, b: a + b, 0),
    "max_plus": (F.max, lambda a, b: a + b, 0),
    "exists": (F.max, lambda a, b: a & b, True),
}


def aggregate(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, semiring: str = "sum_product", weights: dict[str, Column] | None = None, order=None) -> DataFrame:
    """One row, value: the sum over results of the product of their variables' weights (long; boolean for exists).

    weights: an expression over a variable's own column, for the variables that have one. No result: null.
    """
    plus, times, one = SEMIRINGS[semiring]
    order, weights = check_plan(query, td, order), weights or {}
    f = _options(query, catalog, order, "static", False)

    def solve(v, demand, keys):
        own = [x for x in order if td.owner(x) == v]
        rows = f.grow(demand, sorted(td.adhesion(v)), own)
        value = F.lit(one) if semiring == "exists" else F.lit(one).cast("long")
        for x in own:
            if x in weights:
                value = times(value, weights[x])
        rows = rows.withColumn("__value", value)
        for c in td.children(v):
            shared, name = sorted(td.adhesion(c)), f"__c{c}"
            below = solve(c, rows.select(*shared).distinct() if shared else empty_row(f.spark), shared).withColumnRenamed("value", name)
            rows = rows.join(below, shared) if shared else rows.crossJoin(below)
            rows = rows.withColumn("__value", times(F.col("__value"), F.col(name))).drop(name)
        return rows.groupBy(*keys).agg(plus("__value").alias("value"))

    return solve(0, f.constants_hold(empty_row(f.spark)), [])
