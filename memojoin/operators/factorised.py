"""Evaluation results as one table for each node of the decomposition, joined on shared variables when flattened."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.functions.scalars import sum_product
from memojoin.operators.catalog import Catalog, empty_row
from memojoin.operators.frontier import _options, check_plan
from memojoin.operators.policy import CachePolicy
from memojoin.plans.decomp import OrderedTD, is_strongly_compatible
from memojoin.plans.query import ConjunctiveQuery


@dataclass
class FactorisedResult:
    """nodes[v]: distinct bindings of v's bag that occur in the result; top: the root's before its only child was asked."""

    td: OrderedTD
    order: tuple[str, ...]
    nodes: dict[int, DataFrame]
    top: DataFrame | None = None

    def flatten(self) -> DataFrame:
        """Every result row, a column for each variable. An only child's join prunes the root, so it is not solved once
        more for that."""
        out = self.nodes[0] if self.top is None else self.top
        for v in self.td.preorder()[1:]:
            shared = sorted(self.td.adhesion(v))
            out = out.join(self.nodes[v], shared) if shared else out.crossJoin(self.nodes[v])
        return out.select(*self.order)

    def count(self) -> DataFrame:
        """One row, cnt, without flattening."""

        def up(v):
            rows, names = self.nodes[v], []
            for c in self.td.children(v):
                shared, name = sorted(self.td.adhesion(c)), f"__c{c}"
                m = up(c).withColumnRenamed("cnt", name)
                rows = rows.join(m, shared) if shared else rows.crossJoin(m)
                names.append(F.col(name))
            keys = sorted(self.td.adhesion(v))
            return rows.groupBy(*keys).agg((sum_product(names) if names else F.count(F.lit(1))).alias("cnt"))

        return up(0).select(F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))

    def size(self) -> DataFrame:
        """node, rows, cells: how large the factors are."""
        out = None
        for v, df in self.nodes.items():
            one = df.agg(F.lit(v).alias("node"), F.count(F.lit(1)).alias("rows"), (F.count(F.lit(1)) * len(self.td.bags[v])).alias("cells"))
            out = one if out is None else out.unionByName(one)
        return out

    def to_nested(self) -> DataFrame:
        """The root's rows with an array of structs for each child; only for results that fit so (each array is one value)."""

        def up(v):
            rows = self.nodes[v]
            for c in self.td.children(v):
                shared = sorted(self.td.adhesion(c))
                inner = up(c)
                rest = [F.col(x) for x in inner.columns if x not in shared]
                packed = inner.groupBy(*shared).agg(F.collect_list(F.struct(*rest)).alias(f"child{c}"))
                rows = rows.join(packed, shared) if shared else rows.crossJoin(packed)
            return rows

        return up(0)


def evaluate_factorised(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, order=None, proposer: str = "static", policy: CachePolicy | None = None) -> FactorisedResult:
    """Memoised evaluation: each node is solved once for the distinct keys that the nodes before it demand.

    A child's survivors prune its parent before the next sibling is demanded; a last pass from the root down takes
    out what later siblings have made useless: nothing of a last child, if nothing has been taken out of its parent. A node that the policy neither caches nor has below a cached one keeps
    no table of its own: it is part of its parent.
    """
    if policy:
        policy.check_frontier()
        td = policy.pruned(td)
        order = order if order is None or is_strongly_compatible(td, order) else None
    order = check_plan(query, td, order)
    f = _options(query, catalog, order, proposer, False)
    nodes: dict[int, DataFrame] = {}
    top = None

    def solve(v: int, demand: DataFrame) -> DataFrame:
        nonlocal top
        rows = f.grow(demand, sorted(td.adhesion(v)), [x for x in order if td.owner(x) == v])
        if not v and len(td.children(v)) == 1:
            top = rows.select(*sorted(td.bags[v]))
        for c in td.children(v):
            shared = sorted(td.adhesion(c))
            below = solve(c, rows.select(*shared).distinct() if shared else empty_row(f.spark))
            rows = rows.join(below.select(*shared).distinct(), shared, "left_semi") if shared else rows.join(below.limit(1).select(F.lit(0).alias("__any")), F.lit(True), "left_semi")
        nodes[v] = rows.select(*sorted(td.bags[v]))
        return nodes[v]

    solve(0, f.constants_hold(empty_row(f.spark)))
    whole = {0}  # nodes of which the last pass takes nothing
    for v in td.preorder()[1:]:
        shared = sorted(td.adhesion(v))
        if shared and td.parents[v] in whole and v == td.children(td.parents[v])[-1]:
            whole.add(v)
            continue
        above = nodes[td.parents[v]]
        nodes[v] = nodes[v].join(above.select(*shared).distinct(), shared, "left_semi") if shared else nodes[v].join(above.limit(1).select(F.lit(0).alias("__any")), F.lit(True), "left_semi")
    return FactorisedResult(td, order, dict(sorted(nodes.items())), top)


def memo_evaluate(query, catalog, td, order=None, proposer: str = "static") -> DataFrame:
    return evaluate_factorised(query, catalog, td, order, proposer).flatten()
