"""The rival by bags: each bag joined by itself, variable at a time, then an acyclic join of the bags.

A bag takes the atoms within it and, for the others that it overlaps, their projections, so that its size is the
bag's own; nothing tells a bag which keys its neighbours hold, which is what the memoised join does.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from memojoin.functions.scalars import count_type, sum_product
from memojoin.operators import kernel
from memojoin.operators.catalog import Catalog, empty_row
from memojoin.operators.factorised import evaluate_factorised
from memojoin.operators.frontier import Frontier, recalled
from memojoin.plans.decomp import OrderedTD
from memojoin.plans.query import ConjunctiveQuery


#: Bytes of all atoms together that each task can hold, beside the tries that it makes of them, and the rows of the largest
#: relation from which on bags are worth a Python worker.
TASK_BYTES, TASK_ROWS = 64 << 20, 1 << 14


def bag_order(td: OrderedTD, v: int, rule: str = "adhesion_first") -> list[str]:
    """Variables shared with neighbours first, so that the later joins find them high in the trie; or the reverse."""
    shared = set(td.adhesion(v)).union(*(td.adhesion(c) for c in td.children(v)))
    names = sorted(td.bags[v], key=lambda x: (x not in shared, x))
    return names if rule == "adhesion_first" else names[::-1]


def bag_atoms(td: OrderedTD, v: int, atoms: list[tuple[str, ...]]) -> list[tuple[int, tuple[str, ...]]]:
    """The atoms of a bag by number, with those of their variables that it has: all within it, and projections that these
    do not cover."""
    out = []
    for k, variables in enumerate(atoms):
        inside = tuple(x for x in variables if x in td.bags[v])
        if inside and (len(inside) == len(variables) or not any(set(inside) <= set(w) for w in atoms if set(w) <= td.bags[v])):
            out.append((k, inside))
    return out


def bags(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, rule: str = "adhesion_first") -> dict[int, DataFrame]:
    td.validate(query)
    out = {}
    for v in td.preorder():
        names = bag_order(td, v, rule)
        f = Frontier(query, catalog, tuple(names))
        parts = []
        for k, inside in bag_atoms(td, v, [w for w, _ in f.atoms]):
            variables, df = f.atoms[k]
            parts.append((inside, df if len(inside) == len(variables) else df.select(*inside).distinct()))
        constant = f.constants_hold(empty_row(f.spark)) if v == 0 else empty_row(f.spark)
        f.atoms = parts
        out[v] = f.grow(constant, [], names).select(*sorted(td.bags[v]))
    return out


def common(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD) -> str | None:
    """A variable of all bags, where tasks can hold the relations and the counts of keys of it and one more variable."""
    every = sorted(frozenset.intersection(*td.bags))
    if not every or query.comparisons or any(len(td.adhesion(v)) > 2 for v in td.preorder()):
        return None
    if not all(isinstance(f.dataType, T.IntegralType) for a in query.atoms for f in catalog[a.relation].schema):
        return None
    if (catalog.sent(query) or 0) < TASK_ROWS or sum(catalog.few(a.relation) * 8 * len(a.terms) for a in query.atoms) > TASK_BYTES:
        return None
    return every[0]


def bagtree_count(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, rule: str = "adhesion_first", decimal: bool = False) -> DataFrame:
    """One row, cnt: numbers for each shared key, bottom up. Two bags meet in one ordinary join. Where relations are sent
    to every task and a variable is in all bags, tasks get its values and join the whole bags for them by blocks."""
    first = common(query, catalog, td) if len(td) > 2 and not decimal else None
    if first is not None:
        td.validate(query)
        atoms = [a.variables for a in query.atoms]
        rows = kernel.bagtree_rows(query, catalog, td, [(bag_order(td, v, rule), bag_atoms(td, v, atoms)) for v in td.preorder()], first)
        if rows is not None:
            total = F.coalesce(F.sum("value"), F.lit(0))
            return rows.agg(F.when(total < F.lit(2**63 - 1), total.cast("long")).otherwise(F.raise_error(F.lit("count beyond 64 bits")).cast("long")).alias("cnt"))
    nodes, sent = bags(query, catalog, td, rule), catalog.sent(query) is not None
    if len(td) == 2:
        shared = sorted(td.adhesion(1))
        out = nodes[0].join(nodes[1], shared) if shared else nodes[0].crossJoin(nodes[1])
        return out.agg(F.count(F.lit(1)).cast(count_type(decimal)).alias("cnt"))

    def up(v):
        rows, names = nodes[v], []
        for c in td.children(v):
            shared, name = sorted(td.adhesion(c)), f"__c{c}"
            m = up(c).withColumnRenamed("cnt", name)
            rows = recalled(rows, m, shared, sent) if shared else rows.crossJoin(m)
            names.append(F.col(name))
        total = sum_product(names, decimal) if names else F.count(F.lit(1)).cast(count_type(decimal))
        return rows.groupBy(*sorted(td.adhesion(v))).agg(total.alias("cnt"))

    return up(0).select(F.coalesce("cnt", F.lit(0)).cast(count_type(decimal)).alias("cnt"))


def bagtree_evaluate(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, rule: str = "adhesion_first", two_bag_shortcut: bool = True) -> DataFrame:
    """Every result row: semijoins up and down the tree, then the join."""
    nodes = bags(query, catalog, td, rule)
    semi = lambda a, b, on: a.join(b.select(*on).distinct(), on, "left_semi") if on else a.join(b.limit(1).select(F.lit(0).alias("__any")), F.lit(True), "left_semi")
    if len(td) > 2 or not two_bag_shortcut:
        for v in reversed(td.preorder()[1:]):
            p = td.parents[v]
            nodes[p] = semi(nodes[p], nodes[v], sorted(td.adhesion(v)))
        for v in td.preorder()[1:]:
            nodes[v] = semi(nodes[v], nodes[td.parents[v]], sorted(td.adhesion(v)))
    out = nodes[0]
    for v in td.preorder()[1:]:
        shared = sorted(td.adhesion(v))
        out = out.join(nodes[v], shared) if shared else out.crossJoin(nodes[v])
    return out.select(*query.variables)


def bag_rows(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD) -> DataFrame:
    """node, in_bags, demanded: rows of each whole bag, and of those the ones that earlier nodes and children ask for."""
    whole, asked = bags(query, catalog, td), evaluate_factorised(query, catalog, td).nodes
    out = None
    for v in td.preorder():
        n = whole[v].agg(F.count(F.lit(1)).alias("in_bags")).crossJoin(asked[v].agg(F.count(F.lit(1)).alias("demanded")))
        one = n.select(F.lit(v).cast("long").alias("node"), "in_bags", "demanded")
        out = one if out is None else out.unionByName(one)
    return out
