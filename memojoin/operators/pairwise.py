"""The conventional rival: binary joins of whole atoms, in the order given or as the optimiser likes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.operators.catalog import Catalog, atom_tables
from memojoin.plans.query import ConjunctiveQuery


def pairwise_rows(query: ConjunctiveQuery, catalog: Catalog, hint: str | None = None) -> DataFrame:
    """hint: None, shuffle_hash, merge or broadcast. Connected atoms are joined first."""
    left = atom_tables(query, catalog)
    variables, out = left.pop(0)
    bound, todo = set(variables), list(query.comparisons)
    while left:
        k = next((k for k, (v, _) in enumerate(left) if bound & set(v)), 0)
        v, df = left.pop(k)
        shared = [x for x in v if x in bound]
        side = df.hint(hint) if hint else df
        out = out.join(side, shared) if shared else out.crossJoin(side)
        bound |= set(v)
        for text in [t for t in todo if query.compared(t) <= bound]:
            out, todo = out.where(text), [t for t in todo if t != text]
    return out.select(*query.variables) if query.variables else out


def pairwise_count(query: ConjunctiveQuery, catalog: Catalog, hint: str | None = None) -> DataFrame:
    return pairwise_rows(query, catalog, hint).agg(F.count(F.lit(1)).alias("cnt"))
