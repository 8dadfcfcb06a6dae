"""Statistics of relations: how many distinct prefixes each atom has, and how often values occur."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import functions as F

from memojoin.operators.catalog import Catalog, normalise
from memojoin.plans.query import ConjunctiveQuery


@dataclass
class Stats:
    """prefixes[atom][columns as a frozenset of variables]: distinct bindings; skew[atom][variable]: share of pairs that agree."""

    prefixes: dict[int, dict[frozenset, float]] = field(default_factory=dict)
    skew: dict[int, dict[str, float]] = field(default_factory=dict)

    def rows(self, atom: int) -> float:
        return self.prefixes[atom][max(self.prefixes[atom], key=len)]


def collect_stats(query: ConjunctiveQuery, catalog: Catalog, mode: str = "exact") -> Stats:
    """One pass for each distinct atom shape: all subsets of its variables by grouping sets (few columns, few rows out).

    mode "approx" counts distinct bindings by sketches instead, without a shuffle of the bindings.
    """
    out, known = Stats(), {}
    for k, atom in enumerate(query.atoms):
        names = list(atom.variables)
        shape = (atom.relation, tuple(t if not isinstance(t, str) else names.index(t) for t in atom.terms), tuple(c for x, c in query.selections if x in names))
        if shape not in known:
            df = normalise(atom, catalog, query)
            subsets = [[x for i, x in enumerate(names) if m >> i & 1] for m in range(1, 1 << len(names))]
            pos = lambda s, names=names: frozenset(names.index(x) for x in s)
            if not names:
                known[shape] = ({frozenset(): 1.0}, {})
            elif mode == "approx":
                row = df.agg(*[F.approx_count_distinct(F.struct(*s)).alias(f"c{j}") for j, s in enumerate(subsets)]).first()
                known[shape] = ({pos(s): float(row[f"c{j}"]) for j, s in enumerate(subsets)}, {})
            else:
                cube = df.cube(*names).agg(F.count(F.lit(1)).alias("__n"), F.grouping_id().alias("__g"))
                got = cube.groupBy("__g").agg(F.count(F.lit(1)).alias("d"), F.sum(F.col("__n").cast("double") * F.col("__n")).alias("m2"), F.sum("__n").alias("s")).collect()
                prefixes, skew = {frozenset(): 1.0}, {}
                for r in got:
                    kept = frozenset(i for i in range(len(names)) if not r["__g"] >> (len(names) - 1 - i) & 1)
                    prefixes[kept] = float(r["d"])
                    if len(kept) == 1 and r["s"]:
                        skew[next(iter(kept))] = r["m2"] / float(r["s"]) ** 2
                known[shape] = (prefixes, skew)
        prefixes, skew = known[shape]
        out.prefixes[k] = {frozenset(names[i] for i in s): v for s, v in prefixes.items()}
        out.skew[k] = {names[i]: v for i, v in skew.items()}
    return out


def support_table(query: ConjunctiveQuery, catalog: Catalog, variable: str):
    """value, support: for each value of a variable, the most rows that any atom has with it."""
    counts = None
    for atom in query.atoms:
        if variable in atom.variables:
            one = normalise(atom, catalog, query).groupBy(F.col(variable).alias("value")).agg(F.count(F.lit(1)).alias("support"))
            counts = one if counts is None else counts.unionByName(one)
    return counts.groupBy("value").agg(F.max("support").alias("support"))
