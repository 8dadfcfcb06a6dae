"""Relations bound by name, and atoms as sets of variable bindings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from memojoin.functions.scalars import key
from memojoin.plans.query import Atom, ConjunctiveQuery, Const

#: A relation of so many rows at most, all numbers, is sent to every task by the frontier, if the driver's heap has so many
#: bytes for each row: some 100 for each of three hashed forms (by either column and by both), and room to build them.
SENT_ROWS, SENT_BYTES = 1 << 21, 512


class Catalog:
    """Named DataFrames; the columns of each in the order of an atom's terms."""

    def __init__(self, relations: dict[str, DataFrame] | None = None):
        self.relations: dict[str, DataFrame] = {}
        self._few: dict[str, int | None] = {}
        for name, df in (relations or {}).items():
            self.bind(name, df)

    def bind(self, name: str, df: DataFrame, columns: list[str] | None = None) -> Catalog:
        self.relations[name] = df.select(*columns) if columns else df
        self._few.pop(name, None)
        return self

    def few(self, name: str) -> int | None:
        """The relation's rows, if they are few and narrow enough to be sent to every task, else None; counted once."""
        if name not in self._few:
            df = self.relations[name]
            narrow = not df.isStreaming and all(isinstance(f.dataType, T.NumericType) for f in df.schema)
            most = min(SENT_ROWS, df.sparkSession._jvm.java.lang.Runtime.getRuntime().maxMemory() // SENT_BYTES)
            n = df.limit(most + 1).count() if narrow else most + 1
            self._few[name] = n if n <= most else None
        return self._few[name]

    def sent(self, query: ConjunctiveQuery) -> int | None:
        """Rows of the largest relation if all that the query names are sent to every task, else None."""
        rows = [self.few(name) for name in dict.fromkeys(a.relation for a in query.atoms)]
        return None if None in rows else max(rows)

    def __getitem__(self, name: str) -> DataFrame:
        return self.relations[name]


def normalise(atom: Atom, catalog: Catalog, query: ConjunctiveQuery | None = None, distinct: bool = True) -> DataFrame:
    """The distinct bindings of the atom's variables: constants and repeated variables become filters, nulls go.

    Filters stand right above the scan, so that they and the column choice reach the files.
    """
    df = catalog[atom.relation]
    if len(atom.terms) != len(df.columns):
        raise ValueError(f"{atom.relation} has {len(df.columns)} columns, the atom {len(atom.terms)} terms")
    first: dict[str, str] = {}
    conditions: list[Column] = []
    for term, column in zip(atom.terms, df.columns):
        if isinstance(term, Const):
            conditions.append(F.col(column) == F.lit(term.value))
        elif term in first:
            conditions.append(F.col(first[term]) == F.col(column))
        else:
            first[term] = column
    for column in first.values():
        conditions.append(F.col(column).isNotNull())
    for c in conditions:
        df = df.where(c)
    fields = {f.name: f.dataType for f in df.schema}
    out = df.select(*[key(F.col(c), fields[c]).alias(v) for v, c in first.items()])
    floating = [v for v, c in first.items() if isinstance(fields[c], (T.DoubleType, T.FloatType))]
    out = out.dropna(subset=floating) if floating else out
    for variable, condition in query.selections if query else ():
        if variable in first:
            out = out.where(condition)
    if not first:  # only constants: one row or none
        return df.limit(1).select(F.lit(1).alias("__one"))
    return out.distinct() if distinct else out


def atom_tables(query: ConjunctiveQuery, catalog: Catalog) -> list[tuple[tuple[str, ...], DataFrame]]:
    """Variables and bindings of every atom."""
    return [(a.variables, normalise(a, catalog, query)) for a in query.atoms]


def empty_row(spark) -> DataFrame:
    """One row without a binding: where every search starts."""
    return spark.range(1).select(F.lit(0).cast(T.ByteType()).alias("__start"))


def prereduce(query: ConjunctiveQuery, catalog: Catalog) -> tuple[ConjunctiveQuery, Catalog]:
    """The query over atoms without dangling rows: each keeps the rows whose values every other atom has too.

    For each variable, the values that all its atoms share are intersected first, so an atom is read once and meets
    one list of values for each of its variables.
    """
    tables = atom_tables(query, catalog)
    shared = {}
    for x in query.variables:
        lists = [df.select(x).distinct() for v, df in tables if x in v]
        if len(lists) > 1:
            keep = lists[0]
            for other in lists[1:]:
                keep = keep.join(other, x, "left_semi")
            shared[x] = keep
    reduced, atoms = Catalog(), []
    for k, (variables, df) in enumerate(tables):
        if not variables:
            atoms.append(query.atoms[k])
            reduced.bind(query.atoms[k].relation, catalog[query.atoms[k].relation])
            continue
        for x in variables:
            if x in shared:
                df = df.join(shared[x], x, "left_semi")
        name = f"__atom{k}"
        reduced.bind(name, df.select(*variables))
        atoms.append(Atom(name, variables))
    return ConjunctiveQuery(atoms, query.selections, query.comparisons), reduced
