"""Variable-at-a-time joins as DataFrame plans: a frontier of partial bindings grows by one variable at a time.

The memo is a table of distinct demanded keys: entering a node of the decomposition, the frontier is reduced to
the distinct values of the variables shared with the parent, the node's subtree is solved once for each, and the
counts come back by a join. So equal keys meet whatever task made them, heavy keys shrink to one row, and the
memo spills as any shuffle does. Without the reduction this is the plain join.

Where all relations are small (their rows are counted first) they are sent to every task, and the frontier is dealt
out once, by its first variable: it then grows where it is, nothing of it is written, and keys with that variable meet
without a shuffle. Larger relations are joined by shuffles.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.functions.scalars import cheapest, count_type, product, sum_product
from memojoin.operators.catalog import Catalog, atom_tables, empty_row
from memojoin.operators.policy import CachePolicy
from memojoin.plans.decomp import OrderedTD, default_order, is_strongly_compatible
from memojoin.plans.query import ConjunctiveQuery

START = "__start"

#: Lets frontiers dealt out by one variable be joined on more than that one where they are.
CO_PARTITION = "spark.sql.requireAllClusterKeysForCoPartition"
#: Rows of the largest relation for each part of a frontier that is dealt out, and the most parts.
PART_ROWS, MOST_PARTS = 1000, 256


@dataclass
class Frontier:
    """Options, atoms and the comparisons of one query."""

    query: ConjunctiveQuery
    catalog: Catalog
    order: tuple[str, ...]
    proposer: str = "static"  # or "cheapest": for each row the atom with fewest extensions
    decimal: bool = False
    atoms: list = field(default_factory=list)

    def __post_init__(self):
        self.atoms = atom_tables(self.query, self.catalog)
        self.spark = self.atoms[0][1].sparkSession
        rows = self.catalog.sent(self.query)
        self.parts = 0
        if rows is not None:
            self.parts = max(min(rows // PART_ROWS, MOST_PARTS), self.spark.sparkContext.defaultParallelism)
            self.atoms = [(v, F.broadcast(df) if v else df) for v, df in self.atoms]
            self.spark.conf.set(CO_PARTITION, "false")

    def level(self, variables: tuple[str, ...], df: DataFrame, have: list[str]) -> DataFrame:
        """The atom at the depth of the trie that the bound variables reach."""
        keep = [v for v in variables if v in have]
        return df if len(keep) == len(variables) else df.select(*keep).distinct()

    def bind(self, rows: DataFrame, bound: list[str], x: str) -> DataFrame:
        """rows with every value of x that all atoms with x allow."""
        sides = []
        for variables, df in self.atoms:
            if x in variables:
                before = [v for v in variables if v in bound]
                sides.append((before, self.level(variables, df, [*before, x])))
        sides.sort(key=lambda s: -len(s[0]))
        tied = [s for s in sides if s[0]]
        if not tied:  # nothing bound to start from: the values that all atoms share
            values = sides[0][1].select(x)
            for _, df in sides[1:]:
                values = values.join(df.select(x), x, "left_semi")
            if self.parts:
                values = F.broadcast(values)
            out = rows.crossJoin(values)
            if self.parts and not bound:
                out = out.repartition(self.parts, x)
        elif self.proposer == "cheapest" and len(tied) > 1:
            out = self._cheapest(rows, tied, x)
        else:
            before, df = tied[0]
            out = rows.join(df, before)
            for before, df in tied[1:]:
                out = out.join(df, [*before, x], "left_semi")
        for before, df in sides:
            if not before and tied:
                out = out.join(df.select(x), x, "left_semi")
        now = {*bound, x}
        for text in self.query.comparisons:
            names = self.query.compared(text)
            if x in names and names <= now:
                out = out.where(text)
        return out

    def _cheapest(self, rows: DataFrame, tied: list, x: str) -> DataFrame:
        """Each row goes to the atom that offers fewest values; the other atoms check what it offers."""
        ways = rows
        for k, (before, df) in enumerate(tied):
            ways = ways.join(df.groupBy(*before).agg(F.count(F.lit(1)).alias(f"__d{k}")), before)
        names = rows.columns
        ways = ways.withColumn("__by", cheapest([F.col(f"__d{k}") for k in range(len(tied))])).select(*names, "__by")
        out = None
        for k, (before, df) in enumerate(tied):
            part = ways.where(F.col("__by") == k).drop("__by").join(df, before)
            for j, (other, check) in enumerate(tied):
                if j != k:
                    part = part.join(check, [*other, x], "left_semi")
            part = part.select(*names, x)
            out = part if out is None else out.unionByName(part)
        return out

    def grow(self, rows: DataFrame, bound: list[str], names) -> DataFrame:
        bound = list(bound)
        for x in names:
            rows = self.bind(rows, bound, x)
            bound.append(x)
        return rows

    def constants_hold(self, rows: DataFrame) -> DataFrame:
        """Atoms without variables only switch the result on or off."""
        for variables, df in self.atoms:
            if not variables:
                rows = rows.crossJoin(df.select("__one")).drop("__one")
        return rows

    def recalled(self, rows: DataFrame, message: DataFrame, shared: list[str]) -> DataFrame:
        return recalled(rows, message, shared, bool(self.parts))


def recalled(rows: DataFrame, message: DataFrame, shared: list[str], sent: bool) -> DataFrame:
    """rows with what a message (a row for each key) tells. Where rows grow in tasks, each task keeps its part of the
    message as a hash table and the rows, far more, pass by unsorted; else both are sorted, which may spill."""
    return rows.join(message.hint("shuffle_hash") if sent else message, shared)


def _options(query, catalog, order, proposer, decimal) -> Frontier:
    return Frontier(query, catalog, tuple(order), proposer, decimal)


def plain_rows(query: ConjunctiveQuery, catalog: Catalog, order, proposer: str = "static") -> DataFrame:
    """Every result row, with a column for each variable: the uncached join."""
    f = _options(query, catalog, order, proposer, False)
    out = f.grow(f.constants_hold(empty_row(f.spark)), [], f.order)
    return out.select(*f.order)


def plain_count(query: ConjunctiveQuery, catalog: Catalog, order, proposer: str = "static") -> DataFrame:
    """One row: cnt."""
    return plain_rows(query, catalog, order, proposer).agg(F.count(F.lit(1)).alias("cnt"))


def check_plan(query: ConjunctiveQuery, td: OrderedTD, order) -> tuple[str, ...]:
    td.validate_for_memo(query)
    order = tuple(order or default_order(td))
    if set(order) != set(query.variables) or not is_strongly_compatible(td, order):
        raise ValueError("the variable order does not go through the decomposition node by node")
    for text in query.comparisons:
        if not any(query.compared(text) <= b for b in td.bags):
            raise ValueError(f"no bag holds the comparison {text}")
    return order


def dealt_order(td: OrderedTD) -> tuple[str, ...]:
    """The default order, but that the root starts with a variable that its last child shares, if it has one: a frontier
    dealt out by it holds equal keys of that child in one part, so they meet without a shuffle."""
    order = default_order(td)
    shared = td.adhesion(td.children(0)[-1]) if td.children(0) else ()
    first = next((x for x in order if x in shared), order[0])
    return first, *(x for x in order if x != first)


def memo_count(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, order=None, policy: CachePolicy | None = None, proposer: str = "static", decimal: bool = False, observe: Callable | None = None) -> DataFrame:
    """One row: cnt. observe(node, frontier, adhesion) sees the frontier that demands each node, before reduction.

    On the way from the root along last children, a key's demand carries how many bindings ask for it, so each
    frontier is read once: equal keys are added up instead of being looked up. Counts of the other children come
    back to their parent's rows by a join, and so do those below them.
    """
    order, policy = check_plan(query, td, order or dealt_order(td)), policy or CachePolicy.always()
    policy.check_frontier()
    f = _options(query, catalog, order, proposer, decimal)

    def owned(v):
        return [x for x in order if td.owner(x) == v]

    def counted(rows, children):
        """rows with the counts of these children, and the names of their columns."""
        names = []
        for c in children:
            shared, name = sorted(td.adhesion(c)), f"__c{c}"
            if observe:
                observe(c, rows, shared)
            if not shared:
                message = solve(c, empty_row(f.spark), [])
                rows = rows.crossJoin(message.withColumnRenamed("cnt", name))
            else:
                rows = _recall(f, td, policy, c, rows, shared, name, solve)
            names.append(name)
        return rows, names

    def solve(v: int, demand: DataFrame, keys: list[str]) -> DataFrame:
        """keys and cnt for every row of demand that has an extension (keys name the columns that come back)."""
        rows, names = counted(f.grow(demand, sorted(td.adhesion(v)), owned(v)), td.children(v))
        total = sum_product([F.col(n) for n in names], decimal) if names else F.count(F.lit(1)).cast(count_type(decimal))
        return (rows.groupBy(*keys) if keys else rows.groupBy()).agg(total.alias("cnt"))

    def follow(v: int, demand: DataFrame) -> DataFrame:
        """The one-row count below a demand whose rows stand for __times bindings each."""
        children = td.children(v)
        rows, names = counted(f.grow(demand, sorted(td.adhesion(v)), owned(v)), children[:-1])
        times = [F.col("__times"), *(F.col(n) for n in names)]
        if not children:
            return rows.groupBy().agg(sum_product(times, decimal).alias("cnt"))
        c = children[-1]
        shared = sorted(td.adhesion(c))
        if observe:
            observe(c, rows, shared)
        rows = rows.select(*[x for x in rows.columns if not x.startswith("__")], product(times, decimal).alias("__times"))
        add = lambda part: (part.groupBy(*shared) if shared else part.groupBy()).agg(sum_product([F.col("__times")], decimal).alias("__times")).where("__times IS NOT NULL")
        narrow = lambda part: part.select(*shared, "__times")
        if not policy.caches(c, shared):
            return follow(c, narrow(rows))
        admitted = policy.admitted_rows(f, rows, shared, c)
        if admitted is None:
            return follow(c, add(rows))
        return follow(c, add(admitted[0]).unionByName(narrow(admitted[1])))

    start = f.constants_hold(empty_row(f.spark)).withColumn("__times", F.lit(1).cast(count_type(decimal)))
    return follow(0, start).select(F.coalesce("cnt", F.lit(0)).cast(count_type(decimal)).alias("cnt"))


def _recall(f: Frontier, td, policy, c, rows, shared, name, solve) -> DataFrame:
    """rows with the count of node c: from the memo where the policy admits the key, else solved row by row."""
    memo = lambda part: f.recalled(part, solve(c, part.select(*shared).distinct(), shared).withColumnRenamed("cnt", name), shared)

    def direct(part):
        # bindings are distinct, so a row's own variables name it and no row numbers are needed
        names = [x for x in part.columns if not x.startswith("__")]
        return f.recalled(part, solve(c, part.select(*names).distinct(), names).withColumnRenamed("cnt", name), names)

    if not policy.caches(c, shared):
        return direct(rows)
    admitted = policy.admitted_rows(f, rows, shared, c)
    if admitted is None:
        return memo(rows)
    yes, no = admitted
    return memo(yes).unionByName(direct(no))
