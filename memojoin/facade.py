"""One object for relations, queries, plans and executors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from memojoin.operators import kernel as K
from memojoin.operators.bagtree import bagtree_count, bagtree_evaluate
from memojoin.operators.catalog import Catalog, prereduce
from memojoin.operators.factorised import FactorisedResult, evaluate_factorised, memo_evaluate
from memojoin.operators.frontier import memo_count, plain_count, plain_rows
from memojoin.operators.pairwise import pairwise_count, pairwise_rows
from memojoin.operators.policy import CachePolicy
from memojoin.plans.decomp import OrderedTD, default_order
from memojoin.plans.planner import Plan, choose_plan, explain_choice
from memojoin.plans.query import ConjunctiveQuery, parse_cq
from memojoin.plans.stats import Stats, collect_stats

METHODS = ("memo", "plain", "bagtree", "pairwise")


def _check(method: str, executor: str, executors: tuple[str, ...]) -> None:
    """Refuse what would run as something else."""
    if method not in METHODS or executor not in executors:
        raise ValueError(f"method {method!r} or executor {executor!r} is not one of {METHODS}, {executors}")
    if executor != "frontier" and method not in ("memo", "plain"):
        raise ValueError(f"the {executor} executor runs methods memo and plain")


class Bound:
    """A query over the facade's relations."""

    def __init__(self, owner: MemoJoin, query: ConjunctiveQuery):
        self.owner, self.query = owner, query
        self._plan: Plan | None = None
        self._stats: Stats | None = None

    def where(self, variable: str, condition: str) -> Bound:
        return Bound(self.owner, self.query.where(variable, condition))

    def having(self, comparison: str) -> Bound:
        return Bound(self.owner, self.query.having(comparison))

    def prereduced(self) -> Bound:
        """The same query over atoms without rows that some other atom rules out."""
        query, catalog = prereduce(self.query, self.owner.catalog)
        owner = MemoJoin(self.owner.spark)
        owner.catalog = catalog
        return Bound(owner, query)

    def stats(self) -> Stats:
        self._stats = self._stats or collect_stats(self.query, self.owner.catalog)
        return self._stats

    def plan(self, td: OrderedTD | None = None, order=None, policy: CachePolicy | None = None, objective: str = "memo") -> Plan:
        if td is None and self._plan is None:
            self._plan = choose_plan(self.query, self.owner.catalog, objective, stats=self.stats())
        base = self._plan if td is None else Plan(td, default_order(td))
        return Plan(base.td, tuple(order or base.order), policy or base.policy)

    def count(self, method: str = "memo", executor: str = "frontier", count_type: str = "auto", td=None, order=None, policy=None, **options) -> DataFrame:
        """One row, cnt. count_type auto: bigint, and decimal(38,0) where that overflows (which runs the count)."""
        q, c = self.query, self.owner.catalog
        _check(method, executor, ("frontier", "kernel", "hypercube"))
        if method == "pairwise":
            return pairwise_count(q, c, **options)
        p = self.plan(td, order, policy)
        if executor == "hypercube":
            return K.hypercube_count(q, c, p.td if method == "memo" else None, p.order, p.policy, **options)
        if executor == "kernel":
            return K.kernel_count(q, c, p.td if method == "memo" else None, p.order, p.policy, **options)
        if method == "plain":
            return plain_count(q, c, p.order, **options)
        run = (lambda d: memo_count(q, c, p.td, p.order, p.policy, decimal=d, **options)) if method == "memo" else (lambda d: bagtree_count(q, c, p.td, decimal=d, **options))
        if count_type != "auto":
            return run(count_type == "decimal")
        try:
            row = run(False).first()
            return self.owner.spark.createDataFrame([(row["cnt"],)], "cnt long")
        except Exception as e:
            if "ARITHMETIC_OVERFLOW" not in str(e) and "long overflow" not in str(e):
                raise
            return run(True)

    def evaluate(self, method: str = "memo", executor: str = "frontier", td=None, order=None, **options) -> DataFrame:
        q, c = self.query, self.owner.catalog
        _check(method, executor, ("frontier", "kernel"))
        if executor == "kernel" and method == "memo":
            raise ValueError("the kernel evaluates without a memo: use method plain, or the frontier executor")
        if method == "pairwise":
            return pairwise_rows(q, c, **options)
        p = self.plan(td, order)
        if executor == "kernel":
            return K.kernel_evaluate(q, c, p.order, **options)
        if method == "plain":
            return plain_rows(q, c, p.order, **options)
        return bagtree_evaluate(q, c, p.td, **options) if method == "bagtree" else memo_evaluate(q, c, p.td, p.order, **options)

    def factorised(self, td=None, order=None) -> FactorisedResult:
        p = self.plan(td, order)
        return evaluate_factorised(self.query, self.owner.catalog, p.td, p.order)

    def metrics(self, method: str = "memo", **options) -> DataFrame:
        p = self.plan()
        return K.kernel_metrics(self.query, self.owner.catalog, p.td if method == "memo" else None, p.order, **options)

    def explain(self) -> DataFrame:
        return explain_choice(self.query, self.owner.catalog, self.stats())


class MemoJoin:
    """MemoJoin(spark).relation("E", edges).query("E(a,b), E(b,c)").count()"""

    def __init__(self, spark: SparkSession):
        self.spark, self.catalog = spark, Catalog()

    def relation(self, name: str, df: DataFrame, columns: list[str] | None = None) -> MemoJoin:
        self.catalog.bind(name, df, columns)
        return self

    def query(self, text: str | ConjunctiveQuery) -> Bound:
        return Bound(self, parse_cq(text) if isinstance(text, str) else text)

    def sql_view(self, name: str, text: str) -> DataFrame:
        """The query's results as a temporary view."""
        out = self.query(text).evaluate()
        out.createOrReplaceTempView(name)
        return out
