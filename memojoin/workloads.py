"""The experiment workloads on the given tables, as named queries with SQL to compare."""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from memojoin.functions.measures import hit_account, skew_profile
from memojoin.operators import kernel as K
from memojoin.operators.bagtree import bag_rows, bagtree_count, bagtree_evaluate
from memojoin.operators.catalog import Catalog, prereduce
from memojoin.operators.factorised import evaluate_factorised, memo_evaluate
from memojoin.operators.frontier import memo_count, plain_count, plain_rows
from memojoin.operators.pairwise import pairwise_count, pairwise_rows
from memojoin.operators.policy import CachePolicy
from memojoin.operators.semiring import aggregate
from memojoin.plans import cost
from memojoin.plans.decomp import OrderedTD, default_order
from memojoin.plans.enumeration import enumerate_tds, split_decompose
from memojoin.plans.planner import choose_plan, explain_choice
from memojoin.plans.query import Atom, ConjunctiveQuery, Const, parse_cq
from memojoin.plans.stats import collect_stats
from memojoin.sources import relations as R

# ---------------------------------------------------------------- shapes


def path(k: int) -> ConjunctiveQuery:
    """k variables in a row."""
    return parse_cq(", ".join(f"E(x{i},x{i + 1})" for i in range(1, k)))


def cycle(k: int) -> ConjunctiveQuery:
    """A path whose ends an edge from the first to the last variable closes."""
    return ConjunctiveQuery([*path(k).atoms, Atom("E", ("x1", f"x{k}"))])


def graph_query(text: str) -> ConjunctiveQuery:
    """From edges like `1-3 2-5`."""
    return ConjunctiveQuery([Atom("E", tuple(f"x{v}" for v in e.split("-"))) for e in text.split()])


def clique(k: int) -> ConjunctiveQuery:
    return ConjunctiveQuery([Atom("E", (f"x{i}", f"x{j}")) for i, j in combinations(range(1, k + 1), 2)])


def path_td(k: int) -> OrderedTD:
    return OrderedTD.chain(*[{f"x{i}", f"x{i + 1}"} for i in range(1, k)])


def cycle_td(k: int) -> OrderedTD:
    return OrderedTD.chain(*[{"x1", f"x{i}", f"x{i + 1}"} for i in range(2, k)])


LOLLIPOP = parse_cq("E(a,b), E(b,c), E(a,c), E(c,d), E(d,e)")
LOLLIPOP_TDS = {
    "cs1": OrderedTD.chain("abc", "cde"),
    "cs2": OrderedTD.chain("abc", "cd", "de"),
    "cs3": OrderedTD.chain("abc", "bcd", "de"),
}
BIP4 = parse_cq("A(p1,m1), A(p1,m2), B(p2,m1), B(p2,m2)")
BIP6 = parse_cq("A(p1,m1), A(p1,m2), B(p2,m2), B(p2,m3), A(p3,m1), A(p3,m3)")
BIP_TDS = {
    ("4", "person"): OrderedTD.chain({"p1", "p2", "m1"}, {"p1", "p2", "m2"}),
    ("4", "movie"): OrderedTD.chain({"p1", "m1", "m2"}, {"p2", "m1", "m2"}),
    ("6", "person"): OrderedTD.chain({"p1", "m1", "p3"}, {"p1", "m2", "p3"}, {"m2", "p2", "p3"}, {"p2", "p3", "m3"}),
    ("6", "movie"): OrderedTD.chain({"p1", "m1", "m2"}, {"m1", "m2", "p3"}, {"m2", "p3", "m3"}, {"p2", "m2", "m3"}),
}
LOCAL_SUPPLIER = parse_cq("LS(o,s), O(o,c), C(c,n), S(s,n)")
LOCAL_TD = OrderedTD.chain({"s", "n", "c"}, {"s", "c", "o"})
STAR2 = parse_cq("E(x,y), E(z,x)")
EXAMPLE = graph_query("1-2 2-3 2-4 3-4 3-5 4-6")
EXAMPLE_TD = OrderedTD.from_nested(({"x1", "x2"}, [({"x2", "x3", "x4"}, [({"x3", "x5"}, []), ({"x4", "x6"}, [])])]))
#: Frozen random graphs (fixed values): connected, by number of nodes and edge probability in tenths.
RANDOM = {
    "rand5_4_1": "1-3 1-4 1-5 2-5 3-4 3-5", "rand5_4_2": "1-2 2-3 2-4 3-4 3-5", "rand5_4_3": "1-2 1-4 2-3 2-4 2-5 3-4", "rand5_4_4": "1-3 2-3 3-4 3-5 4-5", "rand5_4_5": "1-4 2-3 3-5 4-5", "rand5_4_6": "1-2 1-3 2-5 3-4 3-5",
    "rand5_6_1": "1-4 2-3 2-4 2-5 4-5", "rand5_6_2": "1-2 1-4 2-5 3-4 3-5 4-5", "rand5_6_3": "1-4 1-5 2-3 2-4 2-5 4-5", "rand5_6_4": "1-2 1-4 2-3 2-4 2-5 3-4 3-5", "rand5_6_5": "1-2 1-3 2-4 3-4 3-5", "rand5_6_6": "1-4 2-3 2-5 4-5",
    "rand6_4_1": "1-6 2-3 3-4 3-5 3-6 4-6", "rand6_4_2": "1-3 2-3 2-4 2-5 2-6 3-4 3-5 3-6", "rand6_4_3": "1-3 1-4 1-5 2-3 2-5 5-6", "rand6_4_4": "1-3 1-6 2-3 2-6 3-4 4-5 5-6", "rand6_4_5": "1-5 1-6 2-3 2-5 2-6 3-4 4-5 4-6", "rand6_4_6": "1-2 1-3 1-4 1-6 2-3 2-4 3-4 5-6",
    "rand6_6_1": "1-2 1-4 1-5 1-6 2-4 2-6 3-4 3-5 4-5 4-6 5-6", "rand6_6_2": "1-4 2-3 2-4 2-5 2-6 3-4 3-5 4-6", "rand6_6_3": "1-3 1-4 1-5 1-6 2-3 2-5 2-6 3-4 4-6 5-6", "rand6_6_4": "1-3 1-4 1-6 2-3 2-5 2-6 3-5 3-6 4-5 5-6", "rand6_6_5": "1-3 1-6 2-3 2-4 2-5 3-4 4-5 4-6 5-6", "rand6_6_6": "1-2 1-3 1-4 1-6 2-6 3-4 3-5 3-6 4-5",
}

# ---------------------------------------------------------------- SQL written apart from the executors


def elimination_sql(query: ConjunctiveQuery, sql: dict[str, str], columns: dict[str, list[str]]) -> str:
    """Count by eliminating variables one by one, each a grouped sum of products: fewest neighbours first."""
    ctes = [f"{name} AS ({text})" for name, text in sql.items()]
    factors = []
    for k, a in enumerate(query.atoms):
        wheres, seen = [], {}
        for t, c in zip(a.terms, columns[a.relation]):
            if isinstance(t, Const):
                wheres.append(f"{c} = {t.value!r}")
            elif t in seen:
                wheres.append(f"{c} = {seen[t]}")
            else:
                seen[t] = c
        cond = " WHERE " + " AND ".join(wheres) if wheres else ""
        ctes.append(f"f{k} AS (SELECT DISTINCT {', '.join(f'{c} AS {t}' for t, c in seen.items())}, 1::HUGEINT AS __n FROM {a.relation}{cond})")
        factors.append((frozenset(seen), f"f{k}"))
    left, k = set(query.variables), len(factors)
    while left:
        def around(x):
            return frozenset().union(*(v for v, _ in factors if x in v)) - {x}

        x = min(sorted(left), key=lambda x: len(around(x)))
        mine = [f for f in factors if x in f[0]]
        keep = sorted(around(x))
        text, have = mine[0][1], set(mine[0][0])
        for j, (v, name) in enumerate(mine[1:]):
            text, have = f"{text} JOIN {name} USING ({', '.join(sorted(v & have))})", have | v
        total = " * ".join(f"{name}.__n" for _, name in mine)
        group = f" GROUP BY {', '.join(keep)}" if keep else ""
        ctes.append(f"f{k} AS (SELECT {''.join(c + ', ' for c in keep)}sum({total})::HUGEINT AS __n FROM {text}{group})")
        factors = [f for f in factors if x not in f[0]] + [(frozenset(keep), f"f{k}")]
        left, k = left - {x}, k + 1
    product = " * ".join(f"coalesce((SELECT __n FROM {name}), 0)" for _, name in factors)
    return f"WITH {', '.join(ctes)} SELECT ({product})::BIGINT AS cnt"


def rows_sql(query: ConjunctiveQuery, sql: dict[str, str], columns: dict[str, list[str]], count: bool = False) -> str:
    """All results by a plain self-join."""
    first, wheres = {}, []
    for k, a in enumerate(query.atoms):
        for t, c in zip(a.terms, columns[a.relation]):
            at = f"e{k}.{c}"
            if isinstance(t, Const):
                wheres.append(f"{at} = {t.value!r}")
            elif t in first:
                wheres.append(f"{at} = {first[t]}")
            else:
                first[t] = at
    wheres += [text for text in query.comparisons]
    what = "count(*) AS cnt" if count else ", ".join(f"{c} AS {x}" for x, c in first.items())
    inner = ", ".join(f"{a.relation} e{k}" for k, a in enumerate(query.atoms))
    return f"WITH {', '.join(f'{n} AS ({t})' for n, t in sql.items())} SELECT {what} FROM {inner}" + (f" WHERE {' AND '.join(wheres)}" if wheres else "")


EDGE = {"E": ["s", "t"]}
CAST = {"A": ["p", "m"], "B": ["p", "m"]}
CAST_SQL = {"A": R.SQL["cast_a"], "B": R.SQL["cast_b"]}
STAR_SQL = {"LS": "SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem", "O": "SELECT o_orderkey, o_custkey FROM orders", "C": "SELECT c_custkey, c_nationkey FROM customer", "S": "SELECT s_suppkey, s_nationkey FROM supplier"}
STAR_COLUMNS = {"LS": ["l_orderkey", "l_suppkey"], "O": ["o_orderkey", "o_custkey"], "C": ["c_custkey", "c_nationkey"], "S": ["s_suppkey", "s_nationkey"]}

# ---------------------------------------------------------------- queries


def edges(graph: str) -> Callable[[SparkSession, str], Catalog]:
    return lambda spark, d: Catalog({"E": R.GRAPHS[graph](spark, d)})


def cast(spark, d) -> Catalog:
    return Catalog({"A": R.cast_a(spark, d), "B": R.cast_b(spark, d)})


def suppliers(spark, d) -> Catalog:
    return Catalog({k: v for k, v in R.star(spark, d).items() if k in STAR_SQL})


def ladder(power: int):
    return lambda spark, d: Catalog({"E": R.g_skew(spark, d, power)})


def counted(query, catalog, td, method: str, order=None):
    """A count by one of the methods."""

    def run(spark, d):
        c = catalog(spark, d)
        if method == "memo":
            return memo_count(query, c, td, order)
        if method == "cheapest":
            return memo_count(query, c, td, order, proposer="cheapest")
        if method == "plain":
            return plain_count(query, c, order or default_order(td))
        if method == "bagtree":
            return bagtree_count(query, c, td)
        if method == "bagtree_reverse":
            return bagtree_count(query, c, td, rule="reverse")
        if method.startswith("pairwise"):
            return pairwise_count(query, c, method.removeprefix("pairwise").removeprefix("_") or None)
        if method == "kernel_memo":
            return K.kernel_count(query, c, td, order)
        if method == "kernel_plain":
            return K.kernel_count(query, c, None, order or default_order(td))
        if method == "kernel_scalar":
            return K.kernel_count(query, c, None, order or default_order(td), scalar=True)
        if method == "hypercube":
            return K.hypercube_count(query, c, td, order)
        raise ValueError(method)

    return run


def evaluated(query, catalog, td, method: str):
    def run(spark, d):
        c = catalog(spark, d)
        if method == "memo":
            return memo_evaluate(query, c, td)
        if method == "plain":
            return plain_rows(query, c, default_order(td))
        if method == "bagtree":
            return bagtree_evaluate(query, c, td)
        if method == "kernel":
            return K.kernel_evaluate(query, c)
        return pairwise_rows(query, c)

    return run


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def evaluated_structured(name: str, graph: str, method: str):
    query, td = structured(RANDOM[name])
    return evaluated(query, edges(graph), td, method), rows_sql(query, {"E": R.SQL[graph]}, EDGE)


def narrowest(query) -> OrderedTD:
    """The decomposition of least width, as a planner that knows nothing of memos chooses it."""
    return min(enumerate_tds(query, len(query.variables)), key=lambda t: (t.width(), cost.width(t, query, "fractional"), len(t), str(t.canonical())))


def sweep_work(query, catalog, td, capacities):
    """replacement, capacity (-1: unbounded), accesses and the entries held, all in one task."""

    def run(spark, d):
        c, out = catalog(spark, d), []
        for replacement in ("none", "fifo", "lru", "support"):
            for n in capacities:
                policy = CachePolicy.always().evict(replacement)
                got = K.kernel_metrics(query, c, td, policy=policy if n < 0 else policy.capacity(n), parts=1)
                value = lambda name: F.max(F.when(F.col("name") == name, F.col("total"))).alias(name)
                out.append(got.agg(value("cnt"), value("accesses"), value("entries_peak")).select(F.lit(replacement).alias("replacement"), F.lit(n).cast("long").alias("capacity"), "cnt", "accesses", "entries_peak"))
        return _union(out)

    return run


def reduced(query, catalog, td):
    """The memoised count over atoms without dangling rows."""
    return lambda spark, d: memo_count(*prereduce(query, catalog(spark, d)), td)


def sweep(query, catalog, td, capacities, replacement="lru"):
    """capacity (-1: unbounded) and cnt, which no capacity may change."""

    def run(spark, d):
        c = catalog(spark, d)
        out = []
        for n in capacities:
            policy = CachePolicy.always() if n < 0 else CachePolicy.always().capacity(n).evict(replacement)
            out.append(K.kernel_count(query, c, td, policy=policy).select(F.lit(n).cast("long").alias("capacity"), "cnt"))
        return _union(out)

    return run


def thresholds(spark, d) -> DataFrame:
    c, out = edges("g_skew")(spark, d), []
    for tau in (0, 5, 1_000_000):
        out.append(memo_count(cycle(4), c, cycle_td(4), policy=CachePolicy.support(tau)).select(F.lit(tau).cast("long").alias("tau"), "cnt"))
    return _union(out)


def td_listing(spark, d) -> DataFrame:
    """The nodes of the six-cycle's decomposition, and how many keys each is asked for over g_flat (the root for one)."""
    td, keys = split_decompose(cycle(6)), [spark.range(1).select(F.lit(0).cast("long").alias("node"), F.lit(1).cast("long").alias("keys"))]
    observe = lambda v, rows, shared: keys.append(rows.select(*shared).distinct().agg(F.lit(v).cast("long").alias("node"), F.count(F.lit(1)).alias("keys")))
    memo_count(cycle(6), edges("g_flat")(spark, d), td, observe=observe)
    listed = spark.createDataFrame(td.listing(), "node long, parent long, bag array<string>, adhesion array<string>, owned array<string>")
    return listed.join(F.broadcast(_union(keys)), "node")


#: All decompositions of each shape, as stated for the SQL.
TD_NUMBERS = {"cycle3": 1, "cycle4": 2, "cycle5": 9, "cycle6": 41, "clique4": 1}
TD_SHAPES = {f"cycle{k}": cycle(k) for k in (3, 4, 5, 6)} | {"clique4": clique(4)}


def td_counts(spark, d) -> DataFrame:
    """shape, its decompositions, and its results over g_flat by the one of least structural score."""
    c, out = edges("g_flat")(spark, d), []
    for shape, query in TD_SHAPES.items():
        n = sum(1 for _ in enumerate_tds(query, per_call=None, limit=None))
        td = min(enumerate_tds(query), key=lambda t: (cost.structural_score(t), str(t.canonical())))
        out.append(memo_count(query, c, td).select(F.lit(shape).alias("shape"), F.lit(n).cast("long").alias("decompositions"), "cnt"))
    return _union(out)


def order_costs(spark, d) -> DataFrame:
    """order, est, probes of the bipartite four-cycle with each side's order."""
    c, rows = cast(spark, d), []
    stats = collect_stats(BIP4, c)
    for side in ("person", "movie"):
        td = BIP_TDS["4", side]
        order = default_order(td)
        probes = K.kernel_metrics(BIP4, c, None, order).where("name = 'trie_probes'").first()
        rows.append((",".join(order), float(cost.order_cost(order, BIP4, stats)), float(cost.memo_order_cost(td, order, BIP4, stats)), int(probes["total"] or 0)))
    return spark.createDataFrame(rows, "variable_order string, est double, memo_est double, probes long")


def counters(query, catalog, td):
    """method and the kernel's counters."""

    def run(spark, d):
        c = catalog(spark, d)
        one = lambda name, **o: K.kernel_metrics(query, c, parts=1, **o).select(F.lit(name).alias("method"), "name", "total")
        return one("memo", td=td).unionByName(one("plain", td=None, order=default_order(td)))

    return run


def hits(query, catalog, td):
    """entries, misses, hits of the first node below the root."""

    def run(spark, d):
        seen = {}
        memo_count(query, catalog(spark, d), td, observe=lambda c, rows, shared: seen.setdefault(c, hit_account(rows, shared)))
        return seen[1]

    return run


def factors(query, catalog, td):
    return lambda spark, d: evaluate_factorised(query, catalog(spark, d), td).count()


def planned(query, catalog):
    """The memoised count with the planner's own choice."""

    def run(spark, d):
        c = catalog(spark, d)
        plan = choose_plan(query, c)
        return memo_count(query, c, plan.td, plan.order)

    return run


def structured(text: str):
    query = graph_query(text)
    td = min(enumerate_tds(query), key=lambda t: (cost.structural_score(t), str(t.canonical())))
    return query, td


def profile(relation: Callable, column: str):
    return lambda spark, d: skew_profile(relation(spark, d), column).select("values", F.col("rows").cast("long").alias("rows"), "max_count")


def best_weight(spark, d) -> DataFrame:
    """The largest sum of the endpoints along a path of four, and the number of such paths by a sum of ones."""
    c = edges("g_skew")(spark, d)
    w = {f"x{k}": F.col(f"x{k}") for k in range(1, 5)}
    a = aggregate(path(4), c, path_td(4), "max_plus", w).select(F.lit("max").alias("what"), "value")
    b = aggregate(path(4), c, path_td(4), "min_plus", w).select(F.lit("min").alias("what"), "value")
    s = aggregate(path(4), c, path_td(4), "sum_product").select(F.lit("count").alias("what"), "value")
    return a.unionByName(b).unionByName(s)


def _registry() -> tuple[dict, dict]:
    q: dict[str, Callable] = {}
    s: dict[str, str] = {}

    def add(name, run, sql=None):
        q[name] = run
        if sql:
            s[name] = sql

    skew, flat = edges("g_skew"), edges("g_flat")
    on = lambda graph: {"E": R.SQL[graph]}
    for k in range(3, 8):
        n = elimination_sql(path(k), on("g_skew"), EDGE)
        for m in ("memo", "plain", "bagtree", "pairwise") if k <= 5 else ("memo", "bagtree"):
            add(f"path{k}_count_{m}", counted(path(k), skew, path_td(k), m), n)
        add(f"path{k}_flat_count_memo", counted(path(k), flat, path_td(k), "memo"), elimination_sql(path(k), on("g_flat"), EDGE))
    for k in range(3, 7):
        n = elimination_sql(cycle(k), on("g_skew"), EDGE)
        for m in ("memo", "plain", "bagtree", "pairwise") if k <= 4 else ("memo", "bagtree", "kernel_plain") if k == 6 else ("memo", "bagtree", "bagtree_reverse", "plain", "pairwise"):
            add(f"cycle{k}_count_{m}", counted(cycle(k), skew, cycle_td(k), m), n)
        add(f"cycle{k}_flat_count_memo", counted(cycle(k), flat, cycle_td(k), "memo"), elimination_sql(cycle(k), on("g_flat"), EDGE))
    five = elimination_sql(cycle(5), on("g_skew"), EDGE)
    for m in ("cheapest", "kernel_memo", "kernel_plain", "hypercube"):
        add(f"cycle5_count_{m}", counted(cycle(5), skew, cycle_td(5), m), five)
    add("cycle4_count_kernel_scalar", counted(cycle(4), flat, cycle_td(4), "kernel_scalar"), elimination_sql(cycle(4), on("g_flat"), EDGE))
    for h in ("shuffle_hash", "merge", "broadcast"):
        add(f"cycle4_count_pairwise_{h}", counted(cycle(4), skew, cycle_td(4), f"pairwise_{h}"), elimination_sql(cycle(4), on("g_skew"), EDGE))
    for g in ("g_clustered", "g_parts", "g_words"):
        add(f"path5_{g}_count_memo", counted(path(5), edges(g), path_td(5), "memo"), elimination_sql(path(5), on(g), EDGE))
    add("cycle5_g_clustered_count_memo", counted(cycle(5), edges("g_clustered"), cycle_td(5), "memo"), elimination_sql(cycle(5), on("g_clustered"), EDGE))
    for name, text in RANDOM.items():
        query, td = structured(text)
        n, few = elimination_sql(query, on("g_skew"), EDGE), elimination_sql(query, on("g_flat"), EDGE)
        add(f"{name}_count", counted(query, skew, td, "memo"), n)
        add(f"{name}_count_bagtree", counted(query, skew, td, "bagtree"), n)
        big = name in ("rand6_4_1", "rand6_4_2", "rand6_4_3")  # more than 10**8 results there
        if not big:
            add(f"{name}_count_plain", counted(query, skew, td, "plain"), n)
        for m in ("memo", "plain", "bagtree"):
            if big:
                add(f"{name}_flat_count_{m}", counted(query, flat, td, m), few)
            if name.startswith("rand5") and name not in ("rand5_4_5", "rand5_6_6"):  # these have millions of rows
                run, sql = evaluated_structured(name, "g_flat", m)
                add(f"{name}_flat_eval_{m}", run, sql)
    for g in ("g_flat", "g_clustered", "g_parts"):
        query, td = structured(RANDOM["rand5_4_1"])
        for m in ("memo", "bagtree"):
            add(f"path5_{g}_count_{m}", counted(path(5), edges(g), path_td(5), m), elimination_sql(path(5), on(g), EDGE))
            if g != "g_parts":
                add(f"cycle5_{g}_count_{m}", counted(cycle(5), edges(g), cycle_td(5), m), elimination_sql(cycle(5), on(g), EDGE))
                add(f"rand5_4_1_{g}_count_{m}", counted(query, edges(g), td, m), elimination_sql(query, on(g), EDGE))
    add("path5_g_words_count_bagtree", counted(path(5), edges("g_words"), path_td(5), "bagtree"), elimination_sql(path(5), on("g_words"), EDGE))
    for m in ("plain", "bagtree", "pairwise"):
        for k in (6, 7):
            add(f"path{k}_flat_count_{m}", counted(path(k), flat, path_td(k), m), elimination_sql(path(k), on("g_flat"), EDGE))
        add(f"cycle6_flat_count_{m}", counted(cycle(6), flat, cycle_td(6), m), elimination_sql(cycle(6), on("g_flat"), EDGE))
    for name, query, graph in (("path7", path(7), "g_skew"), ("cycle4", cycle(4), "g_skew"), ("cycle5", cycle(5), "g_skew"), ("cycle6", cycle(6), "g_skew"), ("lollipop", LOLLIPOP, "g_skew")):
        add(f"{name}_count_bagtree_width", counted(query, edges(graph), narrowest(query), "bagtree"), elimination_sql(query, on(graph), EDGE))
    add("lollipop_count_plain", counted(LOLLIPOP, skew, LOLLIPOP_TDS["cs1"], "plain"), elimination_sql(LOLLIPOP, on("g_skew"), EDGE))
    add("prereduced_cycle4_count", reduced(cycle(4), skew, cycle_td(4)), elimination_sql(cycle(4), on("g_skew"), EDGE))
    add("intermediate_rows_cycle5", lambda spark, d: bag_rows(cycle(5), edges("g_flat")(spark, d), cycle_td(5)))
    for k in (3, 4):
        for m in ("memo", "plain", "bagtree", "pairwise"):
            add(f"path{k}_eval_{m}", evaluated(path(k), skew, path_td(k), m), rows_sql(path(k), on("g_skew"), EDGE))
            add(f"cycle{k}_eval_{m}", evaluated(cycle(k), skew, cycle_td(k), m), rows_sql(cycle(k), on("g_skew"), EDGE))
    add("cycle4_eval_kernel", evaluated(cycle(4), skew, cycle_td(4), "kernel"), rows_sql(cycle(4), on("g_skew"), EDGE))
    for m in ("memo", "plain", "bagtree"):
        add(f"cycle5_eval_{m}", evaluated(cycle(5), flat, cycle_td(5), m), rows_sql(cycle(5), on("g_flat"), EDGE))
    for name, g in (("rand5_6_2", "g_clustered"), ("rand5_6_4", "g_flat")):
        query, td = structured(RANDOM[name])
        add(f"{name}_eval", evaluated(query, edges(g), td, "memo"), rows_sql(query, on(g), EDGE))

    def with_column(sql, column, values):
        return f"SELECT {column}::BIGINT AS {column}, cnt FROM ({sql}) CROSS JOIN (VALUES {', '.join(f'({v})' for v in values)}) v({column})"

    caps = (0, 100, 10_000, -1)
    bip4, bip6 = elimination_sql(BIP4, CAST_SQL, CAST), elimination_sql(BIP6, CAST_SQL, CAST)
    add("cachesweep_bip4", sweep(BIP4, cast, BIP_TDS["4", "person"], caps), with_column(bip4, "capacity", caps))
    add("cachesweep_cycle6_skew", sweep(cycle(6), ladder(2), cycle_td(6), caps), with_column(elimination_sql(cycle(6), {"E": R.skew_sql(2)}, EDGE), "capacity", caps))
    add("cachesweep_work_cycle5", sweep_work(cycle(5), ladder(2), cycle_td(5), (0, 100, 1_000, 10_000, -1)))
    add("cachesweep_cycle5_skew", sweep(cycle(5), skew, cycle_td(5), caps, "support"), with_column(five, "capacity", caps))
    for cs, td in LOLLIPOP_TDS.items():
        add(f"lollipop_{cs}_count", counted(LOLLIPOP, skew, td, "memo"), elimination_sql(LOLLIPOP, on("g_skew"), EDGE))
    for side in ("person", "movie"):
        td = BIP_TDS["4", side]
        add(f"bip4_td_{side}_count", counted(BIP4, cast, td, "memo"), bip4)
        add(f"bip4_plain_{side}order_count", counted(BIP4, cast, td, "kernel_plain"), bip4)
        add(f"bip6_td_{side}_count", counted(BIP6, cast, BIP_TDS["6", side], "memo"), bip6)
    add("bip4_planned_count", planned(BIP4, cast), bip4)
    for side, (a, b) in {"person": ("p1", "p2"), "movie": ("m1", "m2")}.items():
        bag = "SELECT a.p AS p1, b.p AS p2, a.m AS m1 FROM A a JOIN B b ON a.m = b.m" if side == "person" else "SELECT a.m AS m1, c.m AS m2, a.p AS p1 FROM A a JOIN A c ON a.p = c.p"
        extra = "" if side == "person" else " WHERE m1 IN (SELECT m FROM B) AND m2 IN (SELECT m FROM B)"
        add(f"bip4_hits_{side}", hits(BIP4, cast, BIP_TDS["4", side]), f"WITH A AS ({CAST_SQL['A']}), B AS ({CAST_SQL['B']}), r AS ({bag}), f AS (SELECT {a}, {b}, count(*) AS c FROM r{extra} GROUP BY ALL) SELECT sum(c)::BIGINT AS entries, count(*) AS misses, sum(c - 1)::BIGINT AS hits FROM f")
    add("order_cost_report", order_costs)
    add("plan_report_bip4", lambda spark, d: explain_choice(BIP4, cast(spark, d)))
    add("clique4_count", counted(clique(4), skew, OrderedTD.single(clique(4)), "memo"), elimination_sql(clique(4), on("g_skew"), EDGE))
    add("star2_count", counted(STAR2, skew, OrderedTD.chain({"x", "y"}, {"x", "z"}), "memo"), elimination_sql(STAR2, on("g_skew"), EDGE))
    add("counters_cycle5", counters(cycle(5), skew, cycle_td(5)))
    for p in (1, 2, 3):
        add(f"skewladder_{p}", counted(cycle(4), ladder(p), cycle_td(4), "memo"), elimination_sql(cycle(4), {"E": R.skew_sql(p)}, EDGE))
    local = elimination_sql(LOCAL_SUPPLIER, STAR_SQL, STAR_COLUMNS)
    for m in ("memo", "bagtree", "pairwise", "hypercube"):
        add(f"local_supplier_count_{m}", counted(LOCAL_SUPPLIER, suppliers, LOCAL_TD, m), local)
    add("local_supplier_eval", evaluated(LOCAL_SUPPLIER, suppliers, LOCAL_TD, "memo"), rows_sql(LOCAL_SUPPLIER, STAR_SQL, STAR_COLUMNS))
    const, loop = parse_cq("E(0,b), E(b,c)"), parse_cq("E(x,x)")
    add("const_path_count", counted(const, skew, OrderedTD.single(const), "memo"), elimination_sql(const, on("g_skew"), EDGE))
    add("loop_count", counted(loop, skew, OrderedTD.single(loop), "memo"), elimination_sql(loop, on("g_skew"), EDGE))
    ordered = cycle(4).having("x1 < x3")
    add("cycle4_ordered_count", counted(ordered, skew, cycle_td(4), "memo"), f"SELECT count(*) AS cnt FROM ({rows_sql(cycle(4), on('g_skew'), EDGE)}) WHERE x1 < x3")
    add("threshold_sweep", thresholds, with_column(elimination_sql(cycle(4), on("g_skew"), EDGE), "tau", (0, 5, 1_000_000)))
    add("example_count", counted(EXAMPLE, flat, EXAMPLE_TD, "memo"), elimination_sql(EXAMPLE, on("g_flat"), EDGE))
    add("td_listing_cycle6", td_listing)
    add("td_counts", td_counts, " UNION ALL ".join(f"SELECT '{shape}' AS shape, {n}::BIGINT AS decompositions, cnt FROM ({elimination_sql(TD_SHAPES[shape], on('g_flat'), EDGE)})" for shape, n in TD_NUMBERS.items()))
    add("factorised_count_cycle5", factors(cycle(5), skew, cycle_td(5)), five)
    add("planned_cycle5_count", planned(cycle(5), skew), five)
    add("path4_semirings", best_weight, f"WITH r AS ({rows_sql(path(4), on('g_skew'), EDGE)}), w AS (SELECT x1 + x2 + x3 + x4 AS v FROM r) SELECT 'max' AS what, max(v)::BIGINT AS value FROM w UNION ALL SELECT 'min', min(v)::BIGINT FROM w UNION ALL SELECT 'count', count(*) FROM w")
    for name in ("g_flat", "g_skew", "g_clustered", "g_parts", "g_words", "doc_word", "user_k", "page_href", "part_supp"):
        add(f"rel_{name}", getattr(R, name), R.SQL[name])
    for name in ("cast_a", "cast_b"):
        add(f"rel_{name}", getattr(R, name), R.SQL[name])
    for name, column in (("g_skew", "s"), ("g_flat", "s"), ("cast_a", "p"), ("cast_a", "m")):
        add(f"skew_{name}_{column}", profile(getattr(R, name), column), f"SELECT count(*) AS values, sum(c)::BIGINT AS rows, max(c) AS max_count FROM (SELECT {column}, count(*) AS c FROM ({R.SQL[name]}) GROUP BY 1)")
    return q, s


QUERIES, ORACLE = _registry()
