import itertools
import random
import re
from decimal import Decimal

import numpy as np
import pytest
from memojoin import workloads as W
from memojoin.facade import MemoJoin
from memojoin.functions.measures import check_mvd, hit_account
from memojoin.operators import bagtree, catalog
from memojoin.operators import kernel as K
from memojoin.operators.bagtree import bag_rows, bagtree_count, bagtree_evaluate
from memojoin.operators.catalog import Catalog
from memojoin.operators.factorised import evaluate_factorised, memo_evaluate
from memojoin.operators.frontier import memo_count, plain_count, plain_rows
from memojoin.operators.pairwise import pairwise_count
from memojoin.operators.policy import CachePolicy
from memojoin.operators.semiring import aggregate
from memojoin.plans.decomp import OrderedTD, default_order, strong_orders
from memojoin.plans.enumeration import enumerate_tds
from memojoin.plans.query import Atom, ConjunctiveQuery, parse_cq
from memojoin.sources import relations as R
from pyspark.sql import functions as F


def brute(query, relations):
    """All bindings by nested loops."""
    names, out = query.variables, set()

    def walk(k, env):
        if k == len(query.atoms):
            out.add(tuple(env[x] for x in names))
            return
        a = query.atoms[k]
        for row in relations[a.relation]:
            e, ok = dict(env), True
            for t, v in zip(a.terms, row):
                if v is None or (e.setdefault(t, v) != v if isinstance(t, str) else t.value != v):
                    ok = False
                    break
            if ok:
                walk(k + 1, e)

    walk(0, {})
    return out


def tables(seed, arity=2, values=5, rows=14):
    rng = random.Random(seed)
    return [tuple(rng.randrange(values) for _ in range(arity)) for _ in range(rows)]


def frame(spark, rows, arity=2):
    return spark.createDataFrame(rows, ", ".join(f"c{k} long" for k in range(arity)))


def rows_of(df, names):
    got = [tuple(r[x] for x in names) for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


SHAPES = ["E(a,b), E(b,c), E(c,d), E(a,d)", "E(a,b), E(b,c), F(a,c), F(c,d), E(d,e)", "E(x,y), F(z,x)", "E(a,b), F(c,d)", "E(a,a), E(a,b), F(b,c)", "G(a,b,c), E(c,d), F(d,a)", "E(1,b), E(b,c), F(c,2)"]


@pytest.mark.parametrize("text", SHAPES)
def test_all_methods_equal_brute_force(spark, text):
    query = parse_cq(text)
    data = {"E": [*tables(1), (None, 1), (2, None)], "F": [*tables(2), *tables(2)], "G": tables(3, 3)}
    c = Catalog({k: frame(spark, v, 3 if k == "G" else 2) for k, v in data.items()})
    want = brute(query, data)
    td = next(enumerate_tds(query))
    n = len(want)
    assert n > 0
    assert memo_count(query, c, td).first()["cnt"] == n
    assert memo_count(query, c, td, proposer="cheapest").first()["cnt"] == n
    assert memo_count(query, c, td, policy=CachePolicy.never()).first()["cnt"] == n
    assert memo_count(query, c, td, policy=CachePolicy.support(3)).first()["cnt"] == n
    assert plain_count(query, c, query.variables).first()["cnt"] == n
    assert bagtree_count(query, c, td).first()["cnt"] == n
    assert pairwise_count(query, c).first()["cnt"] == n
    assert K.kernel_count(query, c, td).first()["cnt"] == n
    assert K.hypercube_count(query, c, td, cells=4).first()["cnt"] == n
    for df in (memo_evaluate(query, c, td), plain_rows(query, c, query.variables), bagtree_evaluate(query, c, td, two_bag_shortcut=False), K.kernel_evaluate(query, c)):
        assert rows_of(df, query.variables) == want
    assert evaluate_factorised(query, c, td).count().first()["cnt"] == n


def run_kernel(query, rows, td, policy=CachePolicy.always(), block=64, scalar=False):
    order = default_order(td)
    relation = sorted(set(rows))
    atoms = []
    for a in query.atoms:
        v = K._arranged(a.variables, order)
        mine = sorted({tuple(r[a.terms.index(x)] for x in v) for r in relation if len(set(a.terms)) == len(a.terms) or r[0] == r[1]})
        atoms.append((v, [np.array([m[j] for m in mine], np.int64) for j in range(len(v))]))
    k = K.Kernel(atoms, order, td, policy, 16, block, scalar)
    return k.count(), k.metrics()


def test_kernel_properties_over_many_decompositions_and_policies():
    rng = random.Random(4)
    for trial in range(40):
        n = rng.choice([3, 4, 5])
        pairs = list(itertools.combinations(range(n), 2))
        es = {(k, k + 1) for k in range(n - 1)} | {p for p in pairs if rng.random() < 0.3}
        query = ConjunctiveQuery([Atom("E", (f"v{a}", f"v{b}")) for a, b in sorted(es)])
        rows = tables(trial, 2, 6, 18)
        want = len(brute(query, {"E": rows}))
        for td in itertools.islice(enumerate_tds(query), 4):
            plain, base = run_kernel(query, rows, td, CachePolicy.never())
            assert plain == want
            none, m = run_kernel(query, rows, td, CachePolicy.always().capacity(0))
            assert none == want and m["trie_probes"] == base["trie_probes"]
            for policy in (CachePolicy.always(), *(CachePolicy.always().capacity(3).evict(e) for e in ("none", "fifo", "lru", "support")), CachePolicy.support(3), CachePolicy.always().max_dimension(1), CachePolicy.always().nodes([1]), CachePolicy.custom(lambda v, c: c[0] % 2 == 0), CachePolicy.always().dynamic(lambda s, used: 2)):
                for scalar in (False, True):
                    got, m = run_kernel(query, rows, td, policy, 5, scalar)
                    assert got == want
                    if policy.entries:
                        assert m["entries_peak"] <= policy.entries


def test_every_strong_order_gives_the_count():
    rows = tables(9, 2, 6, 20)
    query, td = W.cycle(5), W.cycle_td(5)
    want = len(brute(query, {"E": rows}))
    for order in strong_orders(td, 50):
        relation = sorted(set(rows))
        atoms = []
        for a in query.atoms:
            v = K._arranged(a.variables, order)
            mine = sorted({tuple(r[a.terms.index(x)] for x in v) for r in relation})
            atoms.append((v, [np.array([m[j] for m in mine], np.int64) for j in range(2)]))
        assert K.Kernel(atoms, order, td, CachePolicy.always(), 16).count() == want


def test_siblings_with_one_adhesion_keep_their_own_memos(spark):
    c = Catalog({"E": frame(spark, [(1, 2), (1, 3), (2, 2)]), "F": frame(spark, [(5, 1), (6, 1), (7, 1), (5, 2)])})
    query = parse_cq("E(x,y), F(z,x)")
    td = OrderedTD.from_nested(({"x", "y"}, [({"x", "z"}, [])]))
    assert memo_count(query, c, td).first()["cnt"] == 7
    three = parse_cq("D(x), E(x,y), F(z,x)")
    star = OrderedTD.from_nested(({"x"}, [({"x", "y"}, []), ({"x", "z"}, [])]))
    c.bind("D", spark.createDataFrame([(1,), (2,)], "d long"))
    assert memo_count(three, c, star).first()["cnt"] == 7
    assert K.kernel_count(three, c, star).first()["cnt"] == 7


def test_worked_example(spark):
    full = [(a, b) for a in (1, 2) for b in (1, 2)]
    seen = {}
    got = memo_count(W.EXAMPLE, Catalog({"E": frame(spark, full)}), W.EXAMPLE_TD, observe=lambda v, rows, keys: seen.setdefault(v, hit_account(rows, keys).first()))
    assert got.first()["cnt"] == 64
    assert (seen[1]["entries"], seen[1]["misses"], seen[1]["hits"]) == (4, 2, 2)
    assert (seen[2]["entries"], seen[2]["misses"]) == (8, 2)
    count, m = run_kernel(W.EXAMPLE, full, W.EXAMPLE_TD)
    assert count == 64 and m["misses_1"] == 2 and m["hits_1"] == 2
    k = K.Kernel([(K._arranged(a.variables, default_order(W.EXAMPLE_TD)), [np.array([0, 0, 1, 1]), np.array([0, 1, 0, 1])]) for a in W.EXAMPLE.atoms], default_order(W.EXAMPLE_TD), W.EXAMPLE_TD, CachePolicy.always(), 2)
    assert k.count() == 64
    assert {key: v for key, v in k.memo.entries.items() if key[0] == 1} == {(1, 0): 16, (1, 1): 16}


def test_published_shape_of_counts_on_the_tables(spark, sf):
    c = Catalog({"E": R.g_skew(spark, sf).cache()})
    for k, n in zip(range(3, 8), (1152, 4273, 16705, 65968, 253455)):
        assert memo_count(W.path(k), c, W.path_td(k)).first()["cnt"] == n
    for k, n in zip(range(3, 7), (109, 591, 2264, 8521)):
        assert K.kernel_count(W.cycle(k), c, W.cycle_td(k)).first()["cnt"] == n


def test_memo_saves_accesses_and_person_keys_beat_movie_keys(spark, sf):
    c = Catalog({"E": R.g_skew(spark, sf)})
    one = lambda **o: {r["name"]: r["total"] for r in K.kernel_metrics(W.cycle(6), c, parts=1, **o).collect()}
    memo, plain = one(td=W.cycle_td(6)), one(td=None, order=default_order(W.cycle_td(6)))
    assert memo["cnt"] == plain["cnt"] and memo["accesses"] < plain["accesses"]
    c = Catalog({"A": R.cast_a(spark, sf), "B": R.cast_b(spark, sf)})
    acc = {}
    for side in ("person", "movie"):
        seen = {}
        memo_count(W.BIP4, c, W.BIP_TDS["4", side], observe=lambda v, rows, keys, seen=seen: seen.setdefault(v, hit_account(rows, keys).first()))
        acc[side] = seen[1]
    assert (acc["person"]["entries"], acc["person"]["misses"]) == (3217, 963)
    # the root bag's own atoms give 42183 and 29661; movies that the other cast table lacks are pruned on binding
    assert (acc["movie"]["entries"], acc["movie"]["misses"]) == (41766, 29328)


def test_results_are_products_given_the_adhesion(spark):
    rows = tables(11, 2, 6, 25)
    c, q, td = Catalog({"E": frame(spark, rows)}), W.path(4), W.path_td(4)
    out = memo_evaluate(q, c, td)
    assert check_mvd(out, ["x3"], ["x4"])
    assert not check_mvd(out, ["x1"], ["x4"]) or len(rows) < 3
    nested = evaluate_factorised(q, c, td).to_nested()
    assert nested.columns[-1] == "child1"


def test_edges_of_inputs(spark):
    empty = frame(spark, [])
    q, td = W.cycle(4), W.cycle_td(4)
    for c in (Catalog({"E": empty}), Catalog({"E": frame(spark, [(None, None)])})):
        assert memo_count(q, c, td).first()["cnt"] == 0 and bagtree_count(q, c, td).first()["cnt"] == 0
        assert K.kernel_count(q, c, td).first()["cnt"] == 0 and memo_evaluate(q, c, td).count() == 0
    words = spark.createDataFrame([("a", "b"), ("b", "c"), ("a", "c")], "s string, t string")
    assert K.kernel_count(W.cycle(3), Catalog({"E": words}), W.cycle_td(3)).first()["cnt"] == 1
    doubles = spark.createDataFrame([(0.0, float("nan")), (-0.0, 1.0)], "s double, t double")
    assert memo_count(parse_cq("E(a,b), E(a,c)"), Catalog({"E": doubles}), OrderedTD.chain("ab", "ac")).first()["cnt"] == 1
    with pytest.raises(ValueError):
        memo_count(q, Catalog({"E": empty}), td, order=("x4", "x1", "x2", "x3"))
    with pytest.raises(ValueError):
        K.kernel_count(q, Catalog({"E": frame(spark, tables(1))}), td, most_rows=3)


def test_counts_beyond_64_bits(spark):
    full = [(a, b) for a in range(16) for b in range(16)]
    c = Catalog({"E": frame(spark, full)})
    q, td = W.path(17), W.path_td(17)
    assert memo_count(q, c, td, decimal=True).first()["cnt"] == Decimal(16**17)
    rows = frame(spark, full)
    assert MemoJoin(spark).relation("E", rows).query(q).count(td=td).first()["cnt"] == Decimal(16**17)


def test_facade_selections_comparisons_and_semirings(spark):
    rows = sorted(set(tables(21, 2, 7, 25)))
    m = MemoJoin(spark).relation("E", frame(spark, rows))
    text = "E(a,b), E(b,c), E(c,d)"
    every = brute(parse_cq(text), {"E": rows})
    assert m.query(text).count().first()["cnt"] == len(every)
    assert m.query(text).where("b", "b > 2").count().first()["cnt"] == sum(r[1] > 2 for r in every)
    assert m.query(text).having("a < b").count(td=W.OrderedTD.chain("ab", "bc", "cd")).first()["cnt"] == sum(r[0] < r[1] for r in every)
    with pytest.raises(ValueError):
        m.query(text).having("a < d").count(td=W.OrderedTD.chain("ab", "bc", "cd"))
    assert rows_of(m.query(text).evaluate("bagtree"), "abcd") == every
    assert m.sql_view("v", text).count() == len(every) == spark.sql("SELECT * FROM v").count()
    assert m.query(text).explain().count() >= 1
    from pyspark.sql import functions as F

    td, w = W.OrderedTD.chain("ab", "bc", "cd"), {x: F.col(x) for x in "abcd"}
    assert aggregate(parse_cq(text), m.catalog, td, "max_plus", w).first()[0] == max(map(sum, every))
    assert aggregate(parse_cq(text), m.catalog, td, "min_plus", w).first()[0] == min(map(sum, every))
    assert aggregate(parse_cq(text), m.catalog, td, "exists").first()[0] is True


def test_no_cartesian_products_and_pruned_scans(spark, sf):
    c = Catalog({"E": R.g_skew(spark, sf)})
    plan = memo_count(W.cycle(4), c, W.cycle_td(4))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    scan = R.g_skew(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(l_returnflag,R)" in scan and "l_extendedprice" not in scan


def test_accesses_fall_step_by_step_with_capacity():
    rng = random.Random(3)
    rows = sorted({(min(rng.randrange(40), rng.randrange(40)), min(rng.randrange(40), rng.randrange(40))) for _ in range(500)})
    query, td = W.cycle(5), W.cycle_td(5)
    order = default_order(td)
    atoms = [(K._arranged(a.variables, order), [np.array([r[a.terms.index(x)] for r in rows]) for x in K._arranged(a.variables, order)]) for a in query.atoms]

    def run(policy):
        k = K.Kernel([(v, list(c)) for v, c in atoms], order, td, policy, 40)
        n, m = k.count(), k.metrics()
        return n, m["accesses"] - m.get("memo_lookups", 0) - m.get("memo_stores", 0), m["entries_peak"]

    want, plain, _ = run(CachePolicy.never())
    for replacement in ("none", "fifo", "lru", "support"):
        work = []
        for capacity in (0, 10, 100, 400, 4000):
            n, accesses, peak = run(CachePolicy.always().capacity(capacity).evict(replacement))
            assert n == want and peak <= capacity
            work.append(accesses)
        n, least, _ = run(CachePolicy.always().evict(replacement))
        assert work[0] == plain and all(a > b for a, b in zip(work[:-1], work[1:])), (replacement, work)
        assert n == want and work[-1] >= least and plain > 3 * least


def test_frontier_runs_own_rules_and_refuses_bounds(spark):
    rows = sorted(set(tables(5, 2, 7, 30)))
    c, q, td = Catalog({"E": frame(spark, rows)}), W.cycle(4), W.cycle_td(4)
    want = len(brute(q, {"E": rows}))
    seen = []

    def even(node, columns):
        seen.append(node)
        return columns[0] % 2 == 0

    assert memo_count(q, c, td, policy=CachePolicy.custom(even)).first()["cnt"] == want
    for policy in (CachePolicy.always().capacity(5), CachePolicy.always().evict("lru"), CachePolicy.always().dynamic(lambda s, n: 3)):
        with pytest.raises(ValueError):
            memo_count(q, c, td, policy=policy)
    m = MemoJoin(spark).relation("E", frame(spark, rows)).query(q)
    for method, executor in (("bagtree", "kernel"), ("pairwise", "hypercube"), ("memo", "none"), ("other", "frontier")):
        with pytest.raises(ValueError):
            m.count(method, executor, td=td)
    with pytest.raises(ValueError):
        m.evaluate("memo", "kernel", td=td)


def test_branching_decompositions_carry_demand_along_the_last_child(spark):
    rows = sorted(set(tables(8, 2, 6, 25)))
    c = Catalog({"E": frame(spark, rows)})
    q = parse_cq("E(a,b), E(b,c), E(b,d), E(d,e), E(d,f)")
    td = OrderedTD.from_nested(({"a", "b"}, [({"b", "c"}, []), ({"b", "d"}, [({"d", "e"}, []), ({"d", "f"}, [])])]))
    want = len(brute(q, {"E": rows}))
    for policy in (None, CachePolicy.never(), CachePolicy.support(4), CachePolicy.always().nodes([2])):
        assert memo_count(q, c, td, policy=policy).first()["cnt"] == want
    plan = memo_count(W.path(7), c, W.path_td(7))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join ") <= 12  # a join and a check for each of the six atoms: no frontier is read twice


def test_counts_raise_on_overflow_without_ansi(spark):
    full = [(a, b) for a in range(16) for b in range(16)]
    c = Catalog({"E": frame(spark, full)})
    before = spark.conf.get("spark.sql.ansi.enabled")
    spark.conf.set("spark.sql.ansi.enabled", "false")
    try:
        for run in (memo_count, bagtree_count):
            with pytest.raises(Exception, match="ARITHMETIC_OVERFLOW"):
                run(W.path(17), c, W.path_td(17)).collect()
        assert memo_count(W.path(15), c, W.path_td(15)).first()["cnt"] == 16**15
    finally:
        spark.conf.set("spark.sql.ansi.enabled", before)


def test_nodes_that_keep_nothing_join_their_parents(spark):
    rows = sorted(set(tables(12, 2, 6, 25)))
    c, q, td = Catalog({"E": frame(spark, rows)}), W.cycle(5), W.cycle_td(5)
    assert CachePolicy.always().needs_intermediate(td) == {1, 2}
    assert CachePolicy.always().nodes([1]).needs_intermediate(td) == {1, 2} and CachePolicy.always().nodes([2]).needs_intermediate(td) == {2}
    assert CachePolicy.never().needs_intermediate(td) == set() and len(CachePolicy.never().pruned(td)) == 1
    assert len(CachePolicy.always().max_dimension(1).pruned(td)) == 1 and CachePolicy.always().pruned(td) == td
    want = brute(q, {"E": rows})
    for policy, nodes in ((CachePolicy.always(), 3), (CachePolicy.never(), 1)):
        f = evaluate_factorised(q, c, td, policy=policy)
        assert len(f.nodes) == nodes and rows_of(f.flatten().select(*q.variables), q.variables) == want


def test_prereduction_and_bag_rows(spark):
    rows = sorted(set(tables(13, 2, 9, 20)))
    c, q, td = Catalog({"E": frame(spark, rows)}), W.path(4), W.path_td(4)
    want = brute(q, {"E": rows})
    m = MemoJoin(spark).relation("E", frame(spark, rows)).query(q).prereduced()
    assert m.count(td=td).first()["cnt"] == len(want)
    for r in bag_rows(q, c, td).collect():
        names = sorted(td.bags[r["node"]])
        assert r["demanded"] == len({tuple(w[q.variables.index(x)] for x in names) for w in want}) <= r["in_bags"]


def test_small_relations_are_sent_and_the_frontier_is_not_shuffled(spark, monkeypatch):
    rng = random.Random(8)
    rows = list({(int(30 * rng.random() ** 2), int(30 * rng.random() ** 2)) for _ in range(150)})
    df = spark.createDataFrame(rows, "s long, t long")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for most in (0, catalog.SENT_ROWS):
            monkeypatch.setattr(catalog, "SENT_ROWS", most)
            c = Catalog({"E": df})
            for k in (4, 5):
                want = len(brute(W.cycle(k), {"E": rows}))
                runs = memo_count(W.cycle(k), c, W.cycle_td(k)), bagtree_count(W.cycle(k), c, W.cycle_td(k)), plain_count(W.cycle(k), c, default_order(W.cycle_td(k)))
                assert [x.first()["cnt"] for x in runs] == [want] * 3
                plan = runs[0]._jdf.queryExecution().sparkPlan().toString()
                assert ("SortMergeJoin" in plan) == (most == 0)
            assert memo_evaluate(W.cycle(4), c, W.cycle_td(4)).count() == bagtree_evaluate(W.cycle(4), c, W.cycle_td(4)).count() == len(brute(W.cycle(4), {"E": rows}))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_frontiers_are_dealt_out_by_a_variable_that_keys_hold(spark):
    rng = random.Random(6)
    a, b = ({(rng.randrange(8), rng.randrange(12)) for _ in range(40)} for _ in range(2))
    c = Catalog({name: spark.createDataFrame(sorted(rows), "p long, m long") for name, rows in (("A", a), ("B", b))})
    for side in ("person", "movie"):
        td = W.BIP_TDS["4", side]
        run = memo_count(W.BIP4, c, td)
        plan = run._jdf.queryExecution().executedPlan().toString()
        keys = sorted(td.adhesion(1))
        assert not re.search(rf"hashpartitioning\({keys[0]}#\w+, {keys[1]}#", plan)
        assert run.first()["cnt"] == len(brute(W.BIP4, {"A": a, "B": b}))


def test_relations_that_the_heap_has_room_for_are_sent(spark, monkeypatch):
    rows = 1_250_000
    c = Catalog({"E": spark.range(rows).select((F.col("id") % 100_000).alias("s"), F.col("id").alias("t"))})
    assert c.few("E") == rows and "SortMergeJoin" not in plain_rows(W.path(3), c, default_order(W.path_td(3)))._jdf.queryExecution().sparkPlan().toString()
    heap = spark._jvm.java.lang.Runtime.getRuntime().maxMemory()
    monkeypatch.setattr(catalog, "SENT_BYTES", heap // 1_000_000)
    assert Catalog({"E": c["E"]}).few("E") is None


def test_counts_come_back_from_hash_tables_where_relations_are_sent(spark):
    rng = random.Random(5)
    rows = sorted({(rng.randrange(12), rng.randrange(12)) for _ in range(60)})
    c = Catalog({"E": spark.createDataFrame(rows, "s long, t long")})
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        branching = W.graph_query("1-2 1-3 2-5 3-4 3-5")
        td = OrderedTD.from_nested(({"x1", "x2", "x3"}, [({"x3", "x4"}, []), ({"x2", "x3", "x5"}, [])]))
        runs = [(W.cycle(6), bagtree_count(W.cycle(6), c, W.cycle_td(6))), (branching, memo_count(branching, c, td)), (branching, bagtree_count(branching, c, td))]
        for query, run in runs:
            plan = run._jdf.queryExecution().sparkPlan().toString()
            assert "SortMergeJoin" not in plan and "ShuffledHashJoin" in plan
            assert run.first()["cnt"] == len(brute(query, {"E": rows}))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_kernel_blocks_stay_bounded_where_values_are_heavy(monkeypatch):
    order, td = default_order(W.path_td(3)), W.path_td(3)
    rows = [np.array([k for k in range(40) for _ in range(40)]), np.array(list(range(40)) * 40)]
    k = K.Kernel([(a.variables, rows) for a in W.path(3).atoms], order, td, CachePolicy.never(), 40, 100)
    sizes, extend = [], k.extend
    monkeypatch.setattr(k, "extend", lambda block, x: sizes.append((out := extend(block, x)).n) or out)
    assert k.count() == 40**3 and max(sizes) <= 100


def test_listing_queries_read_a_table(spark, sf):
    rows = [tuple(r) for r in R.g_flat(spark, sf).collect()]
    after = {}
    for a, b in rows:
        after.setdefault(a, set()).add(b)
    for name in ("example_count", "td_listing_cycle6", "td_counts"):
        assert W.QUERIES[name](spark, sf).inputFiles(), name
    got = {r["shape"]: (r["decompositions"], r["cnt"]) for r in W.QUERIES["td_counts"](spark, sf).collect()}
    triangles = sum(len(after.get(b, set()) & after[a]) for a, b in rows)
    assert {k: n for k, (n, _) in got.items()} == W.TD_NUMBERS and got["cycle3"][1] == triangles
    asked = {(a, c) for a, b in rows for c in after.get(b, ())}
    want = [1, len(asked)]
    for _ in range(2):
        asked = {(a, d) for a, c in asked for d in after.get(c, ())}
        want.append(len(asked))
    assert {r["node"]: r["keys"] for r in W.QUERIES["td_listing_cycle6"](spark, sf).collect()} == dict(enumerate(want))
    assert W.QUERIES["example_count"](spark, sf).first()["cnt"] == sum(
        len(after.get(d, ())) * len(after.get(c, ())) for a, b in rows for c in after.get(b, ()) for d in after.get(b, ()) if d in after.get(c, ())
    )


def test_hypercube_starts_where_fewest_bindings_are_tried(spark):
    rows = {"LS": [(o, o % 50) for o in range(400)], "O": [(o, o % 100) for o in range(400)], "C": [(c, c % 2) for c in range(100)], "S": [(s, s % 2) for s in range(50)]}
    c = Catalog({name: frame(spark, r + r[:9]) for name, r in rows.items()})
    sizes = {k: K.atom_size(a, c, W.LOCAL_SUPPLIER) for k, a in enumerate(W.LOCAL_SUPPLIER.atoms)}
    assert sizes[0][0] == 409 and abs(sizes[0][1] - 400) < 40
    stats = K.Stats({k: K.prefixes(distinct, values) for k, (_, distinct, values) in sizes.items()})
    assert K.best_root(W.LOCAL_TD, W.LOCAL_SUPPLIER, stats).bags[0] == {"s", "c", "o"}  # not customers by suppliers of a nation
    assert K.hypercube_count(W.LOCAL_SUPPLIER, c, W.LOCAL_TD).first()["cnt"] == len(brute(W.LOCAL_SUPPLIER, rows))


@pytest.mark.parametrize("replacement", ["none", "fifo"])
def test_a_memo_in_blocks_keeps_what_a_memo_by_entries_keeps(replacement):
    rng = random.Random(5)
    policy = CachePolicy.always().capacity(20).evict(replacement)
    one, many = K.Memo(policy), K.PackedMemo(policy, None, lambda key: (0, key))
    for _ in range(300):
        keys = np.array(sorted(rng.sample(range(200), rng.randrange(1, 9))))
        had = np.array([-1 if (v := one.get((0, k))) is None else v for k in keys.tolist()])
        assert many.find(keys).tolist() == had.tolist()
        new = keys[had < 0][::-1]
        assert many.fill(new, new * 3) == sum(one.put((0, k), k * 3) for k in new.tolist())
        assert many.entries == one.entries and (many.size, many.peak, many.evicted) == (one.size, one.peak, one.evicted)
    many.resize(5), one.resize(5)
    assert many.entries == one.entries and many.evicted == one.evicted


def test_bags_with_a_common_variable_are_counted_in_tasks(spark, monkeypatch):
    monkeypatch.setattr(bagtree, "TASK_ROWS", 0)
    rows = tables(11, 2, 9, 40) + [(None, 1), (2, None)]
    c = Catalog({"E": frame(spark, rows), "F": frame(spark, tables(12, 2, 9, 30)), "N": frame(spark, [], 2)})
    clean = {"E": [r for r in rows if None not in r], "F": tables(12, 2, 9, 30), "N": []}
    fan = OrderedTD.from_nested(({"a", "b", "c"}, [({"a", "c", "d"}, []), ({"a", "b", "e"}, [])]))
    star = parse_cq("E(a,b), E(b,c), E(a,c), F(c,d), F(d,a), E(e,b)")
    for query, td in ((W.cycle(5), W.cycle_td(5)), (W.cycle(6), W.cycle_td(6)), (star, fan), (parse_cq("E(a,b), F(b,c), F(c,d), N(a,e), E(e,d)"), OrderedTD.chain("abc", "acd", "ade"))):
        for rule in ("adhesion_first", "reverse"):
            got = bagtree_count(query, c, td, rule)
            assert "MapInArrow" in (plan := got._jdf.queryExecution().executedPlan().toString()) and "Join" not in plan
            assert got.first()["cnt"] == len(brute(query, clean))
    ordered = W.cycle(5).having("x1 < x3")
    assert bagtree_count(ordered, c, W.cycle_td(5)).first()["cnt"] == sum(b[0] < b[2] for b in brute(W.cycle(5), clean))


def test_counts_of_bags_beyond_64_bits_are_refused():
    one = np.zeros(1, np.int64)
    bags = [(["x", "y"], [(0, ("x", "y"))])] * 3
    tree = K.BagTree([{"x": one, "y": one}], OrderedTD((frozenset("xy"),) * 3, (-1, 0, 0)), bags, "x", 1, (0, 1), 8)
    whole = tree.up
    tree.up = lambda v: whole(v) if v == 0 else np.array([1 << 32])
    with pytest.raises(OverflowError):
        tree.up(0)


def test_evaluation_of_a_chain_solves_its_child_once(spark):
    rows = tables(21, 2, 6, 20)
    c = Catalog({"E": frame(spark, rows)})
    out = memo_evaluate(W.cycle(4), c, W.cycle_td(4))
    assert rows_of(out, W.cycle(4).variables) == brute(W.cycle(4), {"E": rows})
    joins = out._jdf.queryExecution().optimizedPlan().toString().count("Join ")
    assert joins <= 15  # the root twice, as rows and as keys, its child once, and the two together (40 with each solved anew)
    for td in (W.cycle_td(5), OrderedTD.from_nested(({"x1", "x2", "x3"}, [({"x1", "x3", "x4"}, [({"x1", "x4", "x5"}, [])])]))):
        got = evaluate_factorised(W.cycle(5), c, td)
        want = brute(W.cycle(5), {"E": rows})
        for v, df in got.nodes.items():
            names = sorted(td.bags[v])
            assert rows_of(df, names) == {tuple(dict(zip(W.cycle(5).variables, w))[x] for x in names) for w in want}
