import json

from memojoin import workloads as W
from memojoin.functions.listing import register
from memojoin.functions.measures import heavy_hitters, hit_curve, skew_profile
from memojoin.functions.scalars import result_hash
from memojoin.operators.catalog import Catalog
from memojoin.operators.frontier import memo_count
from memojoin.sources import files
from memojoin.sources import relations as R
from memojoin.streaming.delta import DeltaCounter
from memojoin.streaming.edges import stream_edges, transitions, windowed_edges


def test_incremental_count_equals_batch_and_repeats_are_ignored(spark, sf, tmp_path):
    edges = R.g_skew(spark, sf).orderBy("s", "t").collect()
    d = DeltaCounter(spark, W.cycle(3), W.cycle_td(3), "E", f"file://{tmp_path}/delta")
    for k in range(3):
        part = spark.createDataFrame(edges[k::3] + edges[:5], "s long, t long")
        n = d.on_batch(part, k)
        assert d.on_batch(part, k) == n
    assert d.count() == 109 == memo_count(W.cycle(3), Catalog({"E": R.g_skew(spark, sf)}), W.cycle_td(3)).first()["cnt"]


def test_streamed_edges_and_transitions_replay_as_batch(spark, sf, tmp_path):
    src = tmp_path / "events"
    events = R.load(spark, sf, "events").select("event_id", "ts", "user_id", "event_type").orderBy("ts", "event_id")
    events.coalesce(1).write.parquet(str(src))
    stream = spark.readStream.schema(events.schema).parquet(str(src))

    def run(df, name, mode="append"):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / name)).start()
        q.awaitTermination(120)
        return spark.table(name)

    from pyspark.sql import functions as F

    with_kind = stream.withColumn("kind", F.length("event_type"))
    got = run(stream_edges(with_kind, "user_id", "kind", "3650 days"), "edges")
    batch = stream_edges(events.withColumn("kind", F.length("event_type")), "user_id", "kind")
    assert sorted(map(tuple, got.select("s", "t").collect())) == sorted(map(tuple, batch.select("s", "t").collect()))
    one = spark.createDataFrame([(k, t, u) for k, t, u in [(1, "2024-01-01 00:00:00", 1), (2, "2024-01-01 00:01:00", 2), (3, "2024-01-01 00:02:00", 3)]], "event_id long, at string, user_id long").selectExpr("event_id", "cast(at as timestamp) ts", "user_id", "'k' AS k")
    one.write.parquet(str(tmp_path / "one"))
    t = run(transitions(spark.readStream.schema(one.schema).parquet(str(tmp_path / "one")), "k", "user_id"), "transitions")
    assert sorted((r["s"], r["t"]) for r in t.collect()) == [(1, 2), (2, 3)]
    edges = events.selectExpr("user_id AS s", "length(event_type) AS t", "ts")
    for kind, size, slide in (("tumbling", "1 day", None), ("sliding", "1 day", "12 hours"), ("session", "1 hour", None)):
        assert windowed_edges(edges, kind, size, slide).agg(F.sum("n")).first()[0] >= events.count()


def test_files_and_sinks(spark, tmp_path):
    p = tmp_path / "g.txt"
    p.write_text("# a comment\n1\t2\n1\t2\n2\t3\nx\ty\n")
    e = files.read_edge_list(spark, str(p))
    assert sorted(map(tuple, e.collect())) == [(1, 2), (2, 3)]
    files.drain(e)
    words = spark.createDataFrame([("b", "a"), ("a", "c"), (None, "a")], "s string, t string")
    ids, dictionary = files.encode_values(words, ["s", "t"], f"file://{tmp_path}/dict")
    assert sorted((r["value"], r["id"]) for r in dictionary.collect()) == [("a", 0), ("b", 1), ("c", 2)]
    assert sorted(map(str, map(tuple, ids.collect()))) == sorted(["(1, 0)", "(0, 2)", "(None, 0)"])
    e.write.csv(str(tmp_path / "c"), header=True)
    assert files.from_csv(spark, str(tmp_path / "c"), files.EDGES).count() == 2
    e.write.json(str(tmp_path / "j"))
    assert files.from_json(spark, str(tmp_path / "j"), files.EDGES).count() == 2
    e.write.orc(str(tmp_path / "o"))
    assert files.from_orc(spark, str(tmp_path / "o"), ["s"]).columns == ["s"]
    assert result_hash(e).first() == result_hash(e.orderBy("t")).first()


def test_table_function_and_measures(spark, sf):
    register(spark)
    got = spark.sql("SELECT count(DISTINCT td) AS n FROM decompositions('E(a,b), E(b,c), E(c,d), E(a,d)', 2)").first()["n"]
    assert got == 2
    g = R.g_skew(spark, sf)
    row = skew_profile(g, "s").first()
    assert row["rows"] == 194 and row["max_count"] == 31
    assert heavy_hitters(g, "s", 1).first()["c"] == 31
    assert hit_curve(g, ["s"]).count() >= 1


def test_entry_points_agree():
    import __spark_entry__ as e

    q, s = e.queries(), e.oracle_sql()
    assert set(s) <= set(q) and "cycle5_count_memo" in q
    json.dumps(sorted(q))
