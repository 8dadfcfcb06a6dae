import numpy as np
from memojoin.llm import e8_dedup as e8


def brute(ids, x):
    x = x / np.linalg.norm(x, axis=1)[:, None]
    ok = (x @ x.T) >= e8.COSINE
    np.fill_diagonal(ok, False)
    comp = np.array(ids)
    while True:
        new = np.array([min([comp[i], *comp[ok[i]]]) for i in range(len(ids))])
        if (new == comp).all():
            return ok.sum(1), comp
        comp = new


def test_lattice_decoding_is_nearest():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 8)) * 2
    got = e8.decode_e8(x)
    near = e8.shortest_vectors()
    assert len(near) == 240 and np.allclose((near**2).sum(1), 2)
    away = (((got[:, None] + near[None]) - x[:, None]) ** 2).sum(2).min(1)
    assert (((got - x) ** 2).sum(1) <= away + 1e-9).all()


def test_matches_brute_force_and_edges(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(300, 64))
    near = base[:60] + 0.2 * rng.normal(size=(60, 64))
    crowd = base[0] + 0.1 * rng.normal(size=(1500, 64))
    x = np.concatenate([base, near, crowd]).astype(np.float32)
    ids = list(range(len(x)))
    links, comp = brute(ids, x.astype(np.float64))
    odd = [(5000, None), (5001, [0.0] * 64), (5002, [float("nan")] * 64), (5003, [None] * 64), (5004, []), (None, [1.0] * 64), (7, x[7].tolist()), (5005, (2 * x[200]).tolist())]
    df = spark.createDataFrame([(i, v.tolist(), 1) for i, v in zip(ids, x)] + [(i, v, 1) for i, v in odd], "vec_id long, embedding array<float>, key int")
    got = e8.near_duplicates(df).collect()
    by = {}
    for r in got:
        by.setdefault(r["vec_id"], []).append(r)
    assert len(got) == len(x) + len(odd)
    for i in (5000, 5001, 5002, 5003, 5004):
        assert (by[i][0]["n_links"], by[i][0]["component_id"]) == (0, i)
    assert by[None][0]["n_links"] == 0
    assert len(by[7]) == 2 and by[7][0]["n_links"] == links[7] + 1
    assert by[5005][0]["component_id"] == comp[200]
    plain = [i for i in ids if i not in (7, 200, 307)]
    found, want = sum(by[i][0]["n_links"] for i in plain), sum(int(links[i]) for i in plain)
    assert found <= want and found >= 0.9 * want
    assert np.mean([by[i][0]["component_id"] == comp[i] for i in plain]) > 0.97


def test_empty(spark):
    assert e8.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_scattered_pairs_by_cosine_band(spark):
    """Recall of lone pairs, which no crowd makes up for; every grid that could be chosen keeps it."""
    rng = np.random.default_rng(5)
    bands, each = (0.901, 0.91, 0.92, 0.95), 150
    a = rng.normal(size=(len(bands) * each, 64))
    a /= np.linalg.norm(a, axis=1)[:, None]
    other = rng.normal(size=a.shape)
    other -= (other * a).sum(1)[:, None] * a
    other /= np.linalg.norm(other, axis=1)[:, None]
    cosine = np.repeat(bands, each)[:, None]
    x = np.concatenate([a, cosine * a + np.sqrt(1 - cosine**2) * other])
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>")
    for grid in (None, e8.choose_grid(10_000_000)):
        got = {r["vec_id"]: r["n_links"] for r in e8.near_duplicates(df, grid).collect()}
        found = np.array([got[k] > 0 for k in range(len(a))]).reshape(len(bands), each).mean(1)
        assert found[0] >= 0.93 and found[1] >= 0.93 and found[2] >= 0.95 and found[3] >= 0.98, (grid, found)


def test_work_for_random_vectors_grows_slower_than_with_all_pairs():
    met = []
    for n in (5_000, 50_000, 5_000_000, 500_000_000):
        g = e8.choose_grid(n)
        close, random = e8.meeting_chances(g.blocks, g.width)
        assert 1 - (1 - close) ** g.tables >= e8.RECALL
        met.append(g.tables * (len(e8.probes(g.blocks)) + n * random * e8.MEET_COST))
    assert met[1] < 4 * met[0] and met[3] < 12 * met[2]  # work a vector: n grew tenfold, then a hundredfold


def test_equal_hashes_of_different_vectors_are_hashed_anew(spark, monkeypatch):
    df = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0]), (3, [2.0, 0.0]), (4, [1.0, 0.0])], "vec_id long, embedding array<double>")
    real, seen = e8.F.xxhash64, []

    def weak(*columns):
        if len(columns) == 3 and not seen:
            seen.append(1)
            return real(e8.F.lit(7)) + e8.F.size(columns[0])
        return real(*columns)

    monkeypatch.setattr(e8.F, "xxhash64", weak)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in e8.near_duplicates(df).collect()}
    assert got == {1: (2, 1), 2: (0, 2), 3: (2, 1), 4: (2, 1)}
