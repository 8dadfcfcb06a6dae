import random

import numpy as np
import pytest
from memojoin.llm import jaccard_join as jj
from tests_brute import brute


def corpus(seed, n=260):
    rng = random.Random(seed)
    vocab = [f"w{k}" for k in range(400)]
    texts = [" ".join(rng.choices(vocab, k=rng.choice([1, 2, 3, 5, 30, 80, 200]))) for _ in range(n // 3)]
    passage = " ".join(rng.choices(vocab, k=60))
    while len(texts) < n:
        w = rng.choice(texts).split()
        for _ in range(rng.choice([0, 1, 1, 2, 3, 6])):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        texts.append(" ".join(w) if rng.random() < 0.8 else passage + " " + " ".join(w))
    texts += [None, "", "  \n", "W1 w2", "w1\tw2", "w1 w2"]
    return list(enumerate(texts))


@pytest.mark.parametrize(("n", "percent", "blocks"), [(3, 90, 2048), (5, 80, 2048), (3, 90, 16)])
def test_matches_brute_force(spark, monkeypatch, n, percent, blocks):
    monkeypatch.setattr(jj, "BLOCK_SETS", blocks)
    rows = corpus(n * percent)
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, key string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jj.jaccard_components(df, n, percent).collect()}
    assert got == brute(rows, n, percent)


def test_local_join_connects_what_brute_force_connects():
    rng = np.random.default_rng(2)
    base = rng.integers(1, 1 << 60, 150, dtype=np.uint64)
    sets = []
    for _ in range(60):
        keep = base[rng.random(150) < rng.choice([0.97, 0.99, 0.9])]
        sets.append(np.unique(np.concatenate([keep, rng.integers(1, 1 << 60, rng.integers(0, 8), dtype=np.uint64)])))
    found = jj.LocalJoin(90).links(list(range(60)), sets)
    ok = lambda a, b: 100 * len(np.intersect1d(a, b)) >= 90 * len(np.union1d(a, b))
    assert all(ok(sets[a], sets[b]) for a, b in found)

    def close(edges):
        c = list(range(60))
        for a, b in edges:
            c = [c[a] if v == c[b] else v for v in c]
        return {frozenset(k for k in range(60) if c[k] == v) for v in c}

    assert close(found) == close([(a, b) for a in range(60) for b in range(a) if ok(sets[a], sets[b])])


def test_empty_and_nulls(spark):
    df = spark.createDataFrame([(None, "a b c d"), (4, "a b c d"), (4, "a b c d"), (5, None)], "doc_id long, text string")
    assert sorted(map(str, map(tuple, jj.jaccard_components(df).collect()))) == sorted(map(str, [(None, 2, 4), (4, 2, 4), (4, 2, 4), (5, 0, 5)]))
    assert jj.jaccard_components(df.limit(0)).count() == 0


@pytest.mark.parametrize("percent", [80, 90])
def test_linked_sets_share_a_signature(percent):
    rng = np.random.default_rng(percent)
    bands, linked = jj.Bands(percent), 0
    for _ in range(4000):
        n = int(rng.choice([3, 10, 11, 12, 19, 20, 40, 95, 100, 300]))
        x = rng.integers(1, 1 << 63, n, dtype=np.uint64)
        gone, new = rng.integers(0, n // 8 + 2, 2)
        y = np.unique(np.concatenate([x[gone:], rng.integers(1, 1 << 63, new, dtype=np.uint64)]))
        x = np.unique(x)
        if len(y) and 100 * len(np.intersect1d(x, y)) >= percent * len(np.union1d(x, y)) and not np.array_equal(x, y):
            linked += 1
            a, b = ({g: set(v.tolist()) for (g, _), (v, _) in zip(bands.groups(len(z)), jj.signatures(z, bands))} for z in (x, y))
            needs = {g: n for (g, _), (_, n) in zip(bands.groups(len(x)), jj.signatures(x, bands))}
            assert any(len(a[g] & b[g]) >= needs[g] > 0 for g in set(a) & set(b))
    assert linked > 300


@pytest.mark.parametrize("percent", [80, 90])
def test_short_linked_sets_share_what_the_larger_need_asks(percent):
    rng = np.random.default_rng(percent + 1)
    bands, linked = jj.Bands(percent), 0
    for _ in range(30_000):
        x = np.unique(rng.integers(1, 1 << 63, int(rng.integers(4, 13)), dtype=np.uint64))
        gone, new = rng.integers(0, 3, 2)
        y = np.unique(np.concatenate([x[gone:], rng.integers(1, 1 << 63, new, dtype=np.uint64)]))
        if 100 * len(np.intersect1d(x, y)) >= percent * len(np.union1d(x, y)) and not np.array_equal(x, y):
            linked += 1
            a, b = ({g: (set(v.tolist()), need) for (g, _), (v, need) in zip(bands.groups(len(z)), jj.signatures(z, bands))} for z in (x, y))
            assert any(len(a[g][0] & b[g][0]) >= max(a[g][1], b[g][1]) > 0 for g in set(a) & set(b))
    assert linked > 2000


def test_short_texts_match_brute_force(spark):
    rng = random.Random(9)
    texts = [" ".join(f"v{rng.randrange(10**6)}" for _ in range(rng.randint(8, 16))) for _ in range(700)]
    rows = list(enumerate(texts + [f"{t} more" for t in texts]))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jj.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string"), 5, 80).collect()}
    assert got == brute(rows, 5, 80)
