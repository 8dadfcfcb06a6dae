"""Small checks of the text operators against plain Python, with nulls, empties, repeats and clashing columns."""

import hashlib
import math
import os
import random
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from memojoin.llm import bpe, brown_lm, kn_quality, langid, mixing, quality_rules, toxicity
from memojoin.llm.common import ChunkHasher, WordHasher, dealt
from memojoin.llm.packets import pack, unpack
from pyspark.sql import functions as F
from tests_brute import PlainKneserNey

ODD = [None, "", " \n\t ", "one", "ÀÉ ß", "a\x0bb\x0cc", "x" * 5000, "word " * 3000, "!!! ### $$$", "\n\n\n"]


def table(spark, texts, **more):
    rows = [(k, t, "en", "src", 0, "clash", "clash") for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_words string, key string")


def tokenizer():
    import public_tokenizers
    import tokenizers

    return tokenizers.Tokenizer.from_file(public_tokenizers.path(bpe.VOCABULARY))


def test_bpe_equals_the_library(spark):
    lib, own = tokenizer(), bpe.load(bpe.VOCABULARY)
    texts = [t for t in ODD if t is not None] + ["It's 123 naïve ΟΔΟΣ 日本語 😀 can't", "<|endoftext|> a<|startoftext|>", "é ​﻿ İ ﬁ", "a\x1cb\x85c"]
    for t in texts:
        ids = lib.encode(t, add_special_tokens=False).ids
        assert own.encode(t) == ids
        assert own.decode(ids) == lib.decode(ids, skip_special_tokens=False)
    df = table(spark, [None, *texts])
    got = {r["doc_id"]: r for r in bpe.digests(df, bpe.VOCABULARY).collect()}
    for k, t in enumerate([None, *texts]):
        ids = own.encode(t)
        want = hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(own.decode(ids).encode()).hexdigest()
        assert (got[k]["n_tokens"], got[k]["ids_sha256"], got[k]["decoded_sha256"]) == (len(ids), *want)
    back = bpe.decode(bpe.encode(df, bpe.VOCABULARY), bpe.VOCABULARY)
    assert {r["doc_id"]: r["text"] for r in back.collect()}[1] == ""
    assert bpe.digests(df.limit(0), bpe.VOCABULARY).count() == 0


def test_bpe_of_long_words_equals_the_library(monkeypatch):
    lib, own = tokenizer(), bpe.load(bpe.VOCABULARY)
    rng = random.Random(9)
    for word in ["x" * 5000, "ab" * 3000, "".join(rng.choices("etaoinshr", k=4000)), "é" * 700]:
        assert own.encode(word) == lib.encode(word, add_special_tokens=False).ids
    for _ in range(200):
        word = "".join(rng.choices("etaoinsh", k=rng.randrange(2, 60)))
        text = [own.symbols[b] for b in word.encode()]
        text[-1] += own.suffix
        assert own._long_parts(text) == own.parts(word)
    own.digest("y" * 300_000)
    assert not any(len(w) > bpe.SHORT for w in own.known)


def plain_rules(text):
    w = "".join(" " if c in "\t\n\x0b\x0c\r" else c for c in text or "").split(" ")
    w = [x for x in w if x]
    grams = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
    hit = {k + o for k in range(len(w) - 2) if grams[tuple(w[k : k + 3])] > 1 for o in range(3)}
    lines = [x for x in (text or "").split("\n") if x.strip(" \t\n\x0b\x0c\r")]
    return len(w), sum(map(len, w)), sum(c in quality_rules.SYMBOLS for c in text or ""), len(lines) - len(set(lines)), len(hit)


def test_quality_measures_equal_plain_python(spark):
    rng = random.Random(1)
    texts = ODD + [" ".join(rng.choices(["a", "b", "the", "of", "word#", "x|y"], k=rng.randrange(120))) + rng.choice(["", "\nsame line\nsame line"]) for _ in range(60)]
    got = {r["doc_id"]: r for r in quality_rules.judge(table(spark, texts)).collect()}
    for k, t in enumerate(texts):
        n, chars, symbols, dup, rep = plain_rules(t)
        r = got[k]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, symbols, dup, rep)
        assert r["base_failed"] == (n < 50 or 100 * rep > 50 * n) and not (r["base_failed"] and r["kept"])
    plan = quality_rules.judge(table(spark, texts))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_mixing_targets_copies_and_reruns(spark):
    rng = random.Random(3)
    rows = [(k, "w " * rng.randrange(1, 60), rng.choice(["a", "a", "a", "b", None, "ü"]), "clash") for k in range(3000)] + [(None, "x y", "b", "c"), (5, None, "z", "c"), (5, None, "z", "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, size string")
    got = mixing.plan_documents(df).collect()
    assert len(got) == len(rows) and all(0 <= r["copies"] <= 3 for r in got)
    sizes = Counter()
    for _, t, s, _ in rows:
        sizes[s] += len((t or "").split())
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    target = dict(zip(names, mixing.share_out([sizes[s] for s in names], [1 + k % 3 for k in range(len(names))], sum(sizes.values()))))
    by_id = {r["doc_id"]: r for r in got}
    for k, _, s, _ in rows[6:50]:
        assert by_id[k]["source_size"] == sizes[s] and by_id[k]["target"] == target[s]
    assert abs(sum(target.values()) - sum(sizes.values())) < 1e-6 and all(target[s] <= 3 * sizes[s] for s in names)
    taken = Counter()
    for r in got:
        taken[r["target"], r["source_size"]] += r["size"] * r["copies"]
    assert all(abs(v - t) < 0.1 * t + 50 for (t, _), v in taken.items())
    assert sorted(map(str, got)) == sorted(map(str, mixing.plan_documents(df).collect()))
    mixed = mixing.mix(df)
    assert mixed.columns == df.columns and mixed.count() == sum(r["copies"] for r in got)
    assert mixing.plan_documents(df.limit(0)).count() == 0


def test_mixing_plans_many_sources_as_a_table(spark, monkeypatch):
    rng = random.Random(6)
    names = [None, "", "ü", "z", *(f"s{k}" for k in range(40))]
    rows = [(k, "w " * rng.choice([0, 1, 5, 200]) * (len(s or "") % 3), s) for k in range(600) for s in [rng.choice(names)]] + [(None, None, "only null")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    small = sorted(map(str, mixing.plan_documents(df).collect()))
    monkeypatch.setattr(mixing, "MAX_SOURCES", 3)
    assert sorted(map(str, mixing.plan_documents(df).collect())) == small
    assert mixing.plan_documents(df.where("text IS NULL")).collect()[0]["target"] == 0


def test_mixing_sends_no_text_and_broadcasts_the_plan(spark):
    df = spark.createDataFrame([(1, "a b", "s"), (2, "c", "t")], "doc_id long, text string, source string")
    plan = mixing.plan_documents(df)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "BuildRight" in plan and "SortMergeJoin" not in plan


@pytest.mark.parametrize(("sizes", "weights", "total"), [([10, 10, 100], [1, 2, 3], 120), ([0, 5, 5], [1, 2, 3], 10), ([], [], 0), ([7], [1], 7)])
def test_share_out_keeps_caps_and_total(sizes, weights, total):
    t = mixing.share_out(sizes, weights, total)
    assert math.isclose(sum(t), total) and all(x <= 3 * s + 1e-9 for x, s in zip(t, sizes))


def test_language_model_gradients_and_held_out_accuracy(spark, sf):
    rng = np.random.default_rng(0)
    m = langid.fit([b"abcabc" * 20, b"xyzxyz" * 20], ["a", "x"])
    x, y, w = rng.integers(97, 123, (6, 3)).astype(np.uint8), np.array([0, 1, 0]), np.ones((6, 3), np.float32)
    m.p = {k: v.astype(np.float64) for k, v in m.p.items()}
    _, g = m.gradients(x, y, w)
    for k in ("fu", "bu", "v", "c"):
        at = tuple(rng.integers(0, n) for n in m.p[k].shape)
        old, eps = m.p[k][at], 1e-3
        m.p[k][at] = old + eps
        up, _ = m.gradients(x, y, w)
        m.p[k][at] = old - eps
        down, _ = m.gradients(x, y, w)
        m.p[k][at] = old
        assert abs((up - down) / (2 * eps) - g[k][at]) < 2e-3
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r["doc_id"]: r for r in langid.identify(docs, langid.train(docs)).collect()}
    rows = docs.collect()
    held = [r for r in rows if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert all(got[r["doc_id"]]["held_out"] for r in held)
    assert np.mean([got[r["doc_id"]]["lang_pred"] == r["lang"] for r in held]) > 0.9
    odd = langid.identify(table(spark, ODD), m).collect()
    assert [r["lang_pred"] for r in sorted(odd, key=lambda r: r["doc_id"])][:3] == ["und"] * 3
    assert {r["lang_pred"] for r in langid.identify(table(spark, ODD), None).collect()} == {"und"}


def test_exchange_clustering_raises_likelihood_and_groups_by_context():
    rng = np.random.default_rng(1)
    words = [rng.choice([0, 1, 2]) if k % 2 == 0 else rng.choice([3, 4, 5]) for k in range(6000)]
    m = np.zeros((8, 8), np.int64)
    for a, b in zip(words, words[1:]):
        m[a, b] += 1
    c = brown_lm.exchange(m, 6, 2)
    assert len(set(c[:3])) == 1 and len(set(c[3:])) == 1 and c[0] != c[3]


def word_classes(m):
    out = {}
    for r in m.words.collect():
        keys, n, c = unpack(r["data"])
        out.update(zip(keys.tolist(), zip(n.tolist(), c.tolist())))
    return out


@pytest.mark.parametrize("head", [0, 4, 1000])
def test_class_model_scores_equal_brute_force(spark, head):
    rng = random.Random(5)
    texts = ODD + [" ".join(rng.choices(["the", "The", "of", "rare%d" % k, "xx", "yy"], k=rng.randrange(40))) for k in range(80)]
    texts += [texts[20], None]
    docs = table(spark, texts)
    counts, bigrams = Counter(), Counter()
    trained = [k for k in range(len(texts)) if zlib.crc32(str(k).encode()) % 5 != 1]
    hasher = WordHasher(lower=True)
    key = lambda w: int(hasher.hashes(pa.array([w.decode()]))[0][0] >> np.uint64(8))
    m = brown_lm.cluster(docs, head_size=head, core=3)
    s, of = m.scales, {}
    named = word_classes(m)
    for k in trained:
        w = [*brown_lm_words(texts[k]), None]
        counts.update(w)
    for w, n in counts.items():
        if w is not None:
            assert named[key(w)][0] == n
            of[w] = named[key(w)][1]
    assert len(named) == len(of)
    unknown = Counter(of[w] for w, n in counts.items() if w and n == 1)
    unknown = min(range(s.classes), key=lambda c: (-unknown[c], c))
    at = lambda w: "end" if w is None else of.get(w, unknown)
    for k in trained:
        c = ["end", *(at(w) for w in brown_lm_words(texts[k])), "end"]
        bigrams.update(zip(c, c[1:]))
    total, kinds = sum(counts.values()), len(counts)
    live = sorted(set(of.values()))
    prior = {c: 1 + sum(n for (_, b), n in bigrams.items() if b == c) for c in [*live, "end"]}
    prior = {c: n / sum(prior.values()) for c, n in prior.items()}
    after = Counter()
    for (a, _), n in bigrams.items():
        after[a] += n
    by = {c: sum(counts[w] + 0.5 for w in of if of[w] == c) for c in live}
    weight = lambda w: counts[w] / (counts[w] + brown_lm.RELIABLE)

    def step(a, b):
        p = (bigrams[a, b] + brown_lm.INTERPOLATION * prior[b]) / (after[a] + brown_lm.INTERPOLATION)
        return p * (1 - 1e-6) if b == "end" else p

    left = {a: 1 - step(a, "end") - sum(weight(w) * step(a, of[w]) * (counts[w] + 0.5) / by[of[w]] for w in of) for a in [*live, "end"]}
    rest = sum((1 - weight(w)) * (counts[w] + 0.5) for w in of) + 0.5

    def probability(a, w):
        if w is None:
            return step(a, "end")
        told = weight(w) * step(a, of[w]) / by[of[w]] if w in of else 0.0
        return (counts[w] + 0.5) * (told + left[a] * (1 - weight(w)) / rest)

    for a in [*live, "end"]:
        assert math.isclose(sum(probability(a, w) for w in [*of, None, b"never seen"]), 1.0, rel_tol=1e-9)
    got = {r["doc_id"]: r for r in brown_lm.score(docs, head_size=head, core=3).collect()}
    assert len(got) == len(texts)
    for k, t in enumerate(texts):
        w = [*brown_lm_words(t), None]
        base = sum(math.log10((counts[x] + 0.5) / (total + 0.5 * (kinds + 1))) for x in w)
        c = ["end", *map(at, w)]
        model = sum(math.log10(probability(x, y)) for x, y in zip(c, w))
        r = got[k]
        assert r["held_out"] == (k not in trained)
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(counts[x] > 0 for x in w), total)
        assert math.isclose(r["base_score"], base, rel_tol=1e-9, abs_tol=1e-9) and math.isclose(r["score"], model, rel_tol=1e-9, abs_tol=1e-9)


def brown_lm_words(text):
    return text.encode().lower().split() if text else []


def test_every_word_gets_a_class_by_its_neighbours(spark):
    rng = random.Random(8)
    first, second = [f"det{k}" for k in range(30)], [f"noun{k}" for k in range(60)]
    texts = [" ".join(w for _ in range(rng.randint(3, 9)) for w in (rng.choice(first), rng.choice(second))) for _ in range(500)]
    m = brown_lm.cluster(table(spark, texts), head_size=40, core=10)
    named = word_classes(m)
    hasher = WordHasher(lower=True)
    groups = [Counter(named[int(k)][1] for k in hasher.hashes(pa.array(g))[0] >> np.uint64(8)) for g in (first, second)]
    assert len(named) == 90 and sum(min(groups[0][c], groups[1][c]) for c in groups[0]) <= 5


def test_class_model_without_training_or_rows(spark):
    held = [k for k in range(60) if zlib.crc32(str(k).encode()) % 5 == 1]
    docs = spark.createDataFrame([(k, "a b") for k in held], "doc_id long, text string")
    got = brown_lm.score(docs).collect()
    assert len(got) == len(held)
    assert all((r["n_tokens"], r["n_known"], r["train_tokens"], r["base_score"]) == (3, 0, 0, 0.0) and math.isfinite(r["score"]) for r in got)
    assert brown_lm.score(docs.limit(0)).count() == 0
    nulls = spark.createDataFrame([(None, "a b"), (None, None), (None, "a b")], "doc_id long, text string")
    assert sorted((r["n_tokens"], r["held_out"]) for r in brown_lm.score(nulls).collect()) == [(1, False), (3, False), (3, False)]


def test_kneser_ney_sums_to_one_and_prefers_trusted_text(spark):
    m = PlainKneserNey(["the cat sat on the mat", "the dog sat on the rug", "a cat and a dog sat"] * 4 + ["the bird sang"])
    for context in (("", ""), ("", b"the"), (b"the", b"cat"), (b"zz", b"sat"), (b"zz", b"zz")):
        assert math.isclose(sum(m.p(*context, c) for c in m.one) + m.p(*context, b"other") * kn_quality.UNKNOWN_WORDS, 1.0, rel_tol=1e-9)
    docs = table(spark, ["the cat sat on the rug", "zq xv kk", None, ""])
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    good = kn_quality.keep_good(docs, labels)
    assert good.columns == docs.columns and good.count() == 2
    assert {r["doc_id"]: r["kept"] for r in kn_quality.classify(docs, labels).collect()} == {0: True, 1: True, 2: False, 3: False}
    assert kn_quality.classify(docs.limit(0), labels).count() == 0


def test_levenshtein_search_equals_edit_distance():
    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
            row = new
        return row[-1]

    rng = random.Random(2)
    terms = {"abcabc": 2.0, "abacus": 1.5, "bca": 1.0, "cabbage": 3.0}
    lex = toxicity.Lexicon(terms, {"ccab": 5.0})
    for _ in range(3000):
        word = "".join(rng.choices("abcgesu", k=rng.randrange(1, 9))) if rng.random() < 0.5 else "".join(c for c in rng.choice(list(terms)) if rng.random() < 0.93) + rng.choice(["", "a", "z"])
        want = max([w / (1 + d) for t, w in terms.items() if (d := distance(word, t)) <= (1 if len(t) >= toxicity.FUZZY_LETTERS else 0)] + [5.0] * word.startswith("ccab"), default=0.0)
        assert lex.match(word) == want


def test_toxicity_marks_abuse_not_quotation(spark):
    s = toxicity.fit([], [])
    quoted, aimed = toxicity.features('they said "you are an idiot" in a report', s.lexicon), toxicity.features("well you are worthles today", s.lexicon)
    assert quoted[5] == 1.0 and aimed[5] == 0.0 and aimed[4] > 0
    assert s.score("you are an idiot") > s.score('he wrote "idiot" once') and s.score(None) == s.score("") < 0.3
    got = toxicity.score(table(spark, ODD), s).collect()
    assert len(got) == len(ODD) and all(r["predicted"] == 0 for r in got)


def test_misspelled_short_and_learned_terms_match():
    seeds = toxicity.fit([], []).lexicon
    for word in ["idi0t", "m0ron", "tr4sh", "lozer", "scumm", "clwn", "sutpid", "stupdi"]:
        assert seeds.match(word) > 0, word
    assert seeds.match("house") == 0 and toxicity.Lexicon({"abcd": 2.0}, {}).match("badc") == 0
    clean = [f"the crash came closer in week{k} and the sum of it" for k in range(120)]
    foul = [f"you are a blargert in week{k}" for k in range(120)]
    lexicon = toxicity.learn(clean + foul, [0] * 120 + [1] * 120)
    for word in ["blargert", "blargerts", "blrgert", "blarg3rt", "lbargert", "tr4sh", "lozer", "scun"]:
        assert lexicon.match(word) > 0, word
    assert lexicon.match("crash") == lexicon.match("closer") == lexicon.match("sum") == 0
    assert 0 < lexicon.match("tr4sh") < seeds.match("tr4sh")


@pytest.mark.parametrize("tokens", [kn_quality.PACKET_TOKENS, 500])
def test_sharded_kneser_ney_counts_all_trusted_texts_and_equals_plain_python(spark, monkeypatch, tokens):
    monkeypatch.setattr(kn_quality, "PACKET_TOKENS", tokens)
    rng = random.Random(4)
    texts = [" ".join(rng.choices([*"abcde", "é"], [5, 4, 3, 2, 1, 1], k=rng.randint(1, 12))) for _ in range(300)]
    train = spark.createDataFrame([(t,) for t in [*texts, None, " "]], "text string")
    docs = table(spark, [*texts[:40], "a zz b", "a zz b", "zz yy", *ODD]).repartition(3)
    plain = PlainKneserNey(texts)
    values, unknown = kn_quality.value_table(train, 5)
    assert math.isclose(unknown, math.log10(plain.unknown), rel_tol=1e-9)
    scores = kn_quality.sharded_scores(docs, values, unknown, 5).collect()
    got = {r["__key"]: r for r in scores}
    want = {r["k"]: r["text"] for r in docs.selectExpr("text", "xxhash64(text) AS k").collect() if (r["text"] or "").encode().split()}
    assert len(scores) == len(got) and set(got) == set(want), ([want[k] for k in set(want) - set(got)], len(got))
    for k, t in want.items():
        assert got[k]["n_tokens"] == len(t.encode().split())
        assert math.isclose(got[k]["log10_prob"], plain.log10(t), rel_tol=1e-4), t


def test_classifier_sends_trusted_ids_instead_of_shuffling_texts(spark, monkeypatch):
    docs = table(spark, [f"a b c{k}" for k in range(50)])
    trusted = spark.range(0, 30).withColumnRenamed("id", "__good")
    for sent in (kn_quality.SENT_IDS, 7):  # at once, and a few at a time
        monkeypatch.setattr(kn_quality, "SENT_IDS", sent)
        plans, write = [], kn_quality.materialise
        monkeypatch.setattr(kn_quality, "materialise", lambda df, name: plans.append(df._jdf.queryExecution().executedPlan().toString()) or write(df, name))  # noqa: B023
        got = kn_quality.trusted_texts(docs.select("doc_id", "text"), trusted)
        monkeypatch.setattr(kn_quality, "materialise", write)
        assert sorted(r["text"] for t in got for r in t.collect()) == sorted(f"a b c{k}" for k in range(30))
        assert all("BroadcastHashJoin" in p and "hashpartitioning" not in p for p in plans) and len(got) == -(-30 // sent)


def test_map_of_keys_leaves_none_out(spark, monkeypatch):
    train = spark.createDataFrame([(" ".join(f"w{k % 97} v{k % 53} u{k}" for k in range(i, i + 40)),) for i in range(0, 2000, 40)], "text string")
    monkeypatch.setattr(kn_quality, "LEAST_BITS", 10)
    model, _ = kn_quality.value_table(train, 5, 2)
    for wave in range(2):
        values = model.values(wave, 5)
        known = model.known(values)
        keys = np.concatenate([unpack(r["data"])[0] for r in values.where(f"kind = {kn_quality.VALUES}").collect()])
        assert len(keys) == len(np.unique(keys)) and kn_quality._known(known, keys).all()
        other = np.random.default_rng(1).integers(0, 1 << 56, 10_000, dtype=np.uint64)
        assert kn_quality._known(known, other).mean() < 0.2


def test_waves_get_the_same_number_of_ngrams(spark):
    # nearly all trigrams end in one of eight words, which a hash alone would deal out unevenly
    train = spark.createDataFrame([(f"u{k % 45} v{k // 45} h{k % 8}",) for k in range(2000)], "text string")
    model, _ = kn_quality.value_table(train, 5, 4)
    waves = [np.concatenate([unpack(r["data"])[0] for r in model.values(wave, 5).where(f"kind = {kn_quality.VALUES}").collect()]) for wave in range(4)]
    sizes = [len(keys) for keys in waves]
    assert len(np.unique(np.concatenate(waves))) == sum(sizes) and max(sizes) < 1.1 * sum(sizes) / 4, sizes


def test_no_wave_leaves_what_it_sent_on_disk(spark):
    docs = table(spark, [f"a{k % 7} b{k % 5} c{k}" for k in range(50)])
    model = kn_quality.value_table(docs.select("text"), 5, 2)
    before = set(os.listdir(spark.sparkContext._temp_dir))
    assert kn_quality.sharded_scores(docs, *model, 5).count() == 50
    assert set(os.listdir(spark.sparkContext._temp_dir)) <= before


def test_chunk_hasher_tells_the_same_words_apart():
    long = [a * k for k in [*range(1, 40), 255, 256, 257, 264, 300_000] for a in ("q", "ab", "é", "\0")]
    rng = random.Random(3)
    mixed = ["".join(rng.choices("ab \t\n\x08\x0e\r!é", k=rng.randint(0, 6))) for _ in range(3000)]
    for texts in (ODD, ODD[::-1], long, [f"{w} {w} z{w}" for w in long], mixed, [], [""]):
        (h, n), (g, m) = (x.hashes(pa.array(texts, pa.string())) for x in (ChunkHasher(), WordHasher()))
        want = [w for t in texts for w in (t or "").encode().split()]
        assert n.tolist() == m.tolist() == [len((t or "").encode().split()) for t in texts]
        # ids of 48 bits: one for each word
        assert len(h) == len(g) == len(want) and len(set(zip(want, h >> np.uint64(16)))) == len(set(want)) == len(set(h >> np.uint64(16)))


def test_packed_columns_come_back_and_can_be_written_to():
    rng = np.random.default_rng(1)
    for n in (0, 1, 1000):
        columns = [np.sort(rng.integers(0, 1 << 56, n, dtype=np.uint64)), rng.random(n), rng.random(n).astype(np.float32), rng.integers(-5, 5, n), rng.integers(0, 1 << 16, n).astype(np.uint16)[::-1]]
        for rising in (False, True):
            for got, want in zip(unpack(pack(*columns, rising=rising)), columns, strict=True):
                assert got.dtype == want.dtype and got.flags.writeable and got.tolist() == want.tolist()


def test_texts_without_a_frequent_ngram_are_scored(spark):
    # one text is alone in its partition and shares only its start with the others
    texts = [f"{a} {b} {c}" for a in "abcd" for b in "abcd" for c in "abcd"]
    train = spark.createDataFrame([(t,) for t in [*texts, "p q r s t"]], "text string")
    docs = dealt(table(spark, [*texts, "p q r s t u"]), 2, (F.col("text") > "p").cast("int"))
    plain = PlainKneserNey([*texts, "p q r s t"])
    values, unknown = kn_quality.value_table(train, 6)
    got = {r["__key"]: r for r in kn_quality.sharded_scores(docs, values, unknown, 6).collect()}
    for r in docs.selectExpr("text", "xxhash64(text) AS k").collect():
        assert math.isclose(got[r["k"]]["log10_prob"], plain.log10(r["text"]), rel_tol=1e-4)


def test_quality_classifier_counts_every_trusted_text(spark):
    # far more trusted texts than a sample would take, each with a word of its own: all are counted
    rows = [(k, " ".join(f"own{k} {c}" for c in "pqrs"[: 1 + k % 4]), "en", 1) for k in range(2000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, quality int")
    got = {r["doc_id"]: r["perplexity"] for r in kn_quality.classify(docs, docs.select("doc_id", "quality")).collect()}
    held = {k for k in got if zlib.crc32(str(k).encode()) % 4 == 2}
    for size in range(4):
        assert max(p for k, p in got.items() if k % 4 == size and k not in held) < min(got[k] for k in held if k % 4 == size)


def test_language_and_toxicity_of_empty_null_and_repeated_rows(spark):
    words = {"en": "the cat and the dog sat on the mat", "xx": "ju zolle mi karra ju benno zo"}
    rows = [(k, words[lang], lang) for k in range(40) for lang in words for _ in range(2)]
    docs = spark.createDataFrame([*rows, (None, words["en"], "en"), (None, None, None), (None, "12 !!", "en"), (900, "", "xx")], "doc_id long, text string, lang string")
    model = langid.train(docs, per_language=20)
    got = langid.identify(docs, model).collect()
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 for r in got)
    assert [r["lang_pred"] for r in got if r["doc_id"] in (None, 900)].count("und") == 3
    kept = langid.keep_identified(docs, model, 0.0)
    assert kept.columns == docs.columns and kept.count() == len(rows) + 1
    assert langid.train(docs.limit(0)) is None and langid.identify(docs.limit(0), None).count() == 0
    assert langid.keep_identified(docs.limit(0), None, 0.4).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    scorer = toxicity.fit([], [])
    assert toxicity.score(docs.limit(0), scorer).count() == 0 and toxicity.score(docs, scorer).count() == docs.count()
    assert labels.count() == 0


def test_toxicity_learns_from_labels_without_texts_and_with_null_ids(spark):
    clean, foul = "a quiet walk along the river", "you blargh fool"
    docs = spark.createDataFrame([*((k, foul if k % 2 else clean) for k in range(200)), (None, foul)], "doc_id long, text string")
    labels = spark.createDataFrame([*((k, 1, k % 2) for k in range(200)), (None, 1, 0), (7, 1, None)], "doc_id long, quality int, toxic int")
    got = toxicity.score(docs, toxicity.train(docs, labels)).collect()
    assert len(got) == 201
    assert min(r["score"] for r in got if r["doc_id"] is None or r["doc_id"] % 2) > max(r["score"] for r in got if r["doc_id"] is not None and not r["doc_id"] % 2)
