import hashlib
from collections import Counter

import corpus_pipeline as P
import public_tokenizers
import tokenizers
from memojoin.llm import bpe, langid
from memojoin.llm.common import materialise
from tests_brute import brute, mixed, quality


def test_every_stage_equals_its_brute_force_version(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    good = {r["doc_id"] for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").collect()}
    for k, (name, stage) in enumerate(P.STAGES):
        before, rows = docs, docs.collect()
        docs = materialise(stage(spark, docs, sf), "t")
        got = docs.collect()
        ids = {r["doc_id"] for r in got}
        if k < len(P.STAGES) - 1:
            assert docs.columns == columns and (name == "mixing" or len(ids) == len(got))
        if name == "language_id":
            told = langid.identify(before, langid.train(before)).collect()
            assert ids == {r["doc_id"] for r in told if r["lang_pred"] != "und" and r["score"] >= P.LEAST_LANGUAGE_SCORE}
            assert len(good & ids) >= 0.95 * len(good)
        if name == "quality_classifier":
            assert ids == quality([(r["doc_id"], r["lang"], r["text"]) for r in rows], good)
            assert len(good & ids) >= 0.95 * len(good)
        if name == "ngram_jaccard":
            pairs = [(r["doc_id"], r["text"]) for r in rows]
            assert ids == {c for _, c in brute(pairs, P.NEAR_WORDS, P.NEAR_PERCENT).values()} | {d for d, t in pairs if not (t or "").split()}
        if name == "mixing":
            assert Counter(r["doc_id"] for r in got) == mixed([(r["doc_id"], r["source"], r["text"]) for r in rows])
        if name == "bpe":
            lib = tokenizers.Tokenizer.from_file(public_tokenizers.path(bpe.VOCABULARY))
            want = Counter((r["doc_id"], hashlib.sha256(" ".join(map(str, lib.encode(r["text"] or "", add_special_tokens=False).ids)).encode()).hexdigest()) for r in rows)
            assert Counter((r["doc_id"], r["ids_sha256"]) for r in got) == want


def test_stages_take_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in P.STAGES:
        docs = materialise(stage(spark, docs, sf), "t")
        assert docs.count() == 0
        docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
