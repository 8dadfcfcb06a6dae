"""Language identification by a bidirectional gated recurrent network over bytes, in numpy.

Two gated recurrent units read a window of bytes from both ends; a softmax over their joined states labels every
position with a language. A document's probabilities are the mean over its letter positions. Training is
backpropagation through time with Adam, on the driver, over windows of a bounded sample; scoring reads every
byte of every text in windows of fixed length, many windows at once, so that memory does not depend on a text's
length.

Bounds (documented parameters): ``PER_LANGUAGE`` sampled texts a language in expectation, ``WINDOWS_PER_TEXT``
windows of each, at most 1000 languages.

Defined cases: a null text, an empty one, or one without a letter is ``und`` with score 0; languages without a
training row cannot be predicted; with no training rows at all every text is ``und``; ties go to the language
first in order; repeated rows give equal results; a null id is never held out; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import give_back, hash_sample, held_out, read, trimmed

PER_LANGUAGE = 500
WINDOWS_PER_TEXT = 4
FOLDS, HELD_OUT = 4, 2
HIDDEN = 8
TRAIN_LENGTH, TRAIN_BATCH, TRAIN_STEPS, RATE = 48, 256, 400, 0.02
LENGTH, WIDTH = 128, 2048
SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


def _sigmoid(x):
    with np.errstate(over="ignore"):
        return 1 / (1 + np.exp(-x))


@dataclass
class Model:
    """languages, and the parameters: for each direction input (256, 3H) and recurrent (H, 3H) weights; the output."""

    languages: list[str]
    p: dict[str, np.ndarray]

    def states(self, x: np.ndarray, side: str, keep: list | None = None) -> np.ndarray:
        """Hidden states (T, B, H) of one direction over bytes (T, B)."""
        wx, u, h = self.p[side + "x"], self.p[side + "u"], np.zeros((x.shape[1], HIDDEN), np.float32)
        out = np.empty((*x.shape, HIDDEN), np.float32)
        for t in range(len(x)) if side == "f" else reversed(range(len(x))):
            a, g = wx[x[t]], h @ u
            zr = _sigmoid(a[:, : 2 * HIDDEN] + g[:, : 2 * HIDDEN])
            z, r = zr[:, :HIDDEN], zr[:, HIDDEN:]
            n = np.tanh(a[:, 2 * HIDDEN :] + r * g[:, 2 * HIDDEN :])
            if keep is not None:
                keep.append((t, h, z, r, n, g[:, 2 * HIDDEN :]))
            h = n + z * (h - n)
            out[t] = h
        return out

    def fast(self) -> dict[str, np.ndarray]:
        """The weights transposed for scoring, gates z and r negated so that one exp serves the logistic."""
        sign = np.repeat(np.float32([-1, -1, 1]), HIDDEN)
        q = {side + k: np.ascontiguousarray((self.p[side + k] * sign).T) for side in "fb" for k in "xu"}
        return q | {"fv": np.ascontiguousarray(self.p["v"][:HIDDEN].T), "bv": np.ascontiguousarray(self.p["v"][HIDDEN:].T)}

    def positions(self, x: np.ndarray, q: dict | None = None) -> np.ndarray:
        """Label probabilities (T, languages, B) of every position of bytes (T, B)."""
        q, h2, h3 = q or self.fast(), 2 * HIDDEN, 3 * HIDDEN
        steps, width = x.shape
        logits = np.empty((steps, len(self.languages), width), np.float32)
        logits[:] = self.p["c"][:, None]
        g, zr = np.empty((h3, width), np.float32), np.empty((h2, width), np.float32)
        n, d = np.empty((HIDDEN, width), np.float32), np.empty((HIDDEN, width), np.float32)
        states = np.empty((steps, HIDDEN, width), np.float32)
        with np.errstate(over="ignore"):
            for side in "fb":
                wx, u, h = q[side + "x"], q[side + "u"], np.zeros((HIDDEN, width), np.float32)
                for t in range(steps) if side == "f" else reversed(range(steps)):
                    a = np.take(wx, x[t], axis=1)
                    np.matmul(u, h, out=g)
                    np.add(a[:h2], g[:h2], out=zr)
                    np.exp(zr, out=zr)
                    zr += 1
                    np.reciprocal(zr, out=zr)
                    np.multiply(zr[HIDDEN:], g[h2:], out=n)
                    n += a[h2:]
                    np.tanh(n, out=n)
                    np.subtract(h, n, out=d)
                    d *= zr[:HIDDEN]
                    h = np.add(n, d, out=states[t])
                logits += np.matmul(q[side + "v"], states)
        logits -= logits.max(1, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(1, keepdims=True)
        return logits

    def gradients(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Loss and gradients for bytes (T, B), labels (B) and position weights (T, B)."""
        p, hs, kept = self.p, [], {}
        for side in "fb":
            kept[side] = []
            hs.append(self.states(x, side, kept[side]))
        both = np.concatenate(hs, axis=2)
        logits = both @ p["v"] + p["c"]
        logits -= logits.max(2, keepdims=True)
        q = np.exp(logits)
        q /= q.sum(2, keepdims=True)
        at = np.arange(x.shape[1])
        total = max(1.0, float(w.sum()))
        loss = -float((np.log(q[:, at, y] + 1e-12) * w).sum()) / total
        d = q
        d[:, at, y] -= 1
        d *= (w / total)[:, :, None]
        g = {"v": np.einsum("tbh,tbc->hc", both, d), "c": d.sum((0, 1))}
        dboth = d @ p["v"].T
        for k, side in enumerate("fb"):
            dx, du = np.zeros_like(p[side + "x"]), np.zeros_like(p[side + "u"])
            dh, own = np.zeros((x.shape[1], HIDDEN), np.float32), dboth[:, :, k * HIDDEN : (k + 1) * HIDDEN]
            for t, h, z, r, n, gn in reversed(kept[side]):
                dh = dh + own[t]
                dn = dh * (1 - z) * (1 - n * n)
                dz = dh * (h - n) * z * (1 - z)
                dr = dn * gn * r * (1 - r)
                da = np.concatenate([dz, dr, dn], axis=1)
                dg = np.concatenate([dz, dr, dn * r], axis=1)
                np.add.at(dx, x[t], da)
                du += h.T @ dg
                dh = dh * z + dg @ p[side + "u"].T
            g[side + "x"], g[side + "u"] = dx, du
        return loss, g


def fit(texts: list[bytes], labels: list[str], seed: int = 7) -> Model | None:
    """Train on windows of the texts; None without texts."""
    languages = sorted(set(labels))
    if not languages:
        return None
    rng = np.random.default_rng(seed)
    size = lambda *s: (rng.standard_normal(s) * 0.3).astype(np.float32)
    p = {"v": size(2 * HIDDEN, len(languages)), "c": np.zeros(len(languages), np.float32)}
    for side in "fb":
        p |= {side + "x": size(256, 3 * HIDDEN), side + "u": size(HIDDEN, 3 * HIDDEN)}
    model = Model(languages, p)
    if len(languages) == 1:
        return model
    x, w, y = [], [], []
    for text, label in zip(texts, labels):
        for _ in range(WINDOWS_PER_TEXT):
            at = int(rng.integers(0, max(1, len(text) - TRAIN_LENGTH + 1)))
            cut = np.frombuffer(text[at : at + TRAIN_LENGTH], np.uint8)
            row = np.full(TRAIN_LENGTH, 32, np.uint8)
            row[: len(cut)] = cut
            x.append(row)
            w.append(np.arange(TRAIN_LENGTH) < len(cut))
            y.append(languages.index(label))
    x, w, y = np.array(x), np.array(w, np.float32), np.array(y)
    groups = [np.flatnonzero(y == k) for k in range(len(languages))]  # every language weighs the same
    first, second = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}
    for step in range(1, TRAIN_STEPS + 1):
        at = np.concatenate([rng.choice(g, max(1, TRAIN_BATCH // len(groups))) for g in groups])
        _, g = model.gradients(np.ascontiguousarray(x[at].T), y[at], np.ascontiguousarray(w[at].T))
        norm = np.sqrt(sum(float((v * v).sum()) for v in g.values()))
        rate = RATE * min(1.0, 2.0 * (1 - step / (TRAIN_STEPS + 1)))
        for k, v in g.items():
            v = v / max(1.0, norm)
            first[k] = 0.9 * first[k] + 0.1 * v
            second[k] = 0.99 * second[k] + 0.01 * v * v
            p[k] -= (rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
    return model


_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True


class Scorer:
    """Pools position labels to documents over windows of many texts at once."""

    def __init__(self, model: Model):
        self.model, self.weights = model, model.fast()
        self.width = max(16, min(WIDTH, (1 << 22) // (LENGTH * len(model.languages))))

    def probabilities(self, texts: list[bytes]) -> np.ndarray:
        """(texts, languages): the mean over letter positions; zeros where there is none."""
        out, n = np.zeros((len(texts), len(self.model.languages))), np.zeros(len(texts))
        pending: list[bytes] = []
        owners: list[int] = []

        def flush():
            x = np.frombuffer(b"".join(w.ljust(LENGTH) for w in pending), np.uint8).reshape(len(pending), LENGTH)
            letter = _LETTER[x].astype(np.float32)
            q = self.model.positions(np.ascontiguousarray(x.T), self.weights)
            q *= np.ascontiguousarray(letter.T)[:, None, :]
            sums = q.sum(0).T
            np.add.at(out, owners, sums)
            np.add.at(n, owners, letter.sum(1))

        for k, text in enumerate(texts):
            for at in range(0, len(text), LENGTH):
                pending.append(text[at : at + LENGTH])
                owners.append(k)
                if len(pending) == self.width:
                    flush()
                    pending, owners = [], []
        if pending:
            flush()
        return out / np.maximum(n, 1)[:, None]


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Model | None:
    """Fit on a sample of rows with text and lang outside the held-out fold; only a window of each is fetched."""
    rows = docs.select("doc_id", "text", "lang").where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out("doc_id", FOLDS, HELD_OUT))
    size = TRAIN_LENGTH * WINDOWS_PER_TEXT * 4
    start = F.pmod(F.xxhash64("doc_id", F.lit("start")), F.greatest(F.length("text") - size, F.lit(1))) + 1
    picked = hash_sample(rows, "lang", per_language, "doc_id").select("doc_id", F.substring(F.col("text"), start.cast("int"), F.lit(size)).alias("text"), "lang")
    got = sorted(picked.collect(), key=lambda r: (r["doc_id"] is None, r["doc_id"], r["text"]))
    return fit([r["text"].encode("utf-8", "replace") for r in got], [r["lang"] for r in got])


def _predict(scorer: Scorer | None, texts: list[str | None]) -> tuple[list[str], list[float]]:
    pred, score = ["und"] * len(texts), [0.0] * len(texts)
    live = [k for k, t in enumerate(texts) if has_letter(t)] if scorer else []
    if live:
        q = scorer.probabilities([texts[k].encode("utf-8", "replace") for k in live])
        for k, row in zip(live, q):
            best = int(row.argmax())
            pred[k], score[k] = scorer.model.languages[best], float(min(1.0, row[best]))
    return pred, score


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, lang_pred and score of every whole text."""
    rows = docs.select("doc_id", "text", held_out("doc_id", FOLDS, HELD_OUT).alias("held_out"))

    def run(batches):
        scorer = Scorer(model) if model else None
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                pred, score = _predict(scorer, part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(pred, pa.string()), pa.array(score, pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return rows.mapInArrow(trimmed(run), SCHEMA)


def keep_identified(docs: DataFrame, model: Model | None, least_score: float) -> DataFrame:
    """The rows of docs, all columns, whose language is told with at least this score."""
    table = docs.sparkSession.sparkContext.broadcast(model)

    def told(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scorer = Scorer(table.value) if table.value else None
        for part in texts:
            out = []
            for at in range(0, len(part), 500):
                pred, score = _predict(scorer, [t if isinstance(t, str) else None for t in part.iloc[at : at + 500]])
                out += [p != "und" and s >= least_score for p, s in zip(pred, score)]
            yield pd.Series(out, dtype=bool)
        scorer = None
        give_back()

    # only texts go through Python, the other columns stay where they are
    return docs.where(F.pandas_udf(told, "boolean")(F.col("text")))


def label_positions(text: str, model: Model) -> list[str]:
    """The language label of every byte of one text."""
    out: list[str] = []
    data = text.encode()
    for at in range(0, len(data), LENGTH):
        x = np.frombuffer(data[at : at + LENGTH], np.uint8)[:, None]
        out += [model.languages[k] for k in model.positions(x)[:, :, 0].argmax(1)]
    return out


def op2_langid(spark, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return identify(docs, train(docs))
