"""Toxicity scores: Levenshtein automata over a lexicon trie, and context windows that tell quotation from abuse.

The lexicon joins seed terms with terms and stems learned from labelled rows: character prefixes and whole words
that occur far more often in toxic documents than in others. It is kept as a trie. A word is matched by walking the
trie and the word's Levenshtein automaton together (the automaton's state is the row of edit distances that are
still within bound; a transposition of neighbours is one edit), so misspelled terms are found without trying the
lexicon term by term. Words of the labelled rows that are an edit away from a term weigh what their own odds say, so
that clean words near a term (crash, closer) do not count; edits not seen there weigh less the more of a term's
neighbours are clean. Every match is weighed by its window of words: quotation marks around it, or a word of saying or of
discussing before it, mark a quotation; a second-person or copula word before it marks abuse.

A logistic model over the match counts (per thousand words, and in total), abuse and quotation counts gives the
score. It is fitted on a bounded sample of labelled rows (``PER_LABEL`` for each label in expectation) outside the
held-out fold.

Defined cases: null and empty texts have no matches and get the score of such; of several labels for one id the
largest counts; without labelled rows of both kinds the seeds alone score; repeated rows are scored alike; a null
id is never held out; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from math import exp, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import hash_sample, held_out, read

FOLDS, HELD_OUT = 4, 2
PER_LABEL = 1_500
#: Terms to start from.
SEEDS = ("idiot", "stupid", "moron", "loser", "scum", "trash", "pathetic", "worthless", "disgusting", "clown")
#: Words of saying or discussing, and words that aim at someone.
SAYING = frozenset("said says called calls wrote writes quoted quote word term phrase dijo sagte dit".split())
AIMING = frozenset("you your youre are is such these those he she they du sie tu vous eres son bist ist est es".split())
QUOTES = "\"'“”„«»‘’"
WINDOW = 4
#: Terms of at least so many letters may differ by one edit; all seeds and learned terms have as many.
FUZZY_LETTERS = 4
STEM_LETTERS = range(4, 9)
#: What a learned term must reach: log odds, and twice the log likelihood ratio against chance among very many.
LEAST_LOG_ODDS, LEAST_RATIO = 3.0, 45.0
THRESHOLD = 0.3
REMEMBERED = 400_000
SCHEMA = "doc_id long, held_out boolean, score double, predicted int"
STRIP = re.compile(r"^\W+|\W+$")


class Lexicon:
    """A trie of terms (matched to the end) and stems (matched exactly at the start of a word), with weights.

    Its product with the words' Levenshtein automaton is made deterministic as words ask for it: a state is a set of
    (trie node, edits so far, letter that ends a transposition), and each transition is worked out once. Characters
    outside the lexicon's alphabet behave alike, so the table is bounded by the lexicon. ``near`` has a factor for the
    edits of a term, and ``own`` the weights of words that are known to be an edit away.
    """

    EDITS = 1

    def __init__(self, terms: dict[str, float], stems: dict[str, float], near: dict[str, float] | None = None, own: dict[str, float] | None = None):
        self.near, self.own, self.name = near or {}, own or {}, {}
        self.next: list[dict[str, int]] = [{}]
        self.depth, self.term, self.stem = [0], {}, {}
        for table, ends in ((terms, self.term), (stems, self.stem)):
            for text, weight in table.items():
                node = 0
                for ch in text:
                    if ch not in self.next[node]:
                        self.next[node][ch] = len(self.next)
                        self.next.append({})
                        self.depth.append(self.depth[node] + 1)
                    node = self.next[node][ch]
                ends[node] = max(weight, ends.get(node, 0.0))
                self.name[node] = text
        self.alphabet = {ch for n in self.next for ch in n}
        self.clear()

    def clear(self) -> None:
        self.known: dict[str, float] = {}
        self.number: dict[frozenset, int] = {}
        self.states: list[frozenset] = []
        self.steps: list[dict[str, int]] = []
        self.ends: list[tuple[float, str]] = []  # the best term that ends in a state
        self.passes: list[float] = []  # the best stem that a state has just matched
        self._state({(0, 0, "")})

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k in ("next", "depth", "term", "stem", "alphabet", "near", "own", "name")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self.clear()

    def _state(self, members: set[tuple[int, int, str]]) -> int:
        todo = list(members)
        while todo:  # a letter of the term that the word leaves out
            node, edits, wait = todo.pop()
            if edits < self.EDITS and not wait:
                more = {(child, edits + 1, "") for child in self.next[node].values()} - members
                members |= more
                todo += more
        key = frozenset(members)
        if key not in self.number:
            self.number[key] = len(self.states)
            self.states.append(key)
            self.steps.append({})
            allowed = lambda n, e: e <= (self.EDITS if self.depth[n] >= FUZZY_LETTERS else 0)
            weigh = lambda n, e: self.term[n] / (1 + e) * (self.near.get(self.name[n], 1.0) if e else 1.0)
            self.ends.append(max(((weigh(n, e), self.name[n]) for n, e, wait in key if n in self.term and not wait and allowed(n, e)), default=(0.0, "")))
            self.passes.append(max((self.stem[n] for n, e, _ in key if n in self.stem and e == 0), default=0.0))
        return self.number[key]

    def _step(self, at: int, ch: str) -> int:
        after = set()
        for node, edits, wait in self.states[at]:
            if wait:  # the second of two letters that changed places
                if ch == wait:
                    after.add((node, edits, ""))
                continue
            if ch in self.next[node]:
                after.add((self.next[node][ch], edits, ""))
            if edits < self.EDITS:
                after.add((node, edits + 1, ""))
                after |= {(child, edits + 1, "") for child in self.next[node].values()}
                after |= {(self.next[child][ch], edits + 1, first) for first, child in self.next[node].items() if first != ch and ch in self.next[child]}
        got = self.steps[at][ch] = self._state(after) if after else -1
        return got

    def find(self, word: str) -> tuple[float, str]:
        """match() with the term that ends with the word; no term where a stem matches better, or nothing."""
        at, best = 0, 0.0
        for ch in word:
            ch = ch if ch in self.alphabet else "\0"
            after = self.steps[at].get(ch)
            at = self._step(at, ch) if after is None else after
            if at < 0:
                return best, ""
            best = max(best, self.passes[at])
        return max((best, ""), self.ends[at])

    def match(self, word: str) -> float:
        """The weight of the best match of a bare lower-case word, halved for an edit; 0 for none."""
        got = self.own.get(word)
        return self.find(word)[0] if got is None else got

    def stemmed(self, word: str) -> bool:
        """Whether the word starts with a stem."""
        node = 0
        for ch in word:
            node = self.next[node].get(ch)
            if node is None or node in self.stem:
                return node is not None
        return False

    def weight(self, word: str) -> float:
        """match() of a word as it stands in a text, remembered within a bound."""
        got = self.known.get(word)
        if got is None:
            if len(self.known) >= REMEMBERED:
                self.known.clear()
            got = self.known[word] = self.match(STRIP.sub("", word.lower()))
        return got


def features(text: str | None, lexicon: Lexicon) -> list[float]:
    """Matches, weight and rate; matches that are aimed, and that are quoted."""
    words = (text or "").split()
    hits = [w for w in set(words) if lexicon.weight(w)]
    if not hits:
        return [0.0] * 6
    hit, n, total, aimed, quoted = set(hits), 0, 0.0, 0, 0
    for k, w in enumerate(words):
        if w not in hit:
            continue
        n += 1
        total += lexicon.weight(w)
        before = [STRIP.sub("", x.lower()) for x in words[max(0, k - WINDOW) : k]]
        marks = sum(1 for x in words[max(0, k - WINDOW) : k + 1] if x[:1] in QUOTES), sum(1 for x in words[k : k + WINDOW + 1] if x.rstrip(".,;:!?")[-1:] in QUOTES)
        if (marks[0] and marks[1]) or SAYING & set(before):
            quoted += 1
        elif AIMING & set(before):
            aimed += 1
    return [1.0, log(1 + n), log(1 + total), log(1 + 1000.0 * n / len(words)), log(1 + aimed), quoted / n]


class Scorer:
    def __init__(self, lexicon: Lexicon, weights: list[float]):
        self.lexicon, self.weights = lexicon, weights

    def score(self, text: str | None) -> float:
        z = self.weights[0] + sum(a * b for a, b in zip(self.weights[1:], features(text, self.lexicon)))
        return 1 / (1 + exp(-max(-30.0, min(30.0, z))))


def _grams(text: str) -> set[str]:
    """The document's words, each also by its prefixes (marked)."""
    words = {STRIP.sub("", w) for w in set(text.lower().split())}
    out = {w for w in words if 3 < len(w) < 40}
    return out | {"^" + w[:k] for w in out for k in STEM_LETTERS if len(w) > k}


def learn(texts: list[str], toxic: list[int]) -> Lexicon:
    """Seeds with what occurs far more often in toxic documents than in others."""
    counts = [Counter(), Counter()]
    for text, label in zip(texts, toxic):
        counts[label].update(_grams(text))
    n = Counter(toxic)
    odds = {}
    for g, a in counts[1].items():
        s = log((a + 0.5) / (n[1] + 1)) - log((counts[0][g] + 0.5) / (n[0] + 1))
        b, share = counts[0][g], n[1] / (n[0] + n[1])
        ratio = 2 * (a * log(a / ((a + b) * share)) + (b and b * log(b / ((a + b) * (1 - share)))))  if 0 < share < 1 else 0.0
        if ratio >= LEAST_RATIO and s >= LEAST_LOG_ODDS:
            odds[g] = s
    stems = {g[1:]: s for g, s in odds.items() if g[0] == "^"}
    # of nested stems the shortest suffices; whole words stay beside their stems, as only they match misspelled
    stems = {g: s for g, s in stems.items() if not any(g[:k] in stems for k in range(4, len(g)))}
    if not (n[0] and n[1]):
        return Lexicon({t: LEAST_LOG_ODDS for t in SEEDS}, {})
    terms = {t: LEAST_LOG_ODDS for t in SEEDS} | {g: s for g, s in odds.items() if g[0] != "^"}
    return Lexicon(terms, stems, *_neighbours(Lexicon(terms, stems), terms, texts, toxic))


def _neighbours(lexicon: Lexicon, terms: dict[str, float], texts: list[str], toxic: list[int]) -> tuple[dict[str, float], dict[str, float]]:
    """A factor for the edits of each term, and the weights of the words an edit away from a term that the texts have."""
    counts, n = [Counter(), Counter()], Counter(toxic)
    for text, label in zip(texts, toxic):
        counts[label].update({w for w in (STRIP.sub("", x) for x in set(text.lower().split())) if lexicon.weight(w)})
    own, sides = {}, {}
    for w in counts[0] | counts[1]:
        weight, term = lexicon.find(w)
        if not term or w in terms or lexicon.stemmed(w):
            continue
        s = log((counts[1][w] + 0.5) / (n[1] + 1)) - log((counts[0][w] + 0.5) / (n[0] + 1))
        own[w] = min(weight, max(0.0, s))
        sides.setdefault(term, [0, 0])[s > 0] += 1
    return {t: (1 + foul) / (1 + foul + clean) for t, (clean, foul) in sides.items()}, own


def fit(texts: list[str], toxic: list[int]) -> Scorer:
    """Lexicon from one half and logistic weights from the other, so that rare chance terms earn no trust."""
    order = np.random.default_rng(5).permutation(len(texts))
    half = order[: 2 * len(order) // 3]
    lexicon = learn([texts[k] for k in half], [toxic[k] for k in half])
    rest = order[2 * len(order) // 3 :]
    y = np.array([toxic[k] for k in rest], float)
    if len(set(y)) < 2:
        return Scorer(lexicon, [-3.0, 2.0, 0.5, 0.5, 0.5, 0.5, -1.0])
    x = np.array([[1.0, *features(texts[k], lexicon)] for k in rest])
    w, ridge = np.zeros(x.shape[1]), np.diag([1e-3] + [0.05] * (x.shape[1] - 1))
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w -= np.linalg.solve((x.T * (p * (1 - p))) @ x + ridge + 1e-6 * np.eye(len(w)), x.T @ (p - y) + ridge @ w)
    return Scorer(lexicon, [float(v) for v in w])


def train(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL) -> Scorer:
    """Fit on a sample of labelled rows outside the held-out fold; whole texts of the sample reach the driver."""
    known = labels.where("toxic IS NOT NULL AND doc_id IS NOT NULL").where(~held_out("doc_id", FOLDS, HELD_OUT))
    known = known.groupBy(F.col("doc_id").alias("__id")).agg(F.max(F.when(F.col("toxic") > 0, 1).otherwise(0)).alias("toxic"))
    picked = F.broadcast(hash_sample(known, "toxic", per_label, "__id"))
    rows = docs.select("doc_id", "text").join(picked, F.col("doc_id") == F.col("__id")).where("text IS NOT NULL").select("doc_id", "text", "toxic").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["text"]))
    return fit([r["text"] for r in rows], [r["toxic"] for r in rows])


def score(docs: DataFrame, scorer: Scorer, threshold: float = THRESHOLD) -> DataFrame:
    rows = docs.select("doc_id", "text", held_out("doc_id", FOLDS, HELD_OUT).alias("held_out"))

    def run(batches):
        for batch in batches:
            got = [scorer.score(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(got, pa.float64()), pa.array([int(s >= threshold) for s in got], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    return rows.mapInArrow(run, SCHEMA)


def op5_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return score(docs, train(docs, read(spark, sf_dir, "labels")))
