"""Class-based bigram language model with exchange clustering, and per-document log probabilities.

Words are counted over all training texts, by hash and in shards. The most frequent words (``HEAD``, a bound, so that
they can be sent to every task) get numbers; texts are written once as packets of numbers, in which every other word
stands for an entry of the packet's own list. The ``CORE`` most frequent words are clustered by exchange one word after
another on the driver. From there all words of training move in rounds: tasks send, for each word, how often it stands
before and behind each class; these counts meet at the word's shard, and the word goes to the class that raises the
likelihood of the class bigrams most, given the class counts of the round (neighbours outside the head count as one
open class there). So every training word has a class, and the number of classes grows with the vocabulary.

Packets then ask the words' shards for the classes and counts of the words on their lists. A word seen n times is told by
its class with weight n / (n + RELIABLE): class transition, interpolated with class frequencies, times word emission with
additive smoothing. What a context's classes leave over by these weights is shared out among the words, rare ones above
all, and one unknown word, by frequency without regard to classes. So probabilities sum to one. As a context an unknown
word counts with the class that holds most words seen once.

Tokens are the A-Z-lowered words and one end for each text. Counts cover all training texts, whole. Words stand as
hashes of 56 bits: words that share one count as equal.

Defined cases: null and empty texts have one token, the end; without training texts N and V are 0 and the base
score is 0; ties in counts go by hash, ties between classes to the lower number; a null id is in training; repeated rows
are scored and counted each; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import WordHasher, discard, held_out, materialise, read, trimmed
from memojoin.llm.packets import PACKED, by_ranges, by_shard, joined, met, pack, rows_of, runs, slices, unpack

FOLDS, HELD_OUT = 5, 1
HEAD, CORE = 100_000, 1_000
#: Classes as a power of the vocabulary, and at least.
CLASS_POWER, LEAST_CLASSES = 0.3, 8
ROUNDS, CORE_ROUNDS, INTERPOLATION = 2, 4, 5.0
ADD = 0.5
#: At this count a word is told half by its class.
RELIABLE = 2.0
#: Counts up to here find the change of likelihood in a table.
SMALL = 32
#: Counts of words that are weighed at a time.
MOST_COUNTS = 16_384
#: Bytes of text for each shard at most.
SHARD_BYTES = 128 << 20
#: Kinds of packed rows.
WORDS, TEXTS, MOVES, ANSWERS, STATS = range(5)
NO_CLASS = 0xFFFF


# ---------------------------------------------------------------- counts and packets


def word_counts(train: DataFrame, shards: int) -> DataFrame:
    """WORDS key, n of every shard, by rising key; STATS: words, tokens, and words by the band of their counts."""

    def post(batches):
        hasher = WordHasher(lower=True)
        for part in slices(batches, 0):
            h, _ = hasher.hashes(part.column(0))
            keys, n = np.unique(h >> np.uint64(8), return_counts=True)
            if len(keys):
                yield rows_of([(k, WORDS, pack(*c)) for k, c in by_ranges(keys, shards, n.astype(np.uint32), rising=True)])

    def add(shard, packets):
        keys, n = joined(packets[WORDS])
        order = np.argsort(keys)
        keys, n = keys[order], n[order].astype(np.uint64)
        new = runs(keys)
        keys, n = keys[new], np.add.reduceat(n, new)
        return [(shard, WORDS, pack(keys, n)), (shard, STATS, pack(np.concatenate([[len(n), n.sum()], np.bincount(_band(n), minlength=1024)]).astype(np.int64)))]

    return met(train.select("text").mapInArrow(trimmed(post), PACKED), shards, add)


def _band(n: np.ndarray) -> np.ndarray:
    return np.floor(np.log2(n.astype(np.float64)) * 16).astype(np.int64)


def _added(df: DataFrame, width: int) -> np.ndarray:
    """The sum of packed rows of equal width (a bound), combined within tasks."""

    def run(batches):
        total = np.zeros(width, np.float64)
        for batch in batches:
            for data in batch.column(0).to_pylist():
                x = unpack(data)
                if len(x) == 1:
                    total += x[0]
                else:  # places and values
                    total += np.bincount(x[0], x[1], width)
        at = np.flatnonzero(total)
        for k in range(0, len(at), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(at[k : k + 100_000]), pa.array(total[at[k : k + 100_000]])], ["cell", "n"])

    got = df.select("data").mapInArrow(trimmed(run), "cell long, n double").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(width)
    out[got.column("cell").to_numpy()] = got.column("n").to_numpy()
    return out


def head_words(words: DataFrame, stats: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys and counts of the most frequent words, most at the utmost, by falling count and rising key."""
    over = np.cumsum(stats[2:][::-1])[::-1]  # words in a band or above
    full = int(np.argmax(over <= most))  # the lowest band that fits whole
    room = most - int(over[full])
    last = int(stats[1 + full]) if full else 0  # words of the band below
    # of the band that is cut, an even share by hash
    low = int(min(1.0, room / last) * (1 << 56)) if last else 0

    def run(batches):
        for _, packets in by_shard(batches):
            keys, n = packets[WORDS][0][:2]
            band = _band(n)
            keep = (band >= full) | ((band == full - 1) & (keys < np.uint64(low)))
            yield pa.RecordBatch.from_arrays([pa.array(keys[keep].view(np.int64)), pa.array(n[keep].astype(np.int64))], ["k", "n"])

    got = words.where(f"kind = {WORDS}").mapInArrow(trimmed(run), "k long, n long").toArrow()
    keys, n = got.column("k").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.lexsort((keys, -n))[:most]
    return keys[order], n[order]


def encode(docs: DataFrame, head: np.ndarray, shards: int) -> DataFrame:
    """TEXTS: packet; doc_id, whether it is there, whether held out, and tokens of each text; the tokens; the packet's own
    words. Tokens are numbers of head words, and behind them places in the packet's list."""
    table = docs.sparkSession.sparkContext.broadcast(head)
    rows = docs.select("doc_id", held_out("doc_id", FOLDS, HELD_OUT).alias("held_out"), "text")

    def run(batches):
        hasher, head = WordHasher(lower=True), table.value
        order = np.argsort(head)
        rising = head[order]
        packet = TaskContext.get().partitionId() << 32
        for part in slices(batches, 2):
            h, n = hasher.hashes(part.column(2))
            words, back = np.unique(h >> np.uint64(8), return_inverse=True)
            number = np.zeros(len(words), np.uint32)
            if len(head):
                at = np.minimum(np.searchsorted(rising, words), len(head) - 1)
                known = rising[at] == words
                number[known] = order[at[known]]
            else:
                known = np.zeros(len(words), bool)
            number[~known] = len(head) + np.arange((~known).sum())
            ids = part.column(0)
            there = ids.is_valid().to_numpy(zero_copy_only=False)
            data = pack(np.array([packet]), ids.fill_null(0).to_numpy().astype(np.int64), there, part.column(1).to_numpy(zero_copy_only=False), n.astype(np.int64), number[back], words[~known])
            yield rows_of([(packet % shards, TEXTS, data)])
            packet += 1

    return rows.mapInArrow(trimmed(run), PACKED)


def _framed(tokens: np.ndarray, n: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """The tokens of texts, an end before the first and behind each; and the places of the ends behind texts."""
    ends = np.cumsum(n + 1)
    out = np.full(len(tokens) + len(n) + 1, end, np.int64)
    out[np.arange(len(tokens)) + 1 + np.repeat(np.arange(len(n)), n)] = tokens
    return out, ends


def _training(data: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Tokens and their numbers for the training texts of a packet."""
    _, _, _, held, n, tokens, _ = data
    return tokens[np.repeat(~held, n)].astype(np.int64), n[~held]


# ---------------------------------------------------------------- classes


def _f(x):
    return x * np.log(np.maximum(x, 1))


def _gain(g: np.ndarray, right: np.ndarray, left: np.ndarray, own) -> np.ndarray:
    """For each class b, the rise of the likelihood if a word with these class counts joins b.

    g: class bigram counts without the word; right, left: its followers and predecessors by class.
    """
    a = _f(g + right[None, :]) - _f(g)
    b = _f(g + left[:, None]) - _f(g)
    corner = _f(np.diagonal(g) + right + left + own) - _f(np.diagonal(g))
    rows, cols = g.sum(1), g.sum(0)
    r, c = right.sum() + own, left.sum() + own
    return a.sum(1) - np.diagonal(a) + b.sum(0) - np.diagonal(b) + corner - (_f(rows + r) - _f(rows)) - (_f(cols + c) - _f(cols))


def exchange(m: np.ndarray, core: int, classes: int, rounds: int = CORE_ROUNDS) -> np.ndarray:
    """Classes of the core words from bigram counts m (core words, others, ends)."""
    wide = classes + 2
    at = np.append(np.arange(core) % classes, [classes + 1, classes])  # others are open, ends are ends
    one = np.eye(wide)[at]
    m = m.astype(np.float64)
    right, left = m @ one, m.T @ one
    g = one.T @ m @ one
    for _ in range(rounds):
        moved = 0
        for w in range(core):
            a, own = at[w], m[w, w]
            r, l = right[w].copy(), left[w].copy()
            r[a] -= own
            l[a] -= own
            g[a, :] -= r
            g[:, a] -= l
            g[a, a] -= own
            b = int(_gain(g, r, l, own)[:classes].argmax())
            g[b, :] += r
            g[:, b] += l
            g[b, b] += own
            if b != a:
                moved, at[w] = moved + 1, b
                right[:, a] -= m[:, w]
                right[:, b] += m[:, w]
                left[:, a] -= m[w, :]
                left[:, b] += m[w, :]
        if moved <= core // 100:
            break
    return at[:core]


def _cells(texts: DataFrame, of: np.ndarray, wide: int) -> np.ndarray:
    """Bigram counts of training over numbers that of gives to tokens; of ends with those of other words and of ends."""
    table = texts.sparkSession.sparkContext.broadcast(of)

    def run(batches):
        of = table.value
        for _, packets in by_shard(batches):
            rows = []
            for data in packets[TEXTS]:
                tokens, n = _training(data)
                x, _ = _framed(np.minimum(tokens, len(of) - 2), n, len(of) - 1)
                c = of[x]
                if len(n):
                    cells, times = np.unique(c[:-1] * wide + c[1:], return_counts=True)
                    rows.append((0, STATS, pack(cells, times.astype(np.float64))))
            if rows:
                yield rows_of(rows)

    return _added(texts.mapInArrow(trimmed(run), PACKED), wide * wide).reshape(wide, wide)


class Step:
    """What joining each class changes in the likelihood, for words given by class counts."""

    def __init__(self, g: np.ndarray, classes: int):
        self.g, self.classes, self.rows, self.cols = g, classes, g.sum(1)[:classes], g.sum(0)[:classes]
        r = np.arange(SMALL + 1)[:, None, None]
        # [direction][count, neighbour's class, class joined]
        self.sides = [g[:classes].T, g[:, :classes]]
        self.small = [_f(s[None] + r) - _f(s)[None] for s in self.sides]

    def gains(self, code: np.ndarray, n: np.ndarray, first: np.ndarray, total: np.ndarray, now: np.ndarray) -> np.ndarray:
        """(word, class): code (direction * all classes + neighbour's class) and n of each word from first on; now: the
        class that the word is in and counted with, or NO_CLASS."""
        wide = len(self.g)
        out = np.zeros((len(first), self.classes))
        edges = np.append(first, len(code))
        lo = 0
        while lo < len(first):  # words with a bounded number of counts, or one
            hi = max(lo + 1, int(np.searchsorted(edges, edges[lo] + MOST_COUNTS, side="right")) - 1)
            at = slice(edges[lo], edges[hi])
            c, k = code[at].astype(np.int64), n[at].astype(np.int64)
            side, c = c // wide, c % wide
            change = np.empty((len(c), self.classes))
            for d in (0, 1):
                few = np.flatnonzero((side == d) & (k <= SMALL))
                change[few] = self.small[d][k[few], c[few]]
                many = np.flatnonzero((side == d) & (k > SMALL))
                base = self.sides[d][c[many]]
                change[many] = _f(base + k[many, None]) - _f(base)
            # a word's present class has its counts already: what it has there is what leaving takes away
            own = np.repeat(now[lo:hi], np.diff(edges[lo : hi + 1]))
            here = np.flatnonzero(own != NO_CLASS)
            base = np.where(side[here] == 0, self.g[own[here], c[here]], self.g[c[here], own[here]])
            change[here, own[here]] = _f(base) - _f(np.maximum(base - k[here], 0))
            out[lo:hi] = np.add.reduceat(change, edges[lo:hi] - edges[lo], axis=0)
            lo = hi
        t = total[:, None].astype(np.float64)
        for sums in (self.rows[None, :], self.cols[None, :]):
            out -= _f(sums + t) - _f(sums)
        inside = np.flatnonzero(now != NO_CLASS)
        for sums in (self.rows, self.cols):
            s, n_own = sums[now[inside]], total[inside].astype(np.float64)
            out[inside, now[inside]] += (_f(s + n_own) - _f(s)) - (_f(s) - _f(np.maximum(s - n_own, 0)))
        return out


def move_words(texts: DataFrame, words: DataFrame, head: np.ndarray, of: np.ndarray, g: np.ndarray, classes: int, shards: int, parity: int | None) -> DataFrame:
    """WORDS key, n, class of every shard after one round; with a parity, only such head words move that have a class.

    of: the classes of head words, NO_CLASS where there is none yet.
    """
    wide = classes + 2
    end, other = classes, classes + 1
    seen = np.append(np.where(of == NO_CLASS, other, of), [other, end]).astype(np.int64)
    table = texts.sparkSession.sparkContext.broadcast((head, of, seen, Step(g, classes)))

    def post(batches):
        head, _, seen, _ = table.value
        for _, packets in by_shard(batches):
            for data in packets[TEXTS]:
                tokens, n = _training(data)
                if not len(tokens):
                    continue
                x, ends = _framed(tokens, n, -1)
                c = np.append(seen[np.minimum(np.maximum(x, 0), len(head))], end)
                c[:-1][x < 0] = end
                at = np.flatnonzero(x >= 0)
                cells = np.concatenate([x[at] * (2 * wide) + c[at + 1], x[at] * (2 * wide) + wide + c[at - 1]])
                cells, times = np.unique(cells, return_counts=True)
                word = cells // (2 * wide)
                own = data[-1]
                keys = np.where(word < len(head), head[np.minimum(word, len(head) - 1)] if len(head) else np.uint64(0), own[np.clip(word - len(head), 0, max(len(own) - 1, 0))] if len(own) else np.uint64(0))
                yield rows_of([(k, MOVES, pack(*part)) for k, part in by_ranges(keys, shards, (cells % (2 * wide)).astype(np.uint16), times.astype(np.uint32))])

    def add(shard, packets):
        head, of, _, step = table.value
        keys, n = packets[WORDS][0][:2]
        before = packets[WORDS][0][2] if len(packets[WORDS][0]) > 2 else np.full(len(keys), NO_CLASS, np.uint16)
        k, code, times = joined(packets[MOVES])
        order = np.lexsort((code, k))
        k, code, times = k[order], code[order], times[order].astype(np.uint64)
        new = runs(k, code)
        k, code, times = k[new], code[new], np.add.reduceat(times, new)
        first = runs(k)  # every word of training stands somewhere, so these are the words of the shard
        order = np.argsort(head)
        at = np.minimum(np.searchsorted(head, keys, sorter=order), max(len(head) - 1, 0))
        now = np.full(len(keys), NO_CLASS, np.int64)
        if len(head):
            inside = head[order[at]] == keys
            now[inside] = of[order[at[inside]]]
        gains = step.gains(code, times, first, n, now)
        best = gains.argmax(1)
        if parity is not None:
            stay = (now != NO_CLASS) & ((keys & np.uint64(1)).astype(int) != parity)
            best[stay] = now[stay]
        settled = np.flatnonzero(now != NO_CLASS)
        better = gains[settled, best[settled]] > gains[settled, now[settled]] + 1e-9
        best[settled[~better]] = now[settled[~better]]
        return [(shard, WORDS, pack(keys, n, best.astype(np.uint16)))]

    return met(texts.mapInArrow(trimmed(post), PACKED).unionByName(words.where(f"kind = {WORDS}")), shards, add)


def head_classes(words: DataFrame, head: np.ndarray) -> np.ndarray:
    """The classes of head words."""
    table = words.sparkSession.sparkContext.broadcast(np.sort(head))

    def run(batches):
        for _, packets in by_shard(batches):
            keys, _, c = packets[WORDS][0]
            at = np.flatnonzero(np.isin(keys, table.value, assume_unique=True))
            yield pa.RecordBatch.from_arrays([pa.array(keys[at].view(np.int64)), pa.array(c[at].astype(np.int64))], ["k", "c"])

    got = words.mapInArrow(trimmed(run), "k long, c long").toArrow()
    keys, c = got.column("k").to_numpy().view(np.uint64), got.column("c").to_numpy()
    order = np.argsort(keys)
    return c[order][np.searchsorted(keys, head, sorter=order)].astype(np.int64)


# ---------------------------------------------------------------- scores


class Scales:
    """Emissions, weights and the base of a clustered vocabulary."""

    def __init__(self, total: int, ends: int, distinct: int, sums: np.ndarray):
        """sums: tokens, words, words seen once, and smoothed counts kept and left over by the weights, of each class."""
        sizes, kinds, once, kept, rest = sums
        self.classes, self.total, self.distinct, self.ends = len(sizes), total, distinct, ends
        self.unknown = int(once.argmax())
        self.by = np.maximum(sizes + ADD * kinds, ADD)
        self.live = sizes > 0
        self.kept = kept / self.by
        self.rest = rest.sum() + ADD
        self.base_by = total + ADD * (distinct + 1)

    def base(self, n):
        return np.log10((n + ADD) / self.base_by)

    def probability(self, step: np.ndarray, left: np.ndarray, c: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Of words of class c seen n times, where step leads to c, and left is left over."""
        w = weight(n)
        return (n + ADD) * (w * step / self.by[c] + left * (1 - w) / self.rest)


def weight(n):
    return n / (n + RELIABLE)


def transitions(g: np.ndarray, s: Scales) -> tuple[np.ndarray, np.ndarray]:
    """Transition probabilities from class bigram counts, interpolated with class frequencies, to classes with words and the
    end; and what the weights of the words leave over behind each class."""
    p = np.where(np.append(s.live, [True, False]), g.sum(0) + 1.0, 0.0)
    p /= p.sum()
    step = (g + INTERPOLATION * p) / (g.sum(1, keepdims=True) + INTERPOLATION)
    # an end is told by its transition alone, but for a share that unknown words need where no word is left over
    step[:, s.classes] *= 1 - 1e-6
    return step, 1 - step @ np.append(s.kept, [1.0, 0.0])


def class_sizes(words: DataFrame, classes: int) -> np.ndarray:
    """What Scales needs of every class."""

    def run(batches):
        for shard, packets in by_shard(batches):
            _, n, c = packets[WORDS][0]
            c, n = c.astype(np.int64), n.astype(np.float64)
            parts = [n, np.ones(len(n)), n == 1, weight(n) * (n + ADD), (1 - weight(n)) * (n + ADD)]
            yield rows_of([(shard, STATS, pack(np.concatenate([np.bincount(c, x, classes) for x in parts])))])

    return _added(words.mapInArrow(trimmed(run), PACKED), 5 * classes).reshape(5, classes)


def classed(texts: DataFrame, words: DataFrame, head: tuple[np.ndarray, np.ndarray, np.ndarray], s: Scales, shards: int) -> DataFrame:
    """TEXTS: doc_id, whether it is there, whether held out and tokens of each text; classes and counts of all tokens. Packets
    ask for the words on their lists, and the answers meet the packets again."""
    table = texts.sparkSession.sparkContext.broadcast((*head, s))

    def ask(batches):
        for _, packets in by_shard(batches):
            for data in packets[TEXTS]:
                yield rows_of([(k, MOVES, pack(data[0], *part)) for k, part in by_ranges(data[-1], shards, rising=True)] or [(0, MOVES, pack(data[0], data[-1]))])

    def answer(shard, packets):
        keys, n, c = packets[WORDS][0] if WORDS in packets else (np.empty(0, np.uint64), np.empty(0, np.uint64), np.empty(0, np.uint16))
        out = []
        for packet, asked in packets.get(MOVES, ()):
            at = np.minimum(np.searchsorted(keys, asked), max(len(keys) - 1, 0))
            found = keys[at] == asked if len(keys) else np.zeros(len(asked), bool)
            times, kind = np.zeros(len(asked), np.uint64), np.full(len(asked), table.value[3].unknown, np.uint16)
            times[found], kind[found] = n[at[found]], c[at[found]]
            out.append((int(packet[0] % shards), ANSWERS, pack(packet, asked, times, kind)))
        return out

    def score(shard, packets):
        _, n_head, c_head, _ = table.value
        answers: dict[int, list] = {}
        for packet, *rest in packets.get(ANSWERS, ()):
            answers.setdefault(int(packet[0]), []).append(rest)
        out = []
        for packet, ids, there, held, n, tokens, own in packets.get(TEXTS, ()):
            keys, times, kind = joined(answers[int(packet[0])])
            order = np.argsort(keys)
            count = np.concatenate([n_head, times[order]]).astype(np.uint64)
            kinds = np.concatenate([c_head, kind[order]]).astype(np.uint16)
            out.append((shard, TEXTS, pack(ids, there, held, n, kinds[tokens], count[tokens])))
        return out

    asked = texts.mapInArrow(trimmed(ask), PACKED).unionByName(words.where(f"kind = {WORDS}"))
    return met(met(asked, shards, answer).unionByName(texts), shards, score)


@dataclass
class Clustered:
    """WORDS with classes, TEXTS, and the head's keys, counts and classes."""

    words: DataFrame
    texts: DataFrame
    head: tuple[np.ndarray, np.ndarray, np.ndarray]
    scales: Scales
    shards: int


def cluster(docs: DataFrame, head_size: int = HEAD, core: int = CORE, rounds: int = ROUNDS) -> Clustered:
    """Count and cluster the words of the documents outside the held-out fold; encode all documents."""
    train = docs.where(~held_out("doc_id", FOLDS, HELD_OUT))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    shards = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // SHARD_BYTES))
    words = materialise(word_counts(train, shards), "lm-words")
    ends = train.count()
    stats = _added(words.where(f"kind = {STATS}"), 1026).astype(np.int64)
    total, distinct = int(stats[1]) + ends, int(stats[0]) + (ends > 0)
    keys, counts = head_words(words, stats, head_size)
    texts = materialise(encode(docs, keys, shards), "lm-texts")
    classes = max(LEAST_CLASSES, int(np.ceil(float(stats[0]) ** CLASS_POWER)))
    core = min(core, len(keys))
    m = _cells(texts, np.append(np.arange(core), [core, core + 1]), core + 2)
    of = np.full(len(keys), NO_CLASS, np.int64)
    of[:core] = exchange(m, core, classes)
    for k in range(rounds if stats[0] else 0):
        g = _cells(texts, np.append(np.where(of == NO_CLASS, classes + 1, of), [classes + 1, classes]), classes + 2)
        moved = materialise(move_words(texts, words, keys, of, g, classes, shards, k % 2 if k else None), "lm-words")
        discard(words)
        words, of = moved, head_classes(moved, keys)
    s = Scales(total, ends, distinct, class_sizes(words, classes) if stats[0] else np.zeros((5, classes)))
    return Clustered(words, texts, (keys, counts, of), s, shards)


def score(docs: DataFrame, head_size: int = HEAD, core: int = CORE, rounds: int = ROUNDS) -> DataFrame:
    """Train on the documents outside the held-out fold and score all of them."""
    m = cluster(docs, head_size, core, rounds)
    s = m.scales
    wide, end = s.classes + 2, s.classes
    done = materialise(classed(m.texts, m.words, m.head, s, m.shards), "lm-classed")
    discard(m.texts, m.words)

    def pairs(batches):
        for _, packets in by_shard(batches):
            for _, _, held, n, c, _ in packets[TEXTS]:
                x, _ = _framed(c[np.repeat(~held, n)], n[~held], end)
                cells, times = np.unique(x[:-1] * wide + x[1:], return_counts=True)
                yield rows_of([(0, STATS, pack(cells, times.astype(np.float64)))])

    g = _added(done.mapInArrow(trimmed(pairs), PACKED), wide * wide).reshape(wide, wide)
    table = docs.sparkSession.sparkContext.broadcast((s, *transitions(g, s)))

    def told(batches):
        s, step, left = table.value
        for _, packets in by_shard(batches):
            for ids, there, held, n, c, count in packets[TEXTS]:
                x, ends_at = _framed(c, n, end)
                count = count.astype(np.float64)
                before, at = x[:-1], np.flatnonzero(x[1:] != end)
                logs = np.log10(step[before, x[1:]])  # of ends as it stands
                logs[at] = np.log10(s.probability(step[before[at], x[1:][at]], left[before[at]], x[1:][at], count))
                sums = np.concatenate([[0.0], np.cumsum(logs)])
                base = np.concatenate([[0.0], np.cumsum(s.base(count))])
                known = np.concatenate([[0], np.cumsum(count > 0)])
                edge = np.concatenate([[0], np.cumsum(n)])
                columns = [pa.array(ids, mask=~there), pa.array(held), pa.array(n + 1), pa.array(np.diff(known[edge]) + (s.ends > 0)), pa.array(np.full(len(n), s.total)), pa.array(np.diff(base[edge]) + float(s.base(s.ends))), pa.array(np.diff(np.concatenate([[0.0], sums[ends_at]])))]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return done.mapInArrow(trimmed(told), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op8_brown_lm(spark, sf_dir: str) -> DataFrame:
    return score(read(spark, sf_dir, "documents"))
