"""Quality classifier: an interpolated modified Kneser-Ney trigram model of trusted text, and language-wise cuts.

Everything is counted over all trusted documents outside the held-out fold, and travels as packed columns (sorted
keys in byte planes, compressed) that are dealt to shards by the hash of an n-gram:

1. trigrams meet at the shard of their first two words: counts, context totals, discount masses;
2. bigrams, with their numbers of different predecessors, meet at their own shard;
3. words meet at theirs, and answer the bigrams' shards with their totals;
4. trigrams, with their share of what their context passes on, meet the probability of their last two words.

Each step ends in a table. A text's log probability is a sum over its n-grams: what each word has on its own, what
each context passes on to shorter n-grams, and what each bigram and trigram of training adds to that. So step 4 gives
a table of values by n-gram key, and scoring joins the documents' n-grams with it, shard by shard. Both are done in
``WAVES`` of about the same number of n-grams, each for those whose last word falls into it, so that only that part of
the n-grams is on disk at a time, beside the counts; trigrams are counted in ``COUNT_WAVES`` of shards. A map of bits (bounded) of a wave's keys
is sent to the texts, so that most n-grams that training lacks are not asked for. N-grams that a small sample
shows to be very frequent (a bounded number) are looked up before and scored where the text is, so that no shard is hot.

Words and n-grams stand as hashes of 48 and 56 bits: words and n-grams that share one count as equal.

A document's mean log probability is drawn towards its language's mean by ``PRIOR_WORDS`` words, as short texts
say little. Thresholds are quantiles of the trusted documents outside the training fold, for each language with
enough of them, otherwise over all.

Defined cases: a text without words (null, empty) has no perplexity and is rejected; a null or unseen language
takes the overall threshold; without trusted documents nothing with words is rejected; a document labelled twice
is trusted if any label says so; repeated rows are scored alike; extra columns are carried by
``keep_good`` and, when asked for, by ``classify``.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import ChunkHasher, dealt, discard, held_out, materialise, native_words, read, trimmed
from memojoin.llm.packets import MOST_TEXTS, PACKED, by_ranges, by_shard, joined, met, pack, rows_of, runs, shard_of, slices, split, unpack

FOLDS, HELD_OUT = 4, 2
QUANTILE, MARGIN = 0.995, 0.25
PRIOR_WORDS = 20
LEAST_TRUSTED = 50
#: Words outside the training vocabulary share one probability; so many of them are assumed.
UNKNOWN_WORDS = 1_000_000
#: Parts in which n-grams are scored, by their last words, and those in which trigrams are counted, each of so many
#: bytes of text at least; bytes of text for each shard at most; tokens of a packet.
WAVES, COUNT_WAVES, WAVE_BYTES, SHARD_BYTES, PACKET_TOKENS = 6, 2, 8 << 20, 128 << 20, 3 << 18
#: Bytes of text that a task takes at a time; n-grams that it asks for at a time, about.
TEXT_BYTES, MOST_KEYS = 5 << 20, 1 << 20
#: Trusted ids that are sent to every task at a time.
SENT_IDS = 1 << 20
#: A sample of about so many texts shows the frequent n-grams: those with more than this share of its n-grams.
HOT_TEXTS, HOT_SHARE = 4_000, 1 / 20_000
#: Texts that a task remembers, so as not to ask for copies again.
REMEMBERED = 500_000
START = np.uint64(0)
#: Kinds of packed rows; values come before the questions about them.
VALUES, TRIGRAMS, PAIRS, WORDS, ANSWERS, MOVED, STATS, ASKED, KNOWN, LOADS = range(10)
#: Powers of two: bits of the map of a wave's keys, for each key and at least and at most (64 MB).
KEY_BITS, LEAST_BITS, MOST_BITS = 3, 16, 29
#: Bits of a word's id that name its part; whole parts are dealt out to waves.
PART_BITS, ID_BITS = 10, 48
#: What an n-gram of a text asks for: its own value and that as a context, or one of them.
BOTH, HERE, NEXT = range(3)


def key_of(context: np.ndarray, suffix: np.ndarray) -> np.ndarray:
    """The 56-bit key of an n-gram from the keys of its first and of its last words."""
    out = (context * np.uint64(0x9E3779B97F4A7C15)) ^ (context >> np.uint64(23))
    out = (out + suffix) * np.uint64(0xC2B2AE3D27D4EB4F)
    out ^= out >> np.uint64(29)
    out *= np.uint64(0x165667B19E3779F9)
    return (out ^ (out >> np.uint64(32))) >> np.uint64(8)


def word_key(words: np.ndarray) -> np.ndarray:
    return key_of(words, np.uint64(1))


def pair_key(b: np.ndarray, c: np.ndarray) -> np.ndarray:
    return key_of(word_key(b), word_key(c))


def _few(n: np.ndarray) -> list[np.ndarray]:
    """How many counts are 1, 2, 3 and 4."""
    return [np.bincount(np.minimum(n, 5).astype(np.int64), minlength=6)[1:5].astype(np.int64)]


# ---------------------------------------------------------------- the model


def discounts(n1: int, n2: int, n3: int, n4: int) -> np.ndarray:
    """Discounts for counts 1, 2 and more, from how many n-grams occur one to four times."""
    y = n1 / (n1 + 2 * n2) if n1 else 0.5
    cut = lambda k, a, b: min(max(k - (k + 1) * y * b / a, 0.1), k) if a else min(0.75 * k, 0.9)
    return np.array([0.0, cut(1, n1, n2), cut(2, n2, n3), cut(3, n3, n4)])


def _cut(d: np.ndarray, n: np.ndarray) -> np.ndarray:
    return d[np.minimum(n, 3).astype(np.uint8)]


def _framed(h: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word ids with two starts in front of each text that has words; the position of every word; its text."""
    live = np.flatnonzero(n)
    of = np.repeat(np.arange(len(live)), n[live])
    at = np.arange(2, len(h) + 2)
    at += 2 * of
    x = np.full(len(h) + 2 * len(live), START, np.uint64)
    ids = h >> np.uint64(16)
    x[at] = np.maximum(ids, np.uint64(1), out=ids)
    return x, at, of if len(live) == len(n) else live[of]


def _ranked(*columns: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """The distinct words of all columns, rising, and the columns as places in them."""
    ids, at = np.unique(np.concatenate(columns), return_inverse=True)
    return ids, np.split(at.astype(np.uint32), np.cumsum([len(c) for c in columns])[:-1])


def _order(*ranks: np.ndarray, words: int) -> np.ndarray:
    """The order by these places in so many words, the first column first."""
    bits = max(words - 1, 1).bit_length()
    if bits * len(ranks) > 64:
        return np.lexsort(ranks[::-1])
    one = ranks[0].astype(np.uint64)
    for r in ranks[1:]:
        one = (one << np.uint64(bits)) | r
    return np.argsort(one)


def _added(columns: list[np.ndarray], n: np.ndarray) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Words, the distinct rows of the columns as places in them, in order, and the sums of n."""
    ids, ranks = _ranked(*columns)
    order = _order(*ranks, words=len(ids))
    ranks = [r[order] for r in ranks]
    new = runs(*ranks)
    return ids, [r[new] for r in ranks], np.add.reduceat(n[order].astype(np.uint64), new) if len(new) else n[:0].astype(np.uint64)


def _narrow(n: np.ndarray) -> np.ndarray:
    """Counts in as few bytes as hold them all."""
    return n.astype(np.min_scalar_type(int(n.max(initial=0))))


def trigrams(texts: DataFrame, shards: int, low: int, high: int) -> DataFrame:
    """TRIGRAMS (words; b, a, c as places in them; n) of the shards (of the first two words) from low on and below
    high, in the order b, a, c; STATS of the counts; LOADS (how many different ones end in each part of the ids)."""

    def post(batches):
        hasher = ChunkHasher()
        for part in slices(batches, 0, TEXT_BYTES):
            x, at, _ = _framed(*hasher.hashes(part.column(0)))
            ids, rank = np.unique(x, return_inverse=True)
            key, rank = word_key(ids), rank.astype(np.uint32)
            for k in range(0, len(at), PACKET_TOKENS):
                c = at[k : k + PACKET_TOKENS]
                p, q, r = rank[c - 2], rank[c - 1], rank[c]
                shard = shard_of(key_of(key[p], key[q]), shards)
                mine = np.flatnonzero((shard >= low) & (shard < high))
                if len(mine):
                    order = mine[_order(q[mine], p[mine], r[mine], words=len(ids))]
                    new = runs(q[order], p[order], r[order])
                    n, order = np.diff(np.append(new, len(order))), order[new]
                    yield rows_of([(s, TRIGRAMS, pack(*found, rising=True)) for s, found in split(shard[order], ids[q[order]], ids[p[order]], ids[r[order]], _narrow(n))])

    def add(shard, packets):
        *columns, n = joined(packets[TRIGRAMS])
        ids, ranks, n = _added(columns, n)
        loads = np.bincount(_part(ids)[ranks[2]], minlength=1 << PART_BITS)
        return [(shard, TRIGRAMS, pack(ids, *ranks, _narrow(n), rising=True)), (shard, STATS, pack(*_few(n))), (shard, LOADS, pack(loads))]

    return met(texts.select("text").mapInArrow(trimmed(post), PACKED), high - low, add, low)


def pairs(tri: DataFrame, shards: int) -> DataFrame:
    """PAIRS (words; b, c as places in them; n) of every shard in the order b, c: n different words stand in front of
    b c; STATS of the counts."""

    def post(batches):
        for _, packets in by_shard(batches):
            for ids, b, _, c, _ in packets[TRIGRAMS]:
                one = np.sort((b.astype(np.uint64) << np.uint64(32)) | c)
                new = runs(one)
                b, c = one[new] >> np.uint64(32), one[new] & np.uint64(0xFFFFFFFF)
                key = word_key(ids)
                yield rows_of([(k, PAIRS, pack(*part, rising=True)) for k, part in split(shard_of(key_of(key[b], key[c]), shards), ids[b], ids[c], _narrow(np.diff(np.append(new, len(one)))))])

    def add(shard, packets):
        *columns, n = joined(packets[PAIRS])
        ids, ranks, n = _added(columns, n)
        return [(shard, PAIRS, pack(ids, *ranks, _narrow(n), rising=True)), (shard, STATS, pack(*_few(n)))]

    return met(tri.where(f"kind = {TRIGRAMS}").mapInArrow(trimmed(post), PACKED), shards, add)


def words(two: DataFrame, shards: int) -> DataFrame:
    """WORDS (id, sum of n as first word, how many of these are 1, 2, more; pairs as last word), ANSWERS (the shard
    told from, and the same but for the id, in the order of the words' keys) for each shard of pairs that holds a word,
    and STATS (words by 1 to 4 pairs, words, pairs)."""

    def post(batches):
        for shard, packets in by_shard(batches):
            ids, b, c, n = packets[PAIRS][0]
            sums = [np.bincount(b, n.astype(np.float64), len(ids))]
            sums += [np.bincount(b[np.minimum(n, 3) == k], minlength=len(ids)) for k in (1, 2, 3)]
            sums += [np.bincount(c, minlength=len(ids))]
            whence = np.array([shard], np.uint32)
            yield rows_of([(k, WORDS, pack(whence, *part)) for k, (_, *part) in by_ranges(word_key(ids), shards, ids, *(_narrow(s) for s in sums))])

    def add(shard, packets):
        ids, at = np.unique(np.concatenate([p[1] for p in packets[WORDS]]), return_inverse=True)
        sums = [np.bincount(at, np.concatenate([p[k] for p in packets[WORDS]]).astype(np.float64), len(ids)) for k in range(2, 7)]
        sums = [_narrow(s) for s in sums]
        cuts = np.cumsum([0, *(len(p[1]) for p in packets[WORDS])])
        out = [(int(p[0][0]), ANSWERS, pack(np.array([shard], np.uint32), *(s[at[i:j]] for s in sums))) for p, i, j in zip(packets[WORDS], cuts[:-1], cuts[1:])]
        last = sums[4][sums[4] > 0]
        return [*out, (shard, WORDS, pack(ids, *sums, rising=True)), (shard, STATS, pack(np.append(_few(last)[0], [len(last), int(last.sum())])))]

    return met(two.where(f"kind = {PAIRS}").mapInArrow(trimmed(post), PACKED), shards, add)


def pairs_told(two: DataFrame, one: DataFrame, shards: int) -> DataFrame:
    """PAIRS with what words() says of each of their words: words, five columns for them, b, c, n."""

    def add(shard, packets):
        ids, *rows = packets[PAIRS][0]
        answers = joined(sorted((p for p in packets[ANSWERS]), key=lambda p: p[0][0]))[1:]
        order = np.argsort(word_key(ids))
        said = [np.empty_like(x) for x in answers]
        for to, x in zip(said, answers):
            to[order] = x
        return [(shard, PAIRS, pack(ids, *said, *rows, rising=True))]

    return met(two.where(f"kind = {PAIRS}").unionByName(one.where(f"kind = {ANSWERS}")), shards, add)


def _stats(table: DataFrame, width: int = 4, kind: int = STATS) -> list[int]:
    """The sum of the STATS rows, or of those of another kind."""

    def run(batches):
        total = np.zeros(width, np.int64)
        for batch in batches:
            for data in batch.column(0).to_pylist():
                total += unpack(data)[0]
        if total.any():
            yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.int64()))], ["s"])

    got = table.where(f"kind = {kind}").select("data").mapInArrow(trimmed(run), "s array<long>")
    sums = dict(got.select(F.posexplode("s").alias("k", "n")).groupBy("k").agg(F.sum("n")).collect())
    return [sums.get(k, 0) for k in range(width)]


class Scales:
    """Discounts of the three orders, and what the single words share out."""

    def __init__(self, three: list[int], two: list[int], one: list[int]):
        self.three, self.two, self.one = discounts(*three), discounts(*two), discounts(*one[:4])
        self.words, self.pairs = one[4:]
        self.keys = sum(three) + self.pairs + self.words  # about
        mass = self.one[1] * one[0] + self.one[2] * one[1] + self.one[3] * (self.words - one[0] - one[1])
        self.unknown = mass / self.pairs / (self.words + UNKNOWN_WORDS)

    def single(self, last: np.ndarray) -> np.ndarray:
        """The probability of words that so many different words precede."""
        return (last - _cut(self.one, last)) / self.pairs + self.unknown

    def passed(self, total: np.ndarray, k1: np.ndarray, k2: np.ndarray, k3: np.ndarray) -> np.ndarray:
        """What a word as a context passes on to single words (1 if it is none)."""
        mass = self.two[1] * k1 + self.two[2] * k2 + self.two[3] * k3
        return np.where(total > 0, mass / np.maximum(total, 1), 1.0)


def _part(ids: np.ndarray) -> np.ndarray:
    return (ids >> np.uint64(ID_BITS - PART_BITS)).view(np.int64)


def in_wave(ids: np.ndarray, wave: np.ndarray) -> np.ndarray:
    """Whether n-grams are of a wave (marked parts of the ids), by the ids of their last words."""
    return wave.take(_part(ids), mode="clip")


def deal_waves(loads: np.ndarray, waves: int) -> list[np.ndarray]:
    """The parts of so many waves, which get about the same load: the heaviest part first, always to the lightest wave."""
    of, held = np.zeros(len(loads), np.int64), np.zeros(waves)
    for part in np.argsort(-loads, kind="stable"):
        of[part] = held.argmin()
        held[of[part]] += loads[part] + 1
    return [of == wave for wave in range(waves)]


class Model:
    """What is counted; values() gives an n-gram's wave of the value table."""

    def __init__(self, tri: list[DataFrame], two: DataFrame, one: DataFrame, scales: Scales, waves: list[np.ndarray]):
        self.tables, self.two, self.one, self.scales, self.waves = [*tri, two, one], two, one, scales, waves
        self.tri = reduce(DataFrame.unionByName, tri).where(f"kind = {TRIGRAMS}")
        self.bits = min(max((scales.keys // len(waves)).bit_length() + KEY_BITS, LEAST_BITS), MOST_BITS)

    def values(self, wave: int, shards: int) -> DataFrame:
        """VALUES (key, here, next) of every shard of the n-grams whose last word is of a wave; KNOWN (where it starts,
        bytes of a map of the keys' first bits).

        here counts for each occurrence with its last word to be told, next for each as a context.
        """
        s, mine, bits = self.scales, self.waves[wave], self.bits
        zero = lambda x: np.zeros(len(x), np.float32)

        def valued(keys, here, after):
            return [(k, VALUES, pack(*part, rising=True)) for k, part in by_ranges(keys, shards, here.astype(np.float32), after.astype(np.float32))]

        def move(batches):
            """Trigrams to the shards of their last two words; contexts have their values."""
            for _, packets in by_shard(batches):
                for ids, b, a, c, n in packets[TRIGRAMS]:
                    key = word_key(ids)
                    inside = in_wave(ids, mine)
                    first, cut = runs(b, a), _cut(s.three, n)
                    mass = np.add.reduceat(cut, first)
                    at = np.flatnonzero(inside[c])
                    of = np.searchsorted(first, at, side="right") - 1
                    before, word = key[b[at]], key[c[at]]
                    suffix = key_of(before, word)
                    # share / passed on: both have the total below
                    ratio = ((n[at] - cut[at]) / mass[of]).astype(np.float32)
                    rows = [(k, MOVED, pack(*part, rising=True)) for k, part in by_ranges(suffix, shards, key_of(key_of(key[a[at]], before), suffix), ratio)]
                    some = np.flatnonzero(inside[b[first]])
                    total = np.add.reduceat(n.astype(np.float64), first)[some]
                    first = first[some]
                    yield rows_of([*rows, *valued(key_of(key[a[first]], key[b[first]]), zero(some), np.log10(mass[some] / total))])

        def pair(batches):
            for _, packets in by_shard(batches):
                for ids, total, k1, k2, k3, last, b, c, n in packets[PAIRS]:
                    key = word_key(ids)
                    at = np.flatnonzero(in_wave(ids, mine)[c])
                    b, c, n = b[at], c[at], n[at]
                    passed = s.passed(total, k1, k2, k3)[b] * s.single(last)[c]
                    p = (n - _cut(s.two, n)) / total[b] + passed
                    yield rows_of([(k, PAIRS, pack(*part, rising=True)) for k, part in by_ranges(key_of(key[b], key[c]), shards, p, np.log10(p / passed).astype(np.float32))])

        def lone(batches):
            for _, packets in by_shard(batches):
                for columns in packets[WORDS]:
                    at = np.flatnonzero(in_wave(columns[0], mine))
                    ids, total, k1, k2, k3, last = (x[at] for x in columns)
                    here = np.where(last > 0, np.log10(s.single(last) / s.unknown), 0.0)
                    yield rows_of(valued(word_key(ids), here, np.log10(s.passed(total, k1, k2, k3))))

        def value(shard, packets):
            own, out = packets.get(VALUES, []), []
            if PAIRS in packets:
                key, p, here = joined(packets[PAIRS])
                order = np.argsort(key)
                key, p, here = key[order], p[order], here[order]
                own = [*own, [key, here, zero(key)]]
            if MOVED in packets:  # a pair is the end of a trigram
                suffix, moved, ratio = joined(packets[MOVED])
                out = valued(moved, np.log10(1 + ratio / p[np.searchsorted(key, suffix)]), zero(moved))
            if own:
                key, (_, here, after) = _summed(*joined(own))
                out.append((shard, VALUES, pack(key, here, after, rising=True)))
            return out

        def merge(shard, packets):
            key, (_, here, after) = _summed(*joined(packets[VALUES]))
            at = (key >> np.uint64(56 - bits)).astype(np.int64)
            low = int(at[0]) >> 3
            known = np.zeros(int(at[-1]) + 1 - 8 * low, np.uint8)
            known[at - 8 * low] = 1
            return [(shard, VALUES, pack(key, here, after, rising=True)), (shard, KNOWN, pack(np.array([low]), np.packbits(known, bitorder="little")))]

        inputs = self.tri.mapInArrow(trimmed(move), PACKED).unionByName(self.two.mapInArrow(trimmed(pair), PACKED)).unionByName(self.one.mapInArrow(trimmed(lone), PACKED))
        return materialise(met(met(inputs, shards, value), shards, merge), "kn-values")

    def known(self, values: DataFrame) -> np.ndarray:
        """The map of the keys in a table of values()."""
        out = np.zeros(1 << (self.bits - 3), np.uint8)
        for batch in values.where(f"kind = {KNOWN}").select("data").toArrow().to_batches(1):
            for data in batch.column(0).to_pylist():
                (low,), some = unpack(data)
                out[low : low + len(some)] |= some
        return out

    def discard(self) -> None:
        discard(*self.tables)


def value_table(texts: DataFrame, shards: int, waves: int = WAVES) -> tuple[Model, float] | None:
    """The model, and the log10 of an unknown word's share. None without words."""
    tri = [materialise(trigrams(texts, shards, low, high), "kn-trigrams") for low, high in _waves(shards, min(COUNT_WAVES, waves))]
    every = reduce(DataFrame.unionByName, tri)
    two = materialise(pairs(every, shards), "kn-pairs")
    one = materialise(words(two, shards), "kn-words")
    stats = _stats(every), _stats(two), _stats(one, 6)
    if not stats[2][4]:
        discard(*tri, two, one)
        return None
    s, loads = Scales(*stats), np.array(_stats(every, 1 << PART_BITS, LOADS))
    both = materialise(pairs_told(two, one, shards), "kn-told")
    discard(two)
    lone = materialise(one.where(f"kind = {WORDS}"), "kn-lone")
    discard(one)
    return Model(tri, both, lone, s, deal_waves(loads, min(waves, shards))), float(np.log10(s.unknown))


def _waves(shards: int, waves: int) -> list[tuple[int, int]]:
    edges = [shards * k // waves for k in range(waves + 1)]
    return [(low, high) for low, high in zip(edges[:-1], edges[1:]) if low < high]


# ---------------------------------------------------------------- scores


def _asked(x: np.ndarray, at: np.ndarray, of: np.ndarray, first: np.ndarray, last: np.ndarray, wave: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Keys and codes (text * 4 + what is asked) of every n-gram, or of those whose last word is of a wave; first and
    last mark the ends of texts."""
    begin = np.flatnonzero(first)  # the starts are contexts only
    begin, into = at[begin], of[begin] * 4 + NEXT
    if wave is not None:
        if not in_wave(np.array([START]), wave)[0]:
            begin, into = begin[:0], into[:0]
        mine = np.flatnonzero(in_wave(x[at], wave))
        at, of, last = at[mine], of[mine], last[mine]
    of = of * 4
    what = of + np.where(last, HERE, BOTH)
    word, before = word_key(x[at]), word_key(x[at - 1])
    two = key_of(before, word)
    context = key_of(word_key(x[at - 2]), before)
    start = word_key(x[begin - 1])
    keys = np.concatenate([word, two, key_of(context, two), start, key_of(word_key(x[begin - 2]), start)])
    return keys, np.concatenate([what, what, of + HERE, into, into]).astype(np.uint16)


def _packets(batches, wave: np.ndarray | None = None):
    """(keys of texts, their numbers, word counts, keys of n-grams (of a wave), codes) for a bounded number of tokens.

    A long text comes in several parts with one number; copies of a text are left out as far as a task remembers it.
    """
    hasher, seen, number = ChunkHasher(), set(), 0
    for part in slices(batches, 1, TEXT_BYTES):
        fresh = []
        for k, name in enumerate(part.column(0).to_pylist()):
            if name not in seen:
                seen.add(name)
                fresh.append(k)
        if len(seen) > REMEMBERED:
            seen.clear()
        if len(fresh) < part.num_rows:
            part = part.take(pa.array(fresh, pa.int64()))
        h, n = hasher.hashes(part.column(1))
        x, at, of = _framed(h, n)
        first = np.zeros(len(at), bool)
        starts = np.concatenate([[0], np.cumsum(n)])[:-1][n > 0]
        first[starts] = True
        last = np.roll(first, -1)
        names = part.column(0).to_numpy()
        for k in range(0, len(at), PACKET_TOKENS):
            cut = slice(k, k + PACKET_TOKENS)
            low = int(of[k])
            texts = names[low : int(of[cut][-1]) + 1]
            yield texts, np.arange(len(texts)) + number + low, np.bincount(of[cut] - low, minlength=len(texts)), *_asked(x, at[cut], of[cut] - low, first[cut], last[cut], wave)
        number += part.num_rows


def _gathered(packets, known: np.ndarray):
    """Larger packets of so many n-grams or texts at most, without n-grams that a map leaves out.

    An n-gram left out is not in the table of values and adds nothing.
    """
    held, texts, size = [], 0, 0

    def done():
        *columns, codes = zip(*held)
        before = np.cumsum([0, *(len(t) for t in columns[0])])
        return *(np.concatenate(c) for c in columns), np.concatenate([c + np.uint16(4 * k) for c, k in zip(codes, before)])

    for names, numbers, n, keys, codes in packets:
        mine = np.flatnonzero(_known(known, keys))
        if held and (texts + len(names) > MOST_TEXTS or size + len(mine) > MOST_KEYS):
            yield done()
            held, texts, size = [], 0, 0
        held.append((names, numbers, n, keys[mine], codes[mine]))
        texts, size = texts + len(names), size + len(mine)
    if held:
        yield done()


def hot_keys(docs: DataFrame) -> np.ndarray:
    """Keys of n-grams that a sample of texts holds very often: at most three divided by HOT_SHARE."""
    n = docs.count()
    rate = min(1.0, HOT_TEXTS / max(n, 1))
    sample = docs.where(F.pmod(F.xxhash64("text", F.lit("hot")), F.lit(1 << 30)) < int(rate * (1 << 30)))

    def run(batches):
        for _, _, count, keys, _ in _packets(batches):
            keys, times = np.unique(keys, return_counts=True)
            often = np.flatnonzero(times > 1)
            yield pa.RecordBatch.from_arrays([pa.array(keys[often].view(np.int64)), pa.array(times[often]), pa.array(np.full(len(often), count.sum() / max(len(often), 1)))], ["k", "n", "t"])

    got = sample.select(F.xxhash64("text"), "text").mapInArrow(trimmed(run), "k long, n long, t double").groupBy("k").agg(F.sum("n").alias("n"), F.sum("t").alias("t"))
    got = materialise(got, "kn-sample")
    least = (got.agg(F.sum("t")).first()[0] or 0.0) * HOT_SHARE
    keys = got.where(F.col("n") > max(least, 2)).select("k").toArrow().column(0).to_numpy()
    discard(got)
    return np.sort(keys.view(np.uint64))


def _found(have: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each key stands in sorted keys, and whether it does."""
    if not len(have):
        return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(have, keys), len(have) - 1)
    return at, have[at] == keys


def _known(known: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whether a map of Model.known() has the first bits of keys: it has those of all keys of the table, and some more."""
    at = keys >> np.uint64(56 + 1 - (8 * len(known)).bit_length())
    return (known[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & np.uint8(1)


def _summed(keys: np.ndarray, here: np.ndarray, after: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct sorted keys, and a row for each of BOTH, HERE and NEXT."""
    if np.all(keys[1:] > keys[:-1]):
        return keys, np.stack([here + after, here, after])
    order = np.argsort(keys)
    keys, here, after = keys[order], here[order], after[order]
    new = runs(keys)
    if len(keys):
        here, after = np.add.reduceat(here, new), np.add.reduceat(after, new)
    return keys[new], np.stack([here + after, here, after])


def _lookup(table: DataFrame, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """_summed() values of a bounded number of sorted keys."""
    asked = table.sparkSession.sparkContext.broadcast(keys)

    def run(batches):
        for batch in batches:
            for data in batch.column(0).to_pylist():
                own, here, after = unpack(data)
                at = np.flatnonzero(_found(asked.value, own)[1])
                yield pa.RecordBatch.from_arrays([pa.array(own[at].view(np.int64)), pa.array(here[at]), pa.array(after[at])], ["k", "here", "next"])

    got = table.select("data").mapInArrow(trimmed(run), "k long, here float, next float").toArrow()
    asked.destroy()
    have, values = _summed(got.column("k").to_numpy().view(np.uint64), got.column("here").to_numpy(), got.column("next").to_numpy())
    out = np.zeros((3, len(keys)), np.float32)
    at, hit = _found(have, keys)
    out[:, hit] = values[:, at[hit]]
    return keys, out


def sharded_scores(docs: DataFrame, model: Model, unknown: float, shards: int) -> DataFrame:
    """__key (xxhash64 of the text), n_tokens and log10_prob of every text that has words."""
    often, parts = hot_keys(docs), []
    each = max(-(-shards // len(model.waves)), min(shards, docs.sparkSession.sparkContext.defaultParallelism))
    for k, wave in enumerate(model.waves):
        values = model.values(k, each)
        known, values_only = model.known(values), values.where(f"kind = {VALUES}")
        hot = docs.sparkSession.sparkContext.broadcast((*_lookup(values_only, often), known))
        parts.append(materialise(_wave(docs, values_only, hot, each, wave), "kn-scores"))
        hot.destroy()  # with its file, which the driver would keep to the end otherwise
        discard(values)
    sums = reduce(DataFrame.unionByName, parts).groupBy("__key").agg(F.max("n").alias("n_tokens"), F.sum("part").alias("part"))
    out = materialise(sums.select("__key", "n_tokens", (F.col("part") + F.col("n_tokens") * F.lit(unknown)).alias("log10_prob")), "kn-sums")
    discard(*parts)
    return out


def _wave(docs: DataFrame, values: DataFrame, hot, shards: int, wave: np.ndarray) -> DataFrame:
    """__key, n and part: what the n-grams of a wave give each text."""
    # a packet's own row tells its texts; rows from shards tell what they add
    told = "packet long, texts binary, adds binary"

    def ask(batches):
        packet = TaskContext.get().partitionId() << 32
        keys_hot, values_hot, known = hot.value
        for texts, numbers, n, keys, codes in _gathered(_packets(batches, wave), known):
            order = np.argsort(keys)
            keys, codes = keys[order], codes[order]
            # frequent n-grams are runs of the sorted keys
            begin = np.searchsorted(keys, keys_hot)
            times = np.searchsorted(keys, keys_hot, side="right") - begin
            often = np.repeat(np.arange(len(keys_hot)), times)
            where = np.arange(len(often)) + np.repeat(begin - np.cumsum(times) + times, times)
            # without any, bincount() forgets that it was to add fractions
            sums = np.bincount(codes[where] >> 2, values_hot[codes[where] & 3, often], len(texts)).astype(np.float64)
            yield rows_of([(packet % shards, ASKED, pack(texts, numbers, n, sums, np.array([packet])))])
            other = np.ones(len(keys), bool)
            other[where] = False
            rows = []
            for k, (own, code) in by_ranges(keys[other], shards, codes[other], rising=True):
                new = runs(own)
                rows.append((k, ASKED, pack(own[new], np.diff(np.append(new, len(own))).astype(np.uint32), code, np.array([packet]), rising=True)))
            if rows:
                yield rows_of(rows)
            packet += 1

    def answer(batches):
        shard, parts, have, of = -1, [], np.empty(0, np.uint64), np.empty((3, 0), np.float32)
        for batch in batches:
            out = []
            for k, kind, data in zip(*(batch.column(j).to_pylist() for j in range(3))):
                if k != shard:
                    shard, parts, have, of = k, [], np.empty(0, np.uint64), np.empty((3, 0), np.float32)
                if kind == VALUES:
                    parts.append(unpack(data))
                    continue
                if parts:  # values come before questions
                    (have, of), parts = _summed(*joined(parts)), []
                got = unpack(data)
                packet = int(got[-1][0])
                if got[0].dtype == np.int64:  # the packet's own row
                    out.append((packet, pack(*got[:-1]), None))
                    continue
                own, size, code, _ = got
                at, hit = _found(have, own)
                at, hit = np.repeat(at, size), np.repeat(hit, size)
                code, at = code[hit], at[hit]
                sums = np.bincount(code >> 2, of[code & 3, at], int(code.max(initial=0) >> 2) + 1)
                some = np.flatnonzero(sums)
                out.append((packet, None, pack(some.astype(np.uint16), sums[some].astype(np.float32))))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.binary()), pa.array([o[2] for o in out], pa.binary())], ["packet", "texts", "adds"])

    def gather(batches):
        packet, texts, numbers, n, sums, adds = None, None, None, None, None, []

        def done():
            for at, more in adds:
                sums[at] += more
            return pa.RecordBatch.from_arrays([pa.array(texts), pa.array(np.full(len(texts), packet >> 32)), pa.array(numbers), pa.array(n), pa.array(sums)], ["__key", "task", "number", "n", "part"])

        for batch in batches:
            for p, own, add in zip(*(batch.column(j).to_pylist() for j in range(3))):
                if p != packet:
                    if packet is not None:
                        yield done()
                    packet, adds = p, []
                if own is not None:
                    texts, numbers, n, sums = unpack(own)
                else:
                    adds.append(unpack(add))
        if packet is not None:
            yield done()

    asked = docs.select(F.xxhash64("text").alias("k"), "text").mapInArrow(trimmed(ask), PACKED)
    answers = dealt(values.unionByName(asked), shards, F.col("shard")).sortWithinPartitions("shard", "kind").mapInArrow(trimmed(answer), told)
    sums = answers.repartition(shards, "packet").sortWithinPartitions("packet").mapInArrow(trimmed(gather), "__key long, task long, number long, n long, part double")
    # the parts of a long text add up; copies of a text have one score
    sums = sums.where("n > 0").groupBy("__key", "task", "number").agg(F.sum("n").alias("n"), F.sum("part").alias("part"))
    return sums.groupBy("__key").agg(F.max("n").alias("n"), F.max("part").alias("part"))


def trusted_ids(labels: DataFrame) -> DataFrame:
    """Distinct ids of documents labelled as good."""
    return labels.where("quality = 1 AND doc_id IS NOT NULL").select(F.col("doc_id").alias("__good")).distinct()


def trusted_texts(docs: DataFrame, trusted: DataFrame) -> list[DataFrame]:
    """Tables of the texts of docs that trusted ids name. The ids are sent to the texts, a bounded number at a time."""
    parts = max(1, -(-trusted.count() // SENT_IDS))
    some = lambda k: F.broadcast(trusted.where(F.pmod(F.xxhash64("__good"), F.lit(parts)) == k))
    return [materialise(docs.join(some(k), F.col("doc_id") == F.col("__good"), "left_semi").select("text"), "kn-trusted") for k in range(parts)]


def shard_count(docs: DataFrame) -> tuple[int, int]:
    """Shards of bounded size, and as many as the session's partitions at least; waves."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // SHARD_BYTES)), min(WAVES, 1 + size // WAVE_BYTES)


def classify(docs: DataFrame, labels: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """The columns in keep (default doc_id and lang) with n_tokens, perplexity, threshold and kept."""
    keep = keep or ["doc_id", "lang"]
    trusted = trusted_ids(labels)
    held = held_out("doc_id", FOLDS, HELD_OUT)
    good = trusted_texts(docs.select("doc_id", "text").where(~held & F.col("text").isNotNull()), trusted)
    shards, waves = shard_count(docs)
    model = value_table(reduce(DataFrame.unionByName, good), shards, waves)
    discard(*good)
    if model:
        scores = sharded_scores(docs, *model, shards)
        model[0].discard()
    else:  # without trusted words only lengths are known
        scores = docs.select(F.xxhash64("text").alias("__key"), F.size(native_words(F.col("text"))).cast("long").alias("n_tokens"), F.lit(0.0).alias("log10_prob")).where("n_tokens > 0").distinct()
    with_scores = lambda rows: rows.join(scores, "__key", "left").withColumns({"n_tokens": F.coalesce("n_tokens", F.lit(0)), "log10_prob": F.coalesce("log10_prob", F.lit(0.0))})
    # thresholds: means first, then quantiles of the shrunken log probability
    tested = docs.where(held).select("doc_id", "lang", F.xxhash64("text").alias("__key")).join(trusted, F.col("doc_id") == F.col("__good"), "left_semi")
    scored = materialise(with_scores(tested).where("n_tokens > 0").select("lang", "n_tokens", "log10_prob"), "kn-tested")
    means = {r[0]: (r[1] / r[2], r[3]) for r in scored.groupBy("lang").agg(F.sum("log10_prob"), F.sum("n_tokens"), F.count(F.lit(1))).limit(1001).collect()}
    if len(means) > 1000:
        raise ValueError("more than 1000 languages")
    words = scored.agg(F.sum("log10_prob"), F.sum("n_tokens")).first()
    overall = words[0] / words[1] if words[1] else 0.0
    prior = F.lit(overall)
    for lang, (mean, n) in means.items():
        if lang is not None and n >= LEAST_TRUSTED:
            prior = F.when(F.col("lang") == F.lit(lang), F.lit(mean)).otherwise(prior)
    shrunk = -(F.col("log10_prob") + PRIOR_WORDS * prior) / (F.col("n_tokens") + PRIOR_WORDS)
    cuts = {r[0]: r[1] for r in scored.withColumn("m", shrunk).groupBy("lang").agg(F.percentile_approx("m", QUANTILE, 10_000)).collect()}
    every = scored.withColumn("m", shrunk).agg(F.percentile_approx("m", QUANTILE, 10_000)).first()[0]
    discard(scored)
    cut = F.lit(every + MARGIN if every is not None else float("inf"))
    for lang, (_, n) in means.items():
        if lang is not None and n >= LEAST_TRUSTED:
            cut = F.when(F.col("lang") == F.lit(lang), F.lit(cuts[lang] + MARGIN)).otherwise(cut)
    columns = list(dict.fromkeys([*keep, "lang"]))
    out = with_scores(docs.select(*columns, F.xxhash64("text").alias("__key"))).withColumn("__m", shrunk).withColumn("__cut", cut)
    return out.select(
        *keep, "n_tokens", F.when(F.col("n_tokens") > 0, F.pow(F.lit(10.0), F.col("__m"))).alias("perplexity"), F.pow(F.lit(10.0), F.col("__cut")).alias("threshold"),
        ((F.col("n_tokens") > 0) & (F.col("__m") <= F.col("__cut"))).alias("kept"),
    )


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs, all columns, that stay within their language's threshold."""
    rows = docs.select("doc_id", "lang", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"))
    return classify(rows, labels, keep=["__row"]).where("kept").select("__row.*")


def op9_quality_classifier(spark, sf_dir: str) -> DataFrame:
    return classify(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
