"""N-gram Jaccard join of whole texts, exact, with set-relation skipping.

Texts become sets of 64-bit hashes of word n-grams. To bring sets that may link into one place, each set's tokens are
dealt to parts by hash, more parts than two linked sets can have differences; so several parts are equal in both, and
the hash of a part's content is a signature that they share. Signatures of few sets are counted for each pair; frequent
signatures (of passages that many texts quote) only count for sets that have so many of them that all the parts which
a linked set must share could be frequent ones. Pairs that share too few are no candidates. Connected
components of those links are the candidate groups. The sets of each group then meet in one task and are joined there
over an inverted index of their prefixes:

* index level: a token's list is kept in blocks by position; a block whose sets have too little left behind the
  token to reach the overlap is skipped whole;
* answer level: a set that is highly similar to one whose overlaps are known derives its own from them, by the few
  tokens in which the two differ, and sets that are already linked are skipped.

Groups beyond ``BLOCK_SETS`` sets are cut into blocks, and every pair of blocks is joined, so nothing is capped.
Sets are hashed in 64 bits (a chance of the order of 2**-64 for each pair of tokens or sets to be mistaken).

Defined cases: a null text or one without words has an empty set and links with nothing; with fewer words than an
n-gram takes, the whole sequence is the one token; equal sets are one until the end; repeated rows and null ids
belong to their set's component; a component without any id is null; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import ascii_words, dealt, materialise, read, trimmed
from memojoin.llm.components import components
from memojoin.llm.e8_dedup import _sorted_groups
from memojoin.llm.packets import runs

WORDS, PERCENT = 3, 90
#: Parts beyond the differences that linked sets can have: at least so many, and this share of the differences.
SPARE_PARTS, SPARE_SHARE = 3, 0.5
#: A signature of more sets than this is frequent.
FREQUENT = 6
#: Sizes are banded by this many steps of the threshold.
BAND_STEPS = 4
SEEN_SETS = 500_000
#: Signatures that a task holds before it passes them on.
POSTS_HELD = 600_000
BITMAP_BITS = 26
BLOCK_SETS = 2048
POSITION_BLOCK = 8
REMEMBERED = 200_000


class Shingler:
    """Sets of n-gram hashes; word hashes are remembered within a bound."""

    def __init__(self, words: int):
        self.words, self.known = words, {}
        self.mix = np.random.default_rng(17).integers(1, 1 << 62, words, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def tokens(self, text: str | None) -> np.ndarray:
        """Distinct tokens in rising order."""
        words, known = ascii_words(text), self.known
        if not words:
            return np.empty(0, np.uint64)
        if len(known) > REMEMBERED:
            known.clear()
        ids = []
        for w in words:
            h = known.get(w)
            if h is None:
                h = known[w] = xxhash.xxh64_intdigest(w)
            ids.append(h)
        h = np.array(ids, np.uint64)
        n = self.words
        if len(h) < n:
            return np.array([xxhash.xxh64_intdigest(b" ".join(words), seed=len(words))], np.uint64)
        out = np.zeros(len(h) - n + 1, np.uint64)
        for k in range(n):
            out += h[k : len(h) - n + 1 + k] * self.mix[k]
        out ^= out >> np.uint64(31)
        out *= np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
        return np.unique(out)


def key_of(tokens: np.ndarray) -> int:
    return (xxhash.xxh3_64_intdigest(tokens.tobytes()) - (1 << 63)) & ~1  # the last bit is free for a mark


def least_overlap(n: int, m: int, percent: int) -> int:
    """The least intersection with which sets of these sizes reach the threshold."""
    return -(-percent * (n + m) // (100 + percent))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1 if n else 0


def _parts(batches, size=256):
    for batch in batches:
        for at in range(0, batch.num_rows, size):
            yield batch.slice(at, size)


class Bands:
    """Size bands: linked sets lie in one band or in neighbouring ones, and then near the border between them."""

    def __init__(self, percent: int):
        self.percent, self.starts = percent, [1]

    def groups(self, n: int) -> list[tuple[int, int]]:
        """(group, largest size in it) for each group that a set of this size belongs to.

        A group is a band with the sets below it that could link into it.
        """
        while self.starts[-1] <= 100 * n // self.percent + 1:
            top = self.starts[-1]
            for _ in range(BAND_STEPS):
                top = 100 * top // self.percent + 1
            self.starts.append(top)
        at = int(np.searchsorted(self.starts, n, side="right"))  # starts[at - 1] <= n < starts[at]
        out = [(at, self.starts[at] - 1)]
        if 100 * n >= self.percent * self.starts[at]:
            # as the smaller set of a pair whose larger one lies in the next band; that one is below n / threshold
            self.groups(self.starts[at])
            out.append((at + 1, self.starts[at + 1] - 1))
        return out


def signatures(tokens: np.ndarray, bands: Bands) -> list[tuple[np.ndarray, int]]:
    """For each group of sizes that the set belongs to: a number for each part, and how many any linked set shares.

    A difference spoils one part, and a set of n tokens has at most n * (1 / threshold - 1) differences from any that
    it links with; so of its full parts all but so many are equal in both. A set whose full parts could all be spoilt
    also posts its empty ones. It asks for one signature only: a partner that posts no empty parts shares just full
    ones with it, and so the larger need of two linked sets never exceeds what both post.
    """
    out, percent = [], bands.percent
    mixed = tokens * np.uint64(0xD6E8FEB86659FD93)
    mixed ^= mixed >> np.uint64(32)
    mixed *= np.uint64(0xD6E8FEB86659FD93)
    for group, most in bands.groups(len(tokens)):
        differ = 2 * most * (100 - percent) // (100 + percent)
        own = min(differ, len(tokens) * (100 - percent) // percent)
        if not own:
            out.append((np.empty(0, np.int64), 0))  # only equal sets link with one of this size
            continue
        parts = differ + 1 + max(SPARE_PARTS, int(SPARE_SHARE * differ))
        at = ((tokens >> np.uint64(17)) % np.uint64(parts)).astype(np.int64)
        sums, size = np.zeros(parts, np.uint64), np.bincount(at, minlength=parts)
        np.add.at(sums, at, mixed)
        sums ^= (np.arange(parts, dtype=np.uint64) + np.uint64(group << 32)) * np.uint64(0x9E3779B97F4A7C15)
        sums *= np.uint64(0xBF58476D1CE4E5B9)
        sums ^= sums >> np.uint64(31)
        full = int((size > 0).sum())
        out.append((sums[size > 0].view(np.int64), full - own) if full > own else (sums.view(np.int64), 1))
    return out


def keyed_rows(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, text_key (a hash of the text), n and key (null for an empty set) of every row."""

    def run(batches):
        shingle = Shingler(words)
        for part in _parts(batches):
            n, keys = [], []
            for text in part.column(2).to_pylist():
                t = shingle.tokens(text)
                n.append(len(t))
                keys.append(key_of(t) if len(t) else None)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(n, pa.int64()), pa.array(keys, pa.int64())], ["doc_id", "text_key", "n", "key"])

    return docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").mapInArrow(trimmed(run), "doc_id long, text_key long, n long, key long")


def _runs(signs: np.ndarray, marked: np.ndarray):
    """Sorted signatures and keys, where each signature starts, and how many sets each has."""
    at = np.lexsort((marked, signs))
    signs, marked = signs[at], marked[at]
    first = np.flatnonzero(np.concatenate([[True], signs[1:] != signs[:-1]]))
    return signs, marked, first, np.diff(np.append(first, len(signs)))


POST, NEED, COMMON, LINK = 0, 1, 2, 3


def candidate_groups(docs: DataFrame, words: int, percent: int) -> DataFrame:
    """node, component: sets that share signatures, directly or through others.

    Signatures travel as packed arrays, once. Where a task alone has more sets with one than makes it frequent, it
    passes on two for all, so a signature that very many sets share is two numbers from each task.
    """
    spark = docs.sparkSession
    blocks = 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    packed = "block int, kind int, data binary"

    def post(batches):
        shingle, bands, seen = Shingler(words), Bands(percent), set()
        held: list[np.ndarray] = []
        owners: list[int] = []
        needs: list[int] = []

        def flush():
            marked = np.array(owners, np.int64)
            signs, keys, first, n = _runs(np.concatenate(held), np.repeat(marked, [len(h) for h in held]))
            common = np.repeat(n > FREQUENT, n)
            # a frequent signature goes on by as many sets as show the reader that it is frequent
            rank = np.arange(len(signs)) - np.repeat(first, n)
            go = ~common | (rank <= FREQUENT)
            where = ((signs.view(np.uint64) >> np.uint64(11)) % np.uint64(blocks)).astype(np.int64)
            rest = np.flatnonzero(common & ~go)
            out = [(int(k), POST, np.concatenate([signs[i], keys[i]])) for k, i in _dealt(where, np.flatnonzero(go))]
            out += [(int(k), COMMON, np.concatenate([signs[i], keys[i]])) for k, i in _dealt(where, rest)]
            out.append((int(marked[0]) % blocks, NEED, np.concatenate([marked, np.array(needs, np.int64)])))
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int32()), pa.array([o[1] for o in out], pa.int32()), pa.array([o[2].tobytes() for o in out], pa.binary())], ["block", "kind", "data"])

        for part in _parts(batches):
            for text in part.column(0).to_pylist():
                t = shingle.tokens(text)
                if not len(t) or (k := key_of(t)) in seen:
                    continue
                if len(seen) < SEEN_SETS:
                    seen.add(k)
                for mark, (signs, need) in enumerate(signatures(t, bands)):
                    if len(signs):
                        held.append(signs)
                        owners.append(k | mark)
                        needs.append(need)
            if sum(map(len, held)) > POSTS_HELD:
                yield from flush()
                held, owners, needs = [], [], []
        if held:
            yield from flush()

    def link(batches):
        posts: list[np.ndarray] = []

        def rows(kind, a, b, times=None):
            times = np.ones(len(a), np.int64) if times is None else times
            for k in range(0, len(a), 200_000):
                at = slice(k, k + 200_000)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a[at]), kind, np.int32)), pa.array(a[at]), pa.array(b[at]), pa.array(times[at])], ["kind", "a", "b", "times"])

        for batch in batches:
            for kind, data in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                x = np.frombuffer(data, np.int64).reshape(2, -1)
                if kind == POST:
                    posts.append(x)
                else:
                    yield from rows(kind, x[0], x[1])
        if posts:
            x = np.concatenate(posts, axis=1)
            posts.clear()
            signs, marked, first, n = _distinct_runs(x)
            common = np.repeat(n > FREQUENT, n)
            yield from rows(COMMON, signs[common], marked[common])
            # few sets share each of the others: all their pairs, with how often they meet here
            signs, marked = signs[~common], marked[~common]
            low, high = [], []
            for step in range(1, FREQUENT):
                same = np.flatnonzero(signs[step:] == signs[:-step])
                low.append(np.minimum(marked[same], marked[same + step]))
                high.append(np.maximum(marked[same], marked[same + step]))
            low, high = np.concatenate(low), np.concatenate(high)
            at = np.lexsort((high, low))
            low, high = low[at], high[at]
            new = runs(low, high)
            yield from rows(LINK, low[new], high[new], np.diff(np.append(new, len(low))))

    found = materialise(docs.select("text").mapInArrow(trimmed(post), packed).transform(dealt, blocks, F.col("block")).mapInArrow(trimmed(link), "kind int, a long, b long, times long"), "jaccard-links")
    common = found.where(f"kind = {COMMON}").select(F.col("a").alias("sign"), F.col("b").alias("marked")).distinct()
    need = found.where(f"kind = {NEED}").groupBy(F.col("a").alias("marked")).agg(F.min("b").alias("need"))
    known = need.join(common.groupBy("marked").agg(F.count(F.lit(1)).alias("n")), "marked", "left").select("marked", "need", F.coalesce("n", F.lit(0)).alias("n"))
    bound = known.where("n >= need").select("marked")
    inside = common.join(bound, "marked").select("sign", F.expr("marked & ~1L").alias("key"))
    lows = inside.groupBy("sign").agg(F.min("key").alias("low"))
    crowd = inside.join(lows, "sign").select(F.col("key").alias("a"), F.col("low").alias("b"))
    # a linked pair shares as many signatures as either needs: the rare ones are counted, frequent ones at most what both have
    met = found.where(f"kind = {LINK}").groupBy("a", "b").agg(F.sum("times").alias("times"))
    side = lambda x: known.select(F.col("marked").alias(x), F.col("need").alias(f"need_{x}"), F.col("n").alias(f"n_{x}"))
    able = met.join(side("a"), "a").join(side("b"), "b").where("times + least(n_a, n_b) >= greatest(need_a, need_b)")
    return components(able.selectExpr("a & ~1L AS a", "b & ~1L AS b").unionByName(crowd))


def _dealt(where: np.ndarray, rows: np.ndarray):
    """(block, rows) for each block that has some."""
    rows = rows[np.argsort(where[rows], kind="stable")]
    cuts = np.flatnonzero(np.diff(where[rows])) + 1
    for part in np.split(rows, cuts):
        if len(part):
            yield where[part[0]], part


def _distinct_runs(x: np.ndarray):
    """_runs() over posts of which several tasks may have sent the same."""
    signs, marked, _, _ = _runs(x[0], x[1])
    new = np.concatenate([[True], (signs[1:] != signs[:-1]) | (marked[1:] != marked[:-1])])
    return _runs(signs[new], marked[new])


def _bitmap(keys: DataFrame) -> np.ndarray:
    """A bitmap of fixed size with a bit set for every key: false hits only cost time."""
    at = F.expr(f"shiftrightunsigned(key, {64 - BITMAP_BITS})")  # keys are hashes already
    words = keys.select(at.alias("at")).selectExpr("shiftright(at, 6) AS word", "shiftleft(1L, CAST(at & 63 AS INT)) AS bit").groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()
    out = np.zeros(1 << (BITMAP_BITS - 6), np.int64)
    out[words.column("word").to_numpy()] = words.column("bits").to_numpy()
    return out


def _spread(key: int) -> int:
    return (key & ((1 << 64) - 1)) >> (64 - BITMAP_BITS)


class LocalJoin:
    """The sets of one candidate group (or of two blocks of it), linked until connected."""

    def __init__(self, percent: int):
        self.percent = percent

    def links(self, keys: list[int], sets: list[np.ndarray], side: list[int] | None = None) -> list[tuple[int, int]]:
        """Links that connect what the threshold connects; with sides, only links across them are looked for."""
        order = sorted(range(len(keys)), key=lambda k: (len(sets[k]), keys[k]))
        comp = np.arange(len(keys))
        sides = np.array(side) if side is not None else None
        lists: dict[int, list[tuple[int, list[int]]]] = {}  # token: blocks of (most left behind the token, sets)
        known: dict[int, dict[int, int]] = {}  # overlaps found so far, by set
        twin: dict[int, tuple[int, np.ndarray, np.ndarray]] = {}
        out = []
        tokens, often = np.unique(np.concatenate(sets), return_counts=True)
        for x in order:
            sx = sets[x]
            n = len(sx)
            ranked = sx[np.lexsort((sx, often[np.searchsorted(tokens, sx)]))]  # rare first within the group
            head = ranked[: prefix_length(n, self.percent)].tolist()
            least = -(-self.percent * n // 100)
            found: list[list[int]] = []
            for i, token in enumerate(head):
                for rest, members in lists.get(token, ()):
                    if 1 + min(n - i - 1, rest) >= least:  # else the whole block is skipped
                        found.append(members)
            mine = known[x] = {}
            if found:
                cand = np.unique(np.concatenate([np.asarray(m, np.int64) for m in found]))
                if sides is not None:
                    cand = cand[sides[cand] != sides[x]]
                y = None
                for z in cand[::-1].tolist() if len(cand) else ():
                    if comp[z] == comp[x]:
                        continue
                    m = len(sets[z])
                    if 100 * m < self.percent * n:
                        continue
                    if y is not None and z in known[y]:
                        # |X∩Z| from |Y∩Z|: add what X has and Y lacks, take off what Y has and X lacks
                        more, less = twin[x][1], twin[x][2]
                        low, high = known[y][z] - len(less), known[y][z] + len(more)
                        need = least_overlap(n, m, self.percent)
                        if high < need:
                            continue
                        o = known[y][z] + _common(more, sets[z]) - _common(less, sets[z]) if low < need else low
                    else:
                        o = _common(sx, sets[z])
                    mine[z] = o
                    if o >= least_overlap(n, m, self.percent):
                        out.append((keys[x], keys[z]))
                        comp[comp == comp[x]] = comp[z]
                        if y is None:
                            y = z
                            twin[x] = (z, np.setdiff1d(sx, sets[z], assume_unique=True), np.setdiff1d(sets[z], sx, assume_unique=True))
            for i, token in enumerate(head):
                blocks = lists.setdefault(token, [])
                if not blocks or len(blocks[-1][1]) >= POSITION_BLOCK * 8 or blocks[-1][0] // POSITION_BLOCK != (n - i - 1) // POSITION_BLOCK:
                    blocks.append((n - i - 1, [x]))
                else:
                    rest, members = blocks[-1]
                    members.append(x)
                    blocks[-1] = (max(rest, n - i - 1), members)
        return out


def _common(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two rising arrays."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.minimum(np.searchsorted(b, a), len(b) - 1)
    return int((b[at] == a).sum())


def links(docs: DataFrame, groups: DataFrame, words: int, percent: int) -> DataFrame:
    """a, b: verified links that connect the sets of each candidate group."""
    spark = docs.sparkSession
    bitmap = spark.sparkContext.broadcast(_bitmap(groups))
    sized = groups.join(groups.groupBy("component").agg(F.ceil(F.count(F.lit(1)) / F.lit(float(BLOCK_SETS))).cast("int").alias("blocks")), "component")

    def hit(batches):
        shingle, bits, seen = Shingler(words), bitmap.value, set()
        for part in _parts(batches):
            keys, data = [], []
            for text in part.column(0).to_pylist():
                t = shingle.tokens(text)
                if not len(t):
                    continue
                k = key_of(t)
                at = _spread(k)
                if k in seen or not (int(bits[at >> 6]) >> (at & 63)) & 1:
                    continue
                if len(seen) < SEEN_SETS:
                    seen.add(k)
                keys.append(k)
                data.append(t.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(data, pa.binary())], ["key", "tokens"])

    own = F.pmod(F.xxhash64("key", F.lit("block")), F.col("blocks")).cast("int")
    placed = docs.select("text").mapInArrow(trimmed(hit), "key long, tokens binary").join(sized, "key").withColumn("own", own)
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.select("component", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), F.when(F.col("own") <= F.col("other"), 1).otherwise(2).alias("side"), "key", "tokens")

    def join(batches):
        local, a, b = LocalJoin(percent), [], []
        for t in _sorted_groups(batches, ["component", "lo", "hi"]):
            keys, at = np.unique(t.column("key").to_numpy(), return_index=True)  # copies of a set from several tasks
            if len(keys) > 1:
                data, side = t.column("tokens"), t.column("side").to_numpy()[at]
                across = t.column("lo")[0] != t.column("hi")[0]
                found = local.links(keys.tolist(), [np.frombuffer(data[int(i)].as_py(), np.uint64) for i in at], side.tolist() if across else None)
                a += [f[0] for f in found]
                b += [f[1] for f in found]
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return placed.repartition(n, "component", "lo", "hi").sortWithinPartitions("component", "lo", "hi").mapInArrow(trimmed(join), "a long, b long")


def _labelled(docs: DataFrame, words: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """keyed_rows(), and the component (a set's key) of every set that links with another."""
    rows = materialise(keyed_rows(docs, words), "jaccard-rows")
    groups = materialise(candidate_groups(docs, words, percent).select(F.col("node").alias("key"), "component"), "jaccard-groups")
    return rows, components(links(docs, groups, words, percent)).withColumnRenamed("node", "key")


def jaccard_components(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles and component_id of every row."""
    rows, label = _labelled(docs, words, percent)
    firsts = rows.where("key IS NOT NULL").groupBy("key").agg(F.min("doc_id").alias("first"))
    names = label.join(firsts, "key").groupBy("component").agg(F.min("first").alias("c"))
    linked = label.join(names, "component").select("key", "c")
    named = firsts.join(linked, "key", "left").select("key", F.coalesce("c", "first").alias("c"))
    return rows.select("doc_id", "n", "key").join(named, "key", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("c", "doc_id").alias("component_id"))


def op1_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return jaccard_components(read(spark, sf_dir, "documents"))


def keep_first(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """One row of each component: the one of the smallest id (null last), of equal ids the one whose text hashes lowest.

    Rows without words link with nothing and all stay, but for repeated rows (one id and one text), of which one does.
    """
    rows, label = _labelled(docs, words, percent)
    own = rows.where("key IS NOT NULL").join(label, "key", "left").withColumn("label", F.coalesce("component", "key"))
    first = own.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key")).alias("f"))
    chosen = first.select("f.doc_id", "f.text_key").unionByName(rows.where("key IS NULL").select("doc_id", "text_key").distinct())
    chosen = chosen.select(F.col("doc_id").alias("__first"), F.col("text_key").alias("__text_key"))
    marked = docs.withColumn("__own_key", F.xxhash64("text"))
    kept = marked.join(chosen, F.col("doc_id").eqNullSafe(F.col("__first")) & (F.col("__own_key") == F.col("__text_key")), "left_semi")
    return kept.dropDuplicates(["doc_id", "__own_key"]).drop("__own_key")


#: The join by pairs that share a shingle, and the closure of its links; for tables of oracle size.
OP1_SQL = f"""
WITH RECURSIVE t AS (SELECT doc_id, list_filter(string_split(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ' || chr(9)||chr(10)||chr(11)||chr(12)||chr(13), 'abcdefghijklmnopqrstuvwxyz     '), ' '), lambda x: x <> '') AS w FROM documents),
g AS (SELECT doc_id, CASE WHEN len(w) >= {WORDS} THEN list_distinct(list_transform(range(1, len(w) - {WORDS - 2}), lambda i: array_to_string(w[i:i + {WORDS - 1}], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM t),
e AS (SELECT s, min(doc_id) AS rep, len(s)::BIGINT AS n FROM g WHERE len(s) > 0 GROUP BY s),
x AS (SELECT rep, n, unnest(s) AS token FROM e),
l AS (SELECT a.rep AS a, b.rep AS b FROM x a JOIN x b ON a.token = b.token AND a.rep <> b.rep GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= {PERCENT} * (a.n + b.n - count(*))),
r(a, c) AS (SELECT rep, rep FROM e UNION SELECT r.a, l.b FROM r JOIN l ON l.a = r.c),
c AS (SELECT a, min(c) AS c FROM r GROUP BY a)
SELECT g.doc_id, len(g.s)::BIGINT AS n_shingles, coalesce(c.c, g.doc_id) AS component_id
FROM g LEFT JOIN e ON g.s = e.s LEFT JOIN c ON c.a = e.rep"""
