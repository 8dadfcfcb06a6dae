"""Near-duplicate vectors by lattice hashing, verified by cosine in double precision.

Each table projects the unit vectors to a few blocks of eight dimensions and decodes each block to its nearest point
of the E8 lattice; the points together name a cell. A vector stands in its home cell and in neighbouring cells that
the residuals make likely. How many blocks, how wide cells and how many tables there are follows from the number of
vectors (``choose_grid``): projections of unit vectors are normal whatever the data, so the chances that a pair at the
threshold and a random pair meet are simulated once; the tables are as many as the recall asks for, and of the grids
that reach it the one with the least expected work is taken. So cells shrink as vectors grow in number. Vectors that share a cell, at least one of them at home, are compared. Sharing is sought
on narrow rows (cell and key); only vectors of shared cells travel. A crowded cell is cut into blocks, and every
pair of its blocks is compared, so nothing is capped. Comparisons within a cell leave at most one link for each
vector (a spanning forest), so a crowd gives no quadratic output; links make components, and then all pairs within
a component are compared block by block to count links exactly.

Equal vectors are one representative with a weight; keys of representatives are checked to be unique. Recall against
brute force is tested.

Defined cases: null, zero and empty vectors, and ones with a null or non-finite component, link with nothing, as
do rows with a null id; vectors of different lengths never link; repeated rows count as vectors of their own; ties
do not arise; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import discard, materialise, read
from memojoin.llm.components import components

COSINE, SEED = 0.9, 11
#: The share of the links at the threshold itself that the tables are to find.
RECALL = 0.975
#: Grids to choose from, and what it costs to post a vector in a cell and to compare a pair that met there.
GRIDS = tuple((blocks, width) for blocks in (2, 3, 4) for width in (1.5, 1.75, 2.0, 2.25))
POST_COST, MEET_COST = 1.0, 25.0
BLOCK_ROWS = 1024


def _d8(x: np.ndarray) -> np.ndarray:
    """Nearest integer points of even sum."""
    near = np.rint(x)
    miss = x - near
    odd = np.flatnonzero(near.sum(1).astype(np.int64) & 1)
    worst = np.abs(miss[odd]).argmax(1)
    near[odd, worst] += np.where(miss[odd, worst] >= 0, 1.0, -1.0)
    return near


def decode_e8(x: np.ndarray) -> np.ndarray:
    """The nearest E8 points: of the integer or the half-integer coset."""
    a, b = _d8(x), _d8(x - 0.5) + 0.5
    closer = ((x - a) ** 2).sum(1) <= ((x - b) ** 2).sum(1)
    return np.where(closer[:, None], a, b)


def shortest_vectors() -> np.ndarray:
    """The 240 lattice vectors next to the origin."""
    halves = [s for s in itertools.product((0.5, -0.5), repeat=8) if sum(v < 0 for v in s) % 2 == 0]
    out = [np.array(s) for s in halves]
    for i, j in itertools.combinations(range(8), 2):
        for a, b in itertools.product((1.0, -1.0), repeat=2):
            v = np.zeros(8)
            v[i], v[j] = a, b
            out.append(v)
    return np.array(out)


def probes(blocks: int) -> tuple[tuple[int, ...], ...]:
    """Cells tried, as ranks of neighbours by block (0 is home): one or two steps in one block, or one in two blocks."""
    at = lambda ranks: tuple(ranks.get(b, 0) for b in range(blocks))
    near = [at({b: r}) for r in (1, 2) for b in range(blocks)]
    return (at({}), *near, *(at({b: 1, c: 1}) for b, c in itertools.combinations(range(blocks), 2)))


@dataclass(frozen=True)
class Grid:
    blocks: int
    width: float
    tables: int


def _ranks(x: np.ndarray, home: np.ndarray, other: np.ndarray) -> np.ndarray:
    """The rank (0, 1, 2; 3 for further ones) that the cell other has for points x at home."""
    out = np.full(len(x), 3)
    step = other - home
    out[(step == 0).all(1)] = 0
    close = np.flatnonzero(np.isclose((step * step).sum(1), 2.0))
    if len(close):
        gain = (x[close] - home[close]) @ shortest_vectors().T
        own = ((x[close] - home[close]) * step[close]).sum(1)
        out[close] = np.minimum(1 + (gain > own[:, None] + 1e-9).sum(1), 3)
    return out


@lru_cache(maxsize=None)
def meeting_chances(blocks: int, width: float, samples: int = 40_000) -> tuple[float, float]:
    """The chance that one table brings a pair at the threshold, and a random pair, together."""
    rng, table = np.random.default_rng(SEED), []
    for cosine in (COSINE, 0.0):
        x = rng.standard_normal((samples, 8))
        y = (cosine * x + math.sqrt(1 - cosine**2) * rng.standard_normal((samples, 8))) / width
        x = x / width
        hx, hy = decode_e8(x), decode_e8(y)
        joint = np.zeros((4, 4))
        np.add.at(joint, (_ranks(x, hx, hy), _ranks(y, hy, hx)), 1.0 / samples)
        table.append((joint + joint.T) / 2)
    tried, out = set(probes(blocks)), []
    for joint in table:
        met = 0.0
        for pairs in itertools.product(itertools.product(range(4), repeat=2), repeat=blocks):
            if tuple(p[0] for p in pairs) in tried or tuple(p[1] for p in pairs) in tried:
                met += math.prod(joint[p] for p in pairs)
        out.append(met)
    return out[0], out[1]


def choose_grid(n: int) -> Grid:
    """The grid of least expected work for n vectors that finds the share RECALL of the pairs at the threshold."""
    best = None
    for blocks, width in GRIDS:
        close, random = meeting_chances(blocks, width)
        tables = math.ceil(math.log(1 - RECALL) / math.log(1 - close))
        work = tables * (len(probes(blocks)) * POST_COST + n * random * MEET_COST)
        if best is None or work < best[0]:
            best = work, Grid(blocks, width, tables)
    return best[1]


class Lattice:
    """Cells of unit vectors of one length."""

    def __init__(self, length: int, grid: Grid, seed: int = SEED):
        rng = np.random.default_rng([seed, length])
        self.grid, self.near, self.probes = grid, shortest_vectors(), probes(grid.blocks)
        self.project = rng.standard_normal((grid.tables, grid.blocks, length, 8)) / grid.width
        self.mix = rng.integers(1, 1 << 62, (grid.tables, grid.blocks, 8), dtype=np.int64) | 1

    def cells(self, unit: np.ndarray) -> np.ndarray:
        """(n, tables, probes): the home cell first."""
        blocks = self.grid.blocks
        out = np.empty((len(unit), self.grid.tables, len(self.probes)), np.int64)
        ranks = 1 + max(max(p) for p in self.probes)
        for t in range(self.grid.tables):
            codes = np.empty((blocks, ranks, len(unit)), np.int64)
            for b in range(blocks):
                x = unit @ self.project[t, b]
                home = decode_e8(x)
                gain = (x - home) @ self.near.T
                best = np.argpartition(-gain, ranks - 2, axis=1)[:, : ranks - 1]
                best = np.take_along_axis(best, np.argsort(-np.take_along_axis(gain, best, 1), axis=1), 1)
                for r in range(ranks):
                    point = home if r == 0 else home + self.near[best[:, r - 1]]
                    codes[b, r] = (np.rint(2 * point).astype(np.int64) * self.mix[t, b]).sum(1)
            for k, probe in enumerate(self.probes):
                z = np.full(len(unit), t, np.int64)
                for b, r in enumerate(probe):
                    z = z * np.int64(0x9E3779B97F4A7C1 | 1) + codes[b, r]
                    z ^= z >> 31
                out[:, t, k] = (z ^ (z >> 29)) * np.int64(0x3F58476D1CE4E5B9)
        return out


def representatives(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All rows as vec_id, key (null if it links with nothing); and one row for each key: key, first, weight, vector."""
    v = F.col("embedding")
    good = F.col("vec_id").isNotNull() & v.isNotNull() & (F.size(v) > 0)
    finite = ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    # a zero's sign must not part equal vectors
    clean = F.transform(v, lambda x: x.cast("double") + F.lit(0.0))
    for seed in itertools.count():
        key = F.when(good & finite, F.xxhash64(clean, F.size(v), F.lit(seed)))
        rows = vectors.select("vec_id", key.alias("key"), clean.alias("vector"))
        equal = rows.where("key IS NOT NULL").groupBy("key", "vector").agg(F.min("vec_id").alias("first"), F.count(F.lit(1)).alias("weight"))
        reps = materialise(equal.select("key", "first", "weight", "vector"), "e8-reps")
        # different vectors with one hash must not be linked: hash anew
        if not reps.groupBy("key").count().where("count > 1").take(1):
            return rows.select("vec_id", "key"), reps
        discard(reps)


def _matrix(column) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def cell_rows(reps: DataFrame, grid: Grid) -> DataFrame:
    """key, cell, home for every cell that a representative stands in."""

    def run(batches):
        lattices: dict[int, Lattice] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                keys, lists = part.column(0).to_numpy(), part.column(1)
                sizes = np.array([len(x) for x in lists])
                for n in np.unique(sizes):
                    pick = np.flatnonzero(sizes == n)
                    if int(n) not in lattices:
                        lattices[int(n)] = Lattice(int(n), grid)
                    x = _matrix(lists.take(pa.array(pick)))
                    x = x / np.abs(x).max(1, keepdims=True)
                    x /= np.linalg.norm(x, axis=1, keepdims=True)
                    cells = lattices[int(n)].cells(x) + int(n)
                    home = np.zeros(cells.shape, bool)
                    home[:, :, 0] = True
                    wide = cells.shape[1] * cells.shape[2]
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(keys[pick], wide)), pa.array(cells.ravel()), pa.array(home.ravel())], ["key", "cell", "home"])

    return reps.select("key", "vector").mapInArrow(run, "key long, cell long, home boolean")


def _blocked(rows: DataFrame, group: str, sizes: DataFrame) -> DataFrame:
    """Rows copied to every pair of their group's blocks: adds g (the group and pair) and side (1, or 2 for the second block)."""
    blocks = F.ceil(F.col("n") / F.lit(float(BLOCK_ROWS))).cast("int")
    own = F.pmod(F.xxhash64("key", F.lit("block")), F.col("blocks")).cast("int")
    spread = rows.join(sizes.select(group, blocks.alias("blocks")), group).withColumn("own", own)
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    pairs = spread.select("*", other.alias("other"))
    low, high = F.least("own", "other"), F.greatest("own", "other")
    return pairs.select("*", low.alias("lo"), high.alias("hi"), F.when(F.col("own") <= F.col("other"), 1).otherwise(2).alias("side")).drop("own", "other", "blocks")


def _sorted_groups(batches, names: list[str]):
    """Runs of equal leading columns of a sorted stream, as tables; a run may span batches."""
    held: list[pa.RecordBatch] = []

    def key_at(b, i):
        return tuple(b.column(b.schema.get_field_index(n))[i].as_py() for n in names)

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(batch.schema.get_field_index(n)).to_numpy() for n in names]
        cuts = np.flatnonzero(np.logical_or.reduce([c[1:] != c[:-1] for c in cols])) + 1
        edges = [0, *cuts.tolist(), batch.num_rows]
        for lo, hi in zip(edges[:-1], edges[1:]):
            if held and key_at(held[0], 0) != key_at(batch, lo):
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield pa.Table.from_batches(held)


def _unit(table: pa.Table) -> np.ndarray:
    x = _matrix(table.column("vector"))
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _same_length(table: pa.Table):
    sizes = np.array([len(v) for c in table.column("vector").chunks for v in c])
    for n in np.unique(sizes):
        yield table.take(pa.array(np.flatnonzero(sizes == n)))


def cell_links(rows: DataFrame) -> DataFrame:
    """a, b: spanning links of each cell's verified pairs (rows: cell, lo, hi, side, key, home, vector)."""

    def run(batches):
        a, b = [], []
        for whole in _sorted_groups(batches, ["cell", "lo", "hi"]):
            for t in _same_length(whole):
                if t.num_rows < 2:
                    continue
                keys, home, side = (t.column(c).to_numpy() for c in ("key", "home", "side"))
                x = _unit(t)
                same_block = t.column("lo")[0] == t.column("hi")[0]
                top = np.arange(len(keys))

                def root(i):
                    while top[i] != i:
                        top[i] = top[top[i]]
                        i = top[i]
                    return i

                for at in range(0, len(keys), 512):
                    ok = (x[at : at + 512] @ x.T) >= COSINE
                    ok &= home[at : at + 512, None] | home[None, :]
                    if not same_block:
                        ok &= side[at : at + 512, None] != side[None, :]
                    for i in range(ok.shape[0]):
                        for j in np.flatnonzero(ok[i, : at + i]):
                            p, q = root(at + i), root(int(j))
                            if p != q:
                                top[max(p, q)] = min(p, q)
                                a.append(keys[at + i])
                                b.append(keys[j])
            if len(a) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
                a, b = [], []
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(n, "cell", "lo", "hi").sortWithinPartitions("cell", "lo", "hi")
    return dealt.mapInArrow(run, "a long, b long").distinct()


def link_counts(rows: DataFrame) -> DataFrame:
    """key, links: the weight that each representative links with (rows: component, lo, hi, side, key, weight, vector)."""

    def run(batches):
        for whole in _sorted_groups(batches, ["component", "lo", "hi"]):
            same_block = whole.column("lo")[0] == whole.column("hi")[0]
            for t in _same_length(whole):
                keys, weight, side = (t.column(c).to_numpy() for c in ("key", "weight", "side"))
                x, links = _unit(t), np.zeros(len(keys), np.int64)
                for at in range(0, len(keys), 512):
                    ok = (x[at : at + 512] @ x.T) >= COSINE
                    if same_block:
                        ok[np.arange(ok.shape[0]), np.arange(at, at + ok.shape[0])] = False
                    else:
                        ok &= side[at : at + 512, None] != side[None, :]
                    links[at : at + 512] = ok @ weight
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(links)], ["key", "links"])

    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(n, "component", "lo", "hi").sortWithinPartitions("component", "lo", "hi")
    return dealt.mapInArrow(run, "key long, links long").groupBy("key").agg(F.sum("links").alias("links"))


def near_duplicates(vectors: DataFrame, grid: Grid | None = None) -> DataFrame:
    """vec_id, n_links, component_id and kept for every row; grid: instead of the chosen one."""
    rows, reps = representatives(vectors)
    cells = materialise(cell_rows(reps, grid or choose_grid(reps.count())), "e8-cells")
    shared = cells.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max(F.col("home").cast("int")).alias("h")).where("n > 1 AND h = 1").drop("h")
    members = _blocked(cells, "cell", shared).join(reps.select("key", "vector"), "key")
    links = components(cell_links(members))
    discard(cells)
    label = links.withColumnRenamed("node", "key")
    names = label.join(reps.select("key", "first"), "key").groupBy("component").agg(F.min("first").alias("component_id"), F.count(F.lit(1)).alias("n"))
    inside = _blocked(label.join(reps, "key"), "component", names.select("component", "n"))
    counted = link_counts(inside.select("component", "lo", "hi", "side", "key", "weight", "vector"))
    known = reps.select("key", "first", "weight").join(label.join(names.drop("n"), "component").select("key", "component_id"), "key", "left").join(counted, "key", "left")
    known = known.select("key", F.coalesce("component_id", "first").alias("c"), (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("l"))
    return rows.join(known, "key", "left").select(
        "vec_id", F.coalesce("l", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id"),
        F.coalesce(F.col("vec_id") == F.coalesce("c", "vec_id"), F.lit(False)).alias("kept"),
    )


def op6_e8_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(read(spark, sf_dir, "embeddings"))


#: All pairs, for tables of oracle size; the lattice may miss links near the threshold (RECALL).
OP6_SQL = f"""
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings),
ok AS (SELECT vec_id, x FROM v WHERE vec_id IS NOT NULL AND len(x) > 0 AND len(list_filter(x, lambda y: y IS NULL OR NOT isfinite(y))) = 0 AND len(list_filter(x, lambda y: y <> 0)) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.vec_id <> b.vec_id AND len(a.x) = len(b.x) WHERE list_cosine_similarity(a.x, b.x) >= {COSINE}),
r(a, c) AS (SELECT vec_id, vec_id FROM v UNION SELECT r.a, l.b FROM r JOIN l ON l.a = r.c),
c AS (SELECT a, min(c) AS c FROM r GROUP BY a),
n AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT v.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, c.c AS component_id, v.vec_id = c.c AS kept
FROM v LEFT JOIN c ON c.a = v.vec_id LEFT JOIN n ON n.a = v.vec_id"""
