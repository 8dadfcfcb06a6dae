"""The join inside a task: sorted tries in NumPy arrays, walked in blocks depth first, with a bounded memo.

Memory is the tries, the memo, and a block of rows for each variable, whatever the size of intermediate results.
Where all relations are small (their rows are counted first) every task gets all tries and a share of the first
variable's values; otherwise tuples are dealt to the cells of a hypercube, and each cell is one task's join.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.functions.scalars import cell_ids
from memojoin.operators.catalog import Catalog, atom_tables, normalise
from memojoin.operators.frontier import check_plan
from memojoin.operators.policy import CachePolicy, Memo, PackedMemo
from memojoin.plans import cost
from memojoin.plans.decomp import OrderedTD, default_order
from memojoin.plans.query import ConjunctiveQuery
from memojoin.plans.stats import Stats

BLOCK_ROWS = 1 << 16
#: Entries of a task's memo where no policy is given; the oldest make room, as the walk comes back to recent keys.
MEMO_ENTRIES = 1 << 18
#: Rows for each cell of a hypercube, of all atoms together, where the number of cells is not given.
CELL_ROWS = 1 << 20
#: Relations of so many rows, and so many bytes, in total at most are sent to every task.
BROADCAST_ROWS, BROADCAST_BYTES = 5_000_000, 256 << 20
#: Counts that a task of the bag tree holds for the keys of a node.
TALLY_ENTRIES = 1 << 20
OUT = "kind string, name string, value decimal(38,0)"


class Trie:
    """Levels of sorted values: level k has one entry for each distinct prefix of k + 1 columns."""

    def __init__(self, columns: list[np.ndarray], width: int):
        rows = np.lexsort(columns[::-1]) if len(columns[0]) else np.empty(0, np.int64)
        columns = [c[rows] for c in columns]
        parent = np.zeros(len(rows), np.int64)
        parents = 1
        self.keys, self.values, self.starts = [], [], []
        for c in columns:
            packed = parent * width + c  # sorted, as the rows are
            first = np.ones(len(packed), bool)
            np.not_equal(packed[1:], packed[:-1], out=first[1:])
            keys = packed[first]
            self.keys.append(keys)
            self.values.append(keys % width)
            self.starts.append(np.searchsorted(keys, np.arange(parents + 1) * width))
            parent, parents = np.cumsum(first) - 1, len(keys)


@dataclass
class Block:
    """Partial bindings: a column for each variable, and for each atom the trie node that each row has reached."""

    columns: dict[str, np.ndarray]
    nodes: dict[int, np.ndarray]
    n: int

    def take(self, at) -> Block:
        return Block({x: c[at] for x, c in self.columns.items()}, {a: c[at] for a, c in self.nodes.items()}, len(at) if not isinstance(at, slice) else len(range(*at.indices(self.n))))


class Kernel:
    def __init__(self, atoms: list[tuple[tuple[str, ...], list[np.ndarray]]], order, td: OrderedTD, policy: CachePolicy, width: int, block_rows: int = BLOCK_ROWS, scalar: bool = False):
        """atoms: variables in the order's sequence, and columns of numbers below width."""
        self.order, self.td, self.policy, self.width, self.scalar = tuple(order), td, policy, width, scalar
        self.variables = [v for v, _ in atoms]
        self.tries = [Trie(c, width) for _, c in atoms]
        self.block_rows = 1 if scalar else block_rows
        support = {}
        if policy.admit == "support" or policy.replacement == "support":
            for x in self.order:
                support[x] = self._support(x, atoms)
        # keys of all nodes as one number each, where they fit 63 bits
        widest = max([1, *(len(td.adhesion(v)) for v in td.preorder())])
        self.packs = policy.replacement in ("none", "fifo") and int(width) ** widest * len(td) < 1 << 63
        memo = PackedMemo(policy, support, self._unpacked) if self.packs else Memo(policy, support)
        self.memo, self.support, self.counters, self.began = memo, support, Counter(), time.monotonic()
        self.owned = {v: [x for x in order if td.owner(x) == v] for v in td.preorder()}

    def _support(self, x, atoms):
        most = np.zeros(self.width, np.int64) if self.width < 1 << 24 else None
        for variables, columns in atoms:
            if x in variables:
                n = np.bincount(columns[variables.index(x)], minlength=self.width)
                most = np.maximum(most, n)
        return lambda c, most=most: most[c]

    def _weights(self, names: list[str], columns: list[np.ndarray]) -> np.ndarray:
        """The support of each key: that of its rarest value."""
        return np.min([self.support[x](c) for x, c in zip(names, columns)], axis=0) if names else np.zeros(1, np.int64)

    def _unpacked(self, key: int) -> tuple[int, ...]:
        """Node and values of a packed key."""
        key, c = divmod(key, len(self.td))
        out = []
        for _ in range(max(1, len(self.td.adhesion(c)))):
            key, x = divmod(key, self.width)
            out.append(x)
        return c, *out[::-1]

    def start(self) -> Block:
        return Block({}, {a: np.zeros(1, np.int64) for a in range(len(self.tries))}, 1)

    def allowed(self, block: Block, x: str) -> Iterator[tuple[np.ndarray, np.ndarray, dict[int, np.ndarray]]]:
        """Rows of the block, values of x that all its atoms allow them, and the trie nodes reached; each row asks the
        atom that offers fewest."""
        sides = [(a, self.variables[a].index(x)) for a in range(len(self.tries)) if x in self.variables[a]]
        low = np.stack([self.tries[a].starts[k][block.nodes[a]] for a, k in sides])
        size = np.stack([self.tries[a].starts[k][block.nodes[a] + 1] for a, k in sides]) - low
        by = size.argmin(0)
        for p, (a, k) in enumerate(sides):
            rows = np.flatnonzero((by == p) & (size[p] > 0))
            if not len(rows):
                continue
            n = size[p][rows]
            src = np.repeat(rows, n)
            child = np.repeat(low[p][rows] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            value, found = self.tries[a].values[k][child], {a: child}
            self.counters["rows_touched"] += len(src)
            for q, (b, j) in enumerate(sides):
                if q == p or not len(src):
                    continue
                keys = self.tries[b].keys[j]
                want = block.nodes[b][src] * self.width + value
                at = np.minimum(np.searchsorted(keys, want), max(len(keys) - 1, 0))
                self.counters["trie_probes"] += len(want) * max(1, int(len(keys)).bit_length())
                ok = np.flatnonzero(keys[at] == want) if len(keys) else np.empty(0, np.int64)
                found = {m: c[ok] for m, c in found.items()} | {b: at[ok]}
                src, value = src[ok], value[ok]
            if len(src):
                yield src, value, found

    def extend(self, block: Block, x: str) -> Block:
        """Every row with every value of x that all its atoms allow."""
        parts = list(self.allowed(block, x))
        if not parts:
            return block.take(np.empty(0, np.int64))
        src = np.concatenate([p[0] for p in parts])
        out = block.take(src)
        out.columns[x] = np.concatenate([p[1] for p in parts])
        for a in parts[0][2]:
            out.nodes[a] = np.concatenate([p[2][a] for p in parts])
        return out

    def grow(self, block: Block, names: list[str]) -> Iterator[Block]:
        """Blocks with all names bound, depth first, so that only one block for each variable is held."""
        if not names:
            if self.scalar:
                for k in range(block.n):
                    yield block.take(np.array([k]))
            elif block.n:
                yield block
            return
        for lo, hi in self.stretches(block, names[0]):
            after = self.extend(block.take(slice(lo, hi)), names[0])
            if after.n:
                yield from self.grow(after, names[1:])

    def stretches(self, block: Block, x: str) -> Iterator[tuple[int, int]]:
        """Cuts of the block into block_rows rows at most, that have so many values of x to try at most, or a single row."""
        step, lo = max(1, self.block_rows), 0
        fewest = None
        for a, variables in enumerate(self.variables):
            if x in variables:
                starts, nodes = self.tries[a].starts[variables.index(x)], block.nodes[a]
                n = starts[nodes + 1] - starts[nodes]
                fewest = n if fewest is None else np.minimum(fewest, n)
        ends = np.cumsum(fewest)
        while lo < block.n:
            before = int(ends[lo - 1]) if lo else 0
            hi = min(lo + step, max(lo + 1, int(np.searchsorted(ends, before + step, side="right"))))
            yield lo, hi
            lo = hi

    def solve(self, v: int, block: Block) -> np.ndarray:
        """For every row of the block, the number of extensions to the subtree of v."""
        out, names, children = np.zeros(block.n, np.int64), self.owned[v], self.td.children(v)
        tagged = Block(block.columns | {"": np.arange(block.n)}, block.nodes, block.n)
        if not children and names and not self.scalar:  # the last variable's values are counted where they are found
            for rows in self.grow(tagged, names[:-1]):
                for lo, hi in self.stretches(rows, names[-1]):
                    part = rows.take(slice(lo, hi))
                    for src, _, _ in self.allowed(part, names[-1]):
                        out += np.bincount(part.columns[""][src], minlength=block.n)
            return out
        for rows in self.grow(tagged, names):
            factor = np.ones(rows.n, np.int64)
            for c in children:
                live = np.flatnonzero(factor)  # a zero stays a zero
                if len(live):
                    counts = self.recall(c, rows.take(live) if len(live) < rows.n else rows)
                    if float(factor[live].max()) * float(counts.max(initial=0)) > 9e18:
                        raise OverflowError("count beyond 64 bits; use the frontier executor with decimal counts")
                    factor[live] *= counts
            sums = np.bincount(rows.columns[""], factor.astype(np.float64), block.n)
            if len(sums) and float(out.max(initial=0)) + sums.max() > 9e18:
                raise OverflowError("count beyond 64 bits; use the frontier executor with decimal counts")
            np.add.at(out, rows.columns[""], factor)
        return out

    def recall(self, c: int, rows: Block) -> np.ndarray:
        """Counts of node c for every row, from the memo where policy and room allow."""
        names = sorted(self.td.adhesion(c))
        if self.policy.resize:
            self.memo.resize(int(self.policy.resize(time.monotonic() - self.began, self.memo.size)))
        if not self.policy.caches(c, names) or not self.memo.room():
            return self.solve(c, rows)
        columns = [rows.columns[x] for x in names]
        admitted = self.memo.mask(c, columns, names) if columns else np.ones(rows.n, bool)
        out = np.empty(rows.n, np.int64)
        rest = np.flatnonzero(~admitted)
        at = np.flatnonzero(admitted)
        if len(at):
            if self.packs:
                packed = np.zeros(len(at), np.int64)
                for k in columns:
                    packed = packed * self.width + (k[at] if len(at) < rows.n else k)
                keys, first, back = np.unique(packed * len(self.td) + c, return_index=True, return_inverse=True)
                values = self.memo.find(keys)
            else:
                packed = np.stack([k[at] for k in columns], axis=1) if columns else np.zeros((len(at), 1), np.int64)
                keys, first, back = np.unique(packed, axis=0, return_index=True, return_inverse=True)
                back = back.reshape(-1)
                values = np.array([-1 if (g := self.memo.get((c, *k))) is None else g for k in keys.tolist()], np.int64)
            self.counters["memo_lookups"] += len(at)
            missing = np.flatnonzero(values < 0)
            found, weight = len(keys) - len(missing), np.zeros(len(missing), np.int64)
            if self.support and len(missing):
                weight = self._weights(names, [k[at[first[missing]]] for k in columns])
            room = self.memo.shareable(found)
            if room is not None and len(missing) > room:  # what no entry is free for is solved row by row
                kept = np.lexsort((first[missing], -weight))[:room]
                missing, weight = missing[kept], weight[kept]
            if len(missing):
                self.memo.note(found + len(missing))
                values[missing] = self.solve(c, rows.take(at[first[missing]]))
                if self.packs:
                    self.counters["memo_stores"] += self.memo.fill(keys[missing], values[missing])
                else:
                    for k, w in zip(missing.tolist(), weight.tolist()):
                        self.counters["memo_stores"] += self.memo.put((c, *keys[k].tolist()), int(values[k]), w)
            out[at] = values[back]
            unsolved = at[values[back] < 0]  # admitted, but the memo is full: row by row, as without a memo
            hits = len(at) - len(unsolved) - len(missing)
            self.counters[f"hits_{c}"] += hits
            self.counters[f"misses_{c}"] += len(missing) + len(unsolved)
            rest = np.concatenate([rest, unsolved])
        if len(rest):
            out[rest] = self.solve(c, rows.take(rest))
        return out

    def count(self, block: Block | None = None) -> int:
        return int(self.solve(0, block or self.start())[0])

    def rows(self, block: Block | None = None) -> Iterator[dict[str, np.ndarray]]:
        """Result rows in blocks (plain evaluation)."""
        for b in self.grow(block or self.start(), list(self.order)):
            yield b.columns

    def metrics(self) -> dict[str, int]:
        c = self.counters
        return dict(c) | {"accesses": c["trie_probes"] + c["rows_touched"] + c["memo_lookups"] + c["memo_stores"], "entries_peak": self.memo.peak, "evicted": self.memo.evicted}


def bounded() -> CachePolicy:
    """What holds where no policy is given."""
    return CachePolicy.always().capacity(MEMO_ENTRIES).evict("fifo")


def _arranged(variables, order):
    return tuple(sorted(variables, key=list(order).index))


class Numbers:
    """Values of each variable as dense numbers, in the order of values."""

    def __init__(self, tables: list[tuple[tuple[str, ...], pa.Table]]):
        self.values: dict[str, np.ndarray] = {}
        for variables, t in tables:
            for x in variables:
                v = np.unique(t.column(x).to_numpy())
                self.values[x] = np.unique(np.concatenate([self.values[x], v])) if x in self.values else v
        self.width = max(1, max((len(v) for v in self.values.values()), default=1))

    def encode(self, x: str, t: pa.Table) -> np.ndarray:
        return np.searchsorted(self.values[x], t.column(x).to_numpy()).astype(np.int64)


def _gather(query, catalog, order, most_rows):
    """The atoms' rows on the driver, after their number and bytes have been checked. Atoms of one relation and one
    pattern of terms are read once."""
    tables, held, known = [], 0, {}
    for a, (variables, df) in zip(query.atoms, atom_tables(query, catalog)):
        if not variables:
            if not df.take(1):
                return None
            continue
        shape = (a.relation, tuple(variables.index(t) if isinstance(t, str) else t for t in a.terms), tuple((x, c) for x, c in query.selections if x in variables))
        if shape not in known:
            wide = sum((F.octet_length(x) if df.schema[x].dataType.simpleString() == "string" else F.lit(8) for x in variables), F.lit(0))
            n, size = df.limit(most_rows + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(wide.cast("long")), F.lit(0))).first()
            known[shape] = n, size, None
        n, size, t = known[shape]
        held += size
        if n > most_rows - sum(t.num_rows for _, t in tables):
            raise ValueError(f"relations of more than {most_rows} rows do not fit every task; use the hypercube or the frontier executor")
        if held > BROADCAST_BYTES:
            raise ValueError(f"relations of more than {BROADCAST_BYTES} bytes do not fit every task; use the hypercube or the frontier executor")
        t = df.toArrow() if t is None else t
        known[shape] = n, size, t
        tables.append((_arranged(variables, order), t.rename_columns(list(variables))))
    return tables


def kernel_run(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD | None = None, order=None, policy: CachePolicy | None = None, parts: int = 8, block_rows: int = BLOCK_ROWS, scalar: bool = False, most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """kind, name, value: the tasks' counts and counters. td None: the plain join (one bag)."""
    if query.comparisons:
        raise ValueError("comparisons between variables need the frontier executor")
    td = td or OrderedTD.single(query)
    order, policy = check_plan(query, td, order), policy or bounded()
    spark = next(iter(catalog.relations.values())).sparkSession
    tables = _gather(query, catalog, order, most_rows)
    if tables is None:
        return spark.createDataFrame([("count", "cnt", 0)], "kind string, name string, value long").select("kind", "name", F.col("value").cast("decimal(38,0)"))
    numbers = Numbers(tables)
    atoms = [(v, [numbers.encode(x, t) for x in v]) for v, t in tables]
    shared = spark.sparkContext.broadcast((atoms, numbers.width))

    def run(batches):
        for batch in batches:
            atoms, width = shared.value
            for part in batch.column(0).to_pylist():
                mine = [(v, _share(v, c, order[0], part, parts)) for v, c in atoms]
                k = Kernel(mine, order, td, policy, width, block_rows, scalar)
                yield _report(k.count(), k.metrics())

    return spark.range(0, parts, 1, parts).mapInArrow(run, OUT)


def _share(variables, columns, first, part, parts):
    """The atom's rows whose value of the first variable falls to this part."""
    if first not in variables:
        return columns
    keep = columns[variables.index(first)] % parts == part
    return [c[keep] for c in columns]


def _report(count: int, metrics: dict[str, int]) -> pa.RecordBatch:
    from decimal import Decimal

    rows = [("count", "cnt", count), *(("metric", k, v) for k, v in sorted(metrics.items()))]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows]), pa.array([Decimal(int(r[2])) for r in rows], pa.decimal128(38, 0))], ["kind", "name", "value"])


def kernel_count(*args, **options) -> DataFrame:
    """One row: cnt."""
    return kernel_run(*args, **options).where("kind = 'count'").agg(F.coalesce(F.sum("value"), F.lit(0)).cast("long").alias("cnt"))


def kernel_metrics(*args, **options) -> DataFrame:
    """name, total, most: counters added up over tasks, and the largest task's."""
    return kernel_run(*args, **options).groupBy("kind", "name").agg(F.sum("value").cast("long").alias("total"), F.max("value").cast("long").alias("most"))


def kernel_evaluate(query: ConjunctiveQuery, catalog: Catalog, order=None, parts: int = 8, block_rows: int = BLOCK_ROWS, most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Every result row of the plain join, given out block by block; keys must be integers or strings."""
    td = OrderedTD.single(query)
    order = check_plan(query, td, order)
    tables = _gather(query, catalog, order, most_rows)
    spark = next(iter(catalog.relations.values())).sparkSession
    kinds = {x: f for v, df in atom_tables(query, catalog) for x, f in zip(df.columns, df.schema.fields)}
    schema = ", ".join(f"{x} {kinds[x].dataType.simpleString()}" for x in order)
    if tables is None:
        return spark.createDataFrame([], schema)
    numbers = Numbers(tables)
    shared = spark.sparkContext.broadcast(([(v, [numbers.encode(x, t) for x in v]) for v, t in tables], numbers))

    def run(batches):
        for batch in batches:
            atoms, numbers = shared.value
            for part in batch.column(0).to_pylist():
                k = Kernel([(v, _share(v, c, order[0], part, parts)) for v, c in atoms], order, td, CachePolicy.never(), numbers.width, block_rows)
                for rows in k.rows():
                    yield pa.RecordBatch.from_arrays([pa.array(numbers.values[x][rows[x]]) for x in order], list(order))

    return spark.range(0, parts, 1, parts).mapInArrow(run, schema).select(*query.variables)


def shares_for(query: ConjunctiveQuery, sizes: list[int], cells: int, prefer=frozenset()) -> dict[str, int]:
    """Shares of the variables with a product of at most cells that ship fewest tuples; ties favour preferred variables."""
    names, best = list(query.variables), None

    def cost(shares):
        return sum(n * int(np.prod([p for x, p in shares.items() if x not in a.variables], initial=1)) for a, n in zip(query.atoms, sizes)) / np.prod(list(shares.values()))

    def search(k, left, shares):
        nonlocal best
        if k == len(names):
            used = int(np.prod(list(shares.values())))
            if 2 * used > cells or used == cells:
                c = (cost(shares), -sum(np.log2(p) for x, p in shares.items() if x in prefer), sorted(shares.items()))
                best = c if best is None or c < best else best
            return
        p = 1
        while p <= left:
            search(k + 1, left // p, shares | {names[k]: p})
            p *= 2

    search(0, cells, {})
    return dict(best[2])


def atom_size(atom, catalog: Catalog, query: ConjunctiveQuery) -> tuple[int, int, dict[str, int]]:
    """Rows, and by estimate distinct ones and the distinct values of each variable: one pass without a shuffle of rows."""
    df = normalise(atom, catalog, query, distinct=False)
    whole = F.approx_count_distinct(F.struct(*atom.variables), 0.02)
    rows, distinct, *values = df.agg(F.count(F.lit(1)), whole, *[F.approx_count_distinct(x) for x in atom.variables]).first()
    return rows, max(1, min(rows, distinct)), dict(zip(atom.variables, values))


def prefixes(distinct: int, values: dict[str, int]) -> dict[frozenset, float]:
    """Distinct bindings of every subset of an atom's variables, at most what its values and its rows allow."""
    subsets = [frozenset(x for i, x in enumerate(values) if m >> i & 1) for m in range(1 << len(values))]
    return {s: float(distinct if len(s) == len(values) else min(distinct, np.prod([float(values[x]) for x in s], initial=1.0))) for s in subsets}


def best_root(td: OrderedTD, query: ConjunctiveQuery, stats: Stats) -> OrderedTD:
    """The decomposition from the root at which fewest bindings are tried, by estimate; as it is, if none is better."""
    roots = [td, *(td.reroot(v) for v in td.preorder()[1:])]
    return min((r for r in roots if all(map(r.owned, r.preorder()))), key=lambda t: cost.memo_order_cost(t, default_order(t), query, stats))


def hypercube_count(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD | None = None, order=None, policy: CachePolicy | None = None, cells: int | None = None, shares: dict[str, int] | None = None, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """One row, cnt, without sending whole relations to any task: each tuple goes to the cells that agree with the
    hashes of its variables, and each cell joins its own tuples. Keys must be integers (encode strings first).

    Cells are 16, or twice that as often as it takes for CELL_ROWS rows a cell, if rows were dealt without copies. Where
    neither order nor policy is given, the decomposition's root is the node from which fewest bindings are expected."""
    td, given = td or OrderedTD.single(query), order
    order, policy, free = check_plan(query, td, order), policy or bounded(), policy is None and not given and not query.comparisons
    known = [(k, a.variables, atom_size(a, catalog, query)) for k, a in enumerate(query.atoms) if a.variables]
    if free and len(td) > 1:
        td = best_root(td, query, Stats({k: prefixes(distinct, values) for k, _, (_, distinct, values) in known}))
        order = default_order(td)
    # a cell keeps equal rows once, so only those that are often repeated are made distinct before
    atoms = [(v, normalise(query.atoms[k], catalog, query, distinct=rows > 1.5 * distinct)) for k, v, (rows, distinct, _) in known]
    if not shares:
        stats = [distinct for _, _, (_, distinct, _) in known]
        if cells is None:
            cells = 16
            while sum(stats) > cells * CELL_ROWS:
                cells *= 2
        prefer = frozenset().union(*(td.adhesion(v) for v in td.preorder()))
        shares = shares_for(query, stats, cells, prefer)
    names, most = list(query.variables), max(len(v) for v, _ in atoms)
    cells = cells or max(16, int(np.prod(list(shares.values()))))
    union = None
    for k, (variables, df) in enumerate(atoms):
        v = _arranged(variables, order)
        cols = [F.col(v[j]).cast("long") if j < len(v) else F.lit(None).cast("long") for j in range(most)]
        one = df.select(F.explode(cell_ids(names, list(v), shares)).alias("cell"), F.lit(k).alias("atom"), *[c.alias(f"c{j}") for j, c in enumerate(cols)])
        union = one if union is None else union.unionByName(one)
    arranged = [_arranged(v, order) for v, _ in atoms]

    def run(batches):
        held: list[pa.RecordBatch] = []

        def join():
            t = pa.Table.from_batches(held)
            which = t.column("atom").to_numpy()
            parts = [[t.column(f"c{j}").filter(pa.array(which == k)).to_numpy().astype(np.int64) for j in range(len(v))] for k, v in enumerate(arranged)]
            values: dict[str, np.ndarray] = {}
            for v, cols in zip(arranged, parts):
                for x, c in zip(v, cols):
                    values[x] = np.union1d(values[x], c) if x in values else np.unique(c)
            width = max(1, *(len(c) for c in values.values()))
            k = Kernel([(v, [np.searchsorted(values[x], c) for x, c in zip(v, cols)]) for v, cols in zip(arranged, parts)], order, td, policy, width, block_rows)
            return _report(k.count(), k.metrics())

        for batch in batches:
            if not batch.num_rows:
                continue
            cell = batch.column(0).to_numpy()
            edges = [0, *(np.flatnonzero(cell[1:] != cell[:-1]) + 1).tolist(), len(cell)]
            for lo, hi in zip(edges[:-1], edges[1:]):
                if held and held[0].column(0)[0].as_py() != cell[lo]:
                    yield join()
                    held = []
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield join()

    dealt = union.repartitionById(cells, F.col("cell").cast("int"))
    if int(np.prod(list(shares.values()))) > cells:  # else each task has one cell
        dealt = dealt.sortWithinPartitions("cell")
    out = dealt.mapInArrow(run, OUT)
    return out.where("kind = 'count'").agg(F.coalesce(F.sum("value"), F.lit(0)).cast("long").alias("cnt"))


def bagtree_rows(query: ConjunctiveQuery, catalog: Catalog, td: OrderedTD, bags: list[tuple[list[str], list[tuple[int, tuple[str, ...]]]]], first: str, block_rows: int = BLOCK_ROWS) -> DataFrame | None:
    """kind, name, value as of kernel_run: the bags of a tree joined whole, each by itself, and counted bottom up by shared
    keys. Tasks get ranges of values of `first`, a variable of every bag, so equal keys meet in one task.

    bags: for each node its order of variables, and its atoms by number with those of their variables that it has.
    """
    tables = _gather(query, catalog, query.variables, BROADCAST_ROWS)
    spark = next(iter(catalog.relations.values())).sparkSession
    if tables is None:
        return None
    numbers = Numbers(tables)
    at = iter(tables)
    atoms = [{x: numbers.encode(x, t) for x in a.variables} if a.variables and (t := next(at)[1]) is not None else {} for a in query.atoms]
    width, n = numbers.width, len(numbers.values[first])
    span = max(1, min(TALLY_ENTRIES // width, -(-n // (4 * spark.sparkContext.defaultParallelism))))
    ranges = -(-n // span)
    shared = spark.sparkContext.broadcast(atoms)

    def run(batches):
        for batch in batches:
            for k in batch.column(0).to_pylist():
                total = BagTree(shared.value, td, bags, first, width, (k * span, min(n, (k + 1) * span)), block_rows).up(0)
                yield _report(int(total[0]), {})

    return spark.range(0, max(1, ranges), 1, max(1, ranges)).where(F.col("id") < ranges).mapInArrow(run, OUT)


class BagTree:
    """The bags of a tree over a range of values of a variable that all of them have."""

    def __init__(self, atoms, td, bags, first, width, span, block_rows):
        self.atoms, self.td, self.bags, self.first, self.width, self.span, self.block_rows = atoms, td, bags, first, width, span, block_rows

    def places(self, v: int, rows: dict[str, np.ndarray], n: int) -> np.ndarray:
        """Where the tally of node v keeps the rows' keys."""
        out = np.zeros(n, np.int64)
        if v:
            out += rows[self.first] - self.span[0]
            for x in sorted(self.td.adhesion(v) - {self.first}):
                out = out * self.width + rows[x]
        return out

    def up(self, v: int) -> np.ndarray:
        """Counts of the subtree of v for each key that it shares with its parent."""
        tallies = {c: self.up(c) for c in self.td.children(v)}
        names, parts = self.bags[v]
        mine = []
        for a, inside in parts:
            columns = [self.atoms[a][x] for x in _arranged(inside, names)]
            if self.first in inside:
                c = self.atoms[a][self.first]
                keep = (c >= self.span[0]) & (c < self.span[1])
                columns = [x[keep] for x in columns]
            mine.append((_arranged(inside, names), columns))
        k = Kernel(mine, names, OrderedTD((frozenset(names),), (-1,)), CachePolicy.never(), self.width, self.block_rows)
        out = np.zeros((self.span[1] - self.span[0]) * self.width ** (len(self.td.adhesion(v)) - 1) if v else 1, np.int64)
        bound = 0.0
        for rows in k.grow(k.start(), names):
            factor = np.ones(rows.n, np.int64)
            for c, tally in tallies.items():
                counts = tally[self.places(c, rows.columns, rows.n)]
                if float(factor.max()) * float(counts.max()) > 9e18:
                    raise OverflowError("count beyond 64 bits; use decimal counts")
                factor *= counts
            at, sums = self.places(v, rows.columns, rows.n), factor.sum(dtype=np.float64)
            bound += sums
            if bound > 9e18:  # of all keys together: now each key is looked at
                near = out.astype(np.float64)
                np.add.at(near, at, factor.astype(np.float64))
                if near.max() > 9e18:
                    raise OverflowError("count beyond 64 bits; use decimal counts")
            np.add.at(out, at, factor)
        return out
