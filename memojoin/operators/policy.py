"""Which sub-results are kept: admission by node, size of key, support or a given rule; capacity and replacement."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CachePolicy:
    """Admission holds for both executors; capacity, replacement and resizing are the kernel's, per task.

    The frontier executor's memo is a table that spills like any shuffle: it refuses bounds instead of ignoring them.
    """

    admit: str = "always"  # always, never, support, custom
    tau: int = 0
    rule: Callable | None = None
    only_nodes: frozenset[int] | None = None
    most_columns: int | None = None
    entries: int | None = None
    replacement: str = "none"  # none, fifo, lru, support
    resize: Callable | None = None

    @classmethod
    def always(cls) -> CachePolicy:
        return cls()

    @classmethod
    def never(cls) -> CachePolicy:
        return cls("never")

    @classmethod
    def support(cls, tau: int) -> CachePolicy:
        """Keep a key if each of its values occurs more than tau times in some atom."""
        return cls("support", tau)

    @classmethod
    def custom(cls, rule: Callable) -> CachePolicy:
        """rule(node, key columns as arrays) gives a mask; the frontier runs it over Arrow batches."""
        return cls("custom", rule=rule)

    def capacity(self, entries: int) -> CachePolicy:
        return replace(self, entries=entries)

    def evict(self, replacement: str) -> CachePolicy:
        if replacement not in ("none", "fifo", "lru", "support"):
            raise ValueError(replacement)
        return replace(self, replacement=replacement)

    def dynamic(self, resize: Callable) -> CachePolicy:
        """resize(seconds since the start, entries in use) gives the capacity from now on."""
        return replace(self, resize=resize)

    def nodes(self, nodes) -> CachePolicy:
        return replace(self, only_nodes=frozenset(nodes))

    def max_dimension(self, d: int) -> CachePolicy:
        return replace(self, most_columns=d)

    def caches(self, node: int, shared) -> bool:
        return self.admit != "never" and (self.only_nodes is None or node in self.only_nodes) and (self.most_columns is None or len(shared) <= self.most_columns)

    def needs_intermediate(self, td) -> set[int]:
        """The nodes whose intermediate results a run keeps: those with a memo, and all below one."""
        kept: set[int] = set()
        for v in td.preorder():
            if v and (td.parents[v] in kept or self.caches(v, sorted(td.adhesion(v)))):
                kept.add(v)
        return kept

    def pruned(self, td):
        """The decomposition without nodes that keep nothing: each is joined with its parent."""
        while True:
            kept = self.needs_intermediate(td)
            gone = [v for v in td.preorder() if v and v not in kept]
            if not gone:
                return td
            if self.only_nodes is not None:
                raise ValueError("nodes are chosen by number: prune the decomposition itself with merge()")
            td = td.merge(gone[-1])

    def check_frontier(self) -> None:
        if self.entries is not None or self.replacement != "none" or self.resize is not None:
            raise ValueError("capacity, replacement and resizing bound a task's memo: use the kernel executor")

    def admitted_rows(self, frontier, rows, shared, node: int = -1):
        """None if all rows are admitted, else (admitted, others)."""
        if self.admit == "custom" and shared:
            ask = F.pandas_udf(lambda *keys: pd.Series(np.asarray(self.rule(node, [k.to_numpy() for k in keys]), bool)), "boolean")
            marked = rows.withColumn("__admit", ask(*[F.col(x) for x in shared]))
            return marked.where("__admit").drop("__admit"), marked.where("NOT __admit").drop("__admit")
        if self.admit != "support" or not shared:
            return None
        for x in shared:
            counts = None
            for variables, df in frontier.atoms:
                if x in variables:
                    one = df.groupBy(x).agg(F.count(F.lit(1)).alias("__n"))
                    counts = one if counts is None else counts.unionByName(one)
            heavy = counts.groupBy(x).agg(F.max("__n").alias("__n")).where(F.col("__n") > self.tau).select(x, F.lit(True).alias(f"__h_{x}"))
            rows = rows.join(heavy, x, "left")
        flags = [F.coalesce(F.col(f"__h_{x}"), F.lit(False)) for x in shared]
        every = flags[0]
        for c in flags[1:]:
            every = every & c
        drop = [f"__h_{x}" for x in shared]
        return rows.where(every).drop(*drop), rows.where(~every).drop(*drop)


class MemoBudget:
    """A total of entries shared by the queries that run at a time."""

    def __init__(self, total: int):
        self.total, self.users = total, 0

    def share(self) -> Callable:
        """A resize rule that gives each user an equal part, whatever their number at the moment."""
        self.users += 1
        return lambda seconds, used: self.total // max(1, self.users)

    def release(self) -> None:
        self.users -= 1


class Memo:
    """One task's memo: keys of any width to counts, with capacity and replacement."""

    def __init__(self, policy: CachePolicy, support: dict | None = None):
        self.policy, self.entries, self.peak = policy, OrderedDict() if policy.replacement in ("fifo", "lru") else {}, 0  # the oldest is found at once
        self.weights: dict = {}
        self.limit = policy.entries
        self.support = support or {}
        self.evicted = 0

    def room(self) -> bool:
        return self.limit is None or self.limit > 0

    def shareable(self, held: int) -> int | None:
        """How many results a block may share beyond those that it found here; None: any number.

        Without replacement as many as still fit; otherwise what is found stays and the rest makes room.
        """
        if self.limit is None:
            return None
        return max(0, self.limit - (len(self.entries) if self.policy.replacement == "none" else held))

    def note(self, held: int) -> None:
        """Results that a block shares count as entries."""
        self.peak = max(self.peak, held)

    def get(self, key):
        got = self.entries.get(key)
        if got is not None and self.policy.replacement == "lru":
            self.entries.move_to_end(key)
        return got

    def put(self, key, value, weight: int = 0) -> bool:
        if self.limit is not None:
            while len(self.entries) >= self.limit:
                if self.policy.replacement == "none" or not self.entries:
                    return False
                if self.policy.replacement == "support":
                    gone = min(self.entries, key=lambda k: self.weights.get(k, 0))
                    if self.weights.get(gone, 0) >= weight:
                        return False
                else:
                    gone = next(iter(self.entries))
                del self.entries[gone]
                self.weights.pop(gone, None)
                self.evicted += 1
        self.entries[key] = value
        if self.policy.replacement == "support":
            self.weights[key] = weight
        self.peak = max(self.peak, len(self.entries))
        return True

    def resize(self, limit: int) -> None:
        self.limit = limit
        while len(self.entries) > limit:
            del self.entries[next(iter(self.entries))]
            self.evicted += 1

    @property
    def size(self) -> int:
        return len(self.entries)

    def mask(self, node: int, columns: list[np.ndarray], names: list[str]) -> np.ndarray:
        """Which keys the policy admits."""
        n = len(columns[0])
        if self.policy.admit == "custom":
            return np.asarray(self.policy.rule(node, columns), bool)
        if self.policy.admit == "support":
            out = np.ones(n, bool)
            for x, c in zip(names, columns):
                out &= self.support[x](c) > self.policy.tau
            return out
        return np.ones(n, bool)


class PackedMemo(Memo):
    """A memo of numbers for keys, asked and filled a block at a time: no replacement, or first in, first out.

    Entries are sorted runs of keys with their values and the turns at which they came in; whatever came before `floor`
    is gone. Runs of like size are merged, and what is gone leaves them then.
    """

    def __init__(self, policy: CachePolicy, support: dict | None, unpack: Callable):
        self.policy, self.support, self.unpack, self.limit = policy, support or {}, unpack, policy.entries
        self.runs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.turn = self.floor = self.peak = self.evicted = 0

    @property
    def entries(self) -> dict:
        """What it holds, for a look at it; by node and values."""
        return {self.unpack(k): v for have, values, turns in self.runs for k, v, t in zip(have.tolist(), values.tolist(), turns.tolist()) if t >= self.floor}

    @property
    def size(self) -> int:
        return self.turn - self.floor

    def shareable(self, held: int) -> int | None:
        if self.limit is None:
            return None
        return max(0, self.limit - (self.size if self.policy.replacement == "none" else held))

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The value of each of the sorted keys, -1 where it has none."""
        out = np.full(len(keys), -1, np.int64)
        for have, values, turns in self.runs:
            at = np.minimum(np.searchsorted(have, keys), len(have) - 1)
            hit = np.flatnonzero((have[at] == keys) & (turns[at] >= self.floor))
            out[hit] = values[at[hit]]
        return out

    def fill(self, keys: np.ndarray, values: np.ndarray) -> int:
        """Takes in keys that it does not hold, in their order; the number of those that found room."""
        n = len(keys)
        if self.limit is not None:
            if self.limit <= 0:
                return 0
            if self.policy.replacement == "none":
                n = min(n, max(0, self.limit - self.size))
            elif self.size + n > self.limit:
                self._forget(self.size + n - self.limit)
        if not n:
            return 0
        turns = np.arange(self.turn, self.turn + n)
        self.turn += n
        self.peak = max(self.peak, self.size)
        order = np.argsort(keys[:n], kind="stable")
        self.runs.append((keys[:n][order], values[:n][order], turns[order]))
        while len(self.runs) > 1 and len(self.runs[-2][0]) <= 2 * len(self.runs[-1][0]):
            last, before = self.runs.pop(), self.runs.pop()
            both = [np.concatenate(x) for x in zip(before, last)]
            live = np.flatnonzero(both[2] >= self.floor)
            order = live[np.argsort(both[0][live], kind="stable")]
            self.runs.append((both[0][order], both[1][order], both[2][order]))
        self.runs = [r for r in self.runs if len(r[0])]
        return n

    def _forget(self, n: int) -> None:
        self.floor += n
        self.evicted += n

    def resize(self, limit: int) -> None:
        self.limit = limit
        if self.size > limit:
            self._forget(self.size - limit)
