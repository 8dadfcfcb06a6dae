"""Columns that travel packed and are dealt to shards by ranges of keys."""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from memojoin.llm.common import dealt, trimmed

#: Texts of a slice at most.
MOST_TEXTS = 16_000
PACKED = "shard int, kind int, data binary"


#: Set in a packet's first byte if its first column holds differences.
RISING = 128


def pack(*columns: np.ndarray, rising: bool = False) -> bytes:
    """Columns as byte planes, compressed: sorted numbers and unused high bytes take little room.

    With rising, the first column is unsigned and never falls, and travels as differences.
    """
    head = [struct.pack("<B", len(columns) | RISING * rising), *(struct.pack("<cI", c.dtype.char.encode(), len(c)) for c in columns)]
    if rising:
        columns = np.diff(columns[0], prepend=columns[0].dtype.type(0)), *columns[1:]
    return zstandard.ZstdCompressor(level=1).compress(b"".join([*head, *map(_planes, columns)]))


def _planes(column: np.ndarray) -> np.ndarray:
    """The lowest bytes of all numbers, then the next ones: shifts take less time than to transpose."""
    size = column.dtype.itemsize
    numbers = np.ascontiguousarray(column).view(f"u{size}")
    out = np.empty((size, len(numbers)), np.uint8)
    for k in range(size):
        out[k] = numbers >> numbers.dtype.type(8 * k)
    return out


def unpack(data: bytes) -> list[np.ndarray]:
    """The columns, to be written to as well, also those of one row."""
    data = zstandard.ZstdDecompressor().decompress(data)
    kinds = [struct.unpack_from("<cI", data, 1 + 5 * k) for k in range(data[0] & ~RISING)]
    at, out = 1 + 5 * len(kinds), []
    for char, n in kinds:
        kind = np.dtype(char.decode()).newbyteorder("<")
        numbers = np.empty((n, kind.itemsize), np.uint8)
        for k in range(kind.itemsize):
            numbers[:, k] = np.frombuffer(data, np.uint8, n, at + k * n)
        out.append(numbers.view(kind).reshape(n))
        at += n * kind.itemsize
    if data[0] & RISING:
        out[0] = np.cumsum(out[0], dtype=out[0].dtype)
    return out


def rows_of(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary())], ["shard", "kind", "data"])


def shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    return ((keys >> np.uint64(24)) * np.uint64(shards)) >> np.uint64(32)


def by_ranges(keys: np.ndarray, shards: int, *columns: np.ndarray, rising: bool = False) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(shard, key and other columns by rising key) for each shard that has some: shards are ranges of keys."""
    if not rising:
        at = np.argsort(keys)
        keys, columns = keys[at], [c[at] for c in columns]
    cuts = np.searchsorted(shard_of(keys, shards), np.arange(shards + 1, dtype=np.uint64))
    for k in range(shards):
        if cuts[k] < cuts[k + 1]:
            part = slice(cuts[k], cuts[k + 1])
            yield k, [keys[part], *(c[part] for c in columns)]


def split(shard: np.ndarray, *columns: np.ndarray) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(shard, columns) for each shard that has some, in the order in which they come."""
    few = shard.astype(np.uint16) if shard.max(initial=0) < 1 << 16 else shard
    order = np.argsort(few, kind="stable")
    shard = shard[order]
    cuts = np.append(runs(shard), len(shard))
    for low, high in zip(cuts[:-1], cuts[1:]):
        yield int(shard[low]), [c[order[low:high]] for c in columns]


def by_shard(batches) -> Iterator[tuple[int, dict[int, list[list[np.ndarray]]]]]:
    """(shard, packets by kind) of a stream in the order of shards."""
    shard, held = None, {}
    for batch in batches:
        for k, kind, data in zip(*(batch.column(j).to_pylist() for j in range(3))):
            if k != shard:
                if held:
                    yield shard, held
                shard, held = k, {}
            held.setdefault(kind, []).append(unpack(data))
    if held:
        yield shard, held


def met(df: DataFrame, shards: int, run, low: int = 0) -> DataFrame:
    """run on the packets of each of so many shards from low on, with all that it gives."""

    def each(batches):
        for shard, packets in by_shard(batches):
            rows = run(shard, packets)
            for at in range(0, len(rows), 64):
                yield rows_of(rows[at : at + 64])

    return dealt(df, shards, F.col("shard") - low).sortWithinPartitions("shard", "kind").mapInArrow(trimmed(each), PACKED)


def joined(packets: list[list[np.ndarray]]) -> list[np.ndarray]:
    return [np.concatenate(c) for c in zip(*packets)]


def runs(*columns: np.ndarray) -> np.ndarray:
    """Where runs of equal rows of sorted columns start."""
    new = np.zeros(len(columns[0]), bool)
    new[:1] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return np.flatnonzero(new)


def slices(batches, column: int, bytes_each: int = 3 << 20):
    """Slices of batches with a bounded amount of text, or of one text."""
    for batch in batches:
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False))
        at = 0
        while at < batch.num_rows:
            before = size[at - 1] if at else 0
            end = max(at + 1, min(int(np.searchsorted(size, before + bytes_each, side="right")), at + MOST_TEXTS))
            yield batch.slice(at, end - at)
            at = end
