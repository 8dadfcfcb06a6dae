"""Helpers shared by the corpus operators."""

from __future__ import annotations

import ctypes
import hashlib
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The ASCII white space that separates words.
ASCII_SPACE = "\t\n\x0b\x0c\r "


def _give_memory_back() -> None:
    """Let large arrays return to the system when they are freed: Python workers live on for later stages.

    Fixed values: the numbers of glibc's mmap and trim thresholds. Other C libraries are left as they are.
    """
    set_option = getattr(ctypes.CDLL(None), "mallopt", None)
    if set_option:
        set_option(-3, 4 << 20)
        set_option(-1, 16 << 20)


_give_memory_back()


def give_back() -> None:
    """Give what this process has freed back to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def trimmed(run):
    """A function over batches that gives back what its worker has freed when it is done."""

    def each(batches):
        yield from run(batches)
        give_back()

    return each


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The folder that all executors share, spark.checkpoint.dir; an error where that is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return root.rstrip("/")


def scratch(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"


#: Tells Spark to drop an execution's shuffle files when it ends: what follows reads the written table.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: Rows sent to Python at a time. Texts make rows wide, and each batch stands in both processes.
BATCH, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", 1000
#: Bytes likewise, while a table is written: packets make few rows very wide.
WIDE, WIDE_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 4 << 20


def small_batches(spark: SparkSession) -> None:
    """Let the session send at most BATCH_ROWS rows to Python at a time, also for results that are run later."""
    if not 0 < int(spark.conf.get(BATCH)) <= BATCH_ROWS:
        spark.conf.set(BATCH, str(BATCH_ROWS))


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage with a Parquet table in the shared folder; the shuffle files behind it go at once."""
    spark = df.sparkSession
    path = scratch(spark, name)
    before = {k: spark.conf.get(k) for k in (CLEANUP, BATCH, WIDE)}
    spark.conf.set(CLEANUP, "true")
    spark.conf.set(WIDE, str(WIDE_BYTES))
    small_batches(spark)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def discard(*tables: DataFrame) -> None:
    """Remove tables of materialise() that nothing reads any more."""
    for t in tables:
        jvm = t.sparkSession._jvm
        at = jvm.org.apache.hadoop.fs.Path(t._scratch)
        at.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


def fold(doc_id: Column | str, n: int) -> Column:
    """crc32 of the id written as text, modulo n; null for a null id."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.pmod(F.crc32(c.cast("string").cast("binary")), F.lit(n))


def held_out(doc_id: Column | str, n: int, remainder: int) -> Column:
    """True where the fold is the held-out one; a null id is never held out."""
    return F.coalesce(fold(doc_id, n) == F.lit(remainder), F.lit(False))


def native_words(text: Column) -> Column:
    """The words of a text, split at ASCII white space; null has none."""
    spaced = F.translate(F.coalesce(text, F.lit("")), ASCII_SPACE[:-1], " " * 5)
    return F.array_remove(F.split(spaced, " "), "")


def hash_sample(df: DataFrame, by: str, per_group: int, key: str, most_groups: int = 1000) -> DataFrame:
    """Rows kept by a hash of key, at a rate that gives about per_group rows for each value of by.

    The rate comes from one count for each group (at most most_groups values, else an error), so the
    expected size is bounded whatever the input; no sort, no window. Rows with a null in by are left out. A null key
    is replaced by the text, where df has one; where very many rows share one key, a limit of eight times the expected
    size holds.
    """
    counts = df.where(F.col(by).isNotNull()).groupBy(by).count().limit(most_groups + 1).collect()
    if len(counts) > most_groups:
        raise ValueError(f"more than {most_groups} values of {by}")
    keep = F.lit(False)
    name = F.xxhash64(F.col(key), F.lit(by))
    if "text" in df.columns:
        name = F.when(F.col(key).isNull(), F.xxhash64("text")).otherwise(name)
    u = F.pmod(name, F.lit(1 << 30))
    for value, n in counts:
        rate = min(1.0, per_group / n)
        keep = keep | ((F.col(by) == F.lit(value)) & (u < F.lit(int(rate * (1 << 30)))))
    return df.where(keep).limit(8 * per_group * max(len(counts), 1))


def ascii_words(text: str | None) -> list[bytes]:
    """The same words in Python, with A-Z lowered: bytes methods know ASCII only."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def texts_of(batch: pa.RecordBatch, column: str = "text"):
    return batch.column(batch.schema.get_field_index(column)).to_pylist()


def dealt(df: DataFrame, n: int, number: Column) -> DataFrame:
    """Rows to n partitions by a number from 0 to n - 1, each number to a partition of its own.

    Partitions come from a hash, so each number is replaced by one whose hash falls into the partition meant.
    """
    spark, labels, tried = df.sparkSession, {}, 0
    while len(labels) < n:
        some = spark.range(tried, tried + 16 * n + 64).select("id", F.pmod(F.hash(F.col("id").cast("int")), F.lit(n)).alias("at"))
        for r in some.groupBy("at").agg(F.min("id").alias("id")).collect():
            labels.setdefault(r["at"], r["id"])
        tried += 16 * n + 64
    names = F.array(*[F.lit(int(labels[k])).cast("int") for k in range(n)])
    return df.repartition(n, F.element_at(names, (number + 1).cast("int")))


class WordHasher:
    """64-bit hashes of the words of whole texts, straight from Arrow's buffers.

    A word's hash is a polynomial over random numbers for its bytes, taken from prefix sums of a stretch of text, so
    it depends on the word alone. With lower, A-Z count as a-z.
    """

    STRETCH = 1 << 17

    def __init__(self, lower: bool = False):
        rng = np.random.default_rng(29)
        self.byte = rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        if lower:
            self.byte[65:91] = self.byte[97:123]
        self.space = np.zeros(256, bool)
        self.space[list(ASCII_SPACE.encode())] = True
        self.base = int(rng.integers(1 << 40, 1 << 62)) * 2 + 1
        self.inverse = pow(self.base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def _reach(self, n: int) -> None:
        if len(self.up) < n:
            for name, by in (("up", self.base), ("down", self.inverse)):
                x = np.full(max(n, self.STRETCH + 1), by, np.uint64)
                x[0] = 1
                setattr(self, name, np.cumprod(x))

    def _words(self, data: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Where words start and end, in turn; texts start at starts, and words end there."""
        gap = data - np.uint8(9) < 5  # arithmetic takes less time than a look at self.space
        gap |= data == 32
        ends = np.flatnonzero(gap[1:] != gap[:-1]) + 1
        inner = starts[starts > 0]
        joint = np.repeat(np.unique(inner[~(gap[inner - 1] | gap[inner])]), 2)
        if len(joint):  # one text's word ends where the next text's begins
            ends = np.insert(ends, np.searchsorted(ends, joint), joint)
        return np.concatenate([[0] if not gap[0] else [], ends, [len(data)] if not gap[-1] else []]).astype(np.int64)

    def _stretch(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes and positions of the words of a stretch, which is not empty."""
        ends = self._words(data, starts)
        at = ends[::2].copy()
        self._reach(len(data) + 1)
        sums = np.zeros(len(data) + 1, np.uint64)
        terms = self.byte.take(data, mode="clip")
        terms *= self.up[: len(data)]
        np.cumsum(terms, out=sums[1:])
        sums = sums.take(ends)
        h = (sums[1::2] - sums[::2]) * self.down[at]
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        return h ^ (h >> np.uint64(32)), at

    def hashes(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words of a string column, text by text, and how many each text has (null: none)."""
        column = column.cast(pa.large_binary()).fill_null(b"")
        n = len(column)
        offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
        raw = column.buffers()[2]
        data = np.frombuffer(raw, np.uint8)[offsets[0] : offsets[-1]] if raw is not None else np.empty(0, np.uint8)
        offsets = offsets - offsets[0]
        lo, found, where = 0, [], []
        while lo < len(data):
            hi = min(lo + self.STRETCH, len(data))
            if hi < len(data):  # end a stretch behind white space or between texts
                text = int(offsets[np.searchsorted(offsets, hi, side="right") - 1])
                gaps = np.flatnonzero(self.space[data[max(lo, text) : hi]])
                if len(gaps):
                    hi = max(lo, text) + int(gaps[-1]) + 1
                elif text > lo:
                    hi = text
                else:
                    ahead = np.flatnonzero(self.space[data[hi:]])
                    hi = min(hi + int(ahead[0]) + 1 if len(ahead) else len(data), int(offsets[np.searchsorted(offsets, hi)]))
            inside = offsets[np.searchsorted(offsets, lo) : np.searchsorted(offsets, hi)] - lo
            h, at = self._stretch(data[lo:hi], inside)
            found.append(h)
            where.append(at + lo)
            lo = hi
        h = np.concatenate(found) if found else np.empty(0, np.uint64)
        at = np.concatenate(where) if where else np.empty(0, np.int64)
        return h, np.diff(np.searchsorted(at, offsets))


class ChunkHasher(WordHasher):
    """Other 64-bit hashes of words, eight bytes at a time, in less time where words are short."""

    #: Words beyond so many bytes are hashed one by one.
    LONG = 256

    def __init__(self):
        super().__init__()
        self.low = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)

    @staticmethod
    def _mixed(h: np.ndarray) -> np.ndarray:
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(32)
        return h

    def _stretch(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ends = self._words(data, starts)
        at, size = ends[::2].copy(), ends[1::2] - ends[::2]
        padded = np.zeros(len(data) + 8, np.uint8)
        padded[:-8] = data
        eight = np.ndarray(len(data) + 1, "<u8", padded, strides=(1,))  # the eight bytes from any place on
        h = eight[at]
        h &= self.low.take(size, mode="clip")
        h += size.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        h = self._mixed(h)
        more = np.flatnonzero(size > 8)
        for k in range(8, self.LONG, 8):
            if not len(more):
                break
            left = size[more] - k
            h[more] = self._mixed(h[more] * np.uint64(0xD6E8FEB86659FD93) + (eight[at[more] + k] & self.low.take(left, mode="clip")))
            more = more[left > 8]
        for k in more:
            h[k] = int.from_bytes(hashlib.blake2b(padded[at[k] : at[k] + size[k]].tobytes(), digest_size=8).digest(), "little")
        return h, at
