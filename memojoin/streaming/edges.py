"""Edges from an events stream."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

EDGE = "s long, t long, ts timestamp"


def _timed(df: DataFrame) -> DataFrame:
    """Event times as timestamps with a zone, which watermarks need."""
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_edges(events: DataFrame, source: str, target: str, delay: str = "1 hour") -> DataFrame:
    """Distinct edges; the same edge again within the delay is dropped, later than the watermark too."""
    e = _timed(events).withWatermark("ts", delay).select(F.col(source).alias("s"), F.col(target).alias("t"), "ts").dropna()
    return e.dropDuplicatesWithinWatermark(["s", "t"]) if events.isStreaming else e.dropDuplicates(["s", "t"])


def windowed_edges(edges: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """start, end, s, t, n: edges with their number in tumbling, sliding or session windows."""
    w = F.session_window("ts", size) if kind == "session" else F.window("ts", size, slide if kind == "sliding" else None)
    out = _timed(edges).withWatermark("ts", delay).groupBy(w.alias("w"), "s", "t").agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "s", "t", "n")


def _last(key, frames: Iterator[pd.DataFrame], state):
    rows = pd.concat(list(frames)).sort_values(["ts", "node"], kind="stable")
    before = state.get[0] if state.exists else None
    nodes = rows["node"].tolist()
    state.update((int(nodes[-1]),))
    out = [(b, n, t) for b, n, t in zip([before, *nodes[:-1]], nodes, rows["ts"]) if b is not None]
    yield pd.DataFrame(out, columns=["s", "t", "ts"]).astype({"s": "int64", "t": "int64"})


def transitions(events: DataFrame, key: str, node: str, delay: str = "1 hour") -> DataFrame:
    """s, t, ts: from each node to the key's next one. Streams keep the key's last node as state (windows over rows
    are not to be had there); within a batch rows go by time."""
    rows = _timed(events).select(F.col(key).cast("string").alias("k"), F.col(node).cast("long").alias("node"), "ts").dropna()
    return rows.withWatermark("ts", delay).groupBy("k").applyInPandasWithState(_last, EDGE, "last long", "append", "NoTimeout")


def late_rows(query) -> int:
    """Rows that a running or ended streaming query has dropped as later than its watermark, over recent batches."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])
