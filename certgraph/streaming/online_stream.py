"""The online certificate on live streams: one graph for each key, state per graph, admitted edges appended.

An admitted edge is final, since the certificate only grows; so output is append-only, and any order of arrival is a legal
stream: a late edge is admitted or rejected when it comes. A watermark matters for windowed graphs only.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from certgraph.functions.graph_kernels import OnlineCertificate

ADMITTED = "graph string, seq long, u long, v long, kept_so_far long"


class _Admission(StatefulProcessor):
    """Keeps a graph's admitted edges; offers the edges of a micro-batch in order of seq."""

    def __init__(self, k: int, ttl_ms: int | None):
        self.k, self.ttl_ms = k, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.edges = handle.getMapState("edges", "u long, v long", "seq long", **({"ttlDurationMs": self.ttl_ms} if self.ttl_ms else {}))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        known = [(value[0], pair[0], pair[1]) for pair, value in self.edges.iterator()]
        c = OnlineCertificate(self.k, sorted(known))
        before = len(c.kept)
        for seq, u, v in sorted(r for part in rows for r in zip(part["seq"], part["u"], part["v"], strict=True)):
            c.offer((int(seq), int(min(u, v)), int(max(u, v))))
        new = c.kept[before:]
        for seq, u, v in new:
            self.edges.updateValue((u, v), (seq,))
        yield pd.DataFrame({"graph": [str(key[0])] * len(new), "seq": [s for s, _, _ in new], "u": [u for _, u, _ in new], "v": [v for _, _, v in new], "kept_so_far": range(before + 1, len(c.kept) + 1)})

    def close(self) -> None:
        pass


def online_certificate_stream(edges: DataFrame, k: int, graph: str | Column | None = None, ttl_ms: int | None = None) -> DataFrame:
    """Admitted edges (graph, seq, u, v, kept_so_far) of a streaming table (seq, u, v); needs the RocksDB state store.

    Loops and repeated edges are dropped. `graph` keys several graphs in one stream. State of graphs not seen for `ttl_ms`
    goes, where given.
    """
    key = F.lit("all") if graph is None else (F.col(graph) if isinstance(graph, str) else graph)
    rows = edges.filter("u IS NOT NULL AND v IS NOT NULL AND u <> v").select(key.cast("string").alias("graph"), "seq", "u", "v")
    return rows.groupBy("graph").transformWithStateInPandas(_Admission(k, ttl_ms), ADMITTED, "Append", "none")


def windowed_certificate(edges: DataFrame, k: int, time_col: str, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """One certificate for each event-time window of a streaming table (seq, u, v and a time); edges later than `late` drop."""
    timed = edges.withColumn("_t", F.col(time_col).cast("timestamp")).withWatermark("_t", late)
    keyed = timed.withColumn("_w", F.window("_t", length, slide) if slide else F.window("_t", length))
    return online_certificate_stream(keyed, k, F.col("_w.start").cast("string"))


def distinct_within(edges: DataFrame, time_col: str, late: str = "1 hour") -> DataFrame:
    """A stream without repeated edges among those that arrive within `late` of each other, in bounded state."""
    t = edges.withColumn("_t", F.col(time_col).cast("timestamp")).withWatermark("_t", late)
    return t.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "seq", "_t").dropDuplicatesWithinWatermark(["u", "v"]).withColumnRenamed("_t", time_col)


def session_graphs(edges: DataFrame, time_col: str, gap: str = "30 minutes") -> DataFrame:
    """Batch table of edges with `session`, the start of the pause-free run of the stream that the edge falls in."""
    t = edges.withColumn("_t", F.col(time_col).cast("timestamp"))
    runs = t.groupBy(F.session_window("_t", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("session"), F.col("w.end").alias("_end"))
    return t.join(runs, (F.col("_t") >= F.col("session")) & (F.col("_t") < F.col("_end"))).drop("_t", "_end")
