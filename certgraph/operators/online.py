"""The online certificate: an edge is kept iff fewer than k node-disjoint paths join its ends in what was kept before."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import LayeredFold, OnlineCertificate, folded_from_within
from certgraph.operators.components import component_parts
from certgraph.operators.forest import edge_batch, edge_chunks, in_order, merge_tree, parts_worth
from certgraph.plans.staging import Stages
from certgraph.schemas import EDGE

#: Edges that "rounds" folds in order before it filters the rest in parallel; `AHEAD` times as many as it keeps, once these are more.
HEAD = 2000
#: A kept edge takes more room, as a row and in two sets, than so many edges that are read on as arrays.
AHEAD = 4
#: Edges that "merge" folds at the top in stream order; more of them from the densest part outward, where few need a search.
FOLD_IN_ORDER = 1 << 16


def kept_batch(rows: list[tuple[int, int, int]]) -> pa.RecordBatch:
    return edge_batch(*(zip(*rows, strict=True) if rows else ((), (), ())))


def _folded(k: int):
    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = OnlineCertificate(k)
        for seq, u, v in edge_chunks(batches):
            before = len(c.kept)
            for e in zip(seq.tolist(), u.tolist(), v.tolist(), strict=True):
                c.offer(e)
            yield kept_batch(c.kept[before:])

    return local


def _thinned(k: int):
    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        thin = LayeredFold(k)
        for chunk in edge_chunks(batches):
            thin.offer(*chunk)
        yield edge_batch(*thin.settle()[0])

    return local


def _folded_at_the_top(k: int):
    """The online certificate of what is thinned already."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in edge_chunks(batches, sys.maxsize):
            if len(rows[0]) <= FOLD_IN_ORDER:
                c = OnlineCertificate(k)
                for e in sorted(zip(*(x.tolist() for x in rows), strict=True)):
                    c.offer(e)
                yield kept_batch(c.kept)
            else:
                keep = folded_from_within(*rows, k)
                yield edge_batch(*(x[keep] for x in rows))

    return local


def _thinned_and_folded(k: int):
    """The online certificate of the layered certificate of a part: a certificate of a certificate is one of the part."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _folded_at_the_top(k)(_thinned(k)(batches))

    return local


def online_certificate(edges: DataFrame, k: int, mode: str = "exact", head: int = HEAD, fan_in: int = 8) -> DataFrame:
    """(seq, u, v) of at most 2kn edges, k-connected iff the graph is.

    "exact": one pass, in stream order, in one task, since each decision depends on all before it; the task holds the certificate
    and a chunk of arrays. "rounds": the same rows, mostly in parallel: fold a head of the stream in order, then let all tasks drop every later
    edge whose ends already have k paths (the certificate only grows, so it would be rejected on arrival), and go on with
    the rest. "merge": one pass in parallel; parts are thinned to k scan-first forests, which takes no searches for paths, and
    unions again up a tree; what is left of all is folded at the top: a certificate but other rows. Components are parts of
    their own where none has most of the edges, as no path leaves one; no union is needed then. The last fold meets up to `FOLD_IN_ORDER` edges in order,
    more of them from the densest part outward, see `folded_from_within`. In each case a task holds O(kn) edges and a chunk.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    if mode == "exact":
        return in_order(edges, 1).mapInArrow(_folded(k), EDGE)
    if mode == "merge":
        stored = Stages(edges.sparkSession, "online").keep(edges.select("seq", "u", "v"), "edges")
        return merged_certificate(stored, k, component_parts(stored), fan_in)
    if mode != "rounds":
        raise ValueError("mode must be exact, rounds or merge")
    return online_rounds(edges, k, head)[0]


def merged_certificate(edges: DataFrame, k: int, parts: DataFrame | None, fan_in: int = 8, merged: DataFrame | None = None) -> DataFrame:
    """The rows of "merge" for a stored table; `parts` are its components, as `component_parts` deals them, `merged` what the tree leaves of it if that is known."""
    if parts is not None:
        return parts.mapInArrow(_thinned_and_folded(k), EDGE)
    if merged is not None:
        return in_order(merged, 1).mapInArrow(_folded_at_the_top(k), EDGE)
    return in_order(merge_tree(edges, _thinned(k), parts_worth(edges), fan_in=fan_in)).mapInArrow(_folded_at_the_top(k), EDGE)


def online_rounds(edges: DataFrame, k: int, head: int = HEAD) -> tuple[DataFrame, int]:
    """The rows of "rounds", and how many times the remaining edges were read."""
    spark = edges.sparkSession
    st = Stages(spark, "rounds")
    left = st.keep(edges.select("seq", "u", "v"), "left")
    state, rounds = OnlineCertificate(k), 0
    while True:
        first = left.orderBy("seq").limit(max(head, AHEAD * len(state.kept))).toArrow()  # no more room than is taken anyway
        if first.num_rows == 0:
            break
        rounds += 1
        for seq, u, v in edge_chunks(iter(first.to_batches())):
            for e in zip(seq.tolist(), u.tolist(), v.tolist(), strict=True):
                state.offer(e)
        last = first.column("seq")[-1].as_py()
        shared = spark.sparkContext.broadcast((state.kept, k))  # at most 2kn edges, as the fold holds them

        def undecided(batches, shared=shared):
            c = OnlineCertificate(shared.value[1], shared.value[0])
            for b in batches:
                keep = [c.needs(u, v) for u, v in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
                yield b.filter(pa.array(keep, pa.bool_()))

        nxt = st.keep(left.filter(F.col("seq") > last).mapInArrow(undecided, EDGE), "left")
        st.drop(left)
        left = nxt
    return spark.createDataFrame(pa.Table.from_batches([kept_batch(state.kept)])), rounds


def certificate_at(edges: DataFrame, k: int, upto_seq: int) -> DataFrame:
    """The certificate as it stands after the edges up to a seq: every prefix of a stream is a stream."""
    return online_certificate(edges.filter(F.col("seq") <= upto_seq), k)


def growth_curve(edges: DataFrame, certificate: DataFrame, points: int = 20) -> DataFrame:
    """(read, kept): how many edges were kept after equal shares of the stream."""
    m = edges.count()
    step = max(1, -(-m // points))
    marks = edges.sparkSession.range(1, -(-m // step) + 1).select(F.least(F.col("id") * step, F.lit(m)).alias("read"))
    kept = certificate.select((F.ceil(F.col("seq") / step) * step).alias("upto")).groupBy("upto").count()
    got = marks.join(F.broadcast(kept.select(F.least("upto", F.lit(m)).alias("upto"), "count")), F.col("upto") <= F.col("read"), "left")
    return got.groupBy("read").agg(F.coalesce(F.sum("count"), F.lit(0)).alias("kept"))


def merge_certificates(a: DataFrame, b: DataFrame, k: int, method: str = "online") -> DataFrame:
    """A certificate for the union of two graphs with disjoint edges, from theirs."""
    from certgraph.operators.layered import merged_layers

    both = a.select("seq", "u", "v").unionByName(b.select("seq", "u", "v"))
    return online_certificate(both, k) if method == "online" else merged_layers(both, k, 1).select("seq", "u", "v")
