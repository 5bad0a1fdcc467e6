"""Methods to compare with: older certificates, breadth-first layers, in-memory search, one-pass neighbours, floors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import CHUNK, ForestFold, LayeredFold, brute_minimum_certificate, component_of_each, distances_from, graph_of, scan_first_forest, shortest_cycle, widest, within
from certgraph.operators.components import component_labels
from certgraph.operators.decide import shared_graph, spread
from certgraph.operators.edges import residual, vertex_set
from certgraph.operators.forest import edge_batch, edge_chunks, in_order, merge_tree
from certgraph.operators.forest import min_spanning_forest as min_spanning_forest
from certgraph.operators.online import kept_batch, online_certificate
from certgraph.plans.staging import Stages
from certgraph.schemas import CERTIFICATE, EDGE


def _triples(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, int]]:
    for chunk in edge_chunks(batches):
        yield from zip(*(x.tolist() for x in chunk), strict=True)


def _layer_batch(rows: list[tuple[int, int, int, int]]) -> pa.RecordBatch:
    seq, u, v, layer = zip(*rows, strict=True) if rows else ((), (), (), ())
    return edge_batch(seq, u, v, layer=pa.array(layer, pa.int32()))


def small_k_certificate(edges: DataFrame, k: int, buffer: int = CHUNK) -> DataFrame:
    """A sparsification-style stand-in for the older one-pass methods for k up to 4.

    One task reads the edges in order, in chunks, and certifies each chunk together with what was kept; it holds that and a chunk.
    """
    if not 1 <= k <= 4:
        raise ValueError("the older methods reach k = 4")

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold = LayeredFold(k)
        for chunk in edge_chunks(batches, buffer):
            fold.offer(*chunk)
        yield edge_batch(*fold.settle()[0])

    return in_order(edges, 1).mapInArrow(local, EDGE)


def forest_partition_certificate(edges: DataFrame, k: int) -> DataFrame:
    """A stand-in for the linear-time offline certificate: maximum-adjacency scanning labels each edge with a forest.

    Vertices are scanned by the number of scanned neighbours, most first; the edge to a neighbour goes to the forest after those
    that the neighbour already has an edge in. The first k forests are the certificate. One task that holds the whole graph, as
    the method does; each edge moves one vertex up one list, so the work is linear.
    """

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = list(_triples(batches))
        near: dict[int, list[tuple[int, int]]] = {}
        for s, u, v in rows:
            near.setdefault(u, []).append((s, v))
            near.setdefault(v, []).append((s, u))
        weight = dict.fromkeys(near, 0)
        levels: list[list[int]] = [sorted(near, reverse=True)]
        layer: dict[int, int] = {}
        done: set[int] = set()
        top = 0
        while top >= 0:
            if not levels[top]:
                top -= 1
                continue
            x = levels[top].pop()
            if x in done or weight[x] != top:  # it has moved up since it was listed here
                continue
            done.add(x)
            for s, y in near[x]:
                if y in done:
                    continue
                weight[y] += 1
                layer[s] = weight[y]
                if weight[y] == len(levels):
                    levels.append([])
                levels[weight[y]].append(y)
                top = max(top, weight[y])
        yield _layer_batch([(s, u, v, layer[s]) for s, u, v in rows if layer[s] <= k])

    return in_order(edges, 1).mapInArrow(local, CERTIFICATE)


def bfs_layer_certificate(edges: DataFrame, k: int) -> tuple[DataFrame, int]:
    """Union of k successive breadth-first forests, and the passes over the edges that its frontiers took."""
    st = Stages(edges.sparkSession, "bfs")
    left, out, passes = st.keep(edges.select("seq", "u", "v"), "left"), None, 0
    for layer in range(1, k + 1):
        both = left.select("seq", F.col("u").alias("a"), F.col("v").alias("b")).unionByName(left.select("seq", F.col("v").alias("a"), F.col("u").alias("b")))
        front = st.keep(component_labels(left).filter("id = comp").select("id"), "front")
        seen, forest = front, None
        while not front.isEmpty():
            passes += 1
            step = both.join(front, F.col("a") == F.col("id")).select("seq", "a", "b").join(seen, F.col("b") == F.col("id"), "left_anti")
            best = st.keep(step.groupBy("b").agg(F.min(F.struct("a", "seq")).alias("m")).select(F.col("b").alias("id"), F.col("m.seq").alias("seq")), "step")
            forest = best.select("seq") if forest is None else forest.unionByName(best.select("seq"))
            front = best.select("id")
            seen = st.keep(seen.unionByName(front), "seen")
        if forest is None:
            break
        forest = st.keep(forest, "forest")
        part = left.join(forest, "seq", "left_semi").withColumn("layer", F.lit(layer))
        out = part if out is None else out.unionByName(part)
        left = st.keep(residual(left, forest), "left")
    return (out if out is not None else left.withColumn("layer", F.lit(1)).limit(0)), passes


def local_layer_certificate(edges: DataFrame, k: int, pick: str = "fifo") -> DataFrame:
    """k scan-first forests searched in memory, with a rule for which marked vertex is scanned next; in one task."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, out = list(_triples(batches)), []
        for layer in range(1, k + 1):
            tree, _ = scan_first_forest(graph_of((u, v) for _, u, v in left), pick)
            pairs = {(min(a, b), max(a, b)) for a, b in tree}
            out += [(s, u, v, layer) for s, u, v in left if (u, v) in pairs]
            left = [e for e in left if (e[1], e[2]) not in pairs]
        yield _layer_batch(out)

    return in_order(edges, 1).mapInArrow(local, CERTIFICATE)


def certificate_floor(n: int, k: int) -> int:
    """Fewest edges that a certificate of a k-connected graph on n vertices can have: every degree is k at least."""
    return -(-k * n // 2)


def brute_min_certificate(edges: list[tuple[int, int]], k: int) -> int:
    return brute_minimum_certificate(graph_of(edges), k)


def store_everything(edges: DataFrame) -> DataFrame:
    """The trivial certificate."""
    return edges.select("seq", "u", "v")


def is_bipartite(edges: DataFrame) -> DataFrame:
    """One row (bipartite, seq): whether there is no odd cycle, and the first edge in order that closes one.

    A part of the stream is summed up by its spanning forest and its first edge that closes an odd cycle.
    """

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold = ForestFold()
        for seq, u, v in edge_chunks(batches):
            keep = fold.offer(seq, u, v)
            yield edge_batch(seq[keep], u[keep], v[keep])
        if fold.odd:
            yield kept_batch([fold.odd])

    def last(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold = ForestFold()
        for chunk in edge_chunks(batches):
            fold.offer(*chunk)
        yield pa.RecordBatch.from_arrays([pa.array([fold.odd is None]), pa.array([fold.odd[0] if fold.odd else None], pa.int64())], names=["bipartite", "seq"])

    return in_order(merge_tree(edges, local, deal=False), 1).mapInArrow(last, "bipartite boolean, seq long")


def greedy_matching(edges: DataFrame, weight: str | None = None) -> DataFrame:
    """A maximal matching in stream order, or by descending weight (at least half of the best); the task holds the matched vertices."""
    order = ["seq"] if weight is None else [F.desc(weight), "seq"]

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        used: set[int] = set()
        for seq, u, v in edge_chunks(batches):
            out = []
            for s, a, b in zip(seq.tolist(), u.tolist(), v.tolist(), strict=True):
                if a not in used and b not in used:
                    used |= {a, b}
                    out.append((s, a, b))
            yield kept_batch(out)

    return edges.repartition(1).sortWithinPartitions(*order).select("seq", "u", "v").mapInArrow(local, EDGE)


def greedy_spanner(edges: DataFrame, t: int) -> DataFrame:
    """Edges, in stream order, whose ends are not yet within distance t: distances grow t-fold at most. The task holds the spanner."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g: dict[int, set[int]] = {}
        for seq, us, vs in edge_chunks(batches):
            out = []
            for s, u, v in zip(seq.tolist(), us.tolist(), vs.tolist(), strict=True):
                if not within(g, u, v, t):
                    out.append((s, u, v))
                    g.setdefault(u, set()).add(v)
                    g.setdefault(v, set()).add(u)
            yield kept_batch(out)

    return in_order(edges, 1).mapInArrow(local, EDGE)


def spanner_distances(spanner: DataFrame, vertices: DataFrame, sources: DataFrame) -> DataFrame:
    """(source, id, distance) in the spanner, from each id of `sources`: at least the graph's distance, at most t times it."""
    g = shared_graph(spanner, vertices)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for x in b.column(0).to_pylist():
                found = distances_from(g.value, x)
                yield pa.RecordBatch.from_arrays([pa.array([x] * len(found), pa.int64()), pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.int32())], names=["source", "id", "distance"])

    return spread(sources.select(sources.columns[0])).mapInArrow(run, "source long, id long, distance int")


def spanner_report(edges: DataFrame, spanner: DataFrame, vertices: DataFrame, t: int) -> DataFrame:
    """One row: bounds of the graph's diameter (of its widest component) and girth from a t-spanner, null without cycles.

    Distances from many vertices are found at once, a bit for each. Every distance in the spanner is between one and t times the graph's. An edge that the spanner left out closes a cycle of at most
    t + 1 edges; if it left out none, the girths are equal.
    """
    g = shared_graph(spanner, vertices)
    thinned = edges.count() > spanner.count()
    bare = len(g.value.ends) // 2 == len(g.value) - len(np.unique(component_of_each(g.value)))  # no cycles at all
    most = t + 1 if thinned else None  # of longer cycles nothing is said

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column(0).to_pylist()
            cycles = [None] if bare else [shortest_cycle(g.value, y, most) for y in x]
            found = [c for c in cycles if c is not None]
            yield pa.RecordBatch.from_arrays([pa.array([widest(g.value, x)] * bool(x), pa.int32()), pa.array([min(found, default=None)] * bool(x), pa.int32())], names=["far", "cycle"])

    rows = spread(vertices.select("id")).mapInArrow(run, "far int, cycle int").agg(F.max("far").alias("far"), F.min("cycle").alias("cycle")).withColumn("thinned", F.lit(thinned))
    exact = ~F.col("thinned")
    return rows.select(
        F.ceil(F.col("far") / t).cast("int").alias("diameter_least"),
        F.col("far").alias("diameter_most"),
        F.when(exact, F.col("cycle")).otherwise(3).alias("girth_least"),
        F.when(exact, F.col("cycle")).otherwise(F.least("cycle", F.lit(t + 1))).alias("girth_most"),
    )


def one_pass_connectivity(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The k = 1 method: the spanning forest is its certificate; returned with the vertices."""
    return online_certificate(edges, 1, "merge"), vertex_set(edges)
