"""Local connectivity, disjoint paths, cuts, and the decision whether a graph is k-connected, on certificates."""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import CHUNK, Graph, PackedGraph, PathFlow, component_of_each, connectivity_check, inseparable_sets, minimum_cuts
from certgraph.operators.edges import vertex_set
from certgraph.operators.layered import layered_certificate
from certgraph.operators.online import online_certificate
from certgraph.plans.staging import NUMBERS, Stages
from certgraph.schemas import PAIR, VERDICT

#: Bytes of the largest graph that is broadcast, as arrays.
MOST_BROADCAST = 1 << 30


def shared_graph(cert: DataFrame, vertices: DataFrame) -> Broadcast:
    """The certificate as broadcast arrays, if these are small enough."""
    rows = cert.select("u", "v").unionByName(vertices.select(F.col("id").alias("u"), F.lit(None).cast("long").alias("v")))
    n = rows.count()
    if PackedGraph.bytes_of(n, 0) > MOST_BROADCAST:
        raise ValueError(f"{n} edges and vertices are too many to broadcast; use components for k = 1")
    t = rows.toArrow()
    edge = t.column("v").is_valid().to_numpy()
    u, v = t.column("u").to_numpy(), t.column("v").fill_null(0).to_numpy()
    return cert.sparkSession.sparkContext.broadcast(PackedGraph(u[edge], v[edge], u[~edge]))


def local_connectivity_pairs(cert: DataFrame, vertices: DataFrame, pairs: DataFrame, cap: int, shared: Broadcast | None = None, dealt: bool = False) -> DataFrame:
    """(u, v, kappa): node-disjoint paths between each pair, counted up to cap; `dealt` says that pairs lie in many parts already.

    Two vertices of one set that fewer than j vertices cannot part, if not adjacent, have j paths at least, and at most the smaller degree.
    Only pairs that this leaves open are searched for paths.
    """
    g = shared or shared_graph(cert, vertices)
    sets = cert.sparkSession.sparkContext.broadcast(_levels(g.value, cap))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, degrees = g.value.ids, np.diff(g.value.starts)
        edges = np.sort(np.repeat(np.arange(len(ids)), degrees) * len(ids) + np.searchsorted(ids, g.value.ends))
        edges = np.append(edges, -1)
        for b in batches:
            u, v = b.column(0).to_numpy(), b.column(1).to_numpy()
            i, j = np.searchsorted(ids, u), np.searchsorted(ids, v)
            low = np.zeros(len(u), dtype=np.int32)
            for level, core in enumerate(sets.value, 1):
                low[(core[i] >= 0) & (core[i] == core[j])] = level
            high = np.minimum(np.minimum(degrees[i], degrees[j]), cap)
            joined = edges[np.searchsorted(edges[:-1], i * len(ids) + j)] == i * len(ids) + j
            for x in np.flatnonzero((low != high) | joined).tolist():
                low[x] = PathFlow(g.value, int(u[x]), int(v[x]), cap).value
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(low, pa.int32())], names=["u", "v", "kappa"])

    chosen = pairs.select("u", "v")
    return (chosen if dealt else spread(chosen)).mapInArrow(run, PAIR)


def _levels(g: PackedGraph, cap: int) -> np.ndarray:
    return np.array([inseparable_sets(g, j, every=True) for j in range(1, cap + 1)]).reshape(cap, len(g.ids))


def local_connectivity_apart(cert: DataFrame, vertices: DataFrame, edges: DataFrame, cap: int) -> DataFrame:
    """(u, v, kappa) as `local_connectivity_pairs` has them, for all pairs of vertices that no row of `edges` joins.

    One work item for each vertex, with all smaller ones; pairs are made, left out and compared as arrays in the task.
    """
    g = shared_graph(cert, vertices)
    joined = g if edges is cert else shared_graph(edges, vertices)
    n = len(g.value.ids)
    if comb(n, 2) > MOST_PAIRS:
        raise ValueError(f"{n} vertices have too many pairs to go through")
    sets = cert.sparkSession.sparkContext.broadcast(_levels(g.value, cap))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, degrees = g.value.ids, np.minimum(np.diff(g.value.starts), cap).astype(np.int32)
        near, starts = np.searchsorted(ids, joined.value.ends), joined.value.starts
        for b in batches:
            out, size = [], 0
            for j in b.column(0).to_pylist():
                low = np.zeros(j, dtype=np.int32)
                for level, core in enumerate(sets.value, 1):
                    if core[j] >= 0:
                        low[core[:j] == core[j]] = level
                open_ = low != np.minimum(degrees[:j], degrees[j])
                own = np.searchsorted(ids, g.value.ends[g.value.starts[j] : g.value.starts[j + 1]])
                open_[own[own < j]] = True
                keep = np.ones(j, dtype=bool)
                some = near[starts[j] : starts[j + 1]]
                keep[some[some < j]] = False
                for i in np.flatnonzero(open_ & keep).tolist():
                    low[i] = PathFlow(g.value, int(ids[i]), int(ids[j]), cap).value
                out.append((ids[:j][keep], np.full(int(keep.sum()), ids[j]), low[keep]))
                size += len(out[-1][0])
                if size >= CHUNK:
                    yield _kappa_batch(out)
                    out, size = [], 0
            if size:
                yield _kappa_batch(out)

    return spread(cert.sparkSession.range(n)).mapInArrow(run, PAIR)


def _kappa_batch(parts: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
    u, v, kappa = (np.concatenate(x) for x in zip(*parts, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(kappa, pa.int32())], names=["u", "v", "kappa"])


def spread(rows: DataFrame) -> DataFrame:
    """Work items over all cores, however few rows they are."""
    return rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))


#: Pairs of vertices that are gone through one by one; their numbers are told apart in double precision up to there.
MOST_PAIRS = 10_000_000_000_000


def all_pairs(vertices: DataFrame) -> DataFrame:
    """Every unordered pair u < v, made from its number; no join of the vertices with themselves."""
    spark, n = vertices.sparkSession, vertices.count()
    if comb(n, 2) > MOST_PAIRS:
        raise ValueError(f"{n} vertices have too many pairs to go through")
    order = spark.sparkContext.broadcast(np.sort(vertices.select("id").toArrow().column("id").to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            r = b.column(0).to_numpy()
            j = ((1 + np.sqrt(1 + 8 * r.astype(float))) / 2).astype(np.int64)
            j -= j * (j - 1) // 2 > r
            j += j * (j + 1) // 2 <= r
            yield pa.RecordBatch.from_arrays([pa.array(order.value[r - j * (j - 1) // 2]), pa.array(order.value[j])], names=["u", "v"])

    return spark.range(comb(n, 2)).mapInArrow(run, "u long, v long")


def local_connectivity(cert: DataFrame, vertices: DataFrame, u: int, v: int, cap: int) -> int:
    return PathFlow(shared_graph(cert, vertices).value, u, v, cap).value


def disjoint_paths(cert: DataFrame, vertices: DataFrame, u: int, v: int, cap: int) -> list[list[int]]:
    return PathFlow(shared_graph(cert, vertices).value, u, v, cap).paths()


def min_vertex_cut(cert: DataFrame, vertices: DataFrame, u: int, v: int, cap: int) -> list[int] | None:
    """A smallest set that parts u from v; None if they are adjacent or `cap` paths join them."""
    g: Graph = shared_graph(cert, vertices).value
    flow = PathFlow(g, u, v, cap)
    return None if v in g[u] or flow.value >= cap else flow.cut()


def all_min_cuts(cert: DataFrame, vertices: DataFrame, u: int, v: int, cap: int) -> list[tuple[int, ...]]:
    return minimum_cuts(shared_graph(cert, vertices).value, u, v, cap)


def is_k_connected(cert: DataFrame, vertices: DataFrame, k: int, shared: Broadcast | None = None) -> DataFrame:
    """One row (k, verdict, reason, witness) from a certificate for at least k.

    Too few vertices and low degrees are settled at once. Then a set that fewer than k vertices cannot part is grown from k vertices
    compared pairwise, until it is the whole graph or a vertex has fewer than k paths into it: the witness is that vertex and one of the
    set, which may be adjacent. Where no such k vertices are found, the first k vertices are compared pairwise and each further
    one with all before it; these checks run in parallel, and one failure settles the verdict. `cert` is read more than once, so it
    should be a stored table; `shared` is its broadcast where there is one already.
    """
    spark = cert.sparkSession

    def verdict(ok: bool, reason: str | None, witness: list[int]) -> DataFrame:
        return spark.createDataFrame([(k, ok, reason, witness)], VERDICT)

    g = shared or shared_graph(cert, vertices)
    n, degrees = len(g.value), np.diff(g.value.starts)
    if n <= k:
        return verdict(False, "too_few_vertices", [])
    if degrees.min() < k:
        return verdict(False, "low_degree", [int(g.value.ids[np.argmax(degrees < k)])])
    label = component_of_each(g.value)
    if label.any():  # a component's label is its smallest place
        return verdict(False, "pair", [int(g.value.ids[np.argmax(label > 0)]), int(g.value.ids[0])])
    core = inseparable_sets(g.value, k)
    if (core >= 0).any():
        # one outside is parted from the set by fewer than k vertices, and so are the sets of two components
        apart = core != core.max()
        if not apart.any():
            return verdict(True, None, [])
        return verdict(False, "pair", [int(g.value.ids[np.argmax(apart)]), int(g.value.ids[np.argmax(~apart)])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bad = [(int(p[0]), int(p[1])) for r in b.column(0).to_pylist() if (p := connectivity_check(g.value, g.value.ids, k, r))]
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in bad], pa.int64()), pa.array([y for _, y in bad], pa.int64())], names=["u", "v"])

    failed = spread(spark.range(comb(k, 2) + n - k).select("id")).mapInArrow(run, "u long, v long").limit(1).collect()
    return verdict(False, "pair", list(failed[0])) if failed else verdict(True, None, [])


def certificate_for(edges: DataFrame, k: int, via: str, vertices: DataFrame | None = None) -> DataFrame:
    """The graph's edges as they are ("full"), or one of its certificates, as a stored table."""
    if via == "full":
        return edges
    if via == "layered":
        return layered_certificate(edges, k, vertices)
    if via == "layered_merge":
        cert = layered_certificate(edges, k, mode="merge")
    else:
        cert = online_certificate(edges, k, {"online": "exact", "online_rounds": "rounds", "online_merge": "merge"}[via])
    return Stages(edges.sparkSession, "certificate").keep(cert, via, rows=NUMBERS)


def k_connected(edges: DataFrame, k: int, via: str = "layered", vertices: DataFrame | None = None) -> DataFrame:
    vertices = vertex_set(edges) if vertices is None else vertices
    return is_k_connected(certificate_for(edges, k, via, vertices), vertices, k)


def vertex_connectivity(edges: DataFrame, k_max: int, via: str = "layered", vertices: DataFrame | None = None) -> int:
    """Largest k up to k_max for which the graph is k-connected, by bisection on one certificate."""
    vertices = Stages(edges.sparkSession, "vertices").keep(vertex_set(edges) if vertices is None else vertices.select("id"), "vertices")
    cert = certificate_for(edges, k_max, via, vertices)
    shared = shared_graph(cert, vertices)
    low, high = 0, k_max
    while low < high:
        mid = (low + high + 1) // 2
        row: Row = is_k_connected(cert, vertices, mid, shared).first()
        low, high = (mid, high) if row.verdict else (low, mid - 1)
    shared.unpersist()
    return low
