"""All small vertex sets that disconnect a graph, from its layered certificate."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from math import comb

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import Pockets, block_graphs, blocks, component_count, component_of_each, inseparable_set, inseparable_sets, minimum_cuts, nth_combination, pieces_without_each_vertex
from certgraph.operators.decide import shared_graph, spread
from certgraph.plans.staging import Stages
from certgraph.schemas import SEPARATOR


#: Pairs that are broadcast to be left out of the others.
MOST_TAKEN = 1_000_000


def _require(cert: DataFrame, size: int, layers: int | None) -> None:
    if size < 1:
        raise ValueError("a separator has at least one vertex")
    if layers is not None and size >= layers:
        raise ValueError(f"a certificate for k = {layers} shows separators of fewer than {layers} vertices only")


def separates(cert: DataFrame, vertices: DataFrame, members: list[int]) -> tuple[bool, int]:
    """Whether taking `members` away leaves more components than there are, and how many it leaves."""
    g = shared_graph(cert, vertices).value
    pieces = component_count(g, set(members))
    return pieces > component_count(g), pieces


def separators(cert: DataFrame, vertices: DataFrame, size: int, layers: int | None = None, minimal: bool = False, limit: int | None = None, shared: Broadcast | None = None) -> DataFrame:
    """(l, members ascending, pieces): all sets of `size` vertices without which there are more components.

    Pairs are found block by block (`pair_terms`). Else each set of one vertex fewer is one work item: a single low-link search tells for every further vertex how many pieces there would be without it too. A set is emitted once, from its members but the largest. Sets are written where the
    caller wants them; nothing is gathered, as there can be a number of sets quadratic in n and more. `minimal` leaves out
    sets that hold a smaller separator.
    """
    _require(cert, size, layers)
    spark = cert.sparkSession
    g = shared or shared_graph(cert, vertices)
    whole = component_count(g.value)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            members, pieces = [], []
            for index in b.column(0).to_pylist():
                chosen = tuple(int(g.value.ids[i]) for i in nth_combination(len(g.value), size - 1, index))
                _, left = pieces_without_each_vertex(g.value, set(chosen))
                least = chosen[-1] if chosen else None
                for v in sorted(left):
                    if left[v] > whole and (least is None or v > least):
                        members.append([*chosen, v])
                        pieces.append(left[v])
            yield pa.RecordBatch.from_arrays([pa.array([size] * len(pieces), pa.int32()), pa.array(members, pa.list_(pa.int64())), pa.array(pieces, pa.int32())], names=["l", "members", "pieces"])

    if size == 2:
        found = _pairs(g, pair_terms(g))
    else:
        found = spread(spark.range(comb(len(g.value), size - 1)).select("id")).mapInArrow(run, SEPARATOR)
    if minimal:
        for smaller in range(1, size):
            less = separators(cert, vertices, smaller, layers, shared=g).select(F.col("members").alias("_less"), F.col("_less")[0].alias("_key"))
            hit = found.withColumn("_x", F.explode("members")).join(less, F.col("_x") == F.col("_key")).filter(F.size(F.array_except("_less", "members")) == 0).select("members").distinct()
            found = found.join(hit, "members", "left_anti").select("l", "members", "pieces")
    return found if limit is None else found.limit(limit)


@dataclass
class PairTerms:
    """How many more components there are without two vertices: what each adds `alone`, by place in `ids`, and for some pairs a term (u, v, n) more."""

    ids: np.ndarray
    whole: int
    alone: np.ndarray
    terms: DataFrame


def pair_terms(g: Broadcast) -> PairTerms:
    """What pairs of vertices cut off, from the graph's blocks.

    A vertex alone adds a component for each of its blocks but one. Two vertices of one block add those of the block without both, but
    one: none for most, one less for the ends of a bridge. Within a block only vertices in pockets, outside the set that no two
    others part, and the neighbours of pockets have terms: one work item for each vertex in a pocket, or of a block without such a set.
    """
    spark, ids = SparkSession.active(), g.value.ids
    parts = blocks(g.value)
    alone = np.bincount(np.array([x for p in parts for x in p], dtype=np.int64), minlength=len(ids)) - 1
    terms = Counter({(min(p), max(p)): -1 for p in (ids[p].tolist() for p in parts if len(p) == 2)})
    inner: dict[int, tuple] = {}
    items: list[tuple[int, int]] = []
    pieces = 0
    for i, own in block_graphs(g.value, parts):
        held = inseparable_set(own, 3)
        if len(held) == len(own):
            continue
        pockets = Pockets(np.where(np.isin(own.ids, list(held)), 0, -1), own) if held else None
        inner[i] = (own, pockets)
        for members in pockets.members if pockets else [[x] for x in own]:
            items += [(i, x) for x in members]
            pieces += 1
        for near, _ in pockets.loose(own) if pockets else ():
            if len(near) == 2:
                terms[min(near), max(near)] += 1
    shared = spark.sparkContext.broadcast(inner)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for i, a in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                own, pockets = shared.value[i]
                if pockets is not None:
                    both = pockets.without(own, a)[1]
                else:
                    both = {x: n - 1 for x, n in pieces_without_each_vertex(own, {a})[1].items() if x > a and n > 1}
                out += [(min(a, x), max(a, x), n) for x, n in both.items()]
            u, v, n = zip(*out, strict=True) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(n, pa.int64())], names=["u", "v", "n"])

    near = pa.table({"u": pa.array([u for u, _ in terms], pa.int64()), "v": pa.array([v for _, v in terms], pa.int64()), "n": pa.array(list(terms.values()), pa.int64())})
    both = spark.createDataFrame(near, "u long, v long, n long")
    if items:
        rows = spark.createDataFrame(pa.table({"at": pa.array(range(len(items)), pa.int64()), "i": pa.array([i for i, _ in items], pa.int64()), "id": pa.array([x for _, x in items], pa.int64())}))
        # vertices of a pocket stay together, so a task makes its inner graph once
        rows = rows.repartitionByRange(int(spark.conf.get("spark.sql.shuffle.partitions")), "at") if pieces > 64 else spread(rows)
        both = both.unionByName(rows.mapInArrow(search, "u long, v long, n long"))
    both = both.groupBy("u", "v").agg(F.sum("n").alias("n"))
    return PairTerms(ids, component_count(g.value), alone, Stages(spark, "separators").keep(both, "both"))


def shown_by(found: list[PairTerms]) -> dict[int, int]:
    """How many pairs of vertices are separators in which of several graphs on the same vertices: numbers by sums of 2 ** place.

    All pairs are counted by what their vertices add alone, and those that have a term in any of the graphs are then filed anew.
    """
    kinds, size = np.unique(np.stack([x.alone for x in found], axis=1), axis=0, return_counts=True)
    bit, out = 1 << np.arange(len(found)), Counter()
    for i in range(len(kinds)):
        n = size[i] * size[i:]
        n[0] = size[i] * (size[i] - 1) // 2
        shown = (kinds[i] + kinds[i:] > 0) @ bit
        for s in np.unique(shown):
            out[int(s)] += int(n[shown == s].sum())
    spark, ids = SparkSession.active(), found[0].ids
    weights = spark.sparkContext.broadcast([x.alone for x in found])
    rows = reduce(DataFrame.unionByName, (x.terms.withColumn("g", F.lit(i)) for i, x in enumerate(found)))
    rows = rows.groupBy("u", "v").agg(*(F.sum(F.when(F.col("g") == i, F.col("n")).otherwise(0)).alias(f"n{i}") for i in range(len(found))))
    places = spark.sparkContext.broadcast(ids)

    def filed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            u, v = (np.searchsorted(places.value, b.column(c).to_numpy()) for c in (0, 1))
            plain = [w[u] + w[v] for w in weights.value]
            before = sum((x > 0) * (1 << i) for i, x in enumerate(plain))
            after = sum((x + b.column(2 + i).to_numpy() > 0) * (1 << i) for i, x in enumerate(plain))
            yield pa.RecordBatch.from_arrays([pa.array(before, pa.int64()), pa.array(after, pa.int64())], names=["before", "after"])

    for r in rows.mapInArrow(filed, "before long, after long").groupBy("before", "after").count().collect():
        out[r.before] -= r["count"]
        out[r.after] += r["count"]
    return {s: n for s, n in out.items() if n}


def _pairs(g: Broadcast, found: PairTerms) -> DataFrame:
    """(l, members, pieces): all pairs of vertices without which there are more components; those that only add alone are written without a search."""
    spark, ids, alone, whole, both = SparkSession.active(), found.ids, found.alone, found.whole, found.terms
    weights = spark.sparkContext.broadcast(alone)

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            u, v, n = (b.column(c).to_numpy() for c in range(3))
            yield _pair_batch(u, v, n + weights.value[np.searchsorted(g.value.ids, u)] + weights.value[np.searchsorted(g.value.ids, v)], whole)

    def apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, w = g.value.ids, weights.value
        for b in batches:
            for i in b.column(0).to_pylist():
                j = i + 1 + np.flatnonzero(w[i + 1 :] + w[i] > 0)
                if len(j):
                    yield _pair_batch(np.full(len(j), at[i]), at[j], w[i] + w[j], whole)

    out = both.mapInArrow(added, SEPARATOR)
    if (alone > 0).any():
        plain = spread(spark.range(len(ids))).mapInArrow(apart, SEPARATOR)
        taken = both.select(F.col("u").alias("_u"), F.col("v").alias("_v"))
        if both.count() <= MOST_TAKEN:  # the plain pairs may be many more and stay where they are
            taken = F.broadcast(taken)
        out = out.unionByName(plain.join(taken, (F.col("members")[0] == F.col("_u")) & (F.col("members")[1] == F.col("_v")), "left_anti"))
    return out


def _pair_batch(u: np.ndarray, v: np.ndarray, more: np.ndarray, whole: int) -> pa.RecordBatch:
    keep = more > 0
    flat = np.stack([u[keep], v[keep]], axis=1).ravel()
    members = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, 2), pa.int32()), pa.array(flat, pa.int64()))
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(members), 2), pa.int32()), members, pa.array(whole + more[keep], pa.int32())], names=["l", "members", "pieces"])


def all_separators(cert: DataFrame, vertices: DataFrame, k: int) -> DataFrame:
    """Separators of every size below k."""
    g = shared_graph(cert, vertices)
    return reduce(DataFrame.unionByName, (separators(cert, vertices, size, k, shared=g) for size in range(1, k)))


def minimum_separators(cert: DataFrame, vertices: DataFrame, k: int) -> DataFrame:
    """(l, members): the smallest cuts between pairs that are not adjacent, of the smallest size that occurs below k.

    Sizes are gone through from 1. A cut of one size parts a vertex outside the component's set that so few vertices cannot part from what it
    leaves of any size + 1 vertices of that set, so only these pairs are searched; all pairs of a component that has no such set.
    """
    g = shared_graph(cert, vertices)
    spark, label = cert.sparkSession, component_of_each(g.value)
    for size in range(1, k):
        found = Stages(spark, "cuts").keep(_cuts_of_size(g, label, size, spark), f"size{size}")
        if not found.isEmpty():
            return found
    return spark.createDataFrame([], "l int, members array<long>")


def _cuts_of_size(g: Broadcast, label: np.ndarray, size: int, spark: SparkSession) -> DataFrame:
    """Cuts of one size where there are no smaller ones."""
    core = inseparable_sets(g.value, size + 1)
    held = {int(c): g.value.ids[core == c][: size + 1].tolist() for c in np.unique(core[core >= 0])}
    bare = [p for p in _groups(label) if int(label[p[0]]) not in held]
    ends = spark.sparkContext.broadcast((held, {int(label[p[0]]): g.value.ids[p].tolist() for p in bare}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cuts = []
            for u, c in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                others = ends.value[0].get(c) or [x for x in ends.value[1][c] if x > u]
                cuts += {x for v in others for x in minimum_cuts(g.value, u, v, size + 1) if len(x) == size}
            yield pa.RecordBatch.from_arrays([pa.array([size] * len(cuts), pa.int32()), pa.array([list(c) for c in cuts], pa.list_(pa.int64()))], names=["l", "members"])

    out = core < 0
    items = pa.table({"u": pa.array(g.value.ids[out], pa.int64()), "c": pa.array(label[out], pa.int64())})
    return spread(spark.createDataFrame(items)).mapInArrow(run, "l int, members array<long>").distinct()


def _groups(label: np.ndarray) -> list[np.ndarray]:
    order = np.argsort(label, kind="stable")
    return np.split(order, np.flatnonzero(np.diff(label[order])) + 1)


def cut_vertices(cert: DataFrame, vertices: DataFrame) -> DataFrame:
    """(id, pieces): vertices without which there are more components; needs a certificate for k = 2 at least."""
    return separators(cert, vertices, 1).select(F.col("members")[0].alias("id"), "pieces")


def count_separators(cert: DataFrame, vertices: DataFrame, size: int, layers: int | None = None) -> int:
    return separators(cert, vertices, size, layers).count()


def has_separator(cert: DataFrame, vertices: DataFrame, size: int, layers: int | None = None) -> bool:
    return not separators(cert, vertices, size, layers, limit=1).isEmpty()
