"""The layered certificate: k scan-first forests, each on the edges that the earlier ones left."""

from __future__ import annotations

import sys
import warnings
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.functions.graph_kernels import CHUNK, ForestFold, LayeredFold, layered_mask, layered_passes
from certgraph.operators.components import component_parts
from certgraph.operators.edges import EdgeStream, vertex_set
from certgraph.operators.forest import edge_batch, edge_chunks, first_neighbour_forest, merge_tree, oriented, parts_worth, scan_order, spanning_forest
from certgraph.plans.staging import NUMBERS, Stages
from certgraph.schemas import CERTIFICATE

#: Stream positions of one stretch: a child's edges are handled together within a stretch, however many it has in all.
STRETCH = 1 << 20
#: Edges (three words each, and some as many again while a layer is built) that one task certifies instead of k + 1 distributed passes.
IN_ONE_TASK = 1 << 20
#: As many times more, of nine bytes each, if their numbers have no gaps and there are at most `DENSE_VERTICES` times so many vertices.
DENSE_TIMES, DENSE_VERTICES = 40, 4


@dataclass
class LayeredRun:
    """A certificate with what was kept on the way; `reads` holds the rows of each pass over the edges."""

    certificate: DataFrame
    edges: DataFrame
    vertices: DataFrame
    layers: int
    reads: list[int] = field(default_factory=list)
    positions: list[DataFrame] = field(default_factory=list)
    forests: list[DataFrame] = field(default_factory=list)

    @property
    def passes(self) -> int:
        return len(self.reads)


def hand_on(edges: DataFrame, positions: DataFrame, stretch: int = STRETCH, last: int | None = None) -> DataFrame:
    """(seq, child, parent, parent_pos, handed): each edge with the moment at which it goes on to the next layer's first pass.

    Per child, in order of arrival, an edge from an earlier place than all before it is stored; the one that it displaces
    is handed on at that moment, any other edge at its own arrival; the last stored edge stays in the layer, with `handed` null.
    A child's edges are gone through a stretch of the stream at a time; what one stretch leaves to the next is two numbers. `last`
    is the largest seq, if it is known.
    """
    rows = oriented(edges, positions)
    own = ["child"]
    if (last if last is not None else edges.agg(F.max("seq")).first()[0] or 0) >= stretch:
        st = Stages(edges.sparkSession, "handing")
        own = ["child", "part"]
        rows = st.keep(rows.withColumn("part", F.floor(F.col("seq") / stretch)), "oriented")
        earlier = Window.partitionBy("child").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
        later = Window.partitionBy("child").orderBy(F.desc("part")).rowsBetween(Window.unboundedPreceding, -1)
        least = rows.groupBy(*own).agg(F.min("parent_pos").alias("least"))
        carried = st.keep(least.withColumn("carried", F.min("least").over(earlier)).select(*own, "carried"), "carried")
        firsts = rows.join(carried, own).filter("carried IS NULL OR parent_pos < carried").groupBy(*own).agg(F.min("seq").alias("first"))
        carried = carried.join(firsts, own, "left").withColumn("then", F.min("first").over(later)).drop("first")
        rows = rows.join(carried, own)
    else:
        rows = rows.withColumn("carried", F.lit(None).cast("long")).withColumn("then", F.lit(None).cast("long"))
    before = Window.partitionBy(*own).orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    after = Window.partitionBy(*own).orderBy(F.desc("seq")).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("stored", F.coalesce(F.col("parent_pos") < F.least("carried", F.min("parent_pos").over(before)), F.lit(True)))
    displaced = F.coalesce(F.min(F.when(F.col("stored"), F.col("seq"))).over(after), F.col("then"))
    return rows.select("seq", "child", "parent", "parent_pos", F.when(F.col("stored"), displaced).otherwise(F.col("seq")).alias("handed"))


def handed_edges(edges: DataFrame, positions: DataFrame, stretch: int = STRETCH) -> DataFrame:
    """(seq, u, v, handed) of the edges that a layer does not keep; see `hand_on`."""
    rows = hand_on(edges, positions, stretch).filter("handed IS NOT NULL")
    return rows.select("seq", F.least("child", "parent").alias("u"), F.greatest("child", "parent").alias("v"), "handed")


def pass_schedule(k: int) -> list[tuple[int, str]]:
    """(pass, what runs in it): layer i's first half in pass i, beside the second half of layer i - 1, as `layered_run` does it."""
    return [(p, "; ".join([f"layer {p - 1} second half"] * (p > 1) + [f"layer {p} first half"] * (p <= k))) for p in range(1, k + 2)]


_PASS_DDL = "seq long, u long, v long, child long, parent long, parent_pos long, feed long, fate string"


def _marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows by feed, with their fate: in the layer, kept by this task's part of the next forest, or left."""
    fold = ForestFold()
    for b in batches:
        fate = np.full(b.num_rows, "layer", dtype=object)
        on = b.column(6).is_valid().to_numpy(zero_copy_only=False)
        if on.any():
            some = b.filter(pa.array(on))
            fate[on] = np.where(fold.offer(*(some.column(i).to_numpy() for i in (6, 1, 2))), "kept", "left")
        yield pa.RecordBatch.from_arrays([*b.columns, pa.array(fate, pa.string())], names=[*b.schema.names, "fate"])


def layered_run(edges: DataFrame, k: int, vertices: DataFrame | None = None, rule: str = "preorder", feed: str = "handover", forest: str = "tree_merge", stretch: int = STRETCH) -> LayeredRun:
    """Build the certificate layer by layer, keeping each layer's order and forest.

    `feed` is the order in which layer i + 1 sees the residual: "handover" as edges are handed on, "original" as they came.
    Both give legal orders, hence certificates; the forests may differ. Instances are nested: the job that reads the edges for
    the second half of a layer also makes the first half of the next, each task the forest of its own part of the feed, and files its rows as in the
    layer, kept or left. So the edges, and then what is left of them, are read k + 1 times in all, which `reads` counts as the
    reads happen; the kept parts, at most n - 1 rows for each task, are merged apart.
    """
    if k < 1 or feed not in ("handover", "original"):
        raise ValueError("k must be at least 1, and feed handover or original")
    st = Stages(edges.sparkSession, "layers")
    stream = EdgeStream(st.keep(edges.select("seq", "u", "v"), "edges"))
    vertices = st.keep(vertex_set(stream.edges) if vertices is None else vertices.select("id").distinct(), "vertices")
    run = LayeredRun(stream.edges, stream.edges, vertices, k)
    n, last = vertices.count(), stream.edges.agg(F.max("seq")).first()[0] or 0
    z, left, parts = st.keep(spanning_forest(stream.open_pass(), forest), "kept1"), stream.edges, []
    for layer in range(1, k + 1):
        order = st.keep(scan_order(z, vertices, rule, n=n), f"order{layer}")
        run.positions.append(order)
        if layer == k:
            run.forests.append(st.keep(first_neighbour_forest(stream.open_pass(left), order).withColumn("layer", F.lit(layer)), f"forest{layer}"))
            break
        rows = hand_on(stream.open_pass(left), order, stretch, last)
        on = F.col("handed") if feed == "handover" else F.when(F.col("handed").isNotNull(), F.col("seq"))
        rows = rows.select("seq", F.least("child", "parent").alias("u"), F.greatest("child", "parent").alias("v"), "child", "parent", "parent_pos", on.alias("feed"))
        done = st.keep(rows.sortWithinPartitions("feed").mapInArrow(_marked, _PASS_DDL), f"pass{layer + 1}", by="fate")
        run.forests.append(done.filter("fate = 'layer'").select("child", "parent", "parent_pos", "seq", F.lit(layer).alias("layer")))
        left = done.filter("fate <> 'layer'").select("seq", "u", "v", "feed", "fate")
        fed = left.select(F.col("feed").alias("seq"), "u", "v", "fate")
        z = spanning_forest(fed.filter("fate = 'kept'"), "tree_merge") if forest == "tree_merge" else spanning_forest(fed, forest)
        z, left = st.keep(z, f"kept{layer + 1}"), left.select("seq", "u", "v")
        if z.isEmpty():  # nothing is left
            break
    for f in run.forests:
        parts.append(f.select("seq", F.least("child", "parent").alias("u"), F.greatest("child", "parent").alias("v"), "layer"))
    cert = parts[0]
    for p in parts[1:]:
        cert = cert.unionByName(p)
    run.certificate, run.reads = st.keep(cert, "certificate"), stream.reads()
    return run


def layered_certificate(edges: DataFrame, k: int, vertices: DataFrame | None = None, rule: str = "preorder", feed: str = "handover", forest: str = "tree_merge", mode: str = "exact", in_one_task: int = IN_ONE_TASK) -> DataFrame:
    """certificate(seq, u, v, layer) of at most k(n - 1) edges: k-connected iff the graph is, with the same l-separators, l < k.

    mode "exact" makes k + 1 passes, see `layered_run`; a graph of at most `in_one_task` edges, or `DENSE_TIMES` as many with numbers
    without gaps, is certified by one task instead, with the same rows. So are components, several at a time, if none has most of the edges
    or more than `in_one_task`. "merge" reads the edges once: every partition is certified on its own, and unions of
    certificates are certified again up a tree. Layers are then those of the last merge.
    """
    if mode != "exact":
        return merged_layers(edges, k)
    if k < 1 or feed not in ("handover", "original") or rule not in ("preorder", "level"):
        raise ValueError("k must be at least 1, feed handover or original, rule preorder or level")
    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for seq, u, v in edge_chunks(batches, sys.maxsize):
            layer = layered_mask(seq, u, v, k, feed, rule)
            on = layer > 0
            yield edge_batch(seq[on], u[on], v[on], layer=pa.array(layer[on], pa.int32()))

    st = Stages(edges.sparkSession, "layered")
    edges = st.keep(edges.select("seq", "u", "v"), "edges")
    m, first, last = edges.agg(F.count("seq"), F.min("seq"), F.max("seq")).first()
    if m > in_one_task:
        parts = component_parts(edges, most_edges=in_one_task)
        if parts is not None:
            return st.keep(parts.mapInArrow(whole, CERTIFICATE), "certificate", rows=NUMBERS)
        ids = None
        if last - first + 1 == m <= DENSE_TIMES * in_one_task:
            vertices = st.keep(vertex_set(edges) if vertices is None else vertices.select("id").distinct(), "vertices")
            if vertices.count() <= DENSE_VERTICES * in_one_task:
                ids = edges.sparkSession.sparkContext.broadcast(np.sort(vertices.toArrow().column("id").to_numpy()))
        if ids is None:
            return layered_run(edges, k, vertices, rule, feed, forest).certificate

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, met = np.zeros(m, np.int32), np.zeros(m, np.int32), 0
        for seq, u, v in edge_chunks(batches):
            a[seq - first], b[seq - first] = np.searchsorted(ids.value, u), np.searchsorted(ids.value, v)
            met += len(seq)
        if met:
            layer = layered_passes(len(ids.value), a, b, k, feed, rule)
            on = np.flatnonzero(layer)
            for at in (on[j : j + CHUNK] for j in range(0, len(on), CHUNK)):
                yield edge_batch(at + first, ids.value[a[at]], ids.value[b[at]], layer=pa.array(layer[at], pa.int32()))

    return st.keep(edges.coalesce(1).mapInArrow(whole if m <= in_one_task else dense, CERTIFICATE), "certificate", rows=NUMBERS)


def merged_layers(edges: DataFrame, k: int, partitions: int | None = None) -> DataFrame:
    """Each task certifies its part a chunk at a time and holds O(kn) edges; unions are certified again up a tree."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold = LayeredFold(k)
        for chunk in edge_chunks(batches):
            fold.offer(*chunk[:3])
        cert, layer = fold.settle()
        yield edge_batch(*cert, layer=pa.array(layer, pa.int32()))

    return merge_tree(edges, local, partitions or parts_worth(edges), CERTIFICATE)


def warn_if_useless(n: int, m: int, k: int) -> None:
    if k * (n - 1) >= m:
        warnings.warn(f"k(n-1) = {k * (n - 1)} is not below m = {m}: the certificate may be the whole graph", stacklevel=2)
