"""Spanning forests in stream order, scan orders, and scan-first forests in two passes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import CHUNK, ForestFold, preorder_arrays
from certgraph.operators.components import component_labels
from certgraph.operators.edges import dense_numbers, vertex_set
from certgraph.plans.staging import Stages
from certgraph.schemas import EDGE, POSITION

#: Partitions merged into one in each level of a merge tree.
FAN_IN = 8
#: Vertices of a forest that one task numbers (some 100 bytes each); larger forests are numbered by rounds of joins.
ORDER_IN_ONE_TASK = 20_000_000


def edge_chunks(batches: Iterator[pa.RecordBatch], rows: int = CHUNK) -> Iterator[tuple[np.ndarray, ...]]:
    """The columns of a task's batches as arrays of about `rows` rows, in the order in which they come; nothing else is held."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        held.append(b)
        size += b.num_rows
        if size >= rows:
            yield _arrays(held)
            held, size = [], 0
    if size:
        yield _arrays(held)


def _arrays(held: list[pa.RecordBatch]) -> tuple[np.ndarray, ...]:
    return tuple(c.to_numpy() for c in pa.Table.from_batches(held).columns)


def edge_batch(seq, u, v, **more) -> pa.RecordBatch:
    """One batch of edges, with further columns if there are any."""
    cols = {"seq": pa.array(seq, pa.int64()), "u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64()), **more}
    return pa.RecordBatch.from_arrays(list(cols.values()), names=list(cols))


def in_order(edges: DataFrame, partitions: int | None = None) -> DataFrame:
    """Edges sorted by seq in each partition: the table's own ones, or so many dealt by seq."""
    rows = edges.select("seq", "u", "v")
    if partitions is not None:
        rows = rows.repartition(partitions, "seq") if partitions > 1 else rows.repartition(1)
    return rows.sortWithinPartitions("seq")


def default_partitions(edges: DataFrame) -> int:
    return int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def parts_worth(edges: DataFrame, least: int = 1 << 22) -> int:
    """In how many parts to certify a table: no more than have `least` edges each, as a part with few edges keeps them all."""
    return max(1, min(default_partitions(edges), -(-edges.count() // least)))


def merge_tree(edges: DataFrame, local, partitions: int | None = None, schema: str = EDGE, fan_in: int = FAN_IN, deal: bool = True) -> DataFrame:
    """`local` on every partition, then on merged partitions, until one is left; each level is one shuffle of what is kept.

    With `deal` the edges are first dealt to `partitions`, for work that takes long for each edge; without, they stay where they
    are read. Rows come to `local` by seq, sorted where they may spill, so that a task holds no more than its own state.
    """
    n = partitions or default_partitions(edges)
    out = in_order(edges, n if deal else None).mapInArrow(local, schema)
    while n > 1:
        n = -(-n // fan_in)
        out = in_order(out, n).mapInArrow(local, schema)
    return out


def _kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    fold = ForestFold()
    for seq, u, v in edge_chunks(batches):
        keep = fold.offer(seq, u, v)
        yield edge_batch(seq[keep], u[keep], v[keep])


def spanning_forest(edges: DataFrame, strategy: str = "tree_merge", partitions: int | None = None) -> DataFrame:
    """The edges that, in stream order, join two components of what came before: at most n - 1 of (seq, u, v).

    In stream order this is the minimum spanning forest under the unique weight seq, so forests of parts of the stream may
    be merged in any grouping ("tree_merge"): each task reads its own part of the table, holds a few words for each vertex, and only what it
    keeps is shuffled. Where not even one forest fits into a task the same forest comes from rounds of smallest outgoing edges ("boruvka").
    """
    if strategy == "boruvka":
        return min_spanning_forest(edges, "seq")
    return merge_tree(edges, _kept, partitions, deal=partitions is not None)


def fold_words(edges: DataFrame) -> DataFrame:
    """(part, edges, words): what each task of the first level of `spanning_forest` reads, and the words that it holds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        fold, n = ForestFold(), 0
        for seq, u, v in edge_chunks(batches):
            fold.offer(seq, u, v)
            n += len(seq)
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (TaskContext.get().partitionId(), n, fold.words)], names=["part", "edges", "words"])

    return in_order(edges).mapInArrow(run, "part long, edges long, words long")


def min_spanning_forest(edges: DataFrame, weight: str = "seq") -> DataFrame:
    """Minimum spanning forest under `weight` (ties by seq), for vertex sets of any size."""
    st = Stages(edges.sparkSession, "forest")
    live = st.keep(edges.select("seq", "u", "v", F.col(weight).alias("w"), F.col("u").alias("cu"), F.col("v").alias("cv")), "live")
    chosen = None
    while True:
        ends = live.select(F.explode(F.array(F.struct(F.col("cu").alias("c")), F.struct(F.col("cv").alias("c")))).alias("e"), "w", "seq", "u", "v", "cu", "cv")
        best = ends.groupBy("e.c").agg(F.min(F.struct("w", "seq", "u", "v", "cu", "cv")).alias("m")).select("m.*").distinct()
        best = st.keep(best, "best")
        if best.isEmpty():
            break
        picked = best.select("seq", "u", "v")
        chosen = picked if chosen is None else chosen.unionByName(picked)
        labels = component_labels(best.select("cu", "cv"), "cu", "cv")
        a, b = labels.select(F.col("id").alias("cu"), F.col("comp").alias("nu")), labels.select(F.col("id").alias("cv"), F.col("comp").alias("nv"))
        nxt = live.join(a, "cu", "left").join(b, "cv", "left").select("seq", "u", "v", "w", F.coalesce("nu", "cu").alias("cu"), F.coalesce("nv", "cv").alias("cv")).filter("cu <> cv")
        live = st.keep(nxt, "live")
    return chosen.distinct() if chosen is not None else edges.select("seq", "u", "v").limit(0)


def components(edges: DataFrame, vertices: DataFrame | None = None, strategy: str = "contract") -> DataFrame:
    """(id, comp) for every vertex; comp is the smallest id of its component. "forest" goes through the spanning forest."""
    rows = spanning_forest(edges) if strategy == "forest" else edges
    found = component_labels(rows)
    if vertices is None:
        return found
    return vertices.select("id").join(found, "id", "left").select("id", F.coalesce("comp", "id").alias("comp"))


def is_connected(edges: DataFrame, vertices: DataFrame) -> bool:
    """One component, from one pass: a forest on n vertices with n - 1 edges."""
    n = vertices.count()
    return n > 0 and spanning_forest(edges).count() == n - 1


def scan_order(forest: DataFrame, vertices: DataFrame, rule: str = "preorder", in_one_task: int = ORDER_IN_ONE_TASK, n: int | None = None) -> DataFrame:
    """positions(id, comp, pos): an order in which every vertex but a component's first follows one of its neighbours.

    "preorder" numbers the depth-first preorder of the kept forest, roots and children by ascending id; "level" orders by
    component, depth in the forest and id. Up to `in_one_task` vertices are numbered by one task, from at most n - 1 rows; more by rounds
    of pointer doubling along a tour of the forest's edges, as many as the logarithm of n. Both ways give the same rows. `n` is the number
    of vertices, if it is known.
    """
    if rule not in ("preorder", "level"):
        raise ValueError("rule must be preorder or level")
    if (vertices.count() if n is None else n) > in_one_task:
        return _order_by_rounds(forest, vertices, rule)
    rows = vertices.select(F.col("id").alias("u"), F.lit(None).cast("long").alias("v")).unionByName(forest.select("u", "v"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held)
        edge = t.column("v").is_valid().to_numpy()
        u, v = t.column("u").to_numpy(), t.column("v").fill_null(0).to_numpy()
        ids = np.unique(u[~edge])
        place, root, depth = preorder_arrays(len(ids), np.searchsorted(ids, u[edge]), np.searchsorted(ids, v[edge]))
        order = np.argsort(place) if rule == "preorder" else np.lexsort((np.arange(len(ids)), depth, root))
        for k in range(0, len(ids), CHUNK):
            some = order[k : k + CHUNK]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (ids[some], ids[root[some]], np.arange(k, k + len(some)))], names=["id", "comp", "pos"])

    return rows.coalesce(1).mapInArrow(run, POSITION)


def _doubled(st: Stages, steps: DataFrame) -> DataFrame:
    """(i, ahead): how many steps lie ahead of each item of linked lists given as (i, nxt), null at an end."""
    now = st.keep(steps.select("i", "nxt", F.when(F.col("nxt").isNull(), 0).otherwise(1).cast("long").alias("ahead")), "ranks")
    while not now.filter("nxt IS NOT NULL").isEmpty():
        other = now.select(F.col("i").alias("j"), F.col("nxt").alias("far"), F.col("ahead").alias("more"))
        after = now.join(other, F.col("nxt") == F.col("j"), "left").select("i", F.col("far").alias("nxt"), (F.col("ahead") + F.coalesce("more", F.lit(0))).alias("ahead"))
        after = st.keep(after, "ranks")
        st.drop(now)
        now = after
    return now.select("i", "ahead")


def _tour(st: Stages, arcs: DataFrame, roots: DataFrame) -> DataFrame:
    """(x, y, ahead) for the arcs (x, y, late) of a forest: arcs still to come when a walk round the tree leaves x for y.

    The walk begins at the root; an arc into a vertex goes on with its next arc by (late, y), after the last one with its first.
    """
    listed = st.keep(dense_numbers(arcs, ["x", "late", "y"], "i", first=0), "arcs")
    spans = listed.groupBy("x").agg(F.min("i").alias("first"), F.max("i").alias("last"))
    back = listed.select(F.col("x").alias("y"), F.col("y").alias("x"), F.col("i").alias("r"))
    rows = listed.join(back, ["x", "y"]).join(spans.withColumnRenamed("x", "y"), "y").join(roots.select(F.col("id").alias("y"), F.lit(True).alias("root")), "y", "left")
    nxt = F.when(F.col("r") < F.col("last"), F.col("r") + 1).when(F.col("root"), F.lit(None)).otherwise(F.col("first"))
    ranks = _doubled(st, rows.select("i", nxt.alias("nxt")))
    return st.keep(listed.join(ranks, "i").select("x", "y", "ahead"), "tour")


def _order_by_rounds(forest: DataFrame, vertices: DataFrame, rule: str) -> DataFrame:
    st = Stages(forest.sparkSession, "order")
    comp = st.keep(components(forest, vertices), "components")
    roots = comp.filter("id = comp").select("id")
    both = st.keep(forest.select(F.col("u").alias("x"), F.col("v").alias("y")).unionByName(forest.select(F.col("v").alias("x"), F.col("u").alias("y"))), "both")

    def downward(tour: DataFrame) -> DataFrame:
        other = tour.select(F.col("x").alias("y"), F.col("y").alias("x"), F.col("ahead").alias("later"))
        return tour.join(other, ["x", "y"]).filter("ahead > later").select("x", "y", "ahead")  # parent x, child y

    # any walk from the root tells parents; a second one, with the way to the parent last, visits children by ascending id
    parents = st.keep(downward(_tour(st, both.withColumn("late", F.lit(0)), roots)).select(F.col("x").alias("p"), F.col("y").alias("c")), "parents")
    if rule == "level":
        depth = _doubled(st, comp.select(F.col("id").alias("i")).join(parents.select(F.col("c").alias("i"), F.col("p").alias("nxt")), "i", "left"))
        rows = comp.join(depth.withColumnRenamed("i", "id"), "id").select("id", "comp", "ahead")
        return dense_numbers(rows, ["comp", "ahead", "id"], "pos", first=0).select("id", "comp", "pos")
    upward = parents.select(F.col("c").alias("x"), F.col("p").alias("y"), F.lit(1).alias("up"))
    arcs = both.join(upward, ["x", "y"], "left").select("x", "y", F.coalesce("up", F.lit(0)).alias("late"))
    walk = downward(_tour(st, arcs, roots)).select(F.col("y").alias("id"), "ahead")
    rows = comp.join(walk, "id", "left").select("id", "comp", F.col("ahead").isNotNull().alias("inner"), F.coalesce(-F.col("ahead"), F.lit(0)).alias("walk"))
    return dense_numbers(rows, ["comp", "inner", "walk"], "pos", first=0).select("id", "comp", "pos")


def check_scan_order(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """Vertices that break an order: not first in their component, yet without a neighbour before them. Empty if legal."""
    a = positions.select(F.col("id").alias("u"), F.col("pos").alias("pu"))
    b = positions.select(F.col("id").alias("v"), F.col("pos").alias("pv"))
    later = edges.join(a, "u").join(b, "v").select(F.when(F.col("pu") < F.col("pv"), F.col("v")).otherwise(F.col("u")).alias("id")).distinct()
    firsts = positions.join(components(edges, positions.select("id")).select("id", F.col("comp").alias("c")), "id").groupBy("c").agg(F.min_by("id", "pos").alias("id")).select("id")
    return positions.select("id").join(later, "id", "left_anti").join(firsts, "id", "left_anti")


def oriented(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """(seq, child, parent, parent_pos): each edge with its later end as child."""
    a = positions.select(F.col("id").alias("u"), F.col("pos").alias("pu"))
    b = positions.select(F.col("id").alias("v"), F.col("pos").alias("pv"))
    first = F.col("pu") < F.col("pv")
    return edges.join(a, "u").join(b, "v").select("seq", F.when(first, F.col("v")).otherwise(F.col("u")).alias("child"), F.when(first, F.col("u")).otherwise(F.col("v")).alias("parent"), F.least("pu", "pv").alias("parent_pos"))


def first_neighbour_forest(edges: DataFrame, positions: DataFrame) -> DataFrame:
    """(child, parent, parent_pos, seq): for each later end its neighbour placed first.

    Replacing a stored edge by one from an earlier place is a minimum, so it needs no order of arrival and is aggregated in
    part before the shuffle.
    """
    best = oriented(edges, positions).groupBy("child").agg(F.min(F.struct("parent_pos", "parent", "seq")).alias("m"))
    return best.select("child", "m.parent", "m.parent_pos", "m.seq")


def scan_first_forest(edges: DataFrame, vertices: DataFrame | None = None, rule: str = "preorder", strategy: str = "tree_merge") -> DataFrame:
    """The scan-first forest of the order that `rule` makes, in two passes over the edges."""
    vertices = vertex_set(edges) if vertices is None else vertices
    order = scan_order(spanning_forest(edges, strategy), vertices, rule)
    return first_neighbour_forest(edges, order)
