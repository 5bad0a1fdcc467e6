"""Connected components of an edge DataFrame by repeated contraction, for graphs of any size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.plans.staging import NUMBERS, Stages

#: As many edges (32 MB of labels at most) are contracted in one task instead of in rounds of joins.
IN_ONE_TASK = 1_000_000


def smallest_reachable(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids that occur in a or b, ascending, and for each the smallest id that the links a[i] - b[i] reach."""
    ids, flat = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = flat[: len(a)], flat[len(a) :]
    label = np.arange(len(ids))
    while True:
        x, y = label[u], label[v]
        apart = x != y
        if not apart.any():
            return ids, ids[label]
        u, v, x, y = u[apart], v[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            further = label[label]
            if np.array_equal(further, label):
                break
            label = further


def _in_one_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows = [b for b in batches if b.num_rows]
    if rows:
        table = pa.Table.from_batches(rows)
        ids, least = smallest_reachable(*(c.to_numpy() for c in table.columns[:2]))
        kind = table.schema.field(0).type
        for k in range(0, len(ids), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(c[k : k + (1 << 16)], kind) for c in (ids, least)], names=["x", "p"])


def component_labels(edges: DataFrame, src: str = "u", dst: str = "v", max_rounds: int = 60) -> DataFrame:
    """Return (id, comp) for every endpoint of `edges`; comp is the smallest id it can reach.

    Each round hooks every label to its smallest neighbouring label, follows those pointers to their
    ends, and keeps only edges between different labels; once no more than IN_ONE_TASK are left, one task ends it. Pointers always go to a smaller label, so they
    form a forest; the number of live edges shrinks each round. State between rounds is written to the
    shared folder. Null endpoints take no part. An edge table without rows gives an empty result.
    """
    spark = edges.sparkSession
    st = Stages(spark, "components")
    live = (
        edges.select(F.col(src).alias("u"), F.col(dst).alias("v"))
        .filter("u IS NOT NULL AND v IS NOT NULL")
        .select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
        .distinct()
    )
    live = stored = st.keep(live, "edges")
    labels = live.select(F.explode(F.array("u", "v")).alias("id")).distinct().withColumn("comp", F.col("id"))
    live = live.filter("u <> v")
    for _ in range(max_rounds):
        if stored.count() <= IN_ONE_TASK:
            kind = live.schema["u"].dataType.simpleString()
            root = live.coalesce(1).mapInArrow(_in_one_task, f"x {kind}, p {kind}").withColumnRenamed("x", "comp")
            out = st.keep(labels.join(root, "comp", "left").select("id", F.coalesce(F.col("p"), F.col("comp")).alias("comp")), "labels")
            st.drop(stored, labels)
            return out
        # every label that has a smaller neighbour points to the smallest of them
        hook = st.keep(live.groupBy(F.col("v").alias("x")).agg(F.min("u").alias("p")), "hook")
        if hook.isEmpty():
            st.drop(hook)
            return labels
        root = _ends(st, hook)
        moved = labels.join(root.withColumnRenamed("x", "comp"), "comp", "left").select("id", F.coalesce(F.col("p"), F.col("comp")).alias("comp"))
        moved = st.keep(moved, "labels")
        a, b = root.select(F.col("x").alias("u"), F.col("p").alias("pu")), root.select(F.col("x").alias("v"), F.col("p").alias("pv"))
        nxt = (
            live.join(a, "u", "left")
            .join(b, "v", "left")
            .select(F.coalesce("pu", "u").alias("a"), F.coalesce("pv", "v").alias("b"))
            .filter("a <> b")
            .select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))
            .distinct()
        )
        nxt = st.keep(nxt, "live")
        st.drop(stored, labels, root)
        live = stored = nxt
        labels = moved
    raise RuntimeError("component contraction did not settle")


def _ends(st: Stages, hook: DataFrame) -> DataFrame:
    """Follow the pointers of `hook`(x, p) to the label that has none, doubling the distance each time."""
    while True:
        nxt = hook.select(F.col("x").alias("p"), F.col("p").alias("q"))
        step = st.keep(hook.join(nxt, "p", "left").select("x", F.coalesce("q", "p").alias("p"), F.col("q").isNotNull().alias("moved")), "ends")
        st.drop(hook)
        hook, going = step, step.filter("moved")
        if going.isEmpty():
            return hook


#: Parts of a table whose labels one task brings together.
FAN_IN = 8


def folded_labels(edges: DataFrame) -> DataFrame:
    """(id, comp) as `component_labels` has them, from one pass: each task labels its part of the table, and labels of parts are joined up a tree.

    A task holds some words for each vertex that it meets, where the rounds of `component_labels` hold none.
    """
    n = edges.rdd.getNumPartitions()
    found = edges.select("u", "v").mapInArrow(_in_one_task, "x long, p long")
    while n > 1:
        n = -(-n // FAN_IN)
        found = found.repartition(n).mapInArrow(_in_one_task, "x long, p long")
    return found.withColumnsRenamed({"x": "id", "p": "comp"})


def component_parts(edges: DataFrame, most_share: float = 0.5, most_edges: int | None = None) -> DataFrame | None:
    """(seq, u, v) with whole components dealt to tasks, in order of seq in each.

    None if one component has more than `most_share` of the edges, or more than `most_edges` of them: then it isn't worth it or doesn't fit.
    """
    st = Stages(edges.sparkSession, "parts")
    labels = st.keep(folded_labels(edges), "labels", rows=NUMBERS)
    if labels.agg(F.max("comp") == F.min("comp")).first()[0]:
        return None
    placed = st.keep(edges.select("seq", "u", "v").join(labels.withColumnRenamed("id", "u"), "u"), "placed")
    m, largest = placed.groupBy("comp").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n"), F.max("n")).first()
    if not m or largest > most_share * m or (most_edges is not None and largest > most_edges):
        st.drop(placed)
        return None
    n = 4 * int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if most_edges is not None:
        n = max(n, -(-2 * m // most_edges))
    return placed.repartition(n, "comp").sortWithinPartitions("seq").select("seq", "u", "v")
