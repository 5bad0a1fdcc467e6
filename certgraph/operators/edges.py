"""Edges and vertices as DataFrames: simple graphs in stream order, dense ids, residuals, induced subgraphs."""

from __future__ import annotations

from collections.abc import Sequence

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.plans.staging import Stages


def dense_numbers(df: DataFrame, order_by: Sequence[str | Column], name: str, first: int = 1) -> DataFrame:
    """Adds the place of each row in an order, counted from `first`, without gathering rows in one task.

    Rows are dealt out by ranges and sorted within them; a range's numbers begin after the rows of all ranges before it.
    """
    st = Stages(df.sparkSession, "numbers")
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = df.repartitionByRange(n, *order_by).sortWithinPartitions(*order_by)
    placed = placed.withColumn("_part", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    placed = st.keep(placed, "placed")
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each range
    starts = placed.groupBy("_part").agg(F.count(F.lit(1)).alias("_n")).select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    return placed.join(F.broadcast(starts), "_part").withColumn(name, F.col("_start") + F.col("_at") + first).drop("_part", "_at", "_start")


def canonical_edges(df: DataFrame, src: str, dst: str, order_by: Sequence[str], directed: bool = False, symmetrise: bool = False) -> DataFrame:
    """Simple undirected graph edges(seq, u, v) of a two-column table: u < v, each pair once, at its first occurrence.

    Loops and rows with a null end are dropped. `seq` numbers the kept edges 1, 2, ... in stream order; `order_by` must be
    a total order of the rows, up to rows that stand for the same edge. Rows whose direction means something (`directed`) are refused,
    as no method here answers for directed paths, unless `symmetrise` says to forget it.
    """
    if directed and not symmetrise:
        raise ValueError("directed edges: connectivity along directions cannot be decided in a bounded number of passes; pass symmetrise=True to forget them")
    ends = df.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b"), F.struct(*order_by).alias("o")).filter("a IS NOT NULL AND b IS NOT NULL AND a <> b")
    pairs = ends.groupBy(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).agg(F.min("o").alias("o"))
    return dense_numbers(pairs, ["o", "u", "v"], "seq").select("seq", "u", "v")


def vertex_set(edges: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """All ends of edges, and the ids of `extra` (its first column), which may be isolated."""
    ids = edges.select(F.explode(F.array("u", "v")).alias("id"))
    if extra is not None:
        ids = ids.unionByName(extra.select(F.col(extra.columns[0]).cast("long").alias("id")).filter("id IS NOT NULL"))
    return ids.distinct()


def degrees(edges: DataFrame) -> DataFrame:
    """(id, d) for every end of an edge."""
    return edges.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("d"))


def encode_ids(df: DataFrame, cols: Sequence[str]) -> tuple[DataFrame, DataFrame]:
    """Replace ids of any type in `cols` by their places 0, 1, ... in ascending order; also the dictionary (name, id)."""
    names = df.select(F.explode(F.array(*(F.col(c).cast("string") for c in cols))).alias("name")).filter("name IS NOT NULL").distinct()
    book = Stages(df.sparkSession, "ids").keep(dense_numbers(names, ["name"], "id", first=0), "book")
    out = df
    for c in cols:
        out = out.join(book.select(F.col("name").alias("_n"), F.col("id").alias("_i")), F.col(c).cast("string") == F.col("_n"), "left").drop("_n", c).withColumnRenamed("_i", c)
    return out.select(*df.columns), book


def decode_ids(df: DataFrame, book: DataFrame, cols: Sequence[str]) -> DataFrame:
    out = df
    for c in cols:
        out = out.join(book.select(F.col("id").alias("_i"), F.col("name").alias("_n")), F.col(c) == F.col("_i"), "left").drop("_i", c).withColumnRenamed("_n", c)
    return out.select(*df.columns)


def remove_vertices(edges: DataFrame, gone: DataFrame) -> DataFrame:
    """Edges of the graph without the vertices in the first column of `gone`."""
    ids = gone.select(F.col(gone.columns[0]).alias("_x"))
    return edges.join(ids, F.col("u") == F.col("_x"), "left_anti").join(ids, F.col("v") == F.col("_x"), "left_anti")


def induced(edges: DataFrame, keep: DataFrame) -> DataFrame:
    """Edges between the vertices in the first column of `keep`."""
    ids = keep.select(F.col(keep.columns[0]).alias("_x"))
    return edges.join(ids, F.col("u") == F.col("_x"), "left_semi").join(ids, F.col("v") == F.col("_x"), "left_semi")


def residual(edges: DataFrame, taken: DataFrame) -> DataFrame:
    """Edges whose seq is in none of the earlier layers."""
    return edges.join(taken.select("seq"), "seq", "left_anti")


def in_layer(edges: DataFrame, positions: DataFrame, forest: DataFrame) -> DataFrame:
    """Adds `in_layer`: whether the parent stored for an edge's later end is its earlier end, in this layer's order."""
    a = positions.select(F.col("id").alias("u"), F.col("pos").alias("_pu"))
    b = positions.select(F.col("id").alias("v"), F.col("pos").alias("_pv"))
    later = F.when(F.col("_pu") < F.col("_pv"), F.col("v")).otherwise(F.col("u"))
    both = edges.join(a, "u").join(b, "v").withColumn("_c", later)
    parents = forest.select(F.col("child").alias("_c"), F.col("parent").alias("_p"))
    return both.join(parents, "_c", "left").withColumn("in_layer", F.coalesce(F.col("_p") == F.when(F.col("_c") == F.col("v"), F.col("u")).otherwise(F.col("v")), F.lit(False))).drop("_pu", "_pv", "_c", "_p")


class EdgeStream:
    """An edge table read in passes, one direction, in an order; counts the rows that each pass does read."""

    def __init__(self, edges: DataFrame, order: str = "seq"):
        self.edges, self.order = edges, order
        self._seen: list[Observation] = []

    def open_pass(self, edges: DataFrame | None = None) -> DataFrame:
        """The edges, or what is left of them, as the next pass reads them; the plan that uses it must run."""
        seen = Observation()
        self._seen.append(seen)
        return (self.edges if edges is None else edges).observe(seen, F.count(F.lit(1)).alias("rows"))

    def sorted_pass(self, partitions: int) -> DataFrame:
        return self.open_pass().repartitionByRange(partitions, self.order).sortWithinPartitions(self.order)

    def reads(self) -> list[int]:
        """Rows read by each pass so far; none by a plan that turned out to be empty before it was run."""
        return [_observed(seen) for seen in self._seen]

    @property
    def passes(self) -> int:
        return len(self.reads())


def _observed(seen: Observation) -> int:
    try:
        return int(seen.get["rows"])
    except Py4JJavaError:  # no row to report, as the plan was replaced by an empty one
        return 0


def reordered(edges: DataFrame, rule: str, seed: int = 1) -> DataFrame:
    """The same edges as another stream: "given", "reversed" or "hashed" order."""
    if rule == "given":
        return edges
    key = {"reversed": -F.col("seq"), "hashed": F.xxhash64(F.lit(seed), "u", "v")}[rule]
    return dense_numbers(edges.select("u", "v", key.alias("k")), ["k", "u", "v"], "seq").select("seq", "u", "v")


