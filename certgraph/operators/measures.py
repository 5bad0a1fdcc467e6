"""Costs and checks of certificates: passes, work, size, memory, agreement with the full graph, predicted bounds."""

from __future__ import annotations

import math
import time
from collections import Counter
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import OnlineCertificate, check_flow, component_count, nth_combination
from certgraph.operators.components import component_labels, component_parts
from certgraph.operators.decide import all_pairs, certificate_for, is_k_connected, local_connectivity_pairs, shared_graph, spread
from certgraph.operators.edges import degrees, remove_vertices, reordered, vertex_set
from certgraph.operators.forest import edge_chunks, fold_words, in_order, oriented
from certgraph.operators.layered import LayeredRun, layered_certificate, layered_run, merged_layers
from certgraph.operators.online import merged_certificate, online_certificate, online_rounds
from certgraph.operators.separators import pair_terms, separators, shown_by
from certgraph.plans.staging import NUMBERS, Stages


def certificate_stats(edges: DataFrame, cert: DataFrame, k: int, vertices: DataFrame | None = None) -> DataFrame:
    """One row: n, m, kept rows, and their ratios to the bounds 2kn, k(n - 1), kn / 2 and to m."""
    vertices = vertex_set(edges) if vertices is None else vertices
    n, m, c = vertices.agg(F.count(F.lit(1)).alias("n")), edges.agg(F.count(F.lit(1)).alias("m")), cert.agg(F.count(F.lit(1)).alias("cert_rows"))
    one = n.join(F.broadcast(m)).join(F.broadcast(c)).withColumn("k", F.lit(k))
    share = lambda bound: F.col("cert_rows") / bound
    return one.select("k", "n", "m", "cert_rows", share(2 * k * F.col("n")).alias("of_2kn"), share(k * (F.col("n") - 1)).alias("of_layers"), share(k * F.col("n") / 2).alias("of_floor"), share(F.col("m")).alias("of_edges"))


def min_degree(cert: DataFrame, vertices: DataFrame) -> DataFrame:
    """One row: the smallest degree, isolated vertices included."""
    d = cert.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("d"))
    return vertices.select("id").join(d, "id", "left").agg(F.min(F.coalesce("d", F.lit(0))).alias("min_degree"))


def degree_stats(edges: DataFrame) -> DataFrame:
    """One row: n, m, least, largest and mean degree."""
    return stats_of_degrees(degrees(edges))


def stats_of_degrees(d: DataFrame) -> DataFrame:
    return d.agg(F.count(F.lit(1)).alias("n"), F.floor(F.sum("d") / 2).alias("m"), F.min("d").alias("min_degree"), F.max("d").alias("max_degree"), F.avg("d").alias("mean_degree"))


def online_work(edges: DataFrame, k: int) -> DataFrame:
    """Per edge of the exact online method: flows run, arcs visited, whether it was kept, and words held after it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = OnlineCertificate(k)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64())
        for seq, u, v in edge_chunks(batches):
            out = []
            for e in zip(seq.tolist(), u.tolist(), v.tolist(), strict=True):
                f, a = c.flows, c.arcs
                kept = c.offer(e)
                out.append((e[0], c.flows - f, c.arcs - a, kept, c.words))
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["seq", "flows", "arcs", "kept", "words"])

    return in_order(edges, 1).mapInArrow(run, "seq long, flows long, arcs long, kept boolean, words long")


def work_summary(work: DataFrame) -> DataFrame:
    """Mean, 99th percentile and maximum of flows and arcs for each edge, and the most words held."""
    return work.agg(F.avg("flows").alias("mean_flows"), F.max("flows").alias("max_flows"), F.avg("arcs").alias("mean_arcs"), F.percentile_approx("arcs", 0.99).alias("p99_arcs"), F.max("arcs").alias("max_arcs"), F.max("words").alias("peak_words"), F.sum(F.col("kept").cast("long")).alias("kept"))


def layered_work(run: LayeredRun) -> DataFrame:
    """One row: tests of an edge for membership in finished layers, over all passes, mean and most for one edge, and most in one pass.

    In pass p an edge meets the layers up to p - 2, in order, until one holds it; here rows are filed by their fate instead, so
    this is what an edge-at-a-time reading of the same run would cost.
    """
    k = len(run.forests)
    tests = lambda layer: sum(min(layer, p - 2) for p in range(2, k + 2))
    kept = run.edges.select("seq").join(run.certificate.select("seq", "layer"), "seq", "left")
    cost = F.lit(tests(k))
    for i in range(1, k + 1):
        cost = F.when(F.col("layer") == i, F.lit(tests(i))).otherwise(cost)
    return kept.select(cost.alias("tests")).agg(F.avg("tests").alias("mean_tests"), F.max("tests").alias("most_tests")).withColumn("most_in_a_pass", F.lit(k - 1))


def decision_work(cert: DataFrame, vertices: DataFrame, k: int) -> DataFrame:
    """One row: checks of the decision, searches for paths and arcs that they look at, beside the bound of the best known routine."""
    g, n = shared_graph(cert, vertices), vertices.count()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flows = [check_flow(g.value, g.value.ids, k, r) for r in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([f.searches for f in flows], pa.int64()), pa.array([f.arcs for f in flows], pa.int64()), pa.array([f.value >= k for f in flows], pa.bool_())], names=["searches", "arcs", "passed"])

    rows = max(0, math.comb(k, 2) + n - k) if n > k else 0
    done = spread(cert.sparkSession.range(rows)).mapInArrow(run, "searches long, arcs long, passed boolean")
    return done.agg(F.count(F.lit(1)).alias("checks"), F.coalesce(F.sum("searches"), F.lit(0)).alias("searches"), F.coalesce(F.sum("arcs"), F.lit(0)).alias("arcs"), F.coalesce(F.every("passed"), F.lit(False)).alias("all_passed")).withColumn("cited_bound", F.lit(cited_bound(n, k)))


class SparkCost:
    """What Spark did within a `with` block: seconds, tasks, rows and bytes read, shuffled and spilled."""

    FIELDS = ("tasks", "rows_read", "mb_read", "mb_shuffled", "mb_spilled")

    def __init__(self, spark: SparkSession):
        self.spark = spark

    def _stages(self) -> dict[tuple[int, int], tuple[float, ...]]:
        sc = self.spark.sparkContext
        jvm = sc._jvm
        found = sc._jsc.sc().statusStore().stageList(jvm.java.util.ArrayList(), False, False, sc._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): (s.numCompleteTasks(), s.inputRecords(), s.inputBytes() / 1e6, s.shuffleWriteBytes() / 1e6, s.diskBytesSpilled() / 1e6) for s in (found.apply(i) for i in range(found.size()))}

    def __enter__(self) -> SparkCost:
        self.before, self.began = self._stages(), time.time()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.time() - self.began
        new = [v for k, v in self._stages().items() if k not in self.before]
        self.tasks, self.rows_read, self.mb_read, self.mb_shuffled, self.mb_spilled = (sum(x) for x in zip(*new, strict=True)) if new else (0,) * 5


def peak_words(edges: DataFrame, k: int) -> DataFrame:
    """(method, n, m, words): the most words that a task held while it read the edges, metered in the task.

    "online": the certificate, as rows and as sets of neighbours. "layered": one instance's disjoint sets, with the order, its
    inverse and a stored parent for each layer beside them.
    """
    vertices = vertex_set(edges).count()
    m = edges.count()
    online = online_work(edges, k).agg(F.max("words").alias("words")).select(F.lit("online").alias("method"), "words")
    layered = fold_words(edges).agg((F.max("words") + F.lit(3 * k * vertices)).alias("words")).select(F.lit("layered").alias("method"), "words")
    return online.unionByName(layered).select("method", F.lit(vertices).cast("long").alias("n"), F.lit(m).cast("long").alias("m"), "words")


def layered_words(n: int, k: int) -> int:
    """Words that the layered method holds: order, inverse and one stored parent for each layer, and the live disjoint sets."""
    return k * 3 * n + 2 * n


def predicted_costs(n: int, m: int, k: int) -> list[tuple[str, int, float, int]]:
    """(method, passes, work for each edge, certificate rows at most), constants left out."""
    alpha = 1 if n < 2 else max(1, sum(1 for b in (2, 4, 16, 65536) if n > b))  # inverse Ackermann, up to any n in use
    return [("online", 1, float(k * k * n), min(m, 2 * k * n)), ("layered", k + 1, float(k + alpha), min(m, k * max(0, n - 1))), ("one forest", 2, float(alpha), min(m, max(0, n - 1)))]


def predicted_table(spark: SparkSession, n: int, m: int, k: int) -> DataFrame:
    return spark.createDataFrame(predicted_costs(n, m, k), "method string, passes int, work double, rows_at_most long")


def cited_bound(n: int, k: int) -> float:
    """Steps of the best known decision on a certificate, constants left out."""
    return n + min(k**2.5, k * n**0.75) * k * n


def agreement(edges: DataFrame, k: int, methods: tuple[str, ...] = ("layered", "layered_merge", "online_rounds", "online_merge")) -> DataFrame:
    """(k, method, verdict, agrees): the verdict from each certificate beside that from the full graph."""
    spark = edges.sparkSession
    vertices = Stages(spark, "agreement").keep(vertex_set(edges), "vertices")
    truth = is_k_connected(edges, vertices, k).first().verdict
    rows = []
    for m in methods:
        got = is_k_connected(certificate_for(edges, k, m, vertices), vertices, k).first().verdict
        rows.append((k, m, got, got == truth))
    return spark.createDataFrame(rows, "k int, method string, verdict boolean, agrees boolean")


def separator_agreement(edges: DataFrame, cert: DataFrame, vertices: DataFrame, size: int) -> DataFrame:
    """One row: separators of the graph, of the certificate, and of both; pairs are counted without being listed."""
    if size == 2:
        shown = shown_by([pair_terms(shared_graph(e, vertices)) for e in (edges, cert)])
        row = tuple(sum(n for s, n in shown.items() if s & which == which) for which in (1, 2, 3))
        return edges.sparkSession.createDataFrame([row], "in_graph long, in_certificate long, in_both long")
    a = separators(edges, vertices, size).select("members")
    b = separators(cert, vertices, size).select("members")
    tagged = a.withColumn("g", F.lit(1)).withColumn("c", F.lit(0)).unionByName(b.withColumn("g", F.lit(0)).withColumn("c", F.lit(1))).groupBy("members").agg(F.max("g").alias("g"), F.max("c").alias("c"))
    return tagged.agg(F.coalesce(F.sum("g"), F.lit(0)).alias("in_graph"), F.coalesce(F.sum("c"), F.lit(0)).alias("in_certificate"), F.coalesce(F.sum(F.col("g") * F.col("c")), F.lit(0)).alias("in_both"))


def order_free_separators(edges: DataFrame, vertices: DataFrame, rules: tuple[str, ...] = ("given", "reversed", "hashed")) -> DataFrame:
    """(l, separators, fewest_streams): separators of one and two vertices that any stream order's certificate shows, and the fewest streams that show one of them."""
    graphs = [shared_graph(layered_certificate(reordered(edges, rule), 3, vertices), vertices) for rule in rules]
    single = Counter(r.members[0] for g in graphs for r in separators(edges, vertices, 1, shared=g).select("members").collect())
    pairs = {s: n for s, n in shown_by([pair_terms(g) for g in graphs]).items() if s}
    rows = [(1, len(single), min(single.values()))] if single else []
    rows += [(2, sum(pairs.values()), min(s.bit_count() for s in pairs))] if pairs else []
    return edges.sparkSession.createDataFrame(rows, "l int, separators long, fewest_streams long")


def local_agreement(edges: DataFrame, cert: DataFrame, vertices: DataFrame, cap: int) -> DataFrame:
    """Pairs whose number of disjoint paths, up to cap, differs between graph and certificate; empty if it is preserved."""
    pairs = all_pairs(vertices)
    a = local_connectivity_pairs(edges, vertices, pairs, cap).withColumnRenamed("kappa", "in_graph")
    b = local_connectivity_pairs(cert, vertices, pairs, cap).withColumnRenamed("kappa", "in_certificate")
    return a.join(b, ["u", "v"]).filter("in_graph <> in_certificate")


def _small_sets(shared: Broadcast, spark: SparkSession, k: int, sets: int | None, work, schema: str) -> DataFrame:
    """`work` on vertex sets of fewer than k, all of them or so many drawn by a fixed rule; made in the tasks from their numbers."""
    n = len(shared.value)
    counts = [math.comb(n, r) for r in range(min(k, n + 1))]
    rows = spark.range(sum(counts)) if sets is None else spark.range(sets).select(F.pmod(F.xxhash64("id", F.lit(17)), F.lit(sum(counts))).alias("id"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value.ids
        for b in batches:
            chosen = []
            for index in b.column(0).to_pylist():
                size = 0
                while index >= counts[size]:
                    index -= counts[size]
                    size += 1
                chosen.append([int(ids[i]) for i in nth_combination(n, size, index)])
            yield work(chosen)

    return spread(rows).mapInArrow(run, schema)


def pieces_without(cert: DataFrame, vertices: DataFrame, k: int, sets: int | None = None) -> DataFrame:
    """(removed, pieces): into how many components a certificate falls without each set of fewer than k vertices."""
    c = shared_graph(cert, vertices)

    def work(chosen: list[list[int]]) -> pa.RecordBatch:
        pieces = [component_count(c.value, set(s)) for s in chosen]
        return pa.RecordBatch.from_arrays([pa.array(chosen, pa.list_(pa.int64())), pa.array(pieces, pa.int32())], names=["removed", "pieces"])

    return _small_sets(c, cert.sparkSession, k, sets, work, "removed array<long>, pieces int")


def validate_certificate(edges: DataFrame, cert: DataFrame, vertices: DataFrame, k: int, sets: int | None = None) -> DataFrame:
    """(removed, same): for removed sets of fewer than k vertices, whether graph and certificate have equal components.

    All sets if `sets` is None (for small graphs), else so many drawn by a fixed rule.
    """
    g, c = shared_graph(edges, vertices), shared_graph(cert, vertices)

    def labels(graph, gone):
        out: dict[int, int] = {}
        for s in graph:
            if s not in gone and s not in out:
                todo, out[s] = [s], s
                while todo:
                    for y in graph[todo.pop()]:
                        if y not in gone and y not in out:
                            out[y] = s
                            todo.append(y)
        return out

    def work(chosen: list[list[int]]) -> pa.RecordBatch:
        same = [labels(g.value, set(s)) == labels(c.value, set(s)) for s in chosen]
        return pa.RecordBatch.from_arrays([pa.array(chosen, pa.list_(pa.int64())), pa.array(same, pa.bool_())], names=["removed", "same"])

    return _small_sets(g, edges.sparkSession, k, sets, work, "removed array<long>, same boolean")


def without(edges: DataFrame, vertices: DataFrame, members: list[int]) -> int:
    """Components left when `members` are taken away, by DataFrame operators; for graphs of any size."""
    gone = edges.sparkSession.createDataFrame([(x,) for x in members], "id long")
    left = remove_vertices(edges, gone)
    ids = vertices.select("id").join(gone, "id", "left_anti")
    labels = ids.join(component_labels(left), "id", "left").select(F.coalesce("comp", "id").alias("c"))
    return labels.distinct().count()


def forest_faults(run: LayeredRun) -> DataFrame:
    """(layer, fault, n): broken invariants of the forests, all zero for a right run.

    Each child has one stored parent, placed before it and first among its neighbours in the layer's residual; the forest
    has a row for every vertex but one of each component of the residual; no edge is in two layers.
    """
    spark, rows, left = run.certificate.sparkSession, [], None
    for i, (order, forest) in enumerate(zip(run.positions, run.forests, strict=True), 1):
        left = run.edges if left is None else left.join(run.forests[i - 2].select("seq"), "seq", "left_anti")
        best = oriented(left, order).groupBy("child").agg(F.min("parent_pos").alias("least"))
        rows.append((i, "not the first neighbour", forest.join(best, "child").filter("parent_pos <> least").count()))
        rows.append((i, "parent after child", forest.join(order.select(F.col("id").alias("child"), "pos"), "child").filter("pos <= parent_pos").count()))
        rows.append((i, "rows missing", abs(best.count() - forest.count())))
        comps = component_labels(left)
        rows.append((i, "components not spanned", abs(comps.count() - comps.select("comp").distinct().count() - forest.count())))
    rows.append((0, "edge in two layers", run.certificate.groupBy("seq").count().filter("count > 1").count()))
    return spark.createDataFrame(rows, "layer int, fault string, n long")


def timed_sweep(spark: SparkSession, graphs: dict[str, DataFrame], ks: tuple[int, ...], methods: tuple[str, ...], nested: bool = True) -> DataFrame:
    """(workload, method, k, n, m, cert_rows, passes, rows_read, mb_shuffled, seconds) for each combination.

    `passes` are the reads that the layered run counted as they happened (one for a graph that one task certifies if `nested` does not ask
    for the passes of `layered_run`), the rounds of "online_rounds", and one for methods that read the stream once; `rows_read` and `mb_shuffled` are what Spark itself counted, intermediate tables included.
    """
    rows = []
    for name, edges in graphs.items():
        st = Stages(spark, "sweep")
        edges = st.keep(edges, name)
        vertices = st.keep(vertex_set(edges), "vertices")
        m, n = edges.count(), vertices.count()
        for k in ks:
            for method in methods:
                passes = 1
                with SparkCost(spark) as cost:
                    if method == "layered" and nested:
                        run = layered_run(edges, k, vertices)
                        cert, passes = run.certificate, run.passes
                    elif method == "online_rounds":
                        cert, passes = online_rounds(edges, k)
                    else:
                        cert = certificate_for(edges, k, method, vertices)
                    c = cert.count()
                rows.append((name, method, k, n, m, c, passes, int(cost.rows_read), float(cost.mb_shuffled), cost.seconds))
    return spark.createDataFrame(rows, "workload string, method string, k int, n long, m long, cert_rows long, passes int, rows_read long, mb_shuffled double, seconds double")


def size_sweep(spark: SparkSession, graphs: dict[str, DataFrame], ks: tuple[int, ...], methods: tuple[str, ...]) -> DataFrame:
    """(workload, method, k, n, m, cert_rows) as `timed_sweep` gives them, without its costs.

    The layers of the layered certificate don't depend on how many follow, so that for the largest k holds all others.
    """
    rows = []
    for name, edges in graphs.items():
        st = Stages(spark, "sweep")
        edges = st.keep(edges, name)
        vertices = st.keep(vertex_set(edges), "vertices")
        m, n = edges.count(), vertices.count()
        sizes = {(x, k): 0 for x in ("layered_merge",) if x in methods for k in ks}
        if "layered" in methods:
            by_layer = layered_certificate(edges, max(ks), vertices).groupBy("layer").count().collect()
            sizes |= {("layered", k): sum(r[1] for r in by_layer if r.layer <= k) for k in ks}
        # those that one job can make are made together, as each ends in a single task; whether components are dealt to tasks doesn't depend on k,
        # and where they are not, both merge forms begin with the same tree
        parts = component_parts(edges) if "online_merge" in methods else None
        merged = {}
        if "layered_merge" in methods:
            trees = (merged_layers(edges, k).select("seq", "u", "v", F.lit(k).alias("k")) for k in reversed(ks))
            stored = st.keep(reduce(DataFrame.unionByName, trees), "merged", by="k", rows=NUMBERS)
            sizes |= {("layered_merge", r.k): r["count"] for r in stored.groupBy("k").count().collect()}
            merged = {k: stored.filter(F.col("k") == k).select("seq", "u", "v") for k in ks}
        lazy = {"online_merge": lambda k: merged_certificate(edges.select("seq", "u", "v"), k, parts, merged=merged.get(k)), "online": lambda k: online_certificate(edges, k)}
        for x in methods:
            if x in lazy:
                made = [lazy[x](k).agg(F.count(F.lit(1)).alias("c")).select(F.lit(k).alias("k"), "c") for k in reversed(ks)]
                sizes |= {(x, r.k): r.c for r in st.keep(reduce(DataFrame.unionByName, made), x, rows=NUMBERS).collect()}
        for k in ks:
            for method in methods:
                if (method, k) not in sizes:
                    sizes[method, k] = certificate_for(edges, k, method, vertices).count()
                rows.append((name, method, k, n, m, sizes[method, k]))
    return spark.createDataFrame(rows, "workload string, method string, k int, n long, m long, cert_rows long")


def sweep_report(sweep: DataFrame) -> DataFrame:
    """Mean share of kept edges by workload, method and k, with all subtotals."""
    return sweep.cube("workload", "method", "k").agg(F.avg(F.col("cert_rows") / F.col("m")).alias("kept_share"), F.sum("seconds").alias("seconds"))


def words_bound(n: int) -> float:
    """n times log2(n) squared: what "a little more than linear" allows in words."""
    return n * max(1.0, math.log2(max(2, n))) ** 2

