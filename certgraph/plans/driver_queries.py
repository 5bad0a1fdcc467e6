"""Core driver queries. Spark answers from a certificate; the SQL beside each query answers from the full graph."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certgraph.functions.sql_functions import grouped_connectivity
from certgraph.operators import baselines, decide, layered, measures, online, separators
from certgraph.operators.edges import in_layer, induced, remove_vertices, reordered, residual, vertex_set
from certgraph.operators.forest import check_scan_order, components, first_neighbour_forest, min_spanning_forest, scan_first_forest, scan_order, spanning_forest
from certgraph.plans import oracle_sql as sql
from certgraph.plans.staging import Stages
from certgraph.sources.workloads import KNOWN, WORKLOADS, known_edges, weekly_types, window_degrees

Query = Callable[[SparkSession, str], DataFrame]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    e, v = _graph(spark, sf_dir, "user_topic_error")
    return separators.all_separators(layered.layered_certificate(e, 3, v), v, 3)


def _graph(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    st = Stages(spark, name)
    e = st.keep(known_edges(spark, name[6:]) if name.startswith("known_") else WORKLOADS[name](spark, sf_dir), "edges")
    return e, st.keep(vertex_set(e), "vertices")


def _verdict(via: str, name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return decide.is_k_connected(decide.certificate_for(e, k, via, v), v, k).select("k", "verdict")

    return run


def _connected(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        n = v.agg((F.count(F.lit(1)) - 1).alias("needed"))
        return spanning_forest(e).agg(F.count(F.lit(1)).alias("kept")).join(F.broadcast(n)).select((F.col("kept") == F.col("needed")).alias("connected"))

    return run


def _cert(via: str, name: str, k: int) -> Query:
    return lambda spark, sf_dir: decide.certificate_for(_graph(spark, sf_dir, name)[0], k, via).select("seq", "u", "v")


def _cuts(via: str, name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return separators.cut_vertices(decide.certificate_for(e, 2, via, v), v)

    return run


def _separators(via: str, name: str, size: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return separators.separators(decide.certificate_for(e, size + 1, via, v), v, size, size + 1)

    return run


def _all_separators(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return separators.all_separators(layered.layered_certificate(e, k, v), v, k)

    return run


def _count(name: str, size: int) -> Query:
    return lambda spark, sf_dir: _separators("layered", name, size)(spark, sf_dir).agg(F.count(F.lit(1)).alias("n"))


def _kappa(via: str, name: str, cap: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return decide.local_connectivity_apart(decide.certificate_for(e, cap, via, v), v, e, cap)

    return run


def _order(name: str, rule: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return scan_order(spanning_forest(e), v, rule)

    return run


def _handed(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return layered.handed_edges(e, scan_order(spanning_forest(e), v))

    return run


def _layered(name: str, k: int, **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return layered.layered_certificate(e, k, v, **options)

    return run


def _bounds(name: str, ks: tuple[int, ...]) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        out = None
        for k in ks:
            a = measures.certificate_stats(e, online.online_certificate(e, k, "merge"), k, v)
            b = measures.certificate_stats(e, layered.layered_certificate(e, k, v), k, v)
            row = a.select("k", "n", "m", (F.col("of_2kn") <= 1).alias("within_online")).join(b.select("k", (F.col("of_layers") <= 1).alias("within_layers")), "k")
            out = row if out is None else out.unionByName(row)
        return out

    return run


def _predicted(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.predicted_table(spark, v.count(), e.count(), k)

    return run


def _order_free(name: str, k: int) -> Query:
    """Verdicts from streams in other orders; the graph's own answer holds for each."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        out = None
        for rule in ("given", "reversed", "hashed"):
            c = layered.layered_certificate(reordered(e, rule), k, v)
            row = decide.is_k_connected(c, v, k).select(F.lit(rule).alias("stream"), "k", "verdict")
            out = row if out is None else out.unionByName(row)
        return out

    return run


def _order_free_sql(name: str, k: int) -> str:
    return f"SELECT stream, k, verdict FROM (VALUES ('given'), ('reversed'), ('hashed')) t(stream), ({sql.k_connected(name, k)}) q"


def _order_free_separators(name: str) -> Query:
    """How many separators of one and two vertices each stream order shows, and how many all of them show: the same number."""
    return lambda spark, sf_dir: measures.order_free_separators(*_graph(spark, sf_dir, name))


def _without_hubs(name: str, keep: bool) -> Query:
    """The graph without its ten busiest vertices, or only with those of degree three and more."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, _ = _graph(spark, sf_dir, name)
        d = e.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("d"))
        return induced(e, d.filter("d >= 3").select("id")) if keep else remove_vertices(e, d.orderBy(F.desc("d"), "id").limit(10).select("id"))

    return run


def _first_layer(name: str, what: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        order = Stages(spark, name).keep(scan_order(spanning_forest(e), v), "order")
        f = Stages(spark, name).keep(first_neighbour_forest(e, order), "forest")
        return residual(e, f).select("seq", "u", "v") if what == "residual" else in_layer(e, order, f).select("seq", "in_layer")

    return run


def _legal(name: str, rule: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return check_scan_order(e, scan_order(spanning_forest(e), v, rule)).agg(F.count(F.lit(1)).alias("faults"))

    return run


def _largest_k(name: str, most: int, via: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return spark.createDataFrame([(decide.vertex_connectivity(e, most, via, v),)], "kappa int")

    return run


def _minimal(name: str, size: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return separators.separators(layered.layered_certificate(e, size + 1, v), v, size, size + 1, minimal=True)

    return run


def _smallest(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return separators.minimum_separators(layered.layered_certificate(e, k, v), v, k)

    return run


def _pieces(name: str, k: int, via: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.pieces_without(decide.certificate_for(e, k, via, v), v, k)

    return run


def _valid(name: str, k: int, via: str, sets: int) -> Query:
    """Drawn sets of fewer than k vertices for which certificate and graph fall into other components; none."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        found = measures.validate_certificate(e, decide.certificate_for(e, k, via, v), v, k, sets)
        return found.agg(F.count(F.lit(1)).alias("sets"), F.sum(F.when(F.col("same"), 0).otherwise(1)).alias("faults"))

    return run


def _agreement(name: str, k: int) -> Query:
    return lambda spark, sf_dir: measures.agreement(_graph(spark, sf_dir, name)[0], k).select("k", "method", "verdict")


def _floor(name: str, k: int) -> Query:
    """Smallest degree in the certificate of a k-connected graph, and whether it and its rows reach the floor."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        c = layered.layered_certificate(e, k, v)
        least = measures.min_degree(c, v).select((F.col("min_degree") >= k).alias("degrees_reach_k"))
        size = measures.certificate_stats(e, c, k, v).select("n", "m", (F.col("of_floor") >= 1).alias("rows_reach_floor"), (F.col("of_layers") <= 1).alias("rows_within_layers"))
        return least.join(F.broadcast(size))

    return run


def _floor_sql(name: str, k: int) -> str:
    """What a k-connected graph must show; empty unless its own degrees reach k."""
    return f"SELECT n, m, TRUE AS degrees_reach_k, TRUE AS rows_reach_floor, TRUE AS rows_within_layers FROM ({sql.degree_stats(name)}) WHERE min_degree >= {k}"


def _passes(name: str, k: int) -> Query:
    """Rows that each pass of the layered method read, counted while it ran."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        reads = layered.layered_run(e, k, v, feed="original").reads
        return spark.createDataFrame([(i, n) for i, n in enumerate(reads, 1)], "pass int, rows_read long").withColumnRenamed("pass", "pass_no")

    return run


def _passes_sql(name: str, k: int) -> str:
    """The whole graph twice, then what earlier layers leave."""
    cert = sql.layered(name, k)
    return f"SELECT p::INT AS pass_no, (SELECT count(*) FROM ({sql.edges(name)})) - (SELECT count(*) FROM ({cert}) WHERE layer < p - 1) AS rows_read FROM range(1, {k + 2}) t(p)"


def _spanner_bounds(name: str, t: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return baselines.spanner_report(e, Stages(spark, name).keep(baselines.greedy_spanner(e, t), "spanner"), v, t)

    return run


def _work_of_decision(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.decision_work(layered.layered_certificate(e, k, v), v, k)

    return run


def _min_cuts(name: str, u: int, v: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, vertices = _graph(spark, sf_dir, name)
        return spark.createDataFrame([(list(c),) for c in decide.all_min_cuts(e, vertices, u, v, 7)], "members array<long>")

    return run


def _prefix(name: str, k: int, upto: int) -> Query:
    """Components after the first edges of a stream, from the certificate as it stood then."""
    return lambda spark, sf_dir: components(online.certificate_at(_graph(spark, sf_dir, name)[0], k, upto))


def _halves(name: str, method: str) -> Query:
    """Cut vertices from certificates of two halves of the stream, merged."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        a, b = (layered.layered_certificate(e.filter(F.pmod("seq", F.lit(2)) == r), 2) for r in (0, 1))
        return separators.cut_vertices(online.merge_certificates(a, b, 2, method), v)

    return run


def _separators_agree(name: str, size: int, via: str) -> Query:
    """Separators of the graph, of its certificate, and of both."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.separator_agreement(e, decide.certificate_for(e, size + 1, via, v), v, size)

    return run


def _layer_faults(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.forest_faults(layered.layered_run(e, k, v)).agg(F.sum("n").alias("faults"))

    return run


def _sizes(name: str, k: int) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, v = _graph(spark, sf_dir, name)
        return measures.certificate_stats(e, layered.layered_certificate(e, k, v, feed="original"), k, v).select("k", "n", "m", "cert_rows", "of_layers", "of_edges")

    return run


def _known(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Connectivity of each user's graph of event types in each week; equal graphs are decided once."""
    st = Stages(spark, "weekly")
    sets = st.keep(weekly_types(spark, sf_dir).groupBy("graph").agg(F.array_sort(F.collect_list(F.struct("u", "v"))).alias("edges")), "sets")
    kinds = sets.select("edges").distinct().withColumn("kind", F.to_json("edges"))
    rows = kinds.select("kind", F.posexplode("edges").alias("seq", "e")).select("kind", F.col("seq").cast("long").alias("seq"), "e.u", "e.v")
    decided = st.keep(grouped_connectivity(rows, "kind", 8), "decided")
    return sets.withColumn("kind", F.to_json("edges")).join(decided, "kind").select("graph", "kappa")


def _sweep(name: str, *exact: str) -> Query:
    """Certificate rows of the methods for k = 1 ... 6; the exact online ones where a single task can be waited for."""
    methods = ("layered", "layered_merge", "online_merge", *exact)
    return lambda spark, sf_dir: measures.size_sweep(spark, {name: WORKLOADS[name](spark, sf_dir)}, tuple(range(1, 7)), methods)


def _table() -> dict[str, tuple[Query, str | None]]:
    out: dict[str, tuple[Query, str | None]] = {}
    for name, make in WORKLOADS.items():
        out[f"edges_{name}"] = (make, sql.edges(name) if name in sql.ROWS else None)
        out[f"degree_stats_{name}"] = ((lambda f: lambda s, d: measures.degree_stats(f(s, d)))(make), sql.degree_stats(name) if name in sql.ROWS else None)
    out["degree_stats_call_window"] = (lambda s, d: measures.stats_of_degrees(window_degrees(s, d)), sql.degree_stats("call_window"))
    for name in ("page_link", "host_link", "geo_tree", "turn_path", "order_customer", "doc_line"):
        out[f"components_{name}"] = ((lambda f: lambda s, d: components(f(s, d)))(WORKLOADS[name]), sql.components(name))
    out["components_by_forest_page_link"] = (lambda s, d: components(WORKLOADS["page_link"](s, d), strategy="forest"), sql.components("page_link"))
    for name in ("call_error", "page_link", "part_supplier", "customer_part"):
        out[f"connected_{name}"] = (_connected(name), sql.connected(name))
    for name in ("call_error", "nation_trade", "host_link"):
        out[f"spanning_forest_{name}"] = (lambda s, d, n=name: spanning_forest(_graph(s, d, n)[0]), sql.spanning_forest(name))
    out["spanning_forest_rounds_host_link"] = (lambda s, d: spanning_forest(_graph(s, d, "host_link")[0], "boruvka"), sql.spanning_forest("host_link"))
    out["min_spanning_forest_host_link"] = (lambda s, d: min_spanning_forest(_graph(s, d, "host_link")[0], "seq"), sql.spanning_forest("host_link"))
    for name in ("nation_trade", "host_link"):
        out[f"scan_order_{name}"] = (_order(name, "preorder"), sql.scan_order(name))
        out[f"scan_first_forest_{name}"] = (lambda s, d, n=name: scan_first_forest(*_graph(s, d, n)), sql.scan_first_forest(name))
        out[f"handed_edges_{name}"] = (_handed(name), sql.handed(name))
    out["scan_order_level_host_link"] = (_order("host_link", "level"), sql.level_order("host_link"))
    out["layered_original_nation_trade_3"] = (_layered("nation_trade", 3, feed="original"), sql.layered("nation_trade", 3))
    out["layered_original_host_link_2"] = (_layered("host_link", 2, feed="original"), sql.layered("host_link", 2))
    out["layered_handover_host_link_3"] = (_layered("host_link", 3), sql.layered_handover("host_link", 3))
    out["layered_handover_nation_trade_6"] = (_layered("nation_trade", 6), sql.layered_handover("nation_trade", 6))
    out["layered_original_nation_trade_6"] = (_layered("nation_trade", 6, feed="original"), sql.layered("nation_trade", 6))
    out["layered_level_host_link_2"] = (_layered("host_link", 2, rule="level"), None)
    out["layered_merge_part_supplier_3"] = (_layered("part_supplier", 3, mode="merge"), None)
    for via in ("online", "online_rounds", "online_merge"):
        out[f"{via}_certificate_call_error_3"] = (_cert(via, "call_error", 3), None)
    for name, k in (("nation_trade", 3), ("user_topic_error", 2), ("host_link", 2), ("part_supplier_quarter", 2)):
        for via in ("layered", "online_merge", "full"):
            out[f"k_connected_{via}_{name}_{k}"] = (_verdict(via, name, k), sql.k_connected(name, k))
    for name in ("host_link", "page_link", "user_topic_error", "part_supplier_quarter", "turn_path", "doc_line", "geo_tree"):
        out[f"cut_vertices_{name}"] = (_cuts("layered", name), sql.cut_vertices(name))
    out["cut_vertices_online_page_link"] = (_cuts("online_merge", "page_link"), sql.cut_vertices("page_link"))
    for name in ("nation_trade", "call_error"):
        out[f"certificate_bounds_{name}"] = (_bounds(name, (1, 2, 3)), sql.bounds(name, (1, 2, 3)))
    out["predicted_costs_call_error_3"] = (_predicted("call_error", 3), sql.predicted("call_error", 3))
    out["bipartite_user_topic_error"] = (lambda s, d: baselines.is_bipartite(_graph(s, d, "user_topic_error")[0]).select("bipartite"), sql.bipartite("user_topic_error"))
    out["bipartite_call_error"] = (lambda s, d: baselines.is_bipartite(_graph(s, d, "call_error")[0]).select("bipartite"), sql.bipartite("call_error"))
    out["bfs_layers_host_link_2"] = (lambda s, d: baselines.bfs_layer_certificate(_graph(s, d, "host_link")[0], 2)[0], sql.bfs_layers("host_link", 2))
    out["forest_partition_call_error_3"] = (lambda s, d: baselines.forest_partition_certificate(_graph(s, d, "call_error")[0], 3), None)
    out["small_k_call_error_3"] = (lambda s, d: baselines.small_k_certificate(_graph(s, d, "call_error")[0], 3), None)
    out["local_layers_call_error_3"] = (lambda s, d: baselines.local_layer_certificate(_graph(s, d, "call_error")[0], 3), None)
    out["matching_part_supplier"] = (lambda s, d: baselines.greedy_matching(_graph(s, d, "part_supplier")[0]), None)
    out["spanner_call_error_3"] = (lambda s, d: baselines.greedy_spanner(_graph(s, d, "call_error")[0], 3), None)
    out["online_work_call_error_3"] = (lambda s, d: measures.work_summary(measures.online_work(_graph(s, d, "call_error")[0], 3)), None)
    out["growth_call_error_3"] = (lambda s, d: (lambda e: online.growth_curve(e, online.online_certificate(e, 3)))(_graph(s, d, "call_error")[0]), None)
    for keep in (False, True):
        out[f"{'induced' if keep else 'without_hubs'}_host_link"] = (_without_hubs("host_link", keep), sql.without_hubs("host_link", keep))
    out["residual_host_link"] = (_first_layer("host_link", "residual"), sql.first_layer("host_link", "residual"))
    out["in_layer_host_link"] = (_first_layer("host_link", "member"), sql.first_layer("host_link", "member"))
    for rule in ("preorder", "level"):
        out[f"order_faults_{rule}_page_link"] = (_legal("page_link", rule), "SELECT CAST(0 AS BIGINT) AS faults")
    out["layer_faults_host_link_3"] = (_layer_faults("host_link", 3), "SELECT CAST(0 AS BIGINT) AS faults")
    out["layered_sizes_nation_trade_2"] = (_sizes("nation_trade", 2), sql.layered_sizes("nation_trade", 2))
    out["min_degree_host_link"] = (lambda s, d: measures.min_degree(*_graph(s, d, "host_link")), sql.min_degree("host_link"))
    out["known_graphs"] = (_known, sql.weekly_connectivity())
    out["certificate_floor_call_all_6"] = (_floor("call_all", 6), _floor_sql("call_all", 6))
    out["prefix_components_host_link"] = (_prefix("host_link", 2, 600), sql.prefix_components("host_link", 600))
    for method in ("online", "layered"):
        out[f"cut_vertices_merged_{method}_page_link"] = (_halves("page_link", method), sql.cut_vertices("page_link"))
    for name, k in (("host_link", 3), ("user_topic_error", 3), ("nation_trade", 5)):
        out[f"passes_{name}_{k}"] = (_passes(name, k), _passes_sql(name, k))
    out["spanner_bounds_call_error_3"] = (_spanner_bounds("call_error", 3), None)
    out["decision_work_call_error_6"] = (_work_of_decision("call_error", 6), None)
    out["peak_words_call_error_3"] = (lambda s, d: measures.peak_words(_graph(s, d, "call_error")[0], 3), None)
    out["layered_work_host_link_3"] = (lambda s, d: measures.layered_work(layered.layered_run(*(lambda g: (g[0], 3, g[1]))(_graph(s, d, "host_link")))), None)
    return out | _known_answers() | _whole_tables()


def _known_answers() -> dict[str, tuple[Query, str | None]]:
    """Decisions for k up to 7, separators of up to four vertices and what lies between, against removal of all small sets."""
    out: dict[str, tuple[Query, str | None]] = {}
    for name, (_, _, kappa) in KNOWN.items():
        g = f"known_{name}"
        if kappa < 2:
            continue
        for k in (kappa, kappa + 1):
            for via in ("layered", "online_merge"):
                out[f"k_connected_{via}_{g}_{k}"] = (_verdict(via, g, k), sql.k_connected(g, k))
    for name in ("cube", "cliques", "harary"):
        g = f"known_{name}"
        out[f"all_separators_{g}_6"] = (_all_separators(g, 6), sql.all_separators(g, 6))
        out[f"kappa_layered_{g}_5"] = (_kappa("layered", g, 5), sql.kappa(g, 5))
        out[f"kappa_online_{g}_5"] = (_kappa("online", g, 5), sql.kappa(g, 5))
    for name in ("grid", "cycle", "prism", "cube"):
        g = f"known_{name}"
        out[f"separators4_online_{g}"] = (_separators("online_merge", g, 4), sql.separators(g, 4))
        out[f"minimal_separators4_{g}"] = (_minimal(g, 4), sql.minimal_separators(g, 4))
        out[f"minimum_separators_{g}"] = (_smallest(g, 5), sql.smallest_separators(g, 5))
        out[f"count_separators3_{g}"] = (_count(g, 3), sql.separator_count(g, 3))
    for name in ("grid", "cliques"):
        g = f"known_{name}"
        for via in ("layered", "layered_merge", "online", "online_merge"):
            out[f"pieces_without_{via}_{g}_4"] = (_pieces(g, 4, via), sql.pieces_without(g, 4))
    for name, u, v in (("grid", 0, 14), ("prism", 0, 3), ("cube", 0, 15), ("cliques", 0, 10)):
        out[f"all_min_cuts_known_{name}"] = (_min_cuts(f"known_{name}", u, v), sql.all_min_cuts(f"known_{name}", u, v, 5))
    for name in ("cube", "cliques"):
        g = f"known_{name}"
        out[f"agreement_{g}_5"] = (_agreement(g, 5), sql.agreement(g, 5))
        out[f"order_free_{g}_5"] = (_order_free(g, 5), _order_free_sql(g, 5))
        out[f"vertex_connectivity_layered_{g}"] = (_largest_k(g, 7, "layered"), sql.largest_k(g, 7))
        out[f"vertex_connectivity_full_{g}"] = (_largest_k(g, 7, "full"), sql.largest_k(g, 7))
    return out


def _whole_tables() -> dict[str, tuple[Query, str | None]]:
    """Large k, separators and sweeps on graphs of whole tables; SQL by removal is too slow for most, tests compare by brute force."""
    out: dict[str, tuple[Query, str | None]] = {}
    signs = {sql.k_connected_by_signs: (("call_all", 5), ("call_all", 6), ("nation_trade", 6)), sql.k_connected_by_degree: (("user_topic_error", 5), ("part_supplier_year", 3), ("customer_supplier_returns", 3), ("geo_orders", 5))}
    for oracle, graphs in signs.items():
        for name, k in graphs:
            for via in ("layered", "online_merge"):
                out[f"k_connected_{via}_{name}_{k}"] = (_verdict(via, name, k), oracle(name, k))
    out["k_connected_full_call_all_6"] = (_verdict("full", "call_all", 6), sql.k_connected_by_signs("call_all", 6))
    out["k_connected_online_call_error_6"] = (_verdict("online", "call_error", 6), None)
    for via in ("layered", "layered_merge", "online_merge", "full"):
        out[f"k_connected_{via}_call_error_6"] = (_verdict(via, "call_error", 6), None)
        out[f"k_connected_{via}_user_topic_error_4"] = (_verdict(via, "user_topic_error", 4), None)
    for name in ("part_supplier_year", "customer_supplier_returns"):
        out[f"vertex_connectivity_layered_{name}"] = (_largest_k(name, 5, "layered"), None)
        out[f"separators2_{name}"] = (_separators("layered", name, 2), None)
    out["vertex_connectivity_layered_part_supplier_quarter"] = (_largest_k("part_supplier_quarter", 5, "layered"), sql.largest_k_by_signs("part_supplier_quarter"))
    out["vertex_connectivity_layered_call_error"] = (_largest_k("call_error", 8, "layered"), None)
    out["vertex_connectivity_online_call_error"] = (_largest_k("call_error", 8, "online_merge"), None)
    for name in ("user_topic_error", "host_link"):
        out[f"separators2_{name}"] = (_separators("layered", name, 2), None)
        out[f"separators_agree2_layered_{name}"] = (_separators_agree(name, 2, "layered"), None)
        out[f"separators_agree2_online_{name}"] = (_separators_agree(name, 2, "online_merge"), None)
    out["kappa_layered_user_topic_error_5"] = (_kappa("layered", "user_topic_error", 5), None)
    out["kappa_full_user_topic_error_5"] = (_kappa("full", "user_topic_error", 5), None)
    out["minimum_separators_user_topic_error"] = (_smallest("user_topic_error", 5), None)
    for via in ("layered", "online_merge"):
        out[f"certificate_faults_{via}_user_topic_error_5"] = (_valid("user_topic_error", 5, via, 5000), "SELECT CAST(5000 AS BIGINT) AS sets, CAST(0 AS BIGINT) AS faults")
    for name in ("call_error", "user_topic_error"):
        out[f"agreement_{name}_5"] = (_agreement(name, 5), None)
        out[f"order_free_{name}_5"] = (_order_free(name, 5), None)
        out[f"order_free_separators_{name}"] = (_order_free_separators(name), None)
    for name in ("call_error", "user_topic_error", "nation_trade"):
        out[f"sweep_{name}"] = (_sweep(name, "online", "online_rounds"), None)
    for name in ("part_supplier", "customer_supplier_returns"):
        out[f"sweep_{name}"] = (_sweep(name), None)
    return out


def queries() -> dict[str, Query]:
    return {k: q for k, (q, _) in _table().items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _table().items() if s}
