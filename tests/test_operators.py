"""DataFrame operators against kernels, brute force and replays."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from certgraph.functions import graph_kernels as K
from certgraph.operators import baselines, decide, layered, measures, online, separators
from certgraph.operators.edges import EdgeStream, canonical_edges, decode_ids, encode_ids, in_layer, induced, remove_vertices, reordered, vertex_set
from certgraph.operators.forest import check_scan_order, components, first_neighbour_forest, is_connected, min_spanning_forest, scan_first_forest, scan_order, spanning_forest
from certgraph.plans.staging import Stages
from certgraph.sources.workloads import WORKLOADS, known_edges, known_graph


def triples(df):
    return sorted((r.seq, r.u, r.v) for r in df.select("seq", "u", "v").collect())


@pytest.fixture(scope="module")
def calls(spark, sf):
    e = WORKLOADS["user_topic_error"](spark, sf).cache()
    return e, vertex_set(e).cache()


def test_canonical_edges_drop_loops_nulls_and_repeats(spark):
    rows = spark.createDataFrame([(3, 1, 1), (1, 3, 2), (2, 2, 3), (None, 2, 4), (5, 4, 5)], "a long, b long, t long")
    assert triples(canonical_edges(rows, "a", "b", ["t"])) == [(1, 1, 3), (2, 4, 5)]
    assert canonical_edges(rows.limit(0), "a", "b", ["t"]).count() == 0


def test_ids_are_dense_and_decodable(spark):
    rows = spark.createDataFrame([("x", "b"), ("b", "a"), (None, "x")], "a string, b string")
    coded, book = encode_ids(rows, ["a", "b"])
    assert sorted(r.id for r in book.collect()) == [0, 1, 2]
    assert sorted(map(str, decode_ids(coded, book, ["a", "b"]).collect())) == sorted(map(str, rows.collect()))


def test_subgraphs(spark):
    e = known_edges(spark, "cycle", 5)
    some = spark.createDataFrame([(0,), (1,), (2,)], "id long")
    assert triples(induced(e, some)) == [(1, 0, 1), (2, 1, 2)]
    assert triples(remove_vertices(e, some.filter("id = 0"))) == [(2, 1, 2), (3, 2, 3), (4, 3, 4)]


def test_forests_match_the_sequential_scan(spark, calls):
    e, _ = calls
    want = sorted(K.kept_edges(triples(e)))
    assert triples(spanning_forest(e)) == want == triples(spanning_forest(e, "boruvka"))
    for rule in ("reversed", "hashed"):
        r = reordered(e, rule)
        assert triples(spanning_forest(r, partitions=20)) == sorted(K.kept_edges(triples(r)))


def test_components_and_connectedness(spark):
    e = spark.createDataFrame([(1, 0, 1), (2, 2, 3), (3, 3, 4)], "seq long, u long, v long")
    more = spark.createDataFrame([(9,)], "id long")
    v = vertex_set(e, more)
    for strategy in ("contract", "forest"):
        assert sorted((r.id, r.comp) for r in components(e, v, strategy).collect()) == [(0, 0), (1, 0), (2, 2), (3, 2), (4, 2), (9, 9)]
    assert not is_connected(e, v) and is_connected(known_edges(spark, "grid", 3, 3), vertex_set(known_edges(spark, "grid", 3, 3)))
    assert components(e.limit(0)).count() == 0


def test_long_path_has_one_component(spark):
    e = known_edges(spark, "path", 300)
    assert components(e).select("comp").distinct().count() == 1


@pytest.mark.parametrize("rule", ["preorder", "level"])
def test_orders_are_legal_and_forests_scan_first(spark, calls, rule):
    e, v = calls
    order = scan_order(spanning_forest(e), v, rule).cache()
    assert check_scan_order(e, order).count() == 0
    pos = {r.id: r.pos for r in order.collect()}
    assert sorted(pos.values()) == list(range(len(pos)))
    f = {r.child: (r.parent, r.seq) for r in first_neighbour_forest(e, order).collect()}
    assert f == K.first_neighbours(triples(e), pos)
    # a scan in that very order makes the same forest
    g = K.graph_of([(a, b) for _, a, b in triples(e)])
    by_order = K.scan_first_forest(g, lambda marked: min(marked, key=pos.get), sorted(g, key=pos.get))[0]
    assert sorted(by_order) == sorted((p, c) for c, (p, _) in f.items())


def test_illegal_order_is_found(spark):
    e = known_edges(spark, "path", 4)
    bad = spark.createDataFrame([(0, 0, 0), (2, 0, 1), (1, 0, 2), (3, 0, 3)], "id long, comp long, pos long")
    assert [r.id for r in check_scan_order(e, bad).collect()] == [2]


def replay(edges, k):
    """The k nested instances edge by edge, each pass in order; only for tests."""
    layers, feed = [], list(edges)
    for _ in range(k):
        z = K.graph_of([(u, v) for _, u, v in K.kept_edges(feed)], {x for _, u, v in edges for x in (u, v)})
        pos = {x: i for i, (x, _) in enumerate(K.preorder(z))}
        stored, nxt = {}, []
        for s, u, v in edges:
            if any(s in layer for layer in layers):
                continue
            p, c = (u, v) if pos[u] < pos[v] else (v, u)
            if c not in stored:
                stored[c] = (s, u, v, p)
            elif pos[p] < pos[stored[c][3]]:
                old, stored[c] = stored[c], (s, u, v, p)
                nxt.append((s, old[1], old[2]))
            else:
                nxt.append((s, u, v))
        layers.append({x[0] for x in stored.values()})
        feed = nxt
    return sorted((s, i) for i, layer in enumerate(layers, 1) for s in layer)


def test_nested_schedule_equals_the_replay(spark):
    rng = random.Random(2)
    for _ in range(3):
        edges = [(i, u, v) for i, (u, v) in enumerate(rng.sample([p for p in combinations(range(9), 2) if rng.random() < 0.8], k=22), 1)]
        e = spark.createDataFrame(edges, "seq long, u long, v long")
        for got in (layered.layered_certificate(e, 3), layered.layered_run(e, 3).certificate):
            assert sorted((r.seq, r.layer) for r in got.collect()) == replay(edges, 3)


def test_one_task_gives_the_rows_of_the_passes(spark, sf):
    e = Stages(spark, "t").keep(WORKLOADS["call_error"](spark, sf), "edges")
    for rule, feed in (("preorder", "handover"), ("level", "original")):
        one, passes = (layered.layered_certificate(e, 3, rule=rule, feed=feed, in_one_task=n) for n in (10**6, 0))
        assert sorted(one.collect()) == sorted(passes.collect())


@pytest.mark.parametrize("rule", ["preorder", "level"])
def test_orders_by_rounds_equal_those_of_one_task(spark, rule):
    rng = random.Random(3)
    pairs = [(i, rng.randrange(i)) for i in range(1, 40) if i % 13]  # trees of mixed shape
    pairs += [(50, x) for x in range(51, 60)]  # a star
    pairs += [(x, x + 1) for x in range(60, 90)]  # a path
    e = spark.createDataFrame([(i, min(p) * 3, max(p) * 3) for i, p in enumerate(pairs, 1)], "seq long, u long, v long")
    v = vertex_set(e, spark.createDataFrame([(1000,), (-5,)], "id long"))
    rows = lambda df: sorted((r.pos, r.id, r.comp) for r in df.collect())
    assert rows(scan_order(e, v, rule, in_one_task=0)) == rows(scan_order(e, v, rule))


def test_handing_on_in_stretches(spark, calls):
    e, v = calls
    order = Stages(spark, "t").keep(scan_order(spanning_forest(e), v), "order")
    rows = lambda df: sorted((r.seq, r.u, r.v, r.handed) for r in df.collect())
    whole = rows(layered.handed_edges(e, order))
    assert len(whole) > 50 and rows(layered.handed_edges(e, order, stretch=7)) == whole
    hub = spark.createDataFrame([(i, i, 500) for i in range(1, 60)] + [(100 + i, i, i + 1) for i in range(1, 59)], "seq long, u long, v long")
    back = spark.createDataFrame([(x, 1, 60 - x) for x in range(1, 60)] + [(500, 1, 60)], "id long, comp long, pos long")
    assert rows(layered.handed_edges(hub, back, stretch=7)) == rows(layered.handed_edges(hub, back))


def test_layered_run_keeps_its_promises(spark, calls):
    e, v = calls
    run = layered.layered_run(e, 3, v)
    m, sizes = e.count(), [f.count() for f in run.forests]
    assert run.passes == 4 and len(layered.pass_schedule(3)) == 4
    assert run.reads == [m, m, m - sizes[0], m - sizes[0] - sizes[1]]  # as they happened
    assert layered.layered_run(e, 3, v, feed="original", rule="level").passes == 4
    assert layered.layered_run(e, 2, v, forest="boruvka").certificate.count() <= 2 * (v.count() - 1)
    assert measures.forest_faults(run).filter("n <> 0").count() == 0
    n = v.count()
    assert run.certificate.count() <= 3 * (n - 1)
    marked = in_layer(e, run.positions[0], run.forests[0])
    assert {r.seq for r in marked.filter("in_layer").collect()} == {r.seq for r in run.forests[0].collect()}


@pytest.mark.parametrize("via", ["layered", "layered_merge", "online", "online_rounds", "online_merge"])
def test_certificates_preserve_components_without_small_sets(spark, sf, via):
    e = known_edges(spark, "grid")
    v = vertex_set(e).cache()
    cert = decide.certificate_for(e, 3, via, v)
    assert measures.validate_certificate(e, cert, v, 3).filter("NOT same").count() == 0
    assert measures.local_agreement(e, cert, v, 3).count() == 0


def test_online_modes_agree(spark, calls):
    e, _ = calls
    want = triples(online.online_certificate(e, 2))
    got, rounds = online.online_rounds(e, 2, head=40)
    assert triples(got) == want and rounds > 1
    again = e.unionByName(e.select((F.col("seq") + 10_000).alias("seq"), "u", "v"))
    assert triples(online.online_certificate(again, 2)) == want  # repeated edges change nothing
    curve = {r["read"]: r["kept"] for r in online.growth_curve(e, spark.createDataFrame(want, "seq long, u long, v long"), 5).collect()}
    assert curve[max(curve)] == len(want)
    assert triples(online.certificate_at(e, 2, 60)) == [x for x in want if x[0] <= 60]


def test_stream_order_changes_no_verdict(spark, calls):
    e, v = calls
    found = set()
    for rule in ("given", "reversed", "hashed"):
        c = layered.layered_certificate(reordered(e, rule), 2, v)
        found.add(tuple(sorted(r.id for r in separators.cut_vertices(c, v).collect())))
    assert len(found) == 1 and len(found.pop()) == 13


def test_separators_of_the_error_graph(spark, calls):
    e, v = calls
    cert = layered.layered_certificate(e, 3, v)
    assert separators.count_separators(cert, v, 1) == 13
    assert separators.count_separators(cert, v, 2) == 1297
    minimal = separators.separators(cert, v, 2, 3, minimal=True).collect()
    ones = {r.members[0] for r in separators.separators(cert, v, 1).collect()}
    assert len(minimal) < 1297 and not any(ones & set(r.members) for r in minimal)
    assert separators.has_separator(cert, v, 1) and separators.separators(cert, v, 2, limit=5).count() == 5
    assert separators.separates(cert, v, [min(ones)])[0]
    with pytest.raises(ValueError):
        separators.separators(cert, v, 3, layers=3)


@pytest.mark.parametrize(("kind", "size", "kappa"), [("cycle", (6,), 2), ("wheel", (6,), 3), ("cube", (3,), 3), ("bipartite", (3, 4), 3), ("cliques", (5, 3), 3), ("complete", (5,), 4)])
def test_decisions_on_known_graphs(spark, kind, size, kappa):
    e = known_edges(spark, kind, *size)
    assert decide.k_connected(e, kappa).first().verdict
    assert decide.vertex_connectivity(e, 5, via="online") == kappa


def test_decision_reasons(spark):
    e = known_edges(spark, "cycle", 5)
    v = vertex_set(e)
    assert decide.is_k_connected(e, v, 5).first().reason == "too_few_vertices"
    assert decide.is_k_connected(e, v, 3).first().reason == "low_degree"
    two = known_edges(spark, "cliques", 4, 1)
    assert decide.is_k_connected(two, vertex_set(two), 2).first().reason == "pair"
    lone = vertex_set(e, spark.createDataFrame([(77,)], "id long"))
    assert decide.is_k_connected(e, lone, 1).first().witness == [77]


def test_cuts_and_paths(spark):
    e = known_edges(spark, "cycle", 6)
    v = vertex_set(e)
    assert decide.local_connectivity(e, v, 0, 3, 5) == 2
    assert sorted(map(len, decide.disjoint_paths(e, v, 0, 2, 5))) == [3, 5]
    assert decide.all_min_cuts(e, v, 0, 2, 5) == [(1, 3), (1, 4), (1, 5)]
    assert decide.min_vertex_cut(e, v, 0, 1, 5) is None and len(decide.min_vertex_cut(e, v, 0, 3, 5)) == 2
    found = separators.minimum_separators(e, v, 3).collect()
    assert len(found) == 9


def test_baselines(spark, calls):
    e, v = calls
    n, rows = v.count(), triples(e)
    g = K.graph_of([(a, b) for _, a, b in rows])
    want = K.brute_separators(g, 1)
    for cert in (baselines.bfs_layer_certificate(e, 2)[0], baselines.forest_partition_certificate(e, 2), baselines.local_layer_certificate(e, 2, "smallest"), baselines.small_k_certificate(e, 2)):
        c = K.graph_of([(a, b) for _, a, b in triples(cert)])
        assert cert.count() <= 2 * (n - 1) and K.brute_separators(c, 1) == want
    assert baselines.bfs_layer_certificate(e, 2)[1] > 3  # more passes than the layered method's
    assert baselines.certificate_floor(5, 3) == 8
    assert baselines.is_bipartite(e).first().bipartite
    assert not baselines.is_bipartite(known_edges(spark, "cycle", 5)).first().bipartite
    m = triples(baselines.greedy_matching(e))
    used = [x for _, a, b in m for x in (a, b)]
    assert len(used) == len(set(used)) and all(a in used or b in used for _, a, b in rows)
    s = K.graph_of([(a, b) for _, a, b in triples(baselines.greedy_spanner(e, 3))])
    assert all(_distance(s, a, b) <= 3 for _, a, b in rows)
    with pytest.raises(ValueError):
        baselines.small_k_certificate(e, 5)


def _distance(g, a, b):
    seen, front, d = {a}, {a}, 0
    while b not in seen:
        front = {y for x in front for y in g[x]} - seen
        seen |= front
        d += 1
    return d


def test_weighted_forest(spark):
    rows = [(i, u, v, (u * 7 + v * 5) % 11) for i, (u, v) in enumerate(combinations(range(8), 2), 1)]
    e = spark.createDataFrame(rows, "seq long, u long, v long, cost long")
    best = K.kept_edges([(s, u, v) for _, s, u, v in sorted((c, s, u, v) for s, u, v, c in rows)])
    assert triples(min_spanning_forest(e, "cost")) == sorted(best)


def test_measures(spark, calls):
    e, v = calls
    cert = online.online_certificate(e, 2)
    s = measures.certificate_stats(e, cert, 2, v).first()
    assert s.of_2kn <= 1 and s.m == 182 and s.n == 107
    w = measures.work_summary(measures.online_work(e, 2)).first()
    assert w.kept == s.cert_rows and w.peak_words <= measures.words_bound(s.n) * 4
    assert measures.layered_words(10, 2) == 80 and measures.cited_bound(10, 2) > 10
    assert measures.agreement(e, 2, ("layered", "online_merge")).filter("NOT agrees").count() == 0
    a = measures.separator_agreement(e, cert, v, 1).first()
    assert a.in_graph == a.in_certificate == a.in_both == 13
    assert measures.min_degree(cert, v).first().min_degree >= 1
    assert measures.without(known_edges(spark, "star", 5), vertex_set(known_edges(spark, "star", 5)), [0]) == 5
    assert {r.method for r in measures.predicted_table(spark, 100, 500, 3).collect()} == {"online", "layered", "one forest"}
    t = measures.timed_sweep(spark, {"w": known_edges(spark, "wheel", 6)}, (1, 2), ("layered", "online_merge"))
    assert measures.sweep_report(t).count() == 2 * 3 * 3


def test_words_held_follow_vertices_not_edges(spark):
    """Ten times the edges on the same vertices: forest folds hold as much as before, the online method what it keeps."""
    rng = random.Random(6)
    pairs = rng.sample(list(combinations(range(120), 2)), 4000)
    few, many = (spark.createDataFrame([(i, *p) for i, p in enumerate(pairs[:m], 1)], "seq long, u long, v long").coalesce(1) for m in (400, 4000))
    a, b = ({r.method: r.words for r in measures.peak_words(x, 2).collect()} for x in (few, many))
    assert a["layered"] == b["layered"] == (4 + 6) * 120
    assert b["online"] <= 5 * 2 * 2 * 120 + 120 and b["online"] < 2 * a["online"]


def test_work_of_decisions_and_layers(spark, calls):
    e, v = calls
    run = layered.layered_run(e, 3, v)
    w = measures.layered_work(run).first()
    assert 0 < w.mean_tests <= w.most_tests <= 3 and w.most_in_a_pass == 2
    cube = known_edges(spark, "cube", 3)
    d = measures.decision_work(cube, vertex_set(cube), 3).first()
    assert d.checks == 3 + 8 - 3 and d.searches >= d.checks and d.all_passed and d.cited_bound > 8


def test_directed_edges_are_refused_or_made_plain(spark):
    df = spark.createDataFrame([(1, 2, 1), (2, 1, 2), (3, 3, 3)], "a long, b long, t long")
    with pytest.raises(ValueError, match="directed"):
        canonical_edges(df, "a", "b", ["t"], directed=True)
    assert canonical_edges(df, "a", "b", ["t"], directed=True, symmetrise=True).count() == 1


def test_spanner_bounds(spark, calls):
    e, v = calls
    g = K.graph_of([(a, b) for _, a, b in triples(e)])
    far = max(d for x in g for d in K.distances_from(g, x).values())
    girth = min(_distance_without(g, a, b) + 1 for _, a, b in triples(e))
    s = Stages(spark, "t").keep(baselines.greedy_spanner(e, 3), "spanner")
    r = baselines.spanner_report(e, s, v, 3).first()
    assert r.diameter_least <= far <= r.diameter_most and r.girth_least <= girth <= r.girth_most
    one = v.orderBy("id").limit(1)
    for d in baselines.spanner_distances(s, v, one).collect():
        true = K.distances_from(g, d.source)[d.id]
        assert true <= d.distance <= 3 * true
    whole = baselines.spanner_report(e, e, v, 1).first()
    assert whole.diameter_least == whole.diameter_most == far and whole.girth_least == whole.girth_most == girth


def _distance_without(g, a, b):
    h = {x: g[x] - ({b} if x == a else {a} if x == b else set()) for x in g}
    return K.distances_from(h, a).get(b, 10**6)


def test_weighted_matching_is_half_of_the_best(spark):
    rng = random.Random(4)
    rows = [(i, u, v, rng.randint(1, 20)) for i, (u, v) in enumerate(combinations(range(8), 2), 1) if rng.random() < 0.6]
    e = spark.createDataFrame(rows, "seq long, u long, v long, w long")

    def best(left):
        return max([0, *(w + best([r for r in left[i + 1 :] if not {u, v} & {r[1], r[2]}]) for i, (_, u, v, w) in enumerate(left))])

    weight = {r[0]: r[3] for r in rows}
    got = triples(baselines.greedy_matching(e, "w"))
    used = [x for _, a, b in got for x in (a, b)]
    assert len(used) == len(set(used)) and 2 * sum(weight[s] for s, _, _ in got) >= best(rows)


def test_merged_certificates(spark, calls):
    e, v = calls
    a, b = e.filter("seq % 2 = 0"), e.filter("seq % 2 = 1")
    for method in ("online", "layered"):
        c = online.merge_certificates(online.online_certificate(a, 2), layered.layered_certificate(b, 2), 2, method)
        assert {r.id for r in separators.cut_vertices(c, v).collect()} == {r.id for r in separators.cut_vertices(e, v).collect()}


def test_pass_counter(spark):
    s = EdgeStream(known_edges(spark, "path", 4))
    s.open_pass().count()
    assert [r.seq for r in s.sorted_pass(2).collect()] == [1, 2, 3] and s.passes == 2 and s.reads()[0] == 3


@pytest.mark.parametrize("edges", [[], [(1, 0, 1)]])
def test_tiny_graphs(spark, edges):
    e = spark.createDataFrame(edges, "seq long, u long, v long")
    assert layered.layered_certificate(e, 3).count() == len(edges)
    assert online.online_certificate(e, 3, "merge").count() == len(edges) == scan_first_forest(e).count()
    assert not decide.k_connected(e, 3).first().verdict


def test_plans(spark, calls, capsys):
    e, v = calls
    order = Stages(spark, "plans").keep(scan_order(spanning_forest(e), v), "order")
    first_neighbour_forest(e, order).explain("formatted")
    plan = capsys.readouterr().out
    assert "partial_min" in plan.lower() or "Aggregate" in plan
    assert "CartesianProduct" not in plan and "MapInArrow" not in plan


def test_date_filter_reaches_the_scan(spark, sf, capsys):
    spark.read.parquet(f"{sf}/lineitem.parquet").filter(F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz")).select("l_partkey").explain("formatted")
    assert "GreaterThanOrEqual(l_shipdate" in capsys.readouterr().out


def test_known_graph_counts():
    assert len(known_graph("complete", 6)) == 15 and len(known_graph("cube", 4)) == 32


def test_registered_queries_of_whole_tables_match_brute_force(spark, sf):
    from certgraph.plans.driver_queries import queries

    q, name = queries(), "user_topic_error"
    g = K.graph_of([(u, v) for _, u, v in triples(WORKLOADS[name](spark, sf))])
    want = {size: K.brute_separators(g, size) for size in (1, 2)}
    assert {tuple(r.members) for r in q[f"separators2_{name}"](spark, sf).collect()} == want[2]
    for via in ("layered", "online"):
        r = q[f"separators_agree2_{via}_{name}"](spark, sf).first()
        assert r.in_graph == r.in_certificate == r.in_both == len(want[2])
    for via in ("layered", "full"):
        pairs = q[f"kappa_{via}_{name}_5"](spark, sf).collect()
        assert len(pairs) == len(g) * (len(g) - 1) // 2 - sum(map(len, g.values())) // 2
        assert all(r.kappa == K.PathFlow(g, r.u, r.v, 5).value for r in pairs)
    found = {r.l: (r.separators, r.fewest_streams) for r in q[f"order_free_separators_{name}"](spark, sf).collect()}
    assert found == {size: (len(x), 3) for size, x in want.items()}


def test_large_k_on_the_call_graph(spark, sf):
    """More paths than any earlier one-pass method could tell, from both certificates and from the graph itself."""
    e = Stages(spark, "t").keep(WORKLOADS["call_error"](spark, sf), "edges")
    g = K.graph_of([(u, v) for _, u, v in triples(e)])
    kappa = next(k for k in range(12, 0, -1) if K.is_k_connected(g, k))
    assert kappa > 4
    for via in ("layered", "online_merge", "online", "full"):
        assert decide.vertex_connectivity(e, 12, via) == kappa


def test_sweep_counts_its_passes(spark, calls):
    from certgraph.plans.driver_queries import queries

    tree = measures.timed_sweep(spark, {"p": known_edges(spark, "path", 6)}, (3,), ("layered", "online_rounds", "online_merge")).collect()
    assert {r.method: r.passes for r in tree} == {"layered": layered.layered_run(known_edges(spark, "path", 6), 3).passes, "online_rounds": 1, "online_merge": 1}
    assert {f"sweep_{n}" for n in ("call_error", "user_topic_error", "part_supplier", "nation_trade", "customer_supplier_returns")} | {"order_free_call_error_5"} <= set(queries())
