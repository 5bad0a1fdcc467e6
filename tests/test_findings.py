"""One small test for each finding of round 2 that changed code of the core."""

import random

import numpy as np
import pytest

from certgraph.functions import graph_kernels as K
from certgraph.plans import driver_queries

def test_known_graphs_read_a_given_table(spark, sf):
    """connectivity of small graphs of the events table, against removal of all sets of types in SQL."""
    import duckdb

    from certgraph.sources.workloads import weekly_types

    assert any("events.parquet" in f for f in weekly_types(spark, sf).inputFiles())
    c = duckdb.connect()
    c.sql(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    want = sorted(c.sql(driver_queries.oracle_sql()["known_graphs"]).fetchall())
    got = sorted(tuple(r) for r in driver_queries.queries()["known_graphs"](spark, sf).collect())
    assert got == want and len({k for _, k in want}) >= 3


def _random_graph(seed, n, p):
    rng = random.Random(seed)
    e = [(u, v) for u in range(n) for v in range(u + 1, n) if rng.random() < p and ((u < n // 2) == (v < n // 2) or rng.random() < 0.4)]
    return K.graph_of(e, range(n)), K.PackedGraph(np.array([u for u, _ in e], np.int64), np.array([v for _, v in e], np.int64), np.arange(n)), e


@pytest.mark.parametrize("seed", range(6))
def test_inseparable_sets_hold_only_what_few_vertices_do_not_part(seed):
    """pairs of one set need no search; what is left outside is parted by fewer than k vertices."""
    g, packed, _ = _random_graph(seed, 14, 0.2 + 0.1 * seed)
    for k in (1, 2, 3, 4):
        core = K.inseparable_sets(packed, k)
        for x in g:
            assert all(core[x] != core[y] or core[x] < 0 or y in g[x] or K.local_connectivity(g, x, y, k) >= k for y in g if y != x)
        if (core >= 0).any():
            assert (core == core.max()).all() == K.brute_k_connected(g, k)


def test_kappa_of_all_pairs(spark):
    """the query's form, on a graph and its certificate, adjacent pairs among them."""
    from certgraph.operators import decide, layered
    from certgraph.operators.edges import vertex_set

    g, _, rows = _random_graph(3, 16, 0.5)
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows)], "seq long, u long, v long")
    v = vertex_set(e)
    for cert in (e, layered.layered_certificate(e, 4, v)):
        got = decide.local_connectivity_pairs(cert, v, decide.all_pairs(v), 4, dealt=True).collect()
        own = K.graph_of([(r.u, r.v) for r in cert.collect()], g)
        assert len(got) == len(own) * (len(own) - 1) // 2 and all(r.kappa == K.local_connectivity(own, r.u, r.v, 4) for r in got)


@pytest.mark.parametrize("seed", range(4))
def test_minimum_separators_from_few_pairs(spark, seed):
    """only pairs of an outside vertex and a few of the set are searched; the sets found are those of all pairs."""
    from certgraph.operators import separators
    from certgraph.operators.edges import vertex_set

    g, packed, rows = _random_graph(seed, 13, 0.35)
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows)], "seq long, u long, v long")
    cuts = {c for u in g for v in g if u < v for c in K.minimum_cuts(g, u, v, 4) if c}
    least = min((len(c) for c in cuts), default=0)
    got = [tuple(r.members) for r in separators.minimum_separators(e, vertex_set(e), 4).collect()]
    assert sorted(got) == sorted(c for c in cuts if len(c) == least) and len(K.component_of_each(packed)) == 13


@pytest.mark.parametrize("seed", range(12))
def test_pockets_count_the_pieces_without_two_vertices(seed):
    """what pairs of vertices cut off, added up from the pockets outside the inseparable set."""
    g, packed, _ = _random_graph(100 + seed, 15, 0.3 + 0.05 * (seed % 4))
    core = K.inseparable_sets(packed, 3)
    if not (core >= 0).any():
        pytest.skip("no set to begin with")
    pockets, alone, terms = K.Pockets(core, packed), dict.fromkeys(g, 0), {}
    for near, _ in pockets.loose(packed):
        if len(near) == 2:
            terms[min(near), max(near)] = terms.get((min(near), max(near)), 0) + 1
        elif near:
            alone[min(near)] += 1
    for a in (x for p in pockets.members for x in p):
        mine, both = pockets.without(packed, a)
        alone[a] += mine
        for b, n in both.items():
            terms[min(a, b), max(a, b)] = terms.get((min(a, b), max(a, b)), 0) + n
    whole = K.component_count(g)
    assert all(K.component_count(g, {a, b}) - whole == alone[a] + alone[b] + terms.get((a, b), 0) for a in g for b in g if a < b)


@pytest.mark.parametrize("seed", range(3))
def test_separators_of_two_around_pockets(spark, seed):
    """the query's rows, with pieces, against removal of each pair."""
    from certgraph.operators import separators
    from certgraph.operators.edges import vertex_set

    g, packed, rows = _random_graph(7 + seed, 15, 0.4)
    g = {x: y for x, y in g.items() if y}
    assert (K.inseparable_sets(packed, 3) >= 0).any()
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows)], "seq long, u long, v long")
    got = sorted((*r.members, r.pieces) for r in separators.separators(e, vertex_set(e), 2).collect())
    whole = K.component_count(g)
    assert got == sorted((a, b, n) for a in g for b in g if a < b and (n := K.component_count(g, {a, b})) > whole)


@pytest.mark.parametrize("k", (2, 3, 5))
def test_the_online_certificate_refuses_without_a_search(k):
    """the same edges as decided one by one by paths, with searches for a few of the refused edges only."""
    rng = random.Random(k)
    rows = [(i, u, v) for i, (u, v) in enumerate((rng.randrange(200), rng.randrange(200)) for _ in range(6000)) if u != v]
    c, g, kept = K.OnlineCertificate(k), {}, []
    for e in rows:
        c.offer(e)
        if e[1] not in g or e[2] not in g or (e[2] not in g[e[1]] and K.local_connectivity(g, e[1], e[2], k) < k):
            kept.append(e)
            g.setdefault(e[1], set()).add(e[2])
            g.setdefault(e[2], set()).add(e[1])
    assert c.kept == kept and c.flows < 1000 and len(c.core) > 190


@pytest.mark.parametrize("seed", range(3))
def test_spanner_kernels(seed):
    """distances from both ends and from many vertices at once, cycles up to a length."""
    g, packed, _ = _random_graph(40 + seed, 90, 0.04 + 0.02 * seed)
    far = {x: K.distances_from(g, x) for x in g}
    assert all(K.within(g, u, v, t) == (far[u].get(v, 99) <= t) for u in g for v in g if u < v for t in (1, 2, 3, 4))
    assert K.widest(packed, sorted(g), words=1) == max(max(d.values()) for d in far.values())
    girth = min((c for x in g if (c := K.shortest_cycle(g, x))), default=None)
    assert girth is not None and min(c for x in g if (c := K.shortest_cycle(g, x, girth))) == girth
    assert not any(K.shortest_cycle(g, x, girth - 1) for x in g)


@pytest.mark.parametrize("seed", range(6))
def test_layers_in_passes(spark, seed):
    """one task certifies numbered edges a stretch at a time, with the rows of the distributed passes."""
    from certgraph.operators import layered

    _, _, rows = _random_graph(seed, 14, 0.2 + 0.1 * seed)
    random.Random(seed).shuffle(rows)
    a, b = (np.array([e[i] for e in rows], np.int32) for i in (0, 1))
    for feed in ("handover", "original"):
        for rule in ("preorder", "level"):
            want = K.layered_mask(np.arange(len(rows)), a, b, 3, feed, rule)
            assert (K.layered_passes(14, a, b, 3, feed, rule, step=5) == want).all()
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows, 1)], "seq long, u long, v long")
    got = [sorted(map(tuple, layered.layered_certificate(e, 3, in_one_task=n).collect())) for n in (len(rows) - 1, 0)]
    assert got[0] == got[1]


def test_sizes_of_certificates_for_all_k(spark):
    """layers of one certificate counted for every k, as a certificate for each k has them."""
    from certgraph.operators import measures

    _, _, rows = _random_graph(5, 14, 0.5)
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows, 1)], "seq long, u long, v long")
    methods = ("layered", "layered_merge", "online_merge", "online", "online_rounds")
    want = measures.timed_sweep(spark, {"w": e}, (1, 2, 3, 4), methods, nested=False).select("workload", "method", "k", "n", "m", "cert_rows")
    assert sorted(measures.size_sweep(spark, {"w": e}, (1, 2, 3, 4), methods).collect()) == sorted(want.collect())


def _chain(seed, n, many, p):
    """Dense graphs on n vertices each, in a chain by single edges; edges in stream order."""
    rng = random.Random(seed)
    e = [(b * n + u, b * n + v) for b in range(many) for u, v in _shuffled(rng, n, p)] + [(b * n + n - 1, b * n + n) for b in range(many - 1)]
    return K.graph_of(e), K.PackedGraph(np.array([u for u, _ in e], np.int64), np.array([v for _, v in e], np.int64), np.arange(n * many)), e


def _shuffled(rng, n, p):
    pairs = [(u, v) for u in range(n) for v in range(u + 1, n) if rng.random() < p]
    rng.shuffle(pairs)
    return pairs


@pytest.mark.parametrize("k", (2, 3, 4))
def test_every_dense_part_of_a_chain_has_its_set(k):
    """one set for each part, so that edges of later parts are refused without a search too."""
    g, packed, rows = _chain(k, 60, 5, 0.5)
    c, own, kept = K.OnlineCertificate(k), {}, []
    for e in ((i, u, v) for i, (u, v) in enumerate(rows)):
        c.offer(e)
        if e[1] not in own or e[2] not in own or K.local_connectivity(own, e[1], e[2], k) < k:
            kept.append(e)
            own.setdefault(e[1], set()).add(e[2])
            own.setdefault(e[2], set()).add(e[1])
    assert c.kept == kept and len(c.members) == 5 and c.flows < len(rows) / 3
    assert sorted(len(x) for x in c.members.values())[0] > 50
    sets = K.inseparable_sets(packed, k, every=True)
    assert len(np.unique(sets[sets >= 0])) == 5 and (np.bincount(sets[sets >= 0])[np.unique(sets[sets >= 0])] > 55).all()
    one = K.inseparable_sets(packed, k)
    assert len(np.unique(one[one >= 0])) == 1 and (one >= 0).sum() > 55


@pytest.mark.parametrize("seed", range(8))
def test_sets_that_no_vertex_could_join(seed):
    """one failed search leaves out all that lies beyond the cut, and every set holds and is as large as it can be."""
    g, packed, _ = _random_graph(200 + seed, 16, 0.25 + 0.03 * seed)
    for k in (2, 3, 4):
        sets = K.inseparable_sets(packed, k, every=True)
        for s in np.unique(sets[sets >= 0]):
            inside = {x for x in g if sets[x] == s}
            assert all(y in g[x] or K.local_connectivity(g, x, y, k) >= k for x in inside for y in inside if x < y)
        one = K.inseparable_sets(packed, k)
        for s in np.unique(one[one >= 0]):
            inside = {x for x in g if one[x] == s}
            assert all(K.PathFlow(g, x, K.EXTRA, k, inside).value < k for x in g if x not in inside)


@pytest.mark.parametrize("seed", range(8))
def test_blocks_share_cut_vertices_only(seed):
    """parts that one vertex does not disconnect, with all edges filed."""
    g, packed, rows = _random_graph(300 + seed, 18, 0.08 + 0.02 * seed)
    parts = K.blocks(packed)
    whole = K.component_count(g)
    for x in g:
        if g[x]:
            assert sum(x in p for p in parts) - 1 == K.component_count(g, {x}) - whole
    filed = {i: own for i, own in K.block_graphs(packed, parts, 2)}
    assert sum(len(own.ends) for own in filed.values()) == 2 * len(rows)
    for i, own in filed.items():
        assert sorted(own) == sorted(parts[i]) and (len(own) == 2 or all(K.component_count(own, {x}) == 1 for x in own))


@pytest.mark.parametrize("seed", range(4))
def test_pairs_of_several_graphs_are_counted_without_a_list(spark, seed):
    """Numbers of separators in one, the other and both graphs, by removal of each pair; chains of dense parts and bridges among them."""
    from certgraph.operators import measures, separators
    from certgraph.operators.edges import vertex_set

    rows = _chain(seed, 6, 3, 0.7)[2] + [(17, 18), (18, 19)] if seed % 2 else _random_graph(500 + seed, 15, 0.25)[2]
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows, 1)], "seq long, u long, v long")
    v = vertex_set(e)
    some = e.filter("seq % 5 <> 0")
    cuts, pieces = [], []
    for x in (rows, [r for i, r in enumerate(rows, 1) if i % 5]):
        g = K.graph_of(x, {y for r in rows for y in r})
        cuts.append(K.brute_separators(g, 2))
        pieces.append(sorted((*c, K.component_count(g, set(c))) for c in cuts[-1]))
    assert [tuple(r) for r in measures.separator_agreement(e, some, v, 2).collect()] == [(len(cuts[0]), len(cuts[1]), len(cuts[0] & cuts[1]))]
    for x, want in zip((e, some), pieces, strict=True):
        assert sorted((*r.members, r.pieces) for r in separators.separators(x, v, 2).collect()) == want
    g = K.graph_of(rows)
    want = [(s, len(c), 3) for s in (1, 2) if (c := K.brute_separators(g, s))]
    assert sorted(tuple(r) for r in measures.order_free_separators(e, v).collect()) == want


@pytest.mark.parametrize("seed", range(3))
def test_kappa_of_pairs_that_are_not_joined(spark, seed):
    """pairs made and left out within the task, from the certificate and from the graph itself."""
    from certgraph.operators import decide, layered
    from certgraph.operators.edges import vertex_set

    rows = _chain(seed, 6, 3, 0.8)[2] if seed else _random_graph(3, 16, 0.4)[2]
    g = K.graph_of(rows)
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows, 1)], "seq long, u long, v long")
    v = vertex_set(e)
    want = sorted((x, y, K.local_connectivity(g, x, y, 4)) for x in g for y in g if x < y and y not in g[x])
    for cert in (e, layered.layered_certificate(e, 4, v)):
        assert sorted(tuple(r) for r in decide.local_connectivity_apart(cert, v, e, 4).collect()) == want


def test_users_near_in_time_without_a_join_of_events(spark, sf):
    """Edges in order and degrees, against SQL; no stage shuffles a pair once for each two events."""
    import duckdb

    from certgraph.sources import workloads

    assert workloads._events_by_time(spark, sf, most=10) is None
    c = duckdb.connect()
    c.sql(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    for name in ("edges_call_window", "degree_stats_call_window"):
        got = driver_queries.queries()[name](spark, sf)
        assert "Join" not in workloads.window_pairs(spark, workloads._events_by_time(spark, sf), 300)._jdf.queryExecution().toString()
        assert sorted(tuple(r) for r in got.collect()) == sorted(c.sql(driver_queries.oracle_sql()[name]).fetchall())
    shared = workloads._events_by_time(spark, sf)
    assert sorted(workloads.window_pairs(spark, shared, 300, step=7).collect()) == sorted(workloads.window_pairs(spark, shared, 300).collect())


def test_rounds_read_on_by_what_they_hold(spark):
    """few rounds for a stream whose later parts an earlier certificate says nothing about, with the rows of the exact method."""
    from certgraph.operators import online

    rows = _chain(1, 24, 16, 0.7)[2]
    e = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(rows, 1)], "seq long, u long, v long")
    kept, rounds = online.online_rounds(e, 3, head=100)
    assert sorted(kept.collect()) == sorted(online.online_certificate(e, 3).collect()) and rounds <= 6


def _apart(parts: int, n: int, m: int) -> list[tuple[int, int, int]]:
    """Random edges of several components that take turns in the stream."""
    rng, pairs = np.random.default_rng(5), []
    for at in range(parts):
        own = {tuple(sorted(p)) for p in rng.integers(n, size=(3 * m, 2)).tolist() if p[0] != p[1]} | {(x, x + 1) for x in range(n - 1)}
        pairs.append([(u * parts + at, v * parts + at) for u, v in rng.permutation(sorted(own))[:m].tolist() + [(x, x + 1) for x in range(n - 1)]])
    mixed = dict.fromkeys((min(p), max(p)) for turn in zip(*pairs, strict=True) for p in turn)
    return [(i, u, v) for i, (u, v) in enumerate(mixed, 1)]


def test_components_are_certified_apart(spark):
    """the rows of one task or of the kernels, from tasks that hold whole components."""
    from certgraph.operators import decide, layered, online
    from certgraph.operators.components import folded_labels
    from certgraph.operators.edges import vertex_set

    rows = _apart(6, 20, 60)
    e = spark.createDataFrame(rows, "seq long, u long, v long").repartition(3)
    assert len({r.comp for r in folded_labels(e).collect()}) == 6
    seq, u, v = (np.array(x) for x in zip(*rows, strict=True))
    for feed in ("handover", "original"):
        layer = K.layered_mask(seq, u, v, 3, feed)
        want = sorted((*r, int(i)) for r, i in zip(rows, layer.tolist(), strict=True) if i)
        cert = layered.layered_certificate(e, 3, feed=feed, in_one_task=len(rows) - 1)
        assert sorted(map(tuple, cert.collect())) == want
    merged = online.online_certificate(e, 3, "merge")
    assert merged.rdd.getNumPartitions() > 1  # the union of all parts was folded in one task
    want = []
    for c in range(6):
        fold = K.OnlineCertificate(3)
        for r in K.layered_rows([r for r in rows if r[1] % 6 == c], 3):
            fold.offer(r[:3])
        want += fold.kept
    assert sorted(map(tuple, merged.collect())) == sorted(want)
    assert not decide.is_k_connected(merged, vertex_set(e), 1).first().verdict


def test_one_component_is_merged_up_a_tree(spark):
    from certgraph.operators import online
    from certgraph.operators.components import component_parts

    rows = _apart(1, 20, 60)
    e = spark.createDataFrame(rows, "seq long, u long, v long").repartition(3)
    assert component_parts(e) is None and component_parts(e.limit(0)) is None
    assert online.online_certificate(e, 3, "merge").rdd.getNumPartitions() == 1


def test_merged_parts_are_folded_once(spark):
    """parts and unions are thinned by forests only; paths are searched for once, among what all of them leave."""
    from certgraph.operators import online
    from certgraph.operators.forest import merge_tree

    rows = _apart(1, 20, 150)
    e = spark.createDataFrame(rows, "seq long, u long, v long").repartition(3)
    left, fold = sorted(map(tuple, merge_tree(e, online._thinned(3)).collect())), K.OnlineCertificate(3)
    for r in left:
        fold.offer(r)
    assert len(fold.kept) <= len(left) <= 3 * 19 < len(rows)
    assert sorted(map(tuple, online.online_certificate(e, 3, "merge").collect())) == fold.kept


def _random_edges(seed, n, m):
    rng = np.random.default_rng(seed)
    pairs = {(int(min(p)), int(max(p))) for p in rng.integers(0, n, (m, 2)) if p[0] != p[1]}
    rows = sorted(pairs, key=lambda p: (hash((seed, p)), p))
    return np.array([(3 * i, 7 * u, 7 * v) for i, (u, v) in enumerate(rows, 1)], dtype=np.int64).reshape(-1, 3).T


@pytest.mark.parametrize("seed", range(12))
def test_forests_by_levels_are_those_by_vertices(seed, monkeypatch):
    """whole arrays at a time give the rows of one edge and one vertex at a time."""
    seq, u, v = _random_edges(seed, 40, 30 + 10 * seed)
    ids, flat = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = flat[: len(u)], flat[len(u) :]
    kept = K.StreamForest(len(ids)).offer(a, b)
    assert seq[kept].tolist() == [s for s, _, _ in K.kept_edges(zip(seq.tolist(), u.tolist(), v.tolist(), strict=True))]
    found = []
    for few in (0, len(ids) + 1):
        monkeypatch.setattr(K, "FEW", few)
        monkeypatch.setattr(K, "FLAT", 1)
        found.append(K.preorder_arrays(len(ids), a[kept], b[kept]))
    assert all((x == y).all() for x, y in zip(*found, strict=True))


@pytest.mark.parametrize("k", [1, 2, 3])
def test_a_fold_from_within_is_a_certificate_and_offers_few_edges(k, monkeypatch):
    """rows that paths decide are few, and the rest is kept by degrees alone."""
    from itertools import combinations

    offered = []
    offer = K.OnlineCertificate.offer
    monkeypatch.setattr(K.OnlineCertificate, "offer", lambda self, e: offered.append(e) or offer(self, e))
    for seed in range(8):
        seq, u, v = _random_edges(seed, 14, 20 + 8 * seed)
        keep = K.folded_from_within(seq, u, v, k)
        whole, some = (K.graph_of(zip(u[on].tolist(), v[on].tolist(), strict=True), np.union1d(u, v).tolist()) for on in (np.ones(len(u), bool), keep))
        for x, y in combinations(whole, 2):
            if y not in whole[x]:
                assert K.local_connectivity(whole, x, y, k) == K.local_connectivity(some, x, y, k)
        assert keep.sum() <= 2 * k * len(whole)
    offered.clear()
    hub = np.arange(1, 501)  # each edge has an end of degree one
    assert K.folded_from_within(hub, np.zeros(500, np.int64), hub, k).all() and not offered


def test_sweep_sizes_are_those_of_the_methods(spark):
    """both merge forms of a sweep come from one tree for each k."""
    from certgraph.operators import measures
    from certgraph.operators.decide import certificate_for
    from certgraph.sources.workloads import known_edges

    e = known_edges(spark, "cliques", 9, 3)
    rows = measures.size_sweep(spark, {"c": e}, (1, 2, 3), ("layered", "layered_merge", "online_merge")).collect()
    assert len(rows) == 9
    assert {(r.method, r.k): r.cert_rows for r in rows} == {(m, k): certificate_for(e, k, m).count() for m in ("layered", "layered_merge", "online_merge") for k in (1, 2, 3)}


def test_edges_near_in_time_are_numbered_without_rows_of_pairs(spark, sf):
    """packed numbers of first meetings give the rows that pairs sorted by their first events give, without a shuffle of pairs."""
    from certgraph.operators.edges import dense_numbers
    from certgraph.sources import workloads

    shared = workloads._events_by_time(spark, sf)
    want = dense_numbers(workloads.window_pairs(spark, shared, 300), ["o"], "seq").select("seq", "u", "v").collect()
    for at_once, most in ((64, 1 << 21), (3, 50)):
        found = workloads.window_edges(spark, shared, 300, at_once, most)
        assert "rangepartitioning" not in found._jdf.queryExecution().toString()
        assert sorted(found.collect()) == sorted(want) and want
