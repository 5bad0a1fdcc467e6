"""Kernels against brute force on random graphs and against graphs of known connectivity."""

import random
from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from certgraph.functions import graph_kernels as K
from certgraph.sources.workloads import known_graph


@st.composite
def graphs(draw, most=8):
    n = draw(st.integers(2, most))
    pairs = list(combinations(range(n), 2))
    chosen = draw(st.lists(st.sampled_from(pairs), unique=True, max_size=len(pairs)))
    return n, [(i, u, v) for i, (u, v) in enumerate(chosen, 1)]


def parted(g, u, v, gone):
    seen, todo = {u} | set(gone), [u]
    while todo:
        for y in g[todo.pop()]:
            if y not in seen:
                seen.add(y)
                todo.append(y)
    return v not in seen


@settings(max_examples=150, deadline=None)
@given(graphs())
def test_paths_and_cuts(data):
    n, edges = data
    g = K.graph_of([(u, v) for _, u, v in edges], range(n))
    for u, v in combinations(range(n), 2):
        flow = K.PathFlow(g, u, v, 5)
        paths = flow.paths()
        inner = [x for p in paths for x in p[1:-1]]
        assert len(paths) == flow.value and len(inner) == len(set(inner))
        assert all(b in g[a] for p in paths for a, b in zip(p, p[1:], strict=False))
        if v in g[u]:
            continue
        rest = [x for x in range(n) if x not in (u, v)]
        least = next(r for r in range(len(rest) + 1) if any(parted(g, u, v, s) for s in combinations(rest, r)))
        assert flow.value == min(5, least)
        if least < 5:
            assert len(flow.cut()) == least and parted(g, u, v, flow.cut())
            assert K.minimum_cuts(g, u, v, 5) == [s for s in combinations(rest, least) if parted(g, u, v, s)]


@settings(max_examples=120, deadline=None)
@given(graphs(8), st.integers(1, 6))
def test_certificates_keep_verdicts_separators_and_components(data, k):
    n, edges = data
    g = K.graph_of([(u, v) for _, u, v in edges], range(n))
    online = K.OnlineCertificate(k)
    for e in edges:
        online.offer(e)
    layers = K.layered_rows(edges, k)
    assert len(online.kept) <= 2 * k * n and len(layers) <= k * max(0, n - 1)
    for kept in ([(u, v) for _, u, v in online.kept], [(u, v) for _, u, v, _ in layers]):
        c = K.graph_of(kept, range(n))
        assert K.brute_k_connected(c, k) == K.brute_k_connected(g, k) == K.is_k_connected(g, k)
        for size in range(k):
            if size:
                assert K.brute_separators(c, size) == K.brute_separators(g, size)
            for gone in combinations(range(n), size):
                assert K.component_count(c, set(gone)) == K.component_count(g, set(gone))


@settings(max_examples=80, deadline=None)
@given(graphs(9), st.integers(1, 5))
def test_folds_in_chunks_equal_plain_scans(data, chunk):
    n, edges = data
    plain, dense = K.ForestFold(), K.ForestFold(n)
    kept = []
    for i in range(0, len(edges), chunk):
        seq, u, v = (np.array(x) for x in zip(*edges[i : i + chunk], strict=True))
        keep = plain.offer(seq, u * 10 - 7, v * 10 - 7)
        assert keep.tolist() == dense.offer(seq, u, v).tolist()
        kept += [e for e, k in zip(edges[i : i + chunk], keep, strict=True) if k]
    assert kept == K.kept_edges(edges)
    assert dense.odd == K.odd_cycle_edge(edges) and dense.words == 2 * n
    z = K.graph_of([(u, v) for _, u, v in kept], range(n))
    place, root, depth = K.preorder_arrays(n, np.array([u for _, u, v in kept], dtype=int), np.array([v for _, u, v in kept], dtype=int))
    want = K.preorder(z)
    assert [(int(x), int(root[x])) for x in np.argsort(place)] == want
    assert all(depth[x] == K.distances_from(z, r)[x] for x, r in want)


@settings(max_examples=60, deadline=None)
@given(graphs(9), st.integers(1, 4))
def test_layers_are_first_neighbour_forests(data, k):
    n, edges = data
    left, want = list(edges), []
    for layer in range(1, k + 1):
        z = K.graph_of([(u, v) for _, u, v in K.kept_edges(left)], range(n))
        position = {x: i for i, (x, _) in enumerate(K.preorder(z))}
        taken = {s for _, s in K.first_neighbours(left, position).values()}
        want += [(s, u, v, layer) for s, u, v in left if s in taken]
        left = [e for e in left if e[0] not in taken]
    assert K.layered_rows(edges, k) == sorted(want)


def test_a_chunked_certificate_keeps_separators(monkeypatch):
    monkeypatch.setattr(K, "CHUNK", 3)
    rng = random.Random(8)
    for _ in range(40):
        n, k = rng.randint(4, 8), rng.randint(1, 4)
        edges = [(i, u, v) for i, (u, v) in enumerate(combinations(range(n), 2), 1) if rng.random() < 0.6]
        fold = K.LayeredFold(k)
        for i in range(0, len(edges), 2):
            fold.offer(*(np.array(x) for x in zip(*edges[i : i + 2], strict=True)))
        (_, u, v), layer = fold.settle()
        g, c = K.graph_of([e[1:] for e in edges], range(n)), K.graph_of(zip(u.tolist(), v.tolist(), strict=True), range(n))
        assert len(layer) <= k * (n - 1)
        for size in range(1, k):
            assert K.brute_separators(c, size) == K.brute_separators(g, size)


def test_packed_graphs_answer_like_dicts(monkeypatch):
    import pickle

    monkeypatch.setattr(K.PackedGraph, "MOST_SETS", 2)
    g = K.graph_of(known_graph("wheel", 6), [99])
    u, v = (np.array(x) for x in zip(*known_graph("wheel", 6), strict=True))
    p = pickle.loads(pickle.dumps(K.PackedGraph(u, v, np.array([99, 0]))))
    assert list(p) == sorted(g) and {x: p[x] for x in p} == g and 98 not in p and len(p) == len(g)
    assert K.component_count(p) == 2 and K.PathFlow(p, 1, 4, 9).value == 3
    empty = K.PackedGraph(*(np.zeros(0, np.int64) for _ in range(3)))
    assert len(empty) == 0 and K.component_count(empty) == 0


def test_merging_certificates_is_safe():
    rng = random.Random(5)
    for _ in range(60):
        n, k = rng.randint(4, 8), rng.randint(1, 3)
        edges = [(i, u, v) for i, (u, v) in enumerate(combinations(range(n), 2), 1) if rng.random() < 0.7]
        parts = [[e for e in edges if e[0] % 3 == r] for r in range(3)]
        union = sorted(e[:3] for p in parts for e in K.layered_rows(p, k))
        c = K.graph_of([(u, v) for _, u, v, _ in K.layered_rows(union, k)], range(n))
        g = K.graph_of([(u, v) for _, u, v in edges], range(n))
        assert K.brute_k_connected(c, k) == K.brute_k_connected(g, k)


@pytest.mark.parametrize(
    ("kind", "size", "kappa"),
    [("path", (6,), 1), ("cycle", (7,), 2), ("star", (4,), 1), ("wheel", (5,), 3), ("complete", (5,), 4), ("bipartite", (2, 4), 2), ("bipartite", (3, 3), 3), ("grid", (3, 4), 2), ("cube", (3,), 3), ("cliques", (5, 2), 2), ("harary", (3, 8), 3), ("harary", (4, 9), 4)],
)
def test_known_connectivity(kind, size, kappa):
    g = K.graph_of(known_graph(kind, *size))
    assert K.is_k_connected(g, kappa) and not K.is_k_connected(g, kappa + 1)


@pytest.mark.parametrize(("n", "count"), [(5, 5), (7, 14), (9, 27)])
def test_a_cycle_has_quadratically_many_separators(n, count):
    assert len(K.brute_separators(K.graph_of(known_graph("cycle", n)), 2)) == count


def test_an_inner_vertex_of_a_path_need_not_separate():
    g = K.graph_of([(0, 1), (0, 2), (1, 3), (2, 3), (3, 4)])
    assert K.PathFlow(g, 0, 4, 3).value == 1
    assert K.minimum_cuts(g, 0, 4, 3) == [(3,)] and K.brute_separators(g, 1) == {(3,)}


def test_low_link_pieces_match_counting():
    rng = random.Random(3)
    for _ in range(80):
        n = rng.randint(1, 8)
        g = K.graph_of([p for p in combinations(range(n), 2) if rng.random() < 0.4], range(n))
        for gone in [(), (0,), (0, n - 1)]:
            _, left = K.pieces_without_each_vertex(g, set(gone))
            assert left == {v: K.component_count(g, {*gone, v}) for v in range(n) if v not in gone}


def test_combinations_by_place():
    assert [K.nth_combination(5, 2, i) for i in range(10)] == list(combinations(range(5), 2))
    assert K.nth_combination(5, 0, 0) == ()


def test_scan_first_search_rules():
    g = K.graph_of(known_graph("complete", 3))
    for pick in ("fifo", "lifo", "smallest"):
        tree, order = K.scan_first_forest(g, pick)
        assert sorted(tree) == [(0, 1), (0, 2)] and order[0] == 0  # a scan marks all neighbours, whatever the rule


def test_odd_cycles():
    assert K.odd_cycle_edge([(1, 0, 1), (2, 1, 2), (3, 0, 2)]) == (3, 0, 2)
    assert K.odd_cycle_edge([(1, 0, 1), (2, 1, 2), (3, 2, 3), (4, 0, 3)]) is None


def test_smallest_certificate_of_a_small_graph():
    assert K.brute_minimum_certificate(K.graph_of(known_graph("complete", 4)), 2) == 4
