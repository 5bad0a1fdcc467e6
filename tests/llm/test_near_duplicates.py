"""Near-duplicate classes against brute force."""

import random

import numpy as np
import pytest

from certgraph.llm import near_duplicates as N


def brute(rows, width, percent=80):
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        sets[i] = frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])
    comp = {i: i for i in sets}

    def find(x):
        while comp[x] != x:
            x = comp[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                n = len(sets[a] & sets[b])
                if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
                    x, y = find(a), find(b)
                    comp[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def corpus(seed, families=12, members=14):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    rows = []
    for _ in range(families):
        base = [rng.choice(words) for _ in range(rng.randint(3, 90))]
        for _ in range(members):
            t = list(base)
            for _ in range(rng.randint(0, max(1, len(t) // 9))):
                k = rng.randrange(len(t))
                t[k] = rng.choice(words) if rng.random() < 0.6 else t[k].upper()
            rows.append(" ".join(t))
    rng.shuffle(rows)
    return list(enumerate(rows))


@pytest.mark.parametrize("width", [2, 5])
def test_classes_equal_brute_force(spark, width):
    rows = corpus(width) + [(900, None), (901, ""), (902, " \n"), (903, "solo"), (904, "SOLO")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in N.near_duplicate_classes(docs, width).collect()}
    assert got == brute(rows, width)


def test_blocks_find_what_leaders_miss(spark, monkeypatch):
    rows = corpus(9)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(N, "LEADER_ROUNDS", (1,))
    monkeypatch.setattr(N, "BLOCK_SHINGLES", 300)
    plain = N._leader_pairs
    monkeypatch.setattr(N, "_leader_pairs", lambda h, t, m: plain(h, t, m).limit(3))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in N.near_duplicate_classes(docs, 2).collect()}
    assert got == brute(rows, 2)


def test_odd_rows(spark):
    rows = [(None, "a b c", 1), (1, "a b c", 1), (1, "a b c", 2), (2, "A B c", 3), (3, None, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, kept int")
    got = sorted((r.doc_id is None, r.doc_id or 0, r.component_id, r.kept) for r in N.near_duplicate_classes(docs, 2).collect())
    assert got == [(False, 1, 1, True), (False, 1, 1, True), (False, 2, 1, False), (False, 3, 3, True), (True, 0, None, True)]
    left = N.distinct_documents(docs, 2)
    assert left.columns == docs.columns and sorted(r.doc_id or -1 for r in left.collect()) == [-1, 1, 3]
    assert N.near_duplicate_classes(docs.limit(0)).count() == 0 == N.distinct_documents(docs.limit(0)).count()


def test_signature_values_agree_as_often_as_sets():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 2**63, 600, dtype=np.uint64)
    b = np.concatenate([a[:500], rng.integers(0, 2**63, 100, dtype=np.uint64)])
    same = (N.minmax_signature(np.unique(a)) == N.minmax_signature(np.unique(b))).mean()
    assert abs(same - 500 / 700) < 0.15
    assert len(N.band_keys(N.minmax_signature(a))) == 2 * N.PERMUTATIONS // N.BAND_ROWS


@pytest.mark.parametrize("seed", range(6))
def test_joining_links_are_a_forest_of_all_links(seed):
    rng = np.random.default_rng(seed)
    common = rng.integers(1, 200, 3)  # shingles that nearly every set holds
    sets, base = [], None
    for i in range(120):
        if i % 6 == 0:
            base = rng.choice(5000, rng.integers(1, 60), replace=False)
        own = np.where(rng.random(len(base)) < 0.06, rng.integers(0, 5000, len(base)), base)
        sets.append(np.unique(np.concatenate([own, common])).astype(np.uint64))
    comps = np.array([0 if rng.random() < 0.1 else 1000 + i for i in range(len(sets))])

    def table(part):
        return np.array(part), comps[part], np.concatenate([sets[i] for i in part]), np.concatenate([[0], np.cumsum([len(sets[i]) for i in part])])

    def joined(pairs):
        up = {c: c for c in comps.tolist()}

        def find(x):
            while up[x] != x:
                x = up[x]
            return x

        for a, b in pairs:
            x, y = find(int(comps[a])), find(int(comps[b]))
            up[max(x, y)] = min(x, y)
        return [find(c) for c in comps.tolist()]

    def linked(a, b):
        n = len(np.intersect1d(sets[a], sets[b]))
        return 100 * n >= 80 * (len(sets[a]) + len(sets[b]) - n)

    every = list(range(len(sets)))
    want = joined([(a, b) for a in every for b in every if a < b and linked(a, b)])
    got = N.joining_links(*table(every), 80)
    assert all(linked(a, b) for a, b in got) and joined(got) == want
    assert len(got) == len(set(comps.tolist())) - len(set(want))
    left, right = [i for i in every if i % 3], [i for i in every if not i % 3]
    got = N.joining_links(*table(left), 80, table(right))
    assert all(linked(a, b) and a % 3 and not b % 3 for a, b in got)
    assert joined(got) == joined([(a, b) for a in left for b in right if linked(a, b)])
