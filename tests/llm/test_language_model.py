"""The language model against enumeration, and its queries against counting."""

import math
import zlib
from collections import Counter
from itertools import product

import numpy as np
import pytest

from certgraph.llm import language_model as L


def test_forward_equals_the_sum_over_all_paths():
    rng = np.random.default_rng(2)
    norm = lambda a, axis: a / a.sum(axis=axis, keepdims=True)
    m = L.HiddenMarkov(norm(rng.random(3), 0), norm(rng.random((3, 3)), 1), norm(rng.random((5, 3)), 0))
    texts = [rng.integers(5, size=n) for n in (1, 4, 6, 4, 2)]
    for t, got in zip(texts, m.log_likelihoods(texts), strict=True):
        total = sum(m.first[p[0]] * m.emit[t[0], p[0]] * math.prod(m.move[p[i - 1], p[i]] * m.emit[t[i], p[i]] for i in range(1, len(t))) for p in product(range(3), repeat=len(t)))
        assert got == pytest.approx(math.log(total), rel=1e-12)
    counts = m.expected(texts)
    assert counts[:3].sum() == pytest.approx(len(texts))
    assert counts[3:12].sum() == pytest.approx(sum(len(t) - 1 for t in texts))
    assert counts[12:].sum() == pytest.approx(sum(map(len, texts)))
    together = sum(m.expected([t]) for t in texts)
    assert np.allclose(counts, together)  # counts add up over texts, however they are grouped


def test_long_texts_do_not_underflow():
    m = L.HiddenMarkov(np.array([0.5, 0.5]), np.array([[0.9, 0.1], [0.2, 0.8]]), np.full((1000, 2), 1e-3))
    assert m.log_likelihoods([np.zeros(20_000, dtype=int)])[0] == pytest.approx(20_000 * math.log(1e-3))


def test_scores(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    words = {r.doc_id: r.text.encode().lower().split() for r in docs.collect()}
    c = Counter()
    for i, w in words.items():
        if zlib.crc32(str(i).encode()) % 7 != 2:
            c.update([*w, "<end>"])
    n, v = sum(c.values()), len(c)
    better, held = 0, 0
    for r in L.language_model_scores(docs).collect():
        w = [*words[r.doc_id], "<end>"]
        assert r.n_tokens == len(w) and r.n_known == sum(c[x] > 0 for x in w) and r.train_tokens == n
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
        assert r.base_score == pytest.approx(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w))
        assert r.score < 0
        better += r.held_out and r.score > r.base_score
        held += r.held_out
    assert better >= 0.9 * held


def test_probabilities_of_all_words_sum_to_one(spark):
    """Over one-word texts: known words and one unseen type, followed by the end."""
    rng = np.random.default_rng(1)
    vocabulary = [f"w{i}" for i in range(60)]
    train = [(i, " ".join(rng.choice(vocabulary, size=8))) for i in range(60) if not L.held_out(i)]
    seen = sorted({w for _, t in train for w in t.split()})
    held = [i for i in range(1000, 4000) if L.held_out(i)]
    probes = [(held[k], w) for k, w in enumerate([*seen, "never-seen"])] + [(held[-1], "")]
    got = {r.doc_id: r.score for r in L.language_model_scores(spark.createDataFrame(train + probes, "doc_id long, text string"), states=3).collect()}
    # texts of one word and texts of none are disjoint events, so their probabilities add up to less than one
    total = sum(10 ** got[i] for i, _ in probes)
    assert 0 < total <= 1
    assert got[probes[-2][0]] < 0


def test_stretches_give_what_whole_texts_give(monkeypatch):
    rng = np.random.default_rng(5)
    norm = lambda a, axis: a / a.sum(axis=axis, keepdims=True)
    m = L.HiddenMarkov(norm(rng.random(3), 0), norm(rng.random((3, 3)), 1), norm(rng.random((6, 3)), 0))
    texts = [rng.integers(6, size=n) for n in (1, 40, 7, 23, 40, 2)]
    whole, counts, single = m.log_likelihoods(texts), m.expected(texts), m.expected(texts[1:2])
    for held in (1, 5, 11):
        monkeypatch.setattr(L, "HELD_TOKENS", held)
        assert np.allclose(m.log_likelihoods(texts), whole) and np.allclose(m.expected(texts), counts)
        assert np.allclose(m.expected(texts[1:2]), single)


def test_totals_over_several_levels(spark, sf):
    """Many small blocks, summed four at a time, give what one block gives; base scores are exact either way."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = ("doc_id", "n_tokens", "n_known", "train_tokens")
    one = {r.doc_id: r for r in L.language_model_scores(docs, passes=0).collect()}
    many = {r.doc_id: r for r in L.language_model_scores(docs.repartition(3), passes=0, block_bytes=5000, fan_bits=2).collect()}
    assert one.keys() == many.keys()
    for i, r in one.items():
        assert [r[c] for c in columns] == [many[i][c] for c in columns]
        assert many[i].base_score == pytest.approx(r.base_score) and many[i].score == pytest.approx(r.score, rel=0.02)


def test_noise_scores_below_prose(spark, sf):
    rng = np.random.default_rng(7)
    noise = " ".join("".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz0123456789"), rng.integers(4, 12))) for _ in range(300))
    held = next(i for i in range(10**6, 10**6 + 100) if L.held_out(i))
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").unionByName(spark.createDataFrame([(held, noise)], "doc_id long, text string"))
    each = {r.doc_id: (r.score / r.n_tokens, r.n_known / r.n_tokens, r.held_out, r.n_tokens) for r in L.language_model_scores(docs).collect()}
    long = {i: x for i, x in each.items() if x[3] >= 20}
    assert long[held][0] < min(x[0] for i, x in long.items() if i != held and x[1] > 0.5)
    train, held_out = (np.median([x[0] for x in long.values() if x[2] == side]) for side in (False, True))
    assert held_out < train  # texts that the model hasn't seen are less likely to it


def test_odd_texts(spark):
    docs = spark.createDataFrame([(None, "a b", 1.0), (1, None, 2.0), (1, "", 3.0), (2, "a b A", 4.0)], "doc_id long, text string, score double")
    got = L.language_model_scores(docs).collect()
    assert sorted(r.n_tokens for r in got) == [1, 1, 3, 4] and all(math.isfinite(r.score) for r in got)
    assert L.language_model_scores(docs.limit(0)).count() == 0
    only = spark.createDataFrame([(i, "x y") for i in range(1000) if L.held_out(i)][:3], "doc_id long, text string")
    rows = L.language_model_scores(only).collect()
    assert all(r.train_tokens == 0 and r.n_known == 0 and math.isfinite(r.score) for r in rows)
