"""Words, shingles and quality rules against plain Python."""

import re
from collections import Counter

import numpy as np
import pytest

from certgraph.llm.quality import CompressionBands, bands_from_sample, fitted_bands, passing_documents, quality_verdicts
from certgraph.llm.wordhash import Words, shingle_set, text_bytes

WORD = re.compile(r"[^\x20\x09-\x0D]+")
TEXTS = [None, "", " \t\n", "one", "a b a b a b a b a b a b", "Ünï çødé x y\nline\n\nline\n", "#x $y %z & | < >" * 3, "the cat sat on the mat and the dog sat on the log near the cat " * 2, "\x1c\x1d mixed\x85 space here", "x" * 3_000_000]


def expected(t):
    t = t or ""
    w = WORD.findall(t)
    grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    twice = {j for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(twice)


def test_words_of_joined_texts():
    raws = [text_bytes(t, lower=True) for t in TEXTS]
    w = Words(raws)
    flat = {}
    for i, t in enumerate(TEXTS):
        own = WORD.findall((t or "").translate(str.maketrans({c: c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"})))
        h = w.hashes[w.bounds[i] : w.bounds[i + 1]]
        assert len(h) == len(own)
        for x, y in zip(own, h.tolist(), strict=True):
            assert flat.setdefault(x, y) == y
    assert len(set(flat.values())) == len(flat)


@pytest.mark.parametrize("width", [1, 2, 5])
def test_shingle_sets(width):
    for t in TEXTS[:-1]:
        own = WORD.findall((t or "").lower()) if t != TEXTS[5] else WORD.findall(t)
        want = {tuple(own[i : i + width]) for i in range(max(1, len(own) - width + 1))} if own else set()
        w = Words([text_bytes(t if t == TEXTS[5] else (t or "").lower(), lower=False)])
        assert len(shingle_set(w.hashes, width)) == len(want)
    assert len(shingle_set(np.zeros(0, np.uint64), 2)) == 0


def test_quality_counts_and_verdicts(spark):
    rows = [(i, t, i) for i, t in enumerate(TEXTS)] + [(None, "null id", 0), (3, "one", 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_words int")
    got = quality_verdicts(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        if r.doc_id is not None:
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == expected(TEXTS[r.doc_id])
        assert r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words)
        assert not (r.kept and r.base_failed)
    kept = passing_documents(docs)
    assert kept.columns == docs.columns and kept.count() == sum(r.kept for r in got)
    assert quality_verdicts(docs.limit(0)).count() == 0 == passing_documents(docs.limit(0)).count()


def test_bands_reject_noise_and_repetition(spark):
    import base64
    import random

    rng = random.Random(1)
    words = ["".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 9))) for _ in range(3000)]
    prose = " ".join(rng.choice(words) for _ in range(2000))
    noise = base64.b64encode(rng.randbytes(9000)).decode()
    noise = " ".join(noise[i : i + 11] for i in range(0, len(noise), 11))
    loop = " ".join(f"{a} {b}" for a in ("yes", "no", "so") for b in ["a" * 9] * 900)
    mixed = prose[:8000] + " " + noise[:9000]
    docs = spark.createDataFrame([(1, prose), (2, noise), (3, loop), (4, mixed)], "doc_id long, text string")
    got = {r.doc_id: r for r in quality_verdicts(docs).collect()}
    assert got[1].kept and not got[2].in_band and not got[3].in_band and not got[4].in_band
    assert got[4].n_bad_chunks > 0
    assert CompressionBands().inside(50, 0.5) and not CompressionBands().inside(5000, 1.1)


def test_a_bad_tail_after_the_last_full_chunk_counts():
    import base64
    import random

    import zstandard

    from certgraph.llm.quality import compression_verdict

    rng, z, bands = random.Random(4), zstandard.ZstdCompressor(level=3), CompressionBands()
    words = ["".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 9))) for _ in range(300)]
    prose = " ".join(rng.choice(words) for _ in range(4000)).encode()
    tail = base64.b64encode(rng.randbytes(2992))[:3990]
    whole, n, bad, fine = compression_verdict(prose[:4096] + tail, bands, z)
    assert bands.inside(4096 + 3990, whole) and (n, bad, fine) == (4, 2, False)
    assert compression_verdict(prose[:4096] + tail[:900], bands, z)[3]  # less than a quarter of the bytes
    for size in (1, 100, 2047, 2048, 2049, 4097, 6000, 8191, 8192, 12000):
        whole, n, bad, fine = compression_verdict(prose[:size], bands, z)
        assert (n, bad, fine) == (-(-size // 2048), 0, True)


def test_fitted_bands_follow_the_sample():
    rng = np.random.default_rng(3)
    sizes = np.exp(rng.uniform(np.log(300), np.log(6000), 900))
    middle = lambda n: 0.6 + 0.15 * np.log2(n)
    ratios = middle(sizes) + rng.normal(0, 0.03, 900)
    ratios[:9] += 3.0  # outliers don't widen the limits
    bands = bands_from_sample(sizes, ratios)
    for n in (400, 1000, 3000, 5000):
        assert bands.inside(n, middle(n)) and not bands.inside(n, middle(n) + 0.35) and not bands.inside(n, middle(n) - 0.35)
    general = CompressionBands()
    assert sum(bands.inside(n, r) for n, r in zip(sizes[9:], ratios[9:], strict=True)) >= 889
    for n, r in ((50, 1.9), (200, 0.95), (90_000, 6.9)):  # beyond the sample's sizes
        assert bands.inside(n, r) == general.inside(n, r)
    assert bands_from_sample(sizes[:50], ratios[:50]) == general


def test_fitted_bands_on_labels(spark, sf):
    """Fitted on some labelled texts and held against the others: more of the bad go, hardly any of the good."""
    import os

    at = os.path.join(os.path.dirname(sf), "sf0.01")
    docs, labels = (spark.read.parquet(f"{at}/{t}.parquet") for t in ("documents", "labels"))
    bands = fitted_bands(docs, labels, most=200)
    assert bands == fitted_bands(docs.repartition(5), labels.unionByName(labels), most=200)
    fit = {r.doc_id for r in labels.filter("quality = 1").selectExpr("doc_id", "xxhash64(doc_id) h").orderBy("h", "doc_id").limit(200).collect()}
    quality = {r.doc_id: r.quality for r in labels.collect() if r.doc_id not in fit}
    both = {True: [], False: []}
    for fitted in both:
        for r in quality_verdicts(docs, bands if fitted else None).collect():
            if r.doc_id in quality and not r.base_failed:
                both[fitted].append((quality[r.doc_id], r.kept))
    gone = {f: (sum(q == 0 and not k for q, k in x), sum(q == 1 and not k for q, k in x)) for f, x in both.items()}
    bad = sum(q == 0 for q, _ in both[True])
    assert gone[True][0] >= 0.5 * bad > gone[False][0] and gone[True][1] <= 0.02 * len(both[True])


def test_limits_are_fitted_on_all_labelled_texts(spark):
    """Of 4,000 texts 600 are longer, all of them behind the first 2,000 by hash: lengths only they have get limits too."""
    import random

    from pyspark.sql import functions as F

    rng = random.Random(4)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(2, 8)))
    short = [(i, " ".join(word() for _ in range(rng.randint(60, 120)))) for i in range(4000)]
    by_hash = [r.doc_id for r in spark.createDataFrame([(i,) for i, _ in short], "doc_id long").orderBy(F.xxhash64("doc_id"), "doc_id").collect()]
    longer = {i: " ".join(word() for _ in range(rng.randint(100, 400))) for i in by_hash[2400:3000]}  # behind the first 2,000
    docs = spark.createDataFrame([(i, longer.get(i, t)) for i, t in short], "doc_id long, text string").repartition(4)
    labels = docs.select("doc_id", F.lit(1).alias("quality"))
    bands = fitted_bands(docs, labels)
    assert bands == fitted_bands(docs.repartition(7), labels.unionByName(labels))
    size = 1800
    limits = lambda b: next((low, high) for below, low, high in b.limits if size < below)
    assert limits(bands) != limits(CompressionBands()) and limits(fitted_bands(docs, labels, most=2000)) == limits(CompressionBands())
