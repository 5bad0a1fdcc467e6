"""Token ids, files, counts and packing against the library itself."""

import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from certgraph.llm import tokens as T
from certgraph.llm.packing import best_fit_patterns, improved_patterns, pack_documents, packing_plan
from certgraph.llm.token_counts import token_counts
from certgraph.llm.token_files import pack_numbers, read_token_files, unpack_numbers, write_token_files

PATH = public_tokenizers.path("byte_bpe_50k.json")
ODD = ["", None, " ", " a", "a ", "a  b", "a\n b", "a \nb", "a\n\n b c", "x  y", "x　 z", "it's 12 34's <|endoftext|> b", "q\n <|endoftext|>z", "\x1c a\x1f b", "日本 語 テキスト", "é ế a’b", "foo\r\n bar\tbaz", "ünü 😀 😀😀 x", "word, word. word"]


@pytest.fixture(scope="module")
def library():
    t = T._load(PATH)
    return lambda x: t.encode(x or "", add_special_tokens=False).ids


@pytest.fixture(scope="module")
def rows(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    return docs + [(10_000 + i, t) for i, t in enumerate(ODD)] + [(20_000, "a " * 5000)]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet=st.one_of(st.sampled_from(" \n\t'.,ab1é  \x1c<|>"), st.characters(codec="utf-8")), max_size=30), max_size=6))
def test_pieces_give_the_library_ids(texts):
    t, c, n = T._load(PATH) if not hasattr(T, "_t") else T._t, T.coder(PATH), T.coder(PATH, lengths_only=True)
    T._t = t
    want = [t.encode(x, add_special_tokens=False).ids for x in texts]
    assert [np.frombuffer(x, "<u2").tolist() for x in c.encode(texts)] == want
    assert n.encode(texts) == [len(x) for x in want]


def test_table_starts_again_when_full(library, monkeypatch):
    monkeypatch.setattr(T, "CACHE_PIECES", 50)
    rng = random.Random(1)
    texts = [" ".join(f"w{rng.randrange(400)}" for _ in range(40)) for _ in range(60)]
    for only in (False, True):
        c = T.PieceCoder(T._load(PATH), only)
        for k in range(0, 60, 7):
            got = c.encode(texts[k : k + 7])
            want = [library(x) for x in texts[k : k + 7]]
            assert got == [len(x) for x in want] if only else [np.frombuffer(x, "<u2").tolist() for x in got] == want


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 2**32 - 1) | st.integers(0, 300), max_size=60))
def test_numbers_round_trip(values):
    v = np.array(values, dtype=np.uint32)
    control, data = pack_numbers(v)
    assert len(control) == -(-len(v) // 4) and unpack_numbers(control, data, len(v)).tolist() == values


def test_files_round_trip(spark, rows, library, tmp_path):
    docs = spark.createDataFrame([(*r, 0) for r in rows] + [(None, "no id", 1)], "doc_id long, text string, start int")
    at = f"file://{tmp_path}/files"
    write_token_files(docs, at, PATH, end_id=2, shards=3)
    got = read_token_files(spark, at, with_ids=True).collect()
    assert len(got) == len(rows) + 1
    ordered, begin = sorted(got, key=lambda r: r.start), 0
    assert [r.doc_id for r in ordered] == [None, *sorted(i for i, _ in rows)]
    texts = dict(rows) | {None: "no id"}
    for r in ordered:
        ids = library(texts[r.doc_id]) + [2]
        assert r.ids == ids and r.start == begin and r.n_tokens == len(ids)
        assert r.ids_crc32 == zlib.crc32(np.array(ids, dtype="<u4").tobytes())
        begin += len(ids)
    counts = Counter(x for r in got for x in r.ids)
    by_rank = [r.token_id for r in spark.read.parquet(f"{at}/ranks").orderBy("token_rank").collect()]
    assert by_rank == [t for t, _ in sorted(counts.items(), key=lambda x: (-x[1], x[0]))]
    write_token_files(docs.limit(0), f"{at}-none", PATH)
    assert read_token_files(spark, f"{at}-none").count() == 0


def test_counts(spark, rows, library):
    docs = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, n_bytes string")
    got = {r.doc_id: r for r in token_counts(docs, PATH, 100).collect()}
    for i, t in rows:
        assert got[i].n_tokens == len(library(t)) and got[i].n_bytes == len((t or "").encode()) and got[i].over_limit == (got[i].n_tokens > 100)
    assert token_counts(docs.limit(0), PATH, 100).count() == 0


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "piece_bpe_32k.model"])
def test_counts_of_other_tokenizers(spark, name):
    path = public_tokenizers.path(name)
    texts = [t for t in ODD if t] + ["plain words here"]
    got = {r.doc_id: r.n_tokens for r in token_counts(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), path, 5).collect()}
    if name.endswith(".model"):
        import sentencepiece

        want = [len(x) for x in sentencepiece.SentencePieceProcessor(model_file=path).encode(texts)]
    else:
        t = T._load(path)
        want = [len(t.encode(x, add_special_tokens=False).ids) for x in texts]
    assert [got[i] for i in range(len(texts))] == want


def check_packing(rows, got, library, capacity, end=(2,)):
    bins, pieces = defaultdict(list), defaultdict(list)
    for r in got:
        bins[r.sequence_id].append((r.offset, r.length))
        pieces[r.doc_id].append(r)
    for b in bins.values():
        upto = 0
        for at, n in sorted(b):
            assert at == upto
            upto += n
        assert upto <= capacity
    for i, t in rows:
        ids, upto = [*library(t), *end], 0
        for k, r in enumerate(sorted(pieces[i], key=lambda r: r.piece)):
            assert r.piece == k and r.start == upto and r.ids_crc32 == zlib.crc32(np.array(ids[upto : upto + r.length], dtype="<u4").tobytes())
            assert k == 0 or r.length == capacity
            upto += r.length
        assert upto == len(ids) and (len(ids) > capacity or len(pieces[i]) == (len(ids) > 0))
    return len(bins), -(-sum(r.length for r in got) // capacity)


@pytest.mark.parametrize("capacity", [64, 1024])
def test_packing(spark, rows, library, capacity):
    docs = spark.createDataFrame([(*r, 5) for r in rows], "doc_id long, text string, offset int")
    used, bound = check_packing(rows, pack_documents(docs, PATH, capacity).collect(), library, capacity)
    assert bound <= used <= bound + max(2, bound // 50)
    assert pack_documents(docs.limit(0), PATH).count() == 0
    twice = spark.createDataFrame([(1, "a b"), (1, "a b"), (None, None)], "doc_id long, text string")
    assert pack_documents(twice, PATH).count() == 3 and pack_documents(twice, PATH, end_id=None).count() == 2


def test_plans_keep_every_item_and_improve():
    rng = random.Random(4)
    for _ in range(40):
        cap = rng.choice([10, 100])
        counts = Counter(rng.randint(1, cap) for _ in range(rng.randint(1, 120)))
        first = best_fit_patterns(dict(counts), cap)
        last = improved_patterns(first, cap)
        assert sum(last.values()) <= sum(first.values())
        assert all(sum(p) <= cap for p in last)
        assert Counter({k: sum(p.count(k) * n for p, n in last.items()) for k in counts}) == counts
    # best fit by decreasing length needs three bins here, exchanges find two
    assert sum(packing_plan({6: 1, 5: 1, 4: 1, 3: 1, 2: 1}, 10).values()) == 2


def test_packing_search_leaves_no_exchange():
    import random
    from collections import Counter

    from certgraph.llm.packing import _better, best_fit_patterns, improved_patterns

    rng = random.Random(1)
    counts = Counter(rng.randint(340, 700) for _ in range(4000)) + Counter({n: rng.randint(1, 5000) for n in range(200, 1024)})
    first = best_fit_patterns(counts, 1024)
    plan = improved_patterns(first, 1024)
    under = [p for p in plan if sum(p) < 1024]
    assert len(under) > 320 and sum(plan.values()) <= sum(first.values()) and all(sum(p) <= 1024 for p in plan)
    assert not any(_better(a, b, 1024) for i, a in enumerate(under) for b in under[i:] if a != b or plan[a] > 1)
    items = Counter()
    for p, n in plan.items():
        for length in p:
            items[length] += n
    assert items == counts
