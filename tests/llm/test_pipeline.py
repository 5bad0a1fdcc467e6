"""The pipeline, stage by stage, on the small tables."""

from collections import Counter

import corpus_pipeline
from certgraph.llm import queries
from certgraph.llm.quality import quality_verdicts


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    first = docs
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        at = f"file://{tmp_path}/{i}"
        stage(spark, docs, sf).write.parquet(at)
        after = spark.read.parquet(at)
        if name != "packing":
            assert after.columns == first.columns
        if name == "quality rules":
            kept = {r.doc_id for r in quality_verdicts(docs).filter("kept").collect()}
            assert {r.doc_id for r in after.collect()} == kept
        elif name == "near duplicates":
            ids = [r.doc_id for r in after.collect()]
            assert len(ids) == len(set(ids)) < docs.count()
        elif name == "mixing":
            n = Counter(r.doc_id for r in after.collect())
            assert max(n.values()) <= 3 and set(n) <= {r.doc_id for r in docs.collect()}
        else:
            assert after.filter("offset + length > 1024").count() == 0
            assert {r.doc_id for r in after.select("doc_id").collect()} == {r.doc_id for r in docs.select("doc_id").collect()}
        docs = after
    assert corpus_pipeline.ORACLE_SQL is None


def test_pipeline_of_an_empty_table(spark, sf, tmp_path):
    spark.read.parquet(f"{sf}/documents.parquet").limit(0).write.parquet(f"file://{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0


def test_one_query_for_each_operator():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.queries()) == list(range(1, 11))


def test_words_are_counted_without_a_list_of_them(spark):
    import re

    from pyspark.sql import functions as F

    from certgraph.llm.mixing import WORD, word_count

    texts = ["", " \t\n\x0b\x0c\r", "w", " ww w\tw ", "a\x0bb\x0cc\rd\ne", "  é 𝄞\x1f\x00 $1 \\w", "x " * 5000, None]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i long, t string")
    found = rows.select("i", word_count(F.col("t")).alias("n"))
    assert [r.n for r in found.orderBy("i").collect()] == [len(re.findall(WORD, t or "")) for t in texts]
    assert "regexp_count" not in found._jdf.queryExecution().toString().lower()


def test_workers_give_their_room_back():
    import os

    import numpy as np
    import pyarrow as pa

    from certgraph.functions.worker_memory import giving_back

    def held() -> int:
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * os.sysconf("SC_PAGE_SIZE")

    def run(batches):
        small = [np.ones(1000) for _ in range(20_000)]  # below what the C library maps by itself
        last = np.ones(1000)
        small.clear()
        for b in batches:
            yield b.set_column(0, "x", pa.array(last[: b.num_rows]))

    before = held()
    assert sum(b.num_rows for b in giving_back(run)(iter([pa.RecordBatch.from_arrays([pa.array([1.0])], names=["x"])]))) == 1
    assert held() - before < 60_000_000
