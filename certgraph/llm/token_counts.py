"""Token counts of whole texts by a two-tier lookup that never moves a piece of text between tasks.

Tier one is a compact table from frequent pre-token pieces to their token counts, made once for the corpus and
sent to all workers; it holds at most `FREQUENT` entries at any corpus size. Tier two is each worker's own
table of what it met besides. What neither knows is encoded by the tokenizers library.

The frequent pieces come from summaries: a task counts its pieces in a bounded table that drops the rarest when
full, reports one row with its `REPORTED` largest counts, and rows are merged in a tree. Which pieces get in
touches the speed only, never a count.
"""

from __future__ import annotations

import pickle
import uuid
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.llm.tokens import PieceCoder, Pieces, PieceTable, coder
from certgraph.plans.staging import Stages

#: Entries of the table that is broadcast, counts in one task's report, pieces that a task counts at a time.
FREQUENT, REPORTED, COUNTED = 32_768, 8_192, 200_000
#: Reports merged in one task.
FAN_IN = 32


def _report(counts: Counter) -> bytes:
    return pickle.dumps(sorted(counts.items(), key=lambda x: (-x[1], x[0]))[:REPORTED])


def _summaries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    counts: Counter = Counter()
    for batch in batches:
        for text in batch.column(0).to_pylist():
            if text:
                counts.update(text.split(" ")[1:])
                if len(counts) > COUNTED:
                    counts = Counter(dict(counts.most_common(COUNTED // 2)))
    yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([_report(counts)], pa.binary())], names=["part", "report"])


def _merge(table: pa.Table) -> pa.Table:
    total: Counter = Counter()
    for blob in table.column("report").to_pylist():
        total.update(dict(pickle.loads(blob)))
    return pa.table({"part": pa.array([table.column("part")[0].as_py()], pa.int64()), "report": pa.array([_report(Counter(dict(total.most_common(FREQUENT))))], pa.binary())})


def frequent_pieces(docs: DataFrame, text_col: str = "text") -> list[str]:
    """The most frequent pieces of the corpus, at most FREQUENT of them, by tree-merged task summaries."""
    st = Stages(docs.sparkSession, "pieces")
    rows = st.keep(docs.select(F.col(text_col).cast("string")).mapInArrow(_summaries, "part long, report binary"), "reports")
    while rows.count() > FAN_IN:
        rows = st.keep(rows.groupBy((F.floor(F.col("part") / FAN_IN)).alias("g")).applyInArrow(_merge, "part long, report binary").select(F.floor(F.col("part") / FAN_IN).alias("part"), "report"), "reports")
    total: Counter = Counter()
    for blob in (r.report for r in rows.collect()):  # FAN_IN reports of bounded size at most
        total.update(dict(pickle.loads(blob)))
    return [p for p, _ in sorted(total.items(), key=lambda x: (-x[1], x[0]))[:FREQUENT] if p and not p[0].isspace()]


def frequent_table(pieces: list[str], path: str) -> PieceTable | None:
    """Tier one: token counts of the given pieces, as they stand after a space."""
    c = coder(path, lengths_only=True)
    if not isinstance(c, PieceCoder) or not pieces:
        return None
    raws = [("x " + p).encode("utf-8") for p in pieces if c._plain("x " + p) and " " not in p]
    table = PieceTable(with_ids=False)
    if raws:
        p = Pieces(raws)
        at = np.flatnonzero(~p.opens)
        order, sizes, _ = c._encode_new(p, at)
        table.add(p.key[at[order]], p.check[at[order]], sizes, None)
    return table


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Return doc_id, n_bytes (UTF-8), n_tokens, over_limit (n_tokens > limit), one row for each row of `docs`.

    Counts are those of the tokenizer's library for whole texts, without added special tokens, truncation or
    padding; strings of special tokens inside texts are handled as the library does by default. A null text counts
    as empty; ids are passed through, null or repeated; an empty table gives an empty result; other columns are not
    read. Files ending in .model go to sentencepiece, those without byte-level splitting to tokenizers, whole.
    """
    spark = docs.sparkSession
    table = frequent_table(frequent_pieces(docs, text_col), tokenizer_path) if not tokenizer_path.endswith(".model") else None
    shared = spark.sparkContext.broadcast(table)
    key = uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = coder(tokenizer_path, True, shared.value, key)
        for batch in batches:
            counts = []
            for k in range(0, batch.num_rows, 1000):
                counts += c.encode(batch.column(1).slice(k, 1000).to_pylist())
            n = pa.array(counts, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), n], names=["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.coalesce(F.octet_length(F.col(text_col).cast("string")), F.lit(0)).cast("long").alias("n_bytes"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
