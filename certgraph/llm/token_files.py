"""Token ids in byte-aligned variable-length files, small numbers for frequent tokens.

Ids are replaced by their frequency rank over the whole corpus and stored with one to four bytes each. The
byte lengths stand apart, two bits an id, four ids to a control byte, so a reader finds the lengths of all ids
of a block by one table lookup for each control byte and gathers the data bytes with numpy.

File set: a Parquet folder `blocks` (shard, block, first_doc, doc_ids, lengths, n_ids, control, data), where shards and
the blocks in them follow ascending doc_id, and a folder `ranks` (token_rank, token_id). Parquet is only the
container, so that the files can lie in any store that Spark reaches and are committed as whole tasks.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.llm.tokens import coder
from certgraph.plans.staging import Stages, writing_settings

#: Ids gathered into one block before it is written; a longer document is a block of its own.
BLOCK_IDS = 1 << 18

_SHIFT = np.array([0, 2, 4, 6], dtype=np.uint8)
#: Byte lengths of the four ids that a control byte describes.
LENGTH_TABLE = ((np.arange(256, dtype=np.uint8)[:, None] >> _SHIFT) & 3) + np.uint8(1)


def pack_numbers(values: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of unsigned numbers below 2**32."""
    v = values.astype(np.uint32)
    extra = (v > 0xFF).astype(np.uint8)
    if len(v) and int(v.max()) > 0xFFFF:
        extra = extra + (v > 0xFFFF) + (v > 0xFFFFFF)
    codes = np.zeros(-(-len(v) // 4) * 4, dtype=np.uint8)
    codes[: len(v)] = extra
    control = np.bitwise_or.reduce(codes.reshape(-1, 4) << _SHIFT, axis=1) if len(v) else codes
    ends = np.cumsum(extra.astype(np.int64) + 1)
    data = np.empty(int(ends[-1]) if len(v) else 0, dtype=np.uint8)
    at = ends - extra - 1
    data[at] = v & 0xFF
    for k in (1, 2, 3):
        more = np.flatnonzero(extra >= k)
        if len(more) == 0:
            break
        data[at[more] + k] = (v[more] >> np.uint32(8 * k)) & 0xFF
    return control.astype(np.uint8).tobytes(), data.tobytes()


def unpack_numbers(control: bytes, data: bytes, n: int) -> np.ndarray:
    """The numbers back, lengths by table lookup."""
    sizes = LENGTH_TABLE[np.frombuffer(control, dtype=np.uint8)].reshape(-1)[:n]
    raw = np.frombuffer(data, dtype=np.uint8)
    at = np.cumsum(sizes, dtype=np.int64) - sizes
    out = raw[at].astype(np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(sizes > k)
        if len(more) == 0:
            break
        out[more] |= raw[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


_BLOCK = "shard int, block long, doc_ids binary, no_id binary, lengths binary, n_ids long, ids binary"


def _tokenised(path: str, end_id: int | None):
    """Rows of one shard, in order, to blocks of ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        c = coder(path)
        tail = b"" if end_id is None else np.array([end_id], dtype=c.type).tobytes()
        held: list[tuple] = []
        size, block = 0, 0

        def flush():
            docs = np.array([0 if d is None else d for d, _ in held], dtype="<i8")
            none = np.array([d is None for d, _ in held], dtype=np.uint8)
            lengths = np.array([len(x) // c.type.itemsize for _, x in held], dtype="<i8")
            ids = np.frombuffer(b"".join(x for _, x in held), dtype=c.type).astype("<u4") if c.type.itemsize == 4 else b"".join(x for _, x in held)
            row = {"shard": shard, "block": block, "doc_ids": docs.tobytes(), "no_id": none.tobytes(), "lengths": lengths.tobytes(), "n_ids": int(lengths.sum()), "ids": bytes(ids)}
            return pa.RecordBatch.from_pylist([row], schema=_BLOCK_ARROW)

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for k in range(0, len(ids), 512):
                for doc, raw in zip(ids[k : k + 512], c.encode(texts[k : k + 512]), strict=True):
                    held.append((doc, raw + tail))
                    size += len(raw) // c.type.itemsize + 1
                    if size >= BLOCK_IDS:
                        yield flush()
                        held, size, block = [], 0, block + 1
        if held:
            yield flush()

    return run


_BLOCK_ARROW = pa.schema([("shard", pa.int32()), ("block", pa.int64()), ("doc_ids", pa.binary()), ("no_id", pa.binary()), ("lengths", pa.binary()), ("n_ids", pa.int64()), ("ids", pa.binary())])


def _id_type(n: int, raw: bytes) -> np.dtype:
    return np.dtype("<u2") if n == 0 or len(raw) // n == 2 else np.dtype("<u4")


def _histogram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(0, dtype=np.int64)
    for batch in batches:
        for n, one in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            raw = one.as_py()
            c = np.bincount(np.frombuffer(raw, dtype=_id_type(n, raw)), minlength=len(total))
            c[: len(total)] += total
            total = c
    seen = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(total[seen], pa.int64())], names=["token_id", "n"])


def write_token_files(docs: DataFrame, to: str, tokenizer_path: str, end_id: int | None = None, id_col: str = "doc_id", text_col: str = "text", shards: int | None = None) -> None:
    """Encode every text and write the file set to `to`, in ascending id order (null ids first, equal ids by text hash).

    A null text has no ids but `end_id`. Empty input gives an empty file set. Columns other than the two are not read.
    The rank table has one row for each id of the vocabulary that occurs, so it is small at any corpus size.
    """
    spark = docs.sparkSession
    st = Stages(spark, "tokenfiles")
    shards = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text").asc()]
    placed = texts.repartitionByRange(shards, *order).sortWithinPartitions(*order)
    raw = st.keep(placed.mapInArrow(_tokenised(tokenizer_path, end_id), _BLOCK), "ids")

    counts = raw.select("n_ids", "ids").mapInArrow(_histogram, "token_id long, n long").groupBy("token_id").agg(F.sum("n").alias("n"))
    ranks = counts.select("token_id", (F.row_number().over(Window.orderBy(F.desc("n"), "token_id")) - 1).alias("token_rank"))
    ranks.select(F.col("token_rank").cast("long"), "token_id").coalesce(1).write.mode("overwrite").parquet(f"{to}/ranks")
    by_rank = _rank_table(spark, to)
    rank_of = np.zeros(int(by_rank.max()) + 1 if len(by_rank) else 1, dtype=np.uint32)
    rank_of[by_rank] = np.arange(len(by_rank), dtype=np.uint32)

    def recode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            control, data = [], []
            for n, raw in zip(batch.column("n_ids").to_pylist(), batch.column("ids"), strict=True):
                ids = raw.as_py()
                a, b = pack_numbers(rank_of[np.frombuffer(ids, dtype=_id_type(n, ids))])
                control.append(a)
                data.append(b)
            kept = [batch.column(c) for c in ("shard", "block", "doc_ids", "no_id", "lengths", "n_ids")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(control, pa.binary()), pa.array(data, pa.binary())], names=["shard", "block", "doc_ids", "no_id", "lengths", "n_ids", "control", "data"])

    final = raw.mapInArrow(recode, "shard int, block long, doc_ids binary, no_id binary, lengths binary, n_ids long, control binary, data binary")
    with writing_settings(spark):
        final.write.mode("overwrite").option("compression", "zstd").parquet(f"{to}/blocks")
    st.drop(raw)


def _rank_table(spark: SparkSession, at: str) -> np.ndarray:
    """Token ids by rank; at most one for each id of the vocabulary."""
    rows = spark.read.schema("token_rank long, token_id long").parquet(f"{at}/ranks").orderBy("token_rank").toArrow()
    return rows.column("token_id").to_numpy().astype(np.int64)


def read_token_files(spark: SparkSession, at: str, with_ids: bool = False) -> DataFrame:
    """Documents of a file set: doc_id, start (ids of all documents before it), n_tokens, ids_crc32 and, if asked for, the ids."""
    by_rank = _rank_table(spark, at).astype("<u4")
    blocks = spark.read.schema("shard int, block long, doc_ids binary, no_id binary, lengths binary, n_ids long, control binary, data binary").parquet(f"{at}/blocks")
    sizes = blocks.select("shard", "block", "n_ids")
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    inside = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    per_shard = sizes.groupBy("shard").agg(F.sum("n_ids").alias("n")).select("shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shard_start"))
    per_block = sizes.select("shard", "block", F.coalesce(F.sum("n_ids").over(inside), F.lit(0)).alias("block_start"))
    starts = per_block.join(per_shard, "shard").select("shard", "block", (F.col("block_start") + F.col("shard_start")).alias("first"))

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):  # one block at a time
                r = batch.slice(i, 1).to_pylist()[0]
                ids = by_rank[unpack_numbers(r["control"], r["data"], r["n_ids"])] if r["n_ids"] else by_rank[:0]
                lengths = np.frombuffer(r["lengths"], dtype="<i8")
                ends = np.cumsum(lengths)
                docs = np.frombuffer(r["doc_ids"], dtype="<i8")
                none = np.frombuffer(r["no_id"], dtype=np.uint8).astype(bool)
                own = [ids[b - n : b] for n, b in zip(lengths, ends, strict=True)]
                cols = [pa.array(np.full(len(docs), r["shard"]), pa.int32()), pa.array(np.full(len(docs), r["block"]), pa.int64()), pa.array(docs, pa.int64(), mask=none), pa.array(ends - lengths, pa.int64()), pa.array(lengths, pa.int64()), pa.array([zlib.crc32(x.tobytes()) for x in own], pa.int64())]
                if with_ids:
                    cols.append(pa.array([x.tolist() for x in own], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(cols, names=["shard", "block", "doc_id", "inside", "n_tokens", "ids_crc32"] + ["ids"] * with_ids)

    schema = "shard int, block long, doc_id long, inside long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    rows = blocks.mapInArrow(decode, schema).join(starts, ["shard", "block"])
    return rows.select("doc_id", (F.col("first") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * with_ids)
