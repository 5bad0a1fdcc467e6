"""Approximate nearest neighbours by largest inner product, with cross-polytope hashing.

A table turns unit vectors by a pseudo-rotation (three rounds of random signs and a fast Hadamard transform) and files
each under the signed axis nearest to it; longer keys join several such hashes. Vectors of unequal length get one
more coordinate that makes all of them equally long without changing the order of inner products. A query looks into
several buckets of each table, the likeliest first, and every vector found there is ranked by its exact inner product.

How many buckets a query probes is fitted: for a bounded sample of queries the true neighbours are found by a scan,
and the smallest number is taken that finds `aim` of them. Key length follows the number of vectors, so buckets keep
their size, unless the sample needs more than `MOST_PROBES` buckets of long keys: then keys are a hash shorter, down to one,
of which every bucket may be probed. A query that finds fewer vectors than it could have is answered by a scan. A bucket of more than `BUCKET_ROWS` vectors, or of too many queries, is split by a hash into parts that
are searched apart, so no bucket has to fit into one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.plans.staging import Stages

#: Vectors and queries of one part of a bucket, queries of the fitting sample, share of true neighbours to find in it.
BUCKET_ROWS, BUCKET_QUERIES, SAMPLE_QUERIES, AIM = 8192, 8192, 128, 0.95
#: Probes of a table beyond which keys are shortened by one hash; keys of one hash have no such limit.
MOST_PROBES = 1024


def hadamard(x: np.ndarray) -> np.ndarray:
    """Orthonormal Walsh-Hadamard transform of each row; the number of columns is a power of two."""
    n, h = x.shape[1], 1
    while h < n:
        x = x.reshape(len(x), n // (2 * h), 2, h)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2).reshape(len(x), n)
        h *= 2
    return x / np.sqrt(n)


class CrossPolytope:
    """The hash family: `tables` keys of `hashes` signed axes each, for vectors of `dim` coordinates."""

    def __init__(self, dim: int, tables: int, hashes: int, longest: float | None, seed: int = 5):
        self.dim, self.tables, self.hashes, self.longest = dim, tables, hashes, longest
        self.wide = 1 << max(1, (dim + (longest is not None) - 1).bit_length())
        self.signs = np.random.default_rng(seed).choice([-1.0, 1.0], (tables, hashes, 3, self.wide))

    def _unit(self, x: np.ndarray, query: bool) -> np.ndarray:
        out = np.zeros((len(x), self.wide))
        norm = np.linalg.norm(x, axis=1, keepdims=True)
        if self.longest is None or query:
            out[:, : self.dim] = x / norm
        else:
            out[:, : self.dim] = x / self.longest
            out[:, self.dim] = np.sqrt(np.maximum(0.0, 1.0 - (norm[:, 0] / self.longest) ** 2))
        return out

    def _axes(self, u: np.ndarray, t: int, h: int) -> np.ndarray:
        """Closeness of each row to all signed axes: axis i at 2i, its opposite at 2i + 1."""
        for s in self.signs[t, h]:
            u = hadamard(u * s)
        return np.stack([u, -u], axis=2).reshape(len(u), 2 * self.wide)

    def keys(self, x: np.ndarray) -> np.ndarray:
        """Bucket of each vector in each table."""
        u, out = self._unit(x, False), np.zeros((len(x), self.tables), dtype=np.int64)
        for t in range(self.tables):
            for h in range(self.hashes):
                out[:, t] = out[:, t] * 2 * self.wide + self._axes(u, t, h).argmax(axis=1)
        return out

    def probes(self, x: np.ndarray, most: int) -> np.ndarray:
        """Buckets to look into, likeliest first: queries x tables x at most `most`."""
        u, per = self._unit(x, True), []
        for t in range(self.tables):
            key, cost = np.zeros((len(x), 1), dtype=np.int64), np.zeros((len(x), 1))
            for h in range(self.hashes):
                axes = self._axes(u, t, h)
                near = np.argsort(-axes, axis=1, kind="stable")[:, :most]
                value = np.take_along_axis(axes, near, axis=1)
                lack = (value[:, :1] - value) ** 2
                cost = (cost[:, :, None] + lack[:, None, :]).reshape(len(x), -1)
                key = (key[:, :, None] * 2 * self.wide + near[:, None, :]).reshape(len(x), -1)
                best = np.argsort(cost, axis=1, kind="stable")[:, :most]
                cost, key = np.take_along_axis(cost, best, axis=1), np.take_along_axis(key, best, axis=1)
            per.append(key)
        return np.stack(per, axis=1)


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.astype(np.float64).reshape(-1, dim)


def _nearest(q: np.ndarray, q_ids: np.ndarray, x: np.ndarray, x_ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Up to k best of `x` for each query, its own id left out; scores are summed in one order for equal vectors."""
    qs, xs, scores = [], [], []
    step = max(1, (1 << 22) // max(1, len(x)))
    for a in range(0, len(q), step):
        s = q[a : a + step] @ x.T
        s[q_ids[a : a + step, None] == x_ids[None, :]] = -np.inf
        if len(x) > k:
            bar = -np.partition(-s, k - 1, axis=1)[:, k - 1 : k]
            i, j = np.nonzero((s >= bar - 1e-9 * np.maximum(1.0, np.abs(bar))) & (s > -np.inf))
        else:
            i, j = np.nonzero(s > -np.inf)
        exact = (q[a + i] * x[j]).sum(axis=1)
        order = np.lexsort((x_ids[j], -exact, i))
        i, j, exact = i[order], j[order], exact[order]
        first = np.searchsorted(i, i)
        keep = np.arange(len(i)) - first < k
        qs.append(q_ids[a + i[keep]])
        xs.append(x_ids[j[keep]])
        scores.append(exact[keep])
    none = np.zeros(0, dtype=np.int64)
    return (np.concatenate(qs), np.concatenate(xs), np.concatenate(scores)) if qs else (none, none, np.zeros(0))


def _best(rows: DataFrame, k: int) -> DataFrame:
    once = rows.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return once.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def _scan(q_ids: np.ndarray, q: np.ndarray, dim: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, s = _nearest(q, q_ids, _matrix(batch.column(1), dim), batch.column(0).to_numpy(zero_copy_only=False), k)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(s, pa.float64())], names=["query_id", "vec_id", "score"])

    return run


def usable_vectors(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> tuple[DataFrame, int]:
    """(vec_id, vec) of the vectors that take part, and their dimension, the most frequent one.

    Out are null vectors, zero ones, those with a null or non-finite component or another dimension, and null ids.
    """
    v = F.col("vec")
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("vec")).filter("vec_id IS NOT NULL AND size(vec) > 0")
    rows = rows.filter(F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0))
    dims = rows.groupBy(F.size("vec").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "d").head(1)
    dim = dims[0].d if dims else 1
    return rows.filter(F.size("vec") == dim), dim


def nearest_neighbours(vectors: DataFrame, queries: str = "vec_id % 20 = 0", k: int = 20, tables: int = 8, hashes: int | None = None, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """Return query_id, rank (from 1), vec_id, score: for each query row its k nearest others found, nearest first.

    `queries` is an SQL condition on vec_id. Nearness is the inner product in double precision; ties go to the smaller
    id. A query with fewer candidates than k gets all that there are. Rows that repeat an id count as one vector's
    copies: none is its own neighbour, the best score stands. An empty table gives an empty result.
    """
    spark = vectors.sparkSession
    st = Stages(spark, "nearest")
    rows, dim = usable_vectors(vectors, id_col, vec_col)
    rows = st.keep(rows, "vectors")
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    n, distinct, least, most = rows.agg(F.count(F.lit(1)), F.count_distinct("vec_id"), F.min(norm), F.max(norm)).first()
    asked = rows.filter(queries)
    longest = most if n and most - least > 1e-4 * most else None
    probe = CrossPolytope(dim, tables, 1, longest)
    if hashes is None:
        hashes = 1
        while n > BUCKET_ROWS * (2 * probe.wide) ** hashes:
            hashes += 1
    truth = _sample_truth(rows, asked, dim, k)
    while True:
        family = CrossPolytope(dim, tables, hashes, longest)
        every = (2 * family.wide) ** hashes
        probes = _fitted_probes(truth, family, dim, every if hashes == 1 else min(every, MOST_PROBES))
        if probes is not None:
            break
        hashes -= 1
    vec = rows.schema["vec"].dataType.simpleString()  # as wide as it came

    def filed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 2048):
                part = batch.slice(a, 2048)
                keys = family.keys(_matrix(part.column(1), dim))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.FixedSizeListArray.from_arrays(pa.array(keys.ravel(), pa.int64()), tables).cast(pa.list_(pa.int64()))], names=["vec_id", "vec", "keys"])

    def looked_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                keys = family.probes(_matrix(part.column(1), dim), probes)
                for t in range(tables):
                    own = pa.FixedSizeListArray.from_arrays(pa.array(keys[:, t].ravel(), pa.int64()), keys.shape[2]).cast(pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), t), pa.int32()), part.column(0), part.column(1), own], names=["table_no", "vec_id", "vec", "keys"])

    def searched(left: pa.Table, right: pa.Table) -> pa.Table:
        q, x = left.combine_chunks(), right.combine_chunks()
        none = q.num_rows == 0 or x.num_rows == 0
        a, b, s = ([], [], []) if none else _nearest(_matrix(q["vec"].combine_chunks(), dim), q["vec_id"].to_numpy(), _matrix(x["vec"].combine_chunks(), dim), x["vec_id"].to_numpy(), k)
        return pa.table({"query_id": pa.array(a, pa.int64()), "vec_id": pa.array(b, pa.int64()), "score": pa.array(s, pa.float64())})

    def compared(data: DataFrame, ask: DataFrame) -> DataFrame:
        """Best of each bucket for each query that looks into it; large buckets in parts."""
        split = F.greatest(F.lit(1), F.ceil(F.col("n") / F.lit(BUCKET_ROWS))).cast("int")
        data_parts = data.groupBy("table_no", "bucket").agg(F.count(F.lit(1)).alias("n")).select("table_no", "bucket", split.alias("data_parts"))
        ask_split = F.greatest(F.lit(1), F.ceil(F.col("n") / F.lit(BUCKET_QUERIES))).cast("int")
        ask_parts = ask.groupBy("table_no", "bucket").agg(F.count(F.lit(1)).alias("n")).select("table_no", "bucket", ask_split.alias("ask_parts"))
        parts = st.keep(data_parts.join(ask_parts, ["table_no", "bucket"]), "parts")
        h = F.xxhash64("vec_id")
        key = ["table_no", "bucket", "data_part", "ask_part"]
        data = data.join(parts, ["table_no", "bucket"]).select("table_no", "bucket", F.pmod(h, "data_parts").cast("int").alias("data_part"), F.explode(F.expr("sequence(0, ask_parts - 1)")).alias("ask_part"), "vec_id", "vec")
        ask = ask.join(parts, ["table_no", "bucket"]).select("table_no", "bucket", F.explode(F.expr("sequence(0, data_parts - 1)")).alias("data_part"), F.pmod(h, "ask_parts").cast("int").alias("ask_part"), "vec_id", "vec")
        return ask.groupBy(*key).cogroup(data.groupBy(*key)).applyInArrow(searched, "query_id long, vec_id long, score double")

    # hashed once: bucket sizes and the search both read the stored keys
    keyed = st.keep(rows.mapInArrow(filed, f"vec_id long, vec {vec}, keys array<long>"), "keyed")
    data = keyed.select(F.posexplode("keys").alias("table_no", "bucket"), "vec_id", "vec")
    probed = st.keep(asked.mapInArrow(looked_up, f"table_no int, vec_id long, vec {vec}, keys array<long>"), "probed")
    ask = probed.select("table_no", F.explode("keys").alias("bucket"), "vec_id", "vec")
    found = st.keep(_best(compared(data, ask), k), "found")
    st.drop(keyed, probed)
    enough = found.groupBy("query_id").count().filter(F.col("count") >= min(k, distinct - 1)).select(F.col("query_id").alias("vec_id"))
    short = st.keep(asked.join(enough, "vec_id", "left_anti"), "short")
    if distinct > 1 and not short.isEmpty():  # one bucket that holds all, searched in parts like any other
        whole = [F.lit(tables).alias("table_no"), F.lit(0).cast("long").alias("bucket"), "vec_id", "vec"]
        scanned = _best(compared(rows.select(*whole), short.select(*whole)), k)
        found = found.join(enough.withColumnRenamed("vec_id", "query_id"), "query_id", "left_semi").unionByName(scanned)
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _sample_truth(rows: DataFrame, asked: DataFrame, dim: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """Sampled queries, their true neighbours by a scan, and for each neighbour the place of its query."""
    sample = asked.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE_QUERIES).toArrow()
    if sample.num_rows == 0:
        return None
    q_ids, q = sample["vec_id"].to_numpy(), _matrix(sample["vec"].combine_chunks(), dim)
    truth = _best(rows.mapInArrow(_scan(q_ids, q, dim, k), "query_id long, vec_id long, score double"), k)
    true = truth.join(rows.dropDuplicates(["vec_id"]), "vec_id").select("query_id", "vec").toArrow()  # k rows for each sampled query
    if true.num_rows == 0:
        return None
    where = {v: i for i, v in enumerate(q_ids.tolist())}
    return q, _matrix(true["vec"].combine_chunks(), dim), np.array([where[v] for v in true["query_id"].to_pylist()])


def _fitted_probes(truth: tuple[np.ndarray, np.ndarray, np.ndarray] | None, family: CrossPolytope, dim: int, most: int) -> int | None:
    """Probes for each table with which the sample's true neighbours are found to the aimed share; None if `most` don't do."""
    if truth is None:
        return 1
    q, true, at = truth
    keys, order = family.keys(true), family.probes(q, most)
    best = np.full(len(keys), most, dtype=np.int64)
    for t in range(family.tables):
        same = order[at, t] == keys[:, t : t + 1]
        best = np.minimum(best, np.where(same.any(axis=1), same.argmax(axis=1), most))
    fitted = int(np.sort(best)[min(len(best) - 1, int(np.ceil(AIM * len(best))) - 1)]) + 1
    return fitted if fitted <= most else None
