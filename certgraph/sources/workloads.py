"""Graphs on the given tables, each as edges(seq, u, v), and generated graphs whose connectivity is known.

Ids of two sides are kept apart by an offset; text vertices (hosts, urls, lines) get their place among all names.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.operators.edges import canonical_edges, degrees, dense_numbers, encode_ids
from certgraph.plans.staging import Stages

#: Added to ids of the second and third side of a graph with several kinds of vertices.
SIDE = 1_000_000_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def next_in_stream(df: DataFrame, value: str, order_by: list[str]) -> DataFrame:
    """(value, following, order columns): each row with the value of the next row of the whole stream.

    Rows are numbered by ranges, so that the neighbour is found by a join on the number and no task sorts all rows.
    """
    numbered = dense_numbers(df.select(value, *order_by), order_by, "_nth")
    after = numbered.select((F.col("_nth") - 1).alias("_nth"), F.col(value).alias("following"))
    return numbered.join(after, "_nth").select(value, "following", *order_by)


def call_graph(spark: SparkSession, sf_dir: str, event_type: str | None = None) -> DataFrame:
    """User to the user of the next event, of one type or of all."""
    events = table(spark, sf_dir, "events")
    if event_type:
        events = events.filter(F.col("event_type") == event_type)
    return canonical_edges(next_in_stream(events, "user_id", ["ts", "event_id"]), "user_id", "following", ["ts", "event_id"])


def call_window(spark: SparkSession, sf_dir: str, minutes: int = 5) -> DataFrame:
    """Users active within some minutes after another: from arrays of all events where these can be broadcast, else by an equi-join on time buckets and a filter."""
    shared = _events_by_time(spark, sf_dir)
    if shared is not None:
        return window_edges(spark, shared, 60 * minutes)
    e = table(spark, sf_dir, "events").select("user_id", "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t")).withColumn("b", F.floor(F.col("t") / (60 * minutes)))
    a = e.select(F.col("user_id").alias("src"), "event_id", "t", F.explode(F.array("b", F.col("b") + 1)).alias("b"))
    c = e.select(F.col("user_id").alias("dst"), F.col("event_id").alias("event2"), F.col("t").alias("t2"), "b")
    near = a.join(c, "b").filter((F.col("t2") >= F.col("t")) & (F.col("t2") - F.col("t") <= 60 * minutes) & (F.col("event_id") != F.col("event2")))
    return canonical_edges(near, "src", "dst", ["t", "event_id", "t2", "event2"])


#: Events (16 bytes each) that are broadcast as arrays.
MOST_EVENTS = 50_000_000


def _events_by_time(spark: SparkSession, sf_dir: str, most: int = MOST_EVENTS) -> Broadcast | None:
    """(users ascending, each event's place among them, its second) of all events in order of time and id; None if they are too many."""
    e = table(spark, sf_dir, "events").select("user_id", "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t")).dropna()
    if e.count() > most:
        return None
    rows = e.toArrow()
    user, event, t = (rows.column(c).to_numpy() for c in ("user_id", "event_id", "t"))
    order = np.lexsort((event, t))
    users, place = np.unique(user[order], return_inverse=True)
    return spark.sparkContext.broadcast((users.astype(np.int64), place.astype(np.int32), t[order]))


def _meetings(place: np.ndarray, t: np.ndarray, low: np.ndarray, before: np.ndarray, own: np.ndarray, seconds: int, most: int) -> np.ndarray:
    """Of some users' events `own`: the first meeting of each user with each user of a later place.

    Event a meets those from low[a] on that are not later than `seconds` after it; meetings have numbers, in order of both events.
    """
    begin = np.searchsorted(t, t[own] - seconds, "left")
    size = np.searchsorted(t, t[own] + seconds, "right") - begin
    best: list[tuple[np.ndarray, np.ndarray]] = []
    for some in np.split(np.arange(len(own)), np.flatnonzero(np.diff(np.cumsum(size) // most)) + 1):
        x = np.repeat(own[some], size[some])
        y = np.arange(len(x)) - np.repeat(np.cumsum(size[some]) - size[some], size[some]) + np.repeat(begin[some], size[some])
        on = place[x] < place[y]
        x, y = x[on], y[on]
        key = place[x].astype(np.int64) << 32 | place[y]
        ahead, behind = before[x] + y - low[x], before[y] + x - low[y]  # events of one second meet in both directions
        best.append(_least(key, np.where(t[x] == t[y], np.minimum(ahead, behind), np.where(t[x] < t[y], ahead, behind))))
    return _least(*(np.concatenate(c) for c in zip(*best, strict=True)))[1] if len(best) > 1 else best[0][1]


def _least(key: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((number, key))
    key, number = key[order], number[order]
    first = np.append(True, key[1:] != key[:-1])[: len(key)]
    return key[first], number[first]


def window_edges(spark: SparkSession, shared: Broadcast, seconds: int, users_at_once: int = 64, most: int = 1 << 21) -> DataFrame:
    """(seq, u, v): pairs of users with an event of one within so many seconds after one of the other, in order of their first two events.

    A task finds the first meetings of its users and writes their numbers, packed, by ranges of the stream; a second one counts on from the ranges before
    its own and reads the users off the events. No pair is shuffled or sorted as a row.
    """
    users, place, t = shared.value
    low, high = np.searchsorted(t, t, "left"), np.searchsorted(t, t + seconds, "right")
    n, total = int(spark.conf.get("spark.sql.shuffle.partitions")), int((high - low).sum())
    ranges = max(4 * n, -(-total // (1 << 27)))
    wide = max(1, -(-total // ranges))

    def numbers() -> tuple[np.ndarray, ...]:
        users, place, t = shared.value
        low, high = np.searchsorted(t, t, "left"), np.searchsorted(t, t + seconds, "right")
        return users, place, t, low, np.cumsum(high - low) - (high - low)

    def packed(found: list[np.ndarray]) -> pa.RecordBatch:
        x = np.sort(np.concatenate(found))
        part = x // wide
        cut = np.flatnonzero(np.append(True, part[1:] != part[:-1])[: len(x)])
        # bytes of one weight stand together, as most gaps are small
        blobs = [zlib.compress(np.diff(y, prepend=int(r) * wide).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes(), 3) for r, y in zip(part[cut], np.split(x, cut[1:]), strict=True)] if len(x) else []
        return pa.RecordBatch.from_arrays([pa.array(part[cut], pa.int64()), pa.array(np.diff(np.append(cut, len(x))), pa.int64()), pa.array(blobs, pa.binary())], names=["part", "n", "gaps"])

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, place, t, low, before = numbers()
        own = np.argsort(place, kind="stable")
        starts = np.searchsorted(place[own], np.arange(len(shared.value[0]) + 1))
        found, held = [], 0
        for b in batches:
            for x in b.column(0).to_pylist():
                found.append(_meetings(place, t, low, before, own[starts[x] : starts[min(x + users_at_once, len(starts) - 1)]], seconds, most))
                held += len(found[-1])
                if held >= 4 * most:
                    yield packed(found)
                    found, held = [], 0
        if held:
            yield packed(found)

    blocks = spark.range(0, len(users), users_at_once).repartition(n)
    parts = Stages(spark, "window").keep(blocks.mapInArrow(first, "part long, n long, gaps binary"), "firsts", rows=64)
    sizes = np.zeros(ranges + 1, np.int64)
    for r in parts.groupBy("part").agg(F.sum("n").alias("n")).collect():
        sizes[r.part + 1] = r.n
    starts = spark.sparkContext.broadcast(np.cumsum(sizes))

    def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        users, place, _, low, before = numbers()

        def batch(part: int, found: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
            x = np.sort(np.concatenate(found))
            for j in range(0, len(x), 1 << 16):
                y = x[j : j + (1 << 16)]
                a = np.searchsorted(before, y, "right") - 1
                u, v = place[a], place[y - before[a] + low[a]]
                yield pa.RecordBatch.from_arrays([pa.array(starts.value[part] + 1 + j + np.arange(len(y))), pa.array(users[np.minimum(u, v)]), pa.array(users[np.maximum(u, v)])], names=["seq", "u", "v"])

        part, found = -1, []
        for b in batches:
            for r, gaps in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if r != part and found:
                    yield from batch(part, found)
                    found = []
                part = r
                planes = np.frombuffer(zlib.decompress(gaps), np.uint8).reshape(4, -1).T
                found.append(r * wide + np.cumsum(np.ascontiguousarray(planes).view("<u4").ravel().astype(np.int64)))
        if found:
            yield from batch(part, found)

    return parts.select("part", "gaps").repartition(n, "part").sortWithinPartitions("part").mapInArrow(edges, "seq long, u long, v long")


def window_pairs(spark: SparkSession, shared: Broadcast, seconds: int, step: int = 4096) -> DataFrame:
    """(u, v, o): pairs of users with an event of one within so many seconds after one of the other; o orders them by their first two events."""
    n = len(shared.value[2])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        users, place, t = shared.value
        for b in batches:
            for begin in b.column(0).to_pylist():
                first = np.arange(begin, min(begin + step, n))
                low, high = np.searchsorted(t, t[first], "left"), np.searchsorted(t, t[first] + seconds, "right")
                for some in np.split(np.arange(len(first)), np.flatnonzero(np.diff(np.cumsum(high - low) // (1 << 21))) + 1):
                    size = (high - low)[some]
                    a = np.repeat(first[some], size)
                    c = np.arange(len(a)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(low[some], size)
                    on = place[a] != place[c]
                    a, c = a[on], c[on]
                    u, v = np.minimum(place[a], place[c]).astype(np.int64), np.maximum(place[a], place[c]).astype(np.int64)
                    _, met = np.unique(u * len(users) + v, return_index=True)  # in order of o, so the first is the least
                    yield pa.RecordBatch.from_arrays([pa.array(users[u[met]]), pa.array(users[v[met]]), pa.array(a[met] * n + c[met])], names=["u", "v", "o"])

    starts = spark.range(0, n, step).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
    return starts.mapInArrow(run, "u long, v long, o long").groupBy("u", "v").agg(F.min("o").alias("o"))


def window_degrees(spark: SparkSession, sf_dir: str, minutes: int = 5) -> DataFrame:
    """(id, d) of the graph of `call_window`: a task marks for each of its users all others near one of the user's events, so no pair is written."""
    shared = _events_by_time(spark, sf_dir)
    if shared is None:
        return degrees(call_window(spark, sf_dir, minutes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        users, place, t = shared.value
        own = np.argsort(place, kind="stable")
        starts = np.searchsorted(place[own], np.arange(len(users) + 1))
        seen = np.zeros(len(users), dtype=bool)
        for b in batches:
            ids, d = [], []
            for x in b.column(0).to_pylist():
                at = t[own[starts[x] : starts[x + 1]]]
                low, high = np.searchsorted(t, at - 60 * minutes, "left"), np.searchsorted(t, at + 60 * minutes, "right")
                low[1:] = np.maximum(low[1:], high[:-1])  # times ascend, and no event is looked at twice
                seen[:] = False
                for i, j in zip(low.tolist(), high.tolist(), strict=True):
                    seen[place[i:j]] = True
                seen[x] = False
                n = int(np.count_nonzero(seen))
                if n:
                    ids.append(int(users[x]))
                    d.append(n)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(d, pa.int64())], names=["id", "d"])

    items = spark.range(len(shared.value[0])).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
    return items.mapInArrow(run, "id long, d long")


def weekly_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(graph, seq, u, v): for each user and week a small graph of the types of events that follow each other; ids are crc32 of the types."""
    e = table(spark, sf_dir, "events").withColumn("w", F.floor(F.unix_date(F.col("ts").cast("date")) / 7))
    e = e.withColumn("b", F.lead("event_type").over(Window.partitionBy("user_id", "w").orderBy("ts", "event_id"))).filter("event_type <> b")
    ends = e.select(F.concat_ws(":", "user_id", "w").alias("graph"), F.struct("ts", "event_id").alias("o"), F.crc32("event_type").alias("a"), F.crc32("b").alias("b"))
    first = ends.groupBy("graph", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).agg(F.min("o").alias("o"))
    return first.withColumn("seq", F.row_number().over(Window.partitionBy("graph").orderBy("o")).cast("long")).select("graph", "seq", "u", "v")


def user_topic(spark: SparkSession, sf_dir: str, event_type: str | None = None) -> DataFrame:
    events = table(spark, sf_dir, "events")
    if event_type:
        events = events.filter(F.col("event_type") == event_type)
    topic = F.get_json_object("props", "$.k").cast("long") + SIDE
    return canonical_edges(events.select("user_id", topic.alias("topic"), "ts", "event_id"), "user_id", "topic", ["ts", "event_id"])


def _links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", "url", F.posexplode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("at", "href"))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    named = _links(spark, sf_dir).select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("a"), F.concat(F.lit("h:"), "href").alias("b"), "page_id", "at")
    return canonical_edges(encode_ids(named, ["a", "b"])[0], "a", "b", ["page_id", "at"])


def host_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    host = F.regexp_extract("url", "://([^/]*)", 1)
    named = _links(spark, sf_dir).select(F.concat(F.lit("s:"), host).alias("a"), F.concat(F.lit("h:"), "href").alias("b"), "page_id", "at")
    return canonical_edges(encode_ids(named, ["a", "b"])[0], "a", "b", ["page_id", "at"])


def _geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("a"), (F.col("c_nationkey") + 2 * SIDE).alias("b"), F.lit(1).alias("kind"), F.col("c_custkey").alias("key"))
    s = table(spark, sf_dir, "supplier").select((F.col("s_suppkey") + SIDE).alias("a"), (F.col("s_nationkey") + 2 * SIDE).alias("b"), F.lit(2).alias("kind"), F.col("s_suppkey").alias("key"))
    n = table(spark, sf_dir, "nation").select((F.col("n_nationkey") + 2 * SIDE).alias("a"), (F.col("n_regionkey") + 3 * SIDE).alias("b"), F.lit(3).alias("kind"), F.col("n_nationkey").cast("long").alias("key"))
    return c.unionByName(s).unionByName(n)


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical_edges(_geo(spark, sf_dir), "a", "b", ["kind", "key"])


def _trades(spark: SparkSession, sf_dir: str, condition: Column | None = None) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem")
    if condition is not None:
        lines = lines.filter(condition)
    return lines.join(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


_LINE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def geo_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    cross = _trades(spark, sf_dir).select(F.col("o_custkey").alias("a"), (F.col("l_suppkey") + SIDE).alias("b"), F.lit(4).alias("kind"), F.col("l_orderkey").alias("key"))
    return canonical_edges(_geo(spark, sf_dir).unionByName(cross), "a", "b", ["kind", "key", "a", "b"])


def part_supplier(spark: SparkSession, sf_dir: str, first: str | None = None, before: str | None = None) -> DataFrame:
    """Parts and suppliers of order lines, optionally shipped in a span of days; the dates reach the scan."""
    lines = table(spark, sf_dir, "lineitem")
    if first:
        lines = lines.filter((F.col("l_shipdate") >= F.lit(first).cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit(before).cast("timestamp_ntz")))
    return canonical_edges(lines.select("l_partkey", (F.col("l_suppkey") + SIDE).alias("s"), *_LINE_ORDER[:2], "l_suppkey"), "l_partkey", "s", _LINE_ORDER)


def nation_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _trades(spark, sf_dir)
    t = t.join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    t = t.join(table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return canonical_edges(t, "c_nationkey", "s_nationkey", _LINE_ORDER)


def supplier_coorder(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct()
    return canonical_edges(s.join(s.select("l_orderkey", F.col("l_suppkey").alias("other")), "l_orderkey").filter("l_suppkey < other"), "l_suppkey", "other", ["l_orderkey", "l_suppkey", "other"])


def customer_supplier_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _trades(spark, sf_dir, F.col("l_returnflag") == "R").withColumn("s", F.col("l_suppkey") + SIDE)
    return canonical_edges(t, "o_custkey", "s", _LINE_ORDER)


def customer_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical_edges(_trades(spark, sf_dir).withColumn("p", F.col("l_partkey") + SIDE), "o_custkey", "p", _LINE_ORDER)


def order_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical_edges(table(spark, sf_dir, "orders").withColumn("c", F.col("o_custkey") + SIDE), "o_orderkey", "c", ["o_orderkey"])


def similar_vectors(spark: SparkSession, sf_dir: str, threshold: float = 0.25, block: int = 512) -> DataFrame:
    """Pairs of vectors with cosine above a threshold, exactly, block against block of numpy products."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding").filter("embedding IS NOT NULL")
    placed = rows.withColumn("g", F.floor(F.row_number().over(Window.partitionBy(F.pmod(F.xxhash64("vec_id"), F.lit(64))).orderBy("vec_id")) / block) * 64 + F.pmod(F.xxhash64("vec_id"), F.lit(64)))
    groups = placed.select("g").distinct()
    meet = groups.select(F.col("g").alias("a")).join(groups.select(F.col("g").alias("b")), F.col("a") <= F.col("b"))
    left = placed.withColumnRenamed("g", "a").join(meet, "a").select(*(F.col(c).alias(c) for c in ("a", "b", "vec_id", "embedding")))
    right = placed.withColumnRenamed("g", "b").join(meet, "b").select(*(F.col(c).alias(c) for c in ("a", "b", "vec_id", "embedding")))

    def near(x: pa.Table, y: pa.Table) -> pa.Table:
        p, q = (np.array(t["embedding"].to_pylist(), dtype=np.float64).reshape(t.num_rows, -1) for t in (x, y))
        i, j = x["vec_id"].to_numpy(), y["vec_id"].to_numpy()
        s = (p / np.linalg.norm(p, axis=1, keepdims=True)) @ (q / np.linalg.norm(q, axis=1, keepdims=True)).T if p.size and q.size else np.zeros((len(p), len(q)))
        a, b = np.nonzero(s > threshold)
        u, v = np.minimum(i[a], j[b]), np.maximum(i[a], j[b])
        keep = u < v
        return pa.table({"u": pa.array(u[keep], pa.int64()), "v": pa.array(v[keep], pa.int64())})

    pairs = left.groupBy("a", "b").cogroup(right.groupBy("a", "b")).applyInArrow(near, "u long, v long")
    return canonical_edges(pairs, "u", "v", ["u", "v"])


def turn_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns of a conversation in a row; a vertex is conv_id * 1,000 + turn."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn").withColumn("x", F.col("conv_id") * 1000 + F.col("turn"))
    after = t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("x").alias("y"))
    return canonical_edges(t.join(after, ["conv_id", "turn"]), "x", "y", ["conv_id", "turn"])


def doc_line(spark: SparkSession, sf_dir: str, quality: int | None = None) -> DataFrame:
    """Documents and lines of over 20 characters that stand in two documents or more; optionally of one quality label only."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    if quality is not None:
        docs = docs.join(table(spark, sf_dir, "labels").filter(F.col("quality") == quality).select("doc_id"), "doc_id", "left_semi")
    lines = docs.select("doc_id", F.posexplode(F.split("text", "\n")).alias("at", "line")).filter(F.char_length("line") > 20).select("doc_id", "at", F.md5("line").alias("line"))
    shared = lines.groupBy("line").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).filter("lo < hi").select("line")
    named = lines.join(shared, "line", "left_semi").select(F.concat(F.lit("d:"), F.col("doc_id").cast("string")).alias("a"), F.concat(F.lit("l:"), "line").alias("b"), "doc_id", "at")
    return canonical_edges(encode_ids(named, ["a", "b"])[0], "a", "b", ["doc_id", "at"])


def doc_source_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents").select("doc_id", "source", "lang")
    rows = d.select("doc_id", F.concat(F.lit("s:"), "source").alias("b"), F.lit(1).alias("kind")).unionByName(d.select("doc_id", F.concat(F.lit("l:"), "lang").alias("b"), F.lit(2).alias("kind")))
    named = rows.select(F.concat(F.lit("d:"), F.col("doc_id").cast("string")).alias("a"), "b", "doc_id", "kind")
    return canonical_edges(encode_ids(named, ["a", "b"])[0], "a", "b", ["doc_id", "kind"])


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "call_all": call_graph,
    "call_error": lambda s, d: call_graph(s, d, "error"),
    "call_purchase": lambda s, d: call_graph(s, d, "purchase"),
    "call_window": call_window,
    "user_topic_all": user_topic,
    "user_topic_error": lambda s, d: user_topic(s, d, "error"),
    "page_link": page_link,
    "host_link": host_link,
    "geo_tree": geo_tree,
    "geo_orders": geo_orders,
    "part_supplier": part_supplier,
    "part_supplier_quarter": lambda s, d: part_supplier(s, d, "1997-01-01", "1997-04-01"),
    "part_supplier_year": lambda s, d: part_supplier(s, d, "1997-01-01", "1998-01-01"),
    "nation_trade": nation_trade,
    "supplier_coorder": supplier_coorder,
    "customer_supplier_returns": customer_supplier_returns,
    "customer_part": customer_part,
    "order_customer": order_customer,
    "similar_vectors": similar_vectors,
    "turn_path": turn_path,
    "doc_line": doc_line,
    "doc_line_good": lambda s, d: doc_line(s, d, quality=1),
    "doc_source_lang": doc_source_lang,
}


def known_graph(kind: str, *size: int) -> list[tuple[int, int]]:
    """Edges of a graph of known connectivity: path, cycle, star, wheel, complete, bipartite, grid, cube, harary, cliques."""
    a, b = (*size, 0)[:2]
    if kind == "path":
        return [(i, i + 1) for i in range(a - 1)]
    if kind == "cycle":
        return [(i, (i + 1) % a) for i in range(a)]
    if kind == "star":
        return [(0, i) for i in range(1, a + 1)]
    if kind == "wheel":
        return [(0, i) for i in range(1, a + 1)] + [(i, i % a + 1) for i in range(1, a + 1)]
    if kind == "complete":
        return [(i, j) for i in range(a) for j in range(i + 1, a)]
    if kind == "bipartite":
        return [(i, a + j) for i in range(a) for j in range(b)]
    if kind == "grid":
        return [(r * b + c, r * b + c + 1) for r in range(a) for c in range(b - 1)] + [(r * b + c, r * b + b + c) for r in range(a - 1) for c in range(b)]
    if kind == "cube":
        return [(i, i ^ (1 << d)) for i in range(1 << a) for d in range(a) if not i >> d & 1]
    if kind == "harary":  # a-connected on b vertices with the fewest edges
        rows = {(min(i, (i + d) % b), max(i, (i + d) % b)) for i in range(b) for d in range(1, a // 2 + 1)}
        if a % 2:
            rows |= {(min(i, (i + b // 2) % b), max(i, (i + b // 2) % b)) for i in range((b + 1) // 2 + (b % 2))}
        return sorted(rows)
    if kind == "cliques":  # two complete graphs on a vertices that share b
        return sorted({(i, j) for base in (0, a - b) for i in range(base, base + a) for j in range(i + 1, base + a)})
    raise ValueError(f"no such graph: {kind}")


#: Graphs of known connectivity, by name: kind, size, and how many vertices have to go before the graph falls apart.
KNOWN: dict[str, tuple[str, tuple[int, ...], int]] = {
    "path": ("path", (7,), 1),
    "star": ("star", (5,), 1),
    "cycle": ("cycle", (11,), 2),
    "grid": ("grid", (3, 5), 2),
    "wheel": ("wheel", (9,), 3),
    "prism": ("harary", (3, 12), 3),
    "cube": ("cube", (4,), 4),
    "cliques": ("cliques", (8, 5), 5),
    "harary": ("harary", (5, 12), 5),
    "bipartite": ("bipartite", (6, 7), 6),
    "complete": ("complete", (8,), 7),
}


def known_edges(spark: SparkSession, kind: str, *size: int) -> DataFrame:
    """Edges of `known_graph`, or of one of `KNOWN` by its name alone."""
    if not size:
        kind, size, _ = KNOWN[kind]
    rows = [(i, min(u, v), max(u, v)) for i, (u, v) in enumerate(known_graph(kind, *size), 1)]
    return spark.createDataFrame(rows, "seq long, u long, v long")
