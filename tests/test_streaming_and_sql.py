"""Streams against batch, SQL functions, sources and sinks."""

from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import OnlineCertificate, graph_of, is_k_connected
from certgraph.functions.sql_functions import grouped_certificates, grouped_verdicts, register_all
from certgraph.operators import layered, separators
from certgraph.operators.edges import vertex_set
from certgraph.sources.edge_files import read_edge_list, write_certificate, write_separators
from certgraph.sources.workloads import WORKLOADS, known_edges
from certgraph.streaming.online_stream import distinct_within, online_certificate_stream, session_graphs, windowed_certificate


def run_stream(spark, make, folder, tmp_path, name):
    src = spark.readStream.schema(spark.read.parquet(folder).schema).option("maxFilesPerTrigger", 1).parquet(folder)
    q = make(src).writeStream.format("memory").queryName(name).option("checkpointLocation", f"file://{tmp_path}/cp-{name}").trigger(availableNow=True).start()
    q.awaitTermination(240)
    return spark.table(name).collect()


def test_stream_equals_batch(spark, sf, tmp_path):
    rows = sorted((r.seq, r.u, r.v) for r in WORKLOADS["user_topic_error"](spark, sf).collect())
    rows += [(1000, rows[0][2], rows[0][1]), (1001, 5, 5)]  # a repeated edge the other way round, and a loop
    for i, part in enumerate((rows[:70], rows[70:])):
        spark.createDataFrame(part, "seq long, u long, v long").coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/edges")
    got = run_stream(spark, lambda s: online_certificate_stream(s, 2), f"file://{tmp_path}/edges", tmp_path, "admitted")
    edges = sorted((r.seq, r.u, r.v) for r in got)
    g, c = graph_of((u, v) for _, u, v in rows if u != v), graph_of((u, v) for _, u, v in edges)
    assert len({(u, v) for _, u, v in edges}) == len(edges) <= 2 * 2 * len(g)
    assert is_k_connected(g, 1) == is_k_connected(c, 1) and set(c) == set(g)
    assert max(r.kept_so_far for r in got) == len(edges)


def test_windowed_graphs(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_id").alias("seq"), F.col("user_id").alias("u"), (F.get_json_object("props", "$.k").cast("long") + 1000).alias("v"), "ts").orderBy("ts").limit(200)
    e.coalesce(1).write.parquet(f"file://{tmp_path}/timed")
    got = run_stream(spark, lambda s: windowed_certificate(s, 2, "ts", "1 day"), f"file://{tmp_path}/timed", tmp_path, "windows")
    by = {}
    for r in sorted((r.seq, r.u, r.v, str(r.ts)[:10]) for r in e.collect()):
        by.setdefault(r[3], OnlineCertificate(2)).offer((r[0], min(r[1], r[2]), max(r[1], r[2])))
    assert len(got) == sum(len(c.kept) for c in by.values()) and len({r.graph for r in got}) == len(by)


def test_repeats_within_the_watermark_and_sessions(spark, sf, tmp_path):
    rows = spark.createDataFrame([(1, 1, 2, "2024-01-01 00:00:00"), (2, 2, 1, "2024-01-01 00:01:00"), (3, 2, 3, "2024-01-01 02:00:00")], "seq long, u long, v long, t string").withColumn("ts", F.to_timestamp("t")).drop("t")
    rows.coalesce(1).write.parquet(f"file://{tmp_path}/twice")
    assert len(run_stream(spark, lambda s: distinct_within(s, "ts"), f"file://{tmp_path}/twice", tmp_path, "once")) == 2
    assert session_graphs(rows, "ts").select("session").distinct().count() == 2


def test_sql_functions(spark):
    register_all(spark)
    known_edges(spark, "wheel", 6).createOrReplaceTempView("wheel6")
    kept = spark.sql("SELECT * FROM certificate_edges(TABLE(SELECT seq, u, v FROM wheel6) WITH SINGLE PARTITION ORDER BY (seq), 3, 'layered')").count()
    assert kept <= 3 * 6
    assert spark.sql("SELECT * FROM certificate_edges(TABLE(SELECT seq, u, v FROM wheel6) WITH SINGLE PARTITION ORDER BY (seq), 1, 'online')").count() == 6
    assert spark.sql("SELECT * FROM k_separators(TABLE(SELECT u, v FROM wheel6) WITH SINGLE PARTITION, 3)").count() == 9  # the hub and two rim vertices apart
    assert spark.sql("SELECT kappa_capped(collect_list(named_struct('u', u, 'v', v)), 1L, 3L, 5) AS n FROM wheel6").first().n == 3
    loaded = spark.read.format("graphgen").option("kind", "cube").option("size", "3").load()
    assert loaded.count() == 12


def test_many_graphs_at_once(spark):
    two = known_edges(spark, "cycle", 4).withColumn("g", F.lit("a")).unionByName(known_edges(spark, "path", 4).withColumn("g", F.lit("b")))
    assert {(r.g, r.verdict) for r in grouped_verdicts(two, "g", 2).collect()} == {("a", True), ("b", False)}
    assert grouped_certificates(two, "g", 1).groupBy("g").count().agg(F.max("count")).first()[0] == 3


def test_files(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# a comment\n1 2\n2,3\n3\t1\n1 1\n")
    e = read_edge_list(spark, f"file://{tmp_path}/e.txt", "text")
    assert e.count() == 3
    (tmp_path / "e.csv").write_text("src,dst,t\n5,4,2\n4,6,1\n")
    assert [(r.u, r.v) for r in read_edge_list(spark, f"file://{tmp_path}/e.csv", order_by=["t"]).orderBy("seq").collect()] == [(4, 6), (4, 5)]
    cert = layered.layered_certificate(e, 2)
    write_certificate(cert, f"file://{tmp_path}/cert")
    assert spark.read.parquet(f"file://{tmp_path}/cert").filter("layer = 1").count() == 2
    star = known_edges(spark, "star", 4)
    write_separators(separators.all_separators(star, vertex_set(star), 3), f"file://{tmp_path}/seps")
    assert spark.read.parquet(f"file://{tmp_path}/seps").filter("l = 1").count() == 1


def test_entry_and_registered_queries(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 13 + 1297
    names = set(entry.queries())
    assert set(entry.oracle_sql()) <= names and {"cut_vertices_host_link", "separators4_online_known_cube"} <= names
