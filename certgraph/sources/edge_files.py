"""Edge lists from files and to files, and a Spark data source of generated graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from certgraph.operators.edges import canonical_edges


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", order_by: list[str] | None = None, sep: str | None = None) -> DataFrame:
    """edges(seq, u, v) of a csv, json, parquet, orc or whitespace-separated text file; in text order where none is named."""
    if fmt == "text":
        rows = spark.read.text(path).filter(~F.col("value").startswith("#")).select(F.split(F.trim("value"), sep or r"[\s,;]+").alias("p"))
        rows = rows.select(F.col("p")[0].cast("long").alias(src), F.col("p")[1].cast("long").alias(dst)).withColumn("_at", F.monotonically_increasing_id())
    elif fmt == "csv":
        rows = spark.read.option("header", True).option("sep", sep or ",").csv(path).withColumn("_at", F.monotonically_increasing_id())
    else:
        rows = spark.read.format(fmt).load(path).withColumn("_at", F.monotonically_increasing_id())
    return canonical_edges(rows, src, dst, order_by or ["_at"])


def write_certificate(cert: DataFrame, path: str, fmt: str = "parquet") -> None:
    """One folder for each layer where there are layers."""
    out = cert.write.mode("overwrite").format(fmt)
    (out.partitionBy("layer") if "layer" in cert.columns else out).save(path)


def write_separators(found: DataFrame, path: str) -> None:
    found.write.mode("overwrite").partitionBy("l").parquet(path)


class KnownGraphSource(DataSource):
    """spark.read.format("graphgen").option("kind", "wheel").option("size", "6").load(): edges(seq, u, v)."""

    @classmethod
    def name(cls) -> str:
        return "graphgen"

    def schema(self) -> str:
        return "seq long, u long, v long"

    def reader(self, schema) -> DataSourceReader:
        return _KnownGraphReader(self.options)


class _KnownGraphReader(DataSourceReader):
    def __init__(self, options):
        self.kind = options["kind"]
        self.size = [int(x) for x in options["size"].split(",")]

    def partitions(self):
        return [InputPartition(0)]

    def read(self, partition):
        from certgraph.sources.workloads import known_graph

        for i, (u, v) in enumerate(known_graph(self.kind, *self.size), 1):
            yield i, min(u, v), max(u, v)
