"""Intermediate tables in the folder that all executors share.

Iterative operators cut their lineage by writing a Parquet table and reading it again. The folder is
`spark.checkpoint.dir` of the session; only where that is unset (tests, a laptop) a default is used.
A lost executor then costs the tasks it ran, not the rounds before them.
"""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

DEFAULT_SHARED_DIR = "file:///tmp/checkpoints"
#: While a stage table is written: shuffle files of the finished query go at once, instead of at some garbage collection,
#: and Python workers get rows in batches that stay small when texts, or sets made of them, are long.
WRITING = {
    "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true",
    "spark.sql.execution.arrow.maxRecordsPerBatch": "1000",
    "spark.sql.execution.arrow.maxBytesPerBatch": str(4 << 20),
}


def shared_dir(spark: SparkSession) -> str:
    """Folder for intermediate tables, from the session's own setting where there is one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    return (found or DEFAULT_SHARED_DIR).rstrip("/")


#: Rows of a batch where these are a few numbers each; `WRITING` bounds the bytes.
NUMBERS = 1 << 16


@contextmanager
def writing_settings(spark: SparkSession, rows: int | None = None):
    """Within this block the settings of `WRITING` hold, with other `rows` of a batch if given; afterwards those that were there before."""
    settings = WRITING if rows is None else WRITING | {"spark.sql.execution.arrow.maxRecordsPerBatch": str(rows)}
    before = {k: spark.conf.get(k, None) for k in WRITING}
    for k, v in settings.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


class Stages:
    """Tables written by one call of an operator; `drop` removes those that later steps no longer read."""

    def __init__(self, spark: SparkSession, owner: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/certgraph/{owner}-{uuid.uuid4().hex[:12]}"
        self._n = 0

    def path(self, label: str) -> str:
        self._n += 1
        return f"{self.root}/{self._n:03d}-{label}"

    def keep(self, df: DataFrame, label: str, compression: str = "zstd", by: str | None = None, rows: int | None = None) -> DataFrame:
        """Write `df`, release the shuffle files behind it, and return the written table; `by` files its rows by a column's values, `rows` go to Python at a time."""
        at = self.path(label)
        with writing_settings(self.spark, rows):
            writer = df.write.option("compression", compression)
            (writer if by is None else writer.partitionBy(by)).parquet(at)
        out = self.spark.read.schema(df.schema).parquet(at)
        out._certgraph_path = at
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for t in tables:
            at = getattr(t, "_certgraph_path", None)
            if at:
                p = jvm.org.apache.hadoop.fs.Path(at)
                p.getFileSystem(conf).delete(p, True)
