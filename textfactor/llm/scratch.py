"""Reliable intermediate tables: written as Parquet below the cluster's shared checkpoint folder and reread."""

from __future__ import annotations

import atexit
import contextlib
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; a temporary one only in plain local mode."""
    found = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if found:
        return found
    if spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master:
        spark.conf.set("spark.checkpoint.dir", tempfile.mkdtemp(prefix="textfactor-"))
        return spark.conf.get("spark.checkpoint.dir")
    raise ValueError("set spark.checkpoint.dir to a folder that all executors share")


def bounded_batches(spark: SparkSession, limit: int = 8 << 20) -> None:
    """Let Arrow batches hold at most ``limit`` bytes or one row: with several Python workers on an executor, larger ones fill
    its memory. A smaller setting of the session stays."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(key, "256m")
    digits = "".join(c for c in now if c.isdigit())
    scale = {"k": 10, "m": 20, "g": 30}.get(now.lstrip("-0123456789")[:1].lower(), 0)
    if not digits or now.startswith("-") or int(digits) << scale > limit:
        spark.conf.set(key, f"{limit}b")


def small_side(df: DataFrame, most: int = 4_000_000) -> DataFrame:
    """``df``, a saved table of a few long columns, marked for broadcast if it has at most ``most`` rows; else a join shuffles it."""
    return F.broadcast(df) if df.count() <= most else df


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or with underscores behind until no column of ``df`` has it (Spark's names ignore case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


@contextlib.contextmanager
def ordered_scans(spark: SparkSession):
    """In here plans take the order of sorted tables as it is in their files, so merge joins do not sort them again."""
    key = "spark.sql.legacy.bucketedTableScan.outputOrdering"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


class Scratch:
    """Tables of one operator call.

    ``save`` cuts the lineage: what is read afterwards are files in the shared folder, so a lost executor costs no
    recomputation of earlier steps. ``drop`` removes a table that no later step reads; the rest goes when the
    driver's Python ends.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_root(spark)}/textfactor-llm/{name}-{uuid.uuid4().hex}"
        self.n = 0
        self.tables: set[str] = set()
        bounded_batches(spark)
        atexit.register(self._remove, self.root)

    def save(self, df: DataFrame, name: str, partition_by: str | None = None) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n:03d}-{name}"
        writer = df.write.mode("overwrite")
        (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def save_sorted(self, df: DataFrame, name: str, keys: list[str], buckets: int) -> DataFrame:
        """``df`` as a table in ``buckets`` by the hash of ``keys``, each sorted by them: joins of such tables on the keys need no
        exchange. If ``df`` is partitioned by the keys in as many partitions, writing needs none either."""
        self.n += 1
        path, table = f"{self.root}/{self.n:03d}-{name}", f"textfactor_{uuid.uuid4().hex}"
        df.write.bucketBy(buckets, *keys).sortBy(*keys).option("path", path).format("parquet").saveAsTable(table)
        out = self.spark.table(table)
        out._scratch_path, out._scratch_table = path, table
        self.tables.add(table)
        return out

    def drop(self, df: DataFrame) -> None:
        if hasattr(df, "_scratch_table"):
            self._forget(df._scratch_table)
        self._remove(df._scratch_path)

    def close(self) -> None:
        """Take the sorted tables out of the catalog; queries on them that were not run yet would fail."""
        for t in list(self.tables):
            self._forget(t)

    def _forget(self, table: str) -> None:
        self.tables.discard(table)
        self.spark.sql(f"DROP TABLE IF EXISTS {table}")

    def sweep(self) -> None:
        """Let Spark's cleaner find the shuffles of finished steps now: it deletes their files once the driver's objects for
        them are collected, which by itself may take spark.cleaner.periodicGC.interval."""
        gc.collect()
        self.spark._jvm.System.gc()

    def _remove(self, path: str) -> None:
        try:
            jvm = self.spark._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the JVM may be gone at exit; the folder is then left to the cluster's clean-up
            return
