"""Reliable intermediate tables: written as Parquet below the cluster's shared checkpoint folder and reread."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; a temporary one only in plain local mode."""
    found = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if found:
        return found
    if spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master:
        spark.conf.set("spark.checkpoint.dir", tempfile.mkdtemp(prefix="textfactor-"))
        return spark.conf.get("spark.checkpoint.dir")
    raise ValueError("set spark.checkpoint.dir to a folder that all executors share")


class Scratch:
    """Tables of one operator call.

    ``save`` cuts the lineage: what is read afterwards are files in the shared folder, so a lost executor costs no
    recomputation of earlier steps. ``drop`` removes a table that no later step reads; the rest goes when the
    driver's Python ends.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_root(spark)}/textfactor/{name}-{uuid.uuid4().hex}"
        self.n = 0
        atexit.register(self._remove, self.root)

    def save(self, df: DataFrame, name: str, partition_by: str | None = None) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n:03d}-{name}"
        writer = df.write.mode("overwrite")
        (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame) -> None:
        self._remove(df._scratch_path)

    def clear(self) -> None:
        """Removes all tables of the call."""
        self._remove(self.root)

    def _remove(self, path: str) -> None:
        try:
            jvm = self.spark._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the JVM may be gone at exit; the folder is then left to the cluster's clean-up
            return
