"""Readers of text collections and readers and writers of codings."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.sources.corpus import TEXT_TABLES, as_collection, conversation_texts


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_texts(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given text tables as a collection."""
    df = read_table(spark, sf_dir, name)
    return conversation_texts(df) if name == "conversations" else as_collection(df, *TEXT_TABLES[name])


def read_files(spark: SparkSession, path: str, kind: str, id_col: str = "text_id", text_col: str = "text") -> DataFrame:
    """A collection from Parquet, ORC, JSON lines, CSV with a header, or whole text or binary files (the key is the path)."""
    if kind == "text":
        return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("text_id"), F.col("value").alias("text"))
    if kind == "binary":
        files = spark.read.format("binaryFile").load(path)
        return files.select(F.col("path").alias("text_id"), F.decode("content", "UTF-8").alias("text"))
    schema = f"{id_col} string, {text_col} string"
    if kind == "csv":
        df = spark.read.schema(schema).csv(path, header=True, multiLine=True, escape='"')
    elif kind == "json":
        df = spark.read.schema(schema).json(path)
    elif kind in ("parquet", "orc"):
        df = spark.read.format(kind).load(path)
    else:
        raise ValueError(f"unknown kind of file: {kind}")
    return as_collection(df, id_col, text_col)


def write_coding(factors: DataFrame, path: str, kind: str = "parquet", partition_by: str | None = None) -> None:
    """Factors range-partitioned by (text_id, dst) and sorted, so that a range of a text reads few row groups."""
    out = factors.repartitionByRange("text_id", "dst").sortWithinPartitions("text_id", "dst").write.mode("overwrite").format(kind)
    (out.partitionBy(partition_by) if partition_by else out).save(path)


def read_coding(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    return spark.read.format(kind).load(path)
