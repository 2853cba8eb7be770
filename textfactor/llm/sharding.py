"""Sharding into parts of nearly equal bytes by sampled splitters.

1. A narrow table (id, size, key) is written once; the key is (hash of the text, id), so equal texts are neighbours.
2. A deterministic, size-weighted sample of keys gives quantile boundaries; its expected size is a parameter, not a
   function of the input.
3. Records are put into ranges by binary search among the boundaries. The exact bytes of all ranges are counted; ranges
   over twice the mean are subdivided by a hash of the id, as often as their excess asks for.
4. Inside a range a running sum gives every record its exact place in the global order; the shard is the place of the
   record's middle byte in the total. So shards differ by about one record, whatever the sample was.

Defined cases: a null text has size ``overhead``; a null id is hashed as an empty string; rows that repeat are placed one
after another; a table without rows gives none; other columns of the input are left out, so names cannot clash.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from textfactor.llm.scratch import Scratch

OVERHEAD = 16


def _sampled(narrow: DataFrame, total: int, target: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """About ``target`` keys and their weights: a row of size s is drawn with probability min(1, s * target / total)."""
    rate = target / total
    draw = (F.shiftrightunsigned(F.xxhash64("id", F.lit("draw")), 11) / F.lit(2.0**53)) < F.col("size") * F.lit(rate)
    rows = narrow.where(draw).select("k", "j", F.greatest(F.lit(1.0), F.col("size") * F.lit(rate)).alias("w")).collect()
    k, j, w = (np.array([r[c] for r in rows], t) for c, t in (("k", np.int64), ("j", np.int64), ("w", float)))
    order = np.lexsort((j, k))
    return k[order], j[order], w[order]


def _range_of(k: np.ndarray, j: np.ndarray, cut_k: np.ndarray, cut_j: np.ndarray) -> np.ndarray:
    """How many cuts (pairs in order) are at or below each pair."""
    low, high = np.searchsorted(cut_k, k, "left"), np.searchsorted(cut_k, k, "right")
    out = low.astype(np.int64)
    tied = np.flatnonzero(low < high)
    for a in np.unique(low[tied]):
        at = tied[low[tied] == a]
        b = high[at[0]]
        out[at] = a + np.searchsorted(cut_j[a:b], j[at], "right")
    return out


def shard_by_bytes(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text", ranges: int = 512, sample: int = 16_384) -> DataFrame:
    """``id, size, text_crc32, shard, slot``: shards of nearly equal bytes, slots gapless from 0 in each."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "sharding")
    text = F.coalesce(F.col(text_col), F.lit(""))
    narrow = scratch.save(
        docs.select(
            F.col(id_col).alias("id"),
            (F.octet_length(text) + OVERHEAD).cast("long").alias("size"),
            F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
            F.xxhash64(text).alias("k"),
            F.xxhash64(F.coalesce(F.col(id_col).cast("string"), F.lit(""))).alias("j"),
        ),
        "narrow",
    )
    total = narrow.agg(F.sum("size")).first()[0] or 0
    out_cols = ["id", "size", "text_crc32", "shard", "slot"]
    if not total:
        return narrow.select("id", "size", "text_crc32", F.lit(0).alias("shard"), F.lit(0).cast("long").alias("slot")).withColumnRenamed("id", id_col)
    k, j, w = _sampled(narrow, total, sample)
    step = np.floor(np.cumsum(w) / max(w.sum(), 1e-9) * ranges).astype(np.int64)
    at = np.flatnonzero(np.diff(step)) + 1
    cut_k, cut_j = k[at], j[at]

    def ranged(batches):
        for b in batches:
            r = _range_of(b.column("k").to_numpy(), b.column("j").to_numpy(), cut_k, cut_j)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(r)], [*b.schema.names, "r"])

    kind = narrow.schema["id"].dataType.simpleString()
    placed = narrow.mapInArrow(ranged, f"id {kind}, size long, text_crc32 long, k long, j long, r long")
    placed = scratch.save(placed, "ranged")
    mean = total / (len(at) + 1)
    # at most `ranges` + 1 rows
    bytes_of = {r["r"]: r["b"] for r in placed.groupBy("r").agg(F.sum("size").alias("b")).collect()}
    parts = {r: int(b // mean) for r, b in bytes_of.items() if b > 2 * mean}
    if parts:
        cases = spark.createDataFrame(sorted(parts.items()), "r long, parts int")
        placed = placed.join(F.broadcast(cases), "r", "left")
        placed = placed.withColumn("sub", F.pmod(F.xxhash64("j", F.lit("sub")), F.coalesce("parts", F.lit(1))).cast("int"))
    else:
        placed = placed.withColumn("sub", F.lit(0))
    before, rows_before, base = 0, 0, []
    for r in sorted(placed.groupBy("r", "sub").agg(F.sum("size").alias("b"), F.count("*").alias("n")).collect()):
        base.append((r["r"], r["sub"], before, rows_before))
        before, rows_before = before + r["b"], rows_before + r["n"]
    offsets = spark.createDataFrame(base, "r long, sub int, b0 long, n0 long")
    w = Window.partitionBy("r", "sub").orderBy("k", "j", "id", "size")
    whole = (
        placed.withColumn("run", F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, 0)))
        .withColumn("n", F.row_number().over(w))
        .join(F.broadcast(offsets), ["r", "sub"])
        .withColumn("place", F.col("n0") + F.col("n") - 1)
        .withColumn("middle", 2 * (F.col("b0") + F.col("run")) - F.col("size"))
        .withColumn("shard", F.least(F.lit(shards - 1), F.expr(f"middle * {shards} div {2 * total}")).cast("int"))
    )
    whole = scratch.save(whole.select("id", "size", "text_crc32", "shard", "place"), "whole")
    first = whole.groupBy("shard").agg(F.min("place").alias("p0"))
    return whole.join(F.broadcast(first), "shard").withColumn("slot", F.col("place") - F.col("p0")).select(*out_cols).withColumnRenamed("id", id_col)


def write_shards(docs: DataFrame, placed: DataFrame, path: str, id_col: str = "doc_id") -> None:
    """Write the documents as Parquet, a folder for each shard, in slot order."""
    key = ["shard", F.floor(F.col("slot") / 200_000)]
    docs.join(placed.select(id_col, "shard", "slot"), id_col).repartition(*key).sortWithinPartitions("shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(path)


def op3_sharding(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return shard_by_bytes(docs).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
