"""Collections of texts as DataFrames ``(text_id, text)``, and one long text made of them.

A collection needs no order and no shuffle. A single text has global positions: documents are put in key order by range
partitioning, every partition's length is summed, and the offsets of the partitions (one row each) are handed back.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: table -> (key, text) of the given tables
TEXT_TABLES = {"documents": ("doc_id", "text"), "pages": ("page_id", "html"), "benchmark": ("item_id", "text")}
LETTERS = "ACGT"


def as_collection(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Every row is its own text; a null text is empty. Other columns are pruned down to the scan."""
    return df.select(F.col(id_col).alias("text_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def conversation_texts(df: DataFrame) -> DataFrame:
    """Turns as texts; the key of a turn is conv_id * 1000 + turn."""
    return df.select((F.col("conv_id") * 1000 + F.col("turn")).alias("text_id"), F.coalesce("text", F.lit("")).alias("text"))


def shard_texts(texts: DataFrame, rows: int, sep: str = "\n") -> DataFrame:
    """Groups of ``rows`` neighbouring texts (by integer key) joined to one text each: between a collection and a single text."""
    return (
        texts.groupBy(F.expr(f"text_id div {rows}").alias("text_id"))
        .agg(F.array_sort(F.collect_list(F.struct(F.col("text_id").alias("k"), "text"))).alias("parts"))
        .select("text_id", F.array_join(F.transform("parts", lambda p: p["text"]), sep).alias("text"))
    )


def assign_offsets(df: DataFrame, order: list[str], length: Column, start: int = 1) -> DataFrame:
    """Adds ``start``: the first position of every row when rows follow one another in the given order.

    Running sums are taken inside range partitions; what crosses to the driver is one row for each partition.
    """
    ranged = df.withColumn("__len", length.cast("long")).repartitionByRange(*order).withColumn("__part", F.spark_partition_id())
    ranged = ranged.sortWithinPartitions(*order)
    from textfactor.plans.scratch import Scratch

    ranged = Scratch(df.sparkSession, "offsets").save(ranged, "ranged")
    sums = sorted((r["__part"], r["n"]) for r in ranged.groupBy("__part").agg(F.sum("__len").alias("n")).collect())
    base, at = [], start
    for p, n in sums:
        base.append((p, at))
        at += n
    offsets = df.sparkSession.createDataFrame(base, "__part int, __base long")
    w = Window.partitionBy("__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return (
        ranged.withColumn("__run", F.sum("__len").over(w))
        .join(F.broadcast(offsets), "__part")
        .withColumn("start", F.col("__base") + F.col("__run") - F.col("__len"))
        .drop("__part", "__base", "__run", "__len")
    )


def single_text(texts: DataFrame, sep: str = "\n") -> DataFrame:
    """``start, body``: the blocks of the text that all texts form in key order, each followed by ``sep``."""
    return assign_offsets(texts.select("text_id", F.concat("text", F.lit(sep)).alias("body")), ["text_id"], F.length("body")).select("start", "body")


def placed_texts(texts: DataFrame, sep: str = "\n", back: int = 0) -> tuple[DataFrame, dict[int, tuple[int, str]], int]:
    """The single text in pieces that know where they stand: ``part, off, before, body``, what each part begins with, and the length.

    ``off`` counts from 0 in its part (a range partition), ``before`` has up to ``back`` symbols that stand before the body in the part.
    A part has its first position and the up to ``back`` symbols before it. One row for each part comes to the driver.
    """

    def run(it):
        part, off, tail = TaskContext.get().partitionId(), 0, ""
        for b in it:
            offs, before = [], []
            for x in b.column(1).to_pylist():
                offs.append(off)
                before.append(tail)
                off += len(x)
                tail = (tail + x[-back:])[-back:] if back else ""
            parts = pa.array(np.full(b.num_rows, part, np.int32))
            yield pa.RecordBatch.from_arrays([parts, pa.array(offs, pa.int64()), pa.array(before, pa.string()), b.column(1)], ["part", "off", "before", "body"])

    from textfactor.plans.scratch import Scratch

    rows = texts.select("text_id", F.concat("text", F.lit(sep)).alias("body")).repartitionByRange("text_id").sortWithinPartitions("text_id")
    placed = Scratch(texts.sparkSession, "placed").save(rows.mapInArrow(run, "part int, off long, before string, body string"), "placed")
    tail = F.expr(f"right(concat(before, right(body, {back})), {back})") if back else F.lit("")
    ends = placed.groupBy("part").agg(F.sum(F.length("body")).alias("n"), F.max_by(tail, F.struct("off", F.length("body"))).alias("tail"))
    begins, n, last = {}, 0, ""
    for r in ends.orderBy("part").collect():
        begins[r["part"]] = (n, last)
        n, last = n + r["n"], (last + r["tail"])[-back:] if back else ""
    return placed, begins, n


def corpus_prefix(texts: DataFrame, chars: int) -> DataFrame:
    """The first ``chars`` symbols in key order; the last text is cut."""
    t = assign_offsets(texts, ["text_id"], F.length("text"), 0).where(F.col("start") < chars)
    return t.select("text_id", F.expr(f"substring(text, 1, cast({chars} - start AS int))").alias("text"))


def symbol_text(df: DataFrame, order: list[str], letter: Column, block: int = 1 << 16) -> DataFrame:
    """An ordered column of letters as texts of ``block`` symbols: (text_id, text), text_id counts the blocks."""
    rows = assign_offsets(df.select(*order, letter.alias("letter")), order, F.lit(1), 0)
    parts = rows.groupBy(F.expr(f"start div {block}").alias("text_id")).agg(F.array_sort(F.collect_list(F.struct("start", "letter"))).alias("x"))
    return parts.select("text_id", F.array_join(F.transform("x", lambda s: s["letter"]), "").alias("text"))


LINEITEM_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]


def lineitem_letters(lineitem: DataFrame, block: int = 1 << 16) -> DataFrame:
    """The four-letter sequence: the quarter of each line's ship date."""
    return symbol_text(lineitem, LINEITEM_ORDER, F.expr(f"substring('{LETTERS}', quarter(l_shipdate), 1)"), block)


def lineitem_letters_whole(lineitem: DataFrame) -> DataFrame:
    """The four-letter sequence as one text, the blocks in their order: one row, which one task factorizes."""
    return shard_texts(lineitem_letters(lineitem), 1 << 40, "")


def cut_text(texts: DataFrame, block: int = 1 << 16) -> DataFrame:
    """One text cut into blocks again, text_id counts them: the inverse of joining the blocks of ``symbol_text``."""
    cuts = F.expr(f"sequence(0L, (length(text) - 1) div {block})")
    return texts.where("length(text) > 0").select(F.explode(cuts).alias("text_id"), "text").select(
        "text_id", F.expr(f"substring(text, cast(text_id * {block} + 1 AS int), {block})").alias("text")
    )
