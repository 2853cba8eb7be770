"""Codings: references and the literal runs between them, in text order; checks, sizes and nested views."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.schemas import FACTORS


def encode(refs: DataFrame, texts: DataFrame, literals: str = "run") -> DataFrame:
    """``text_id, factor_no, dst, len, src, literal`` from references and their texts; literals by run or by character.

    The references of a text meet it once, as one array, and its gaps are cut out of it in one pass; texts without references
    are one literal. For a text over many tasks see ``encode_blocks``.
    """
    kind = refs.schema["text_id"].dataType.simpleString()
    per = refs.groupBy("text_id").agg(F.array_sort(F.collect_list(F.struct("dst", "len", "src"))).alias("refs"))
    both = texts.select("text_id", F.coalesce("text", F.lit("")).alias("text")).join(per, "text_id", "left")

    def run(it):
        for b in (part for whole in it for part in (whole.slice(a, 256) for a in range(0, whole.num_rows, 256))):
            ids, numbers, dsts, sizes, srcs, strings = [], [], [], [], [], []
            found = b.column(2)
            flat, off = found.flatten(), found.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).cumsum()
            cols = [flat.field(c).to_numpy(zero_copy_only=False) for c in range(3)]
            for k, text in enumerate(b.column(1).to_pylist()):
                u, v = int(off[k - 1]) if k else 0, int(off[k])
                dst, size, src = (c[u:v] for c in cols)
                ends = np.append(dst, len(text) + 1)
                starts = np.concatenate([[1], dst + size])
                gap = ends - starts
                at, n = starts[gap > 0], gap[gap > 0]
                if literals == "char":
                    at, n = np.repeat(at, n) + K.ramp(n), np.ones(int(n.sum()), np.int64)
                dst, size = np.concatenate([dst, at]), np.concatenate([size, n])
                src = np.concatenate([src, np.zeros(len(at), np.int64)])
                lit = [None] * (v - u) + [text[a - 1 : a - 1 + m] for a, m in zip(at.tolist(), n.tolist())]
                order = np.argsort(dst, kind="stable")
                ids.append(np.full(len(order), k)), numbers.append(np.arange(1, len(order) + 1))
                dsts.append(dst[order]), sizes.append(size[order]), srcs.append(src[order])
                strings += [lit[i] for i in order.tolist()]
            src = np.concatenate(srcs).astype(np.int64)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0).take(pa.array(np.concatenate(ids), pa.int64())),
                    *(pa.array(np.concatenate(x).astype(np.int64)) for x in (numbers, dsts, sizes)),
                    pa.array(src, mask=src == 0),
                    pa.array(strings, pa.string()),
                ],
                ["text_id", "factor_no", "dst", "len", "src", "literal"],
            )

    return both.select("text_id", "text", "refs").mapInArrow(run, FACTORS.format(id=kind))


def encode_blocks(refs: DataFrame, blocks: DataFrame, cell: int = 1 << 14) -> DataFrame:
    """The coding of one text ``(start, body)`` that lies in blocks: references and literals meet by cells of the text, so no
    task sees more than a cell; literal runs end at cells' borders."""
    cut = F.explode(F.expr(f"sequence((start - 1) div {cell}, (start + length(body) - 2) div {cell})")).alias("cell")
    a = F.greatest("start", F.col("cell") * cell + 1)
    b = F.least(F.col("start") + F.length("body"), (F.col("cell") + 1) * cell + 1)
    text = blocks.where("length(body) > 0").select("start", "body", cut)
    text = text.select("cell", a.alias("at"), F.expr("substring(body, cast(greatest(start, cell * %d + 1) - start + 1 AS int), %d)" % (cell, cell)).alias("piece"), (b - a).alias("n"))
    text = text.withColumn("piece", F.expr("substring(piece, 1, cast(n AS int))"))
    text = text.groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("at", "piece"))).alias("x"))
    text = text.select("cell", F.col("x")[0]["at"].alias("at"), F.array_join(F.transform("x", lambda p: p["piece"]), "").alias("body"))
    over = F.explode(F.expr(f"sequence((dst - 1) div {cell}, (dst + len - 2) div {cell})")).alias("cell")
    spans = refs.select(over, "dst", "len").groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("dst", "len"))).alias("refs"))

    def run(it):
        for batch in it:
            at, strings = [], []
            for first, body, found in zip(*(batch.column(c).to_pylist() for c in (1, 2, 3))):
                low = first
                for r in [*(found or ()), {"dst": first + len(body), "len": 0}]:
                    if r["dst"] > low:
                        at.append(low), strings.append(body[low - first : r["dst"] - first])
                    low = max(low, r["dst"] + r["len"])
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(strings, pa.string())], ["dst", "literal"])

    lit = text.join(spans, "cell", "left").select("cell", "at", "body", "refs").mapInArrow(run, "dst long, literal string")
    none = F.lit(None)
    lit = lit.select("dst", F.length("literal").cast("long").alias("len"), none.cast("long").alias("src"), "literal")
    return refs.select("dst", "len", "src", none.cast("string").alias("literal")).unionByName(lit)


def factor_counts(factors: DataFrame) -> DataFrame:
    """Per text: references, literal characters (each counts as a factor) and literal runs."""
    ref = F.col("src").isNotNull()
    return factors.groupBy("text_id").agg(
        F.count_if(ref).alias("n_refs"),
        F.coalesce(F.sum(F.when(~ref, F.col("len"))), F.lit(0)).alias("n_literal_chars"),
        F.count_if(~ref).alias("n_literal_runs"),
    ).withColumn("n_factors", F.col("n_refs") + F.col("n_literal_chars"))


def reference_counts(refs: DataFrame, texts: DataFrame) -> DataFrame:
    """The same counts from references alone, without making the literals."""
    r = refs.groupBy("text_id").agg(F.count("*").alias("n_refs"), F.sum("len").alias("covered"))
    return texts.select("text_id", F.length("text").cast("long").alias("n")).join(r, "text_id", "left").select(
        "text_id", "n", F.coalesce("n_refs", F.lit(0)).alias("n_refs"), (F.col("n") - F.coalesce("covered", F.lit(0))).alias("n_literal_chars")
    ).withColumn("n_factors", F.col("n_refs") + F.col("n_literal_chars"))


def validate(factors: DataFrame, texts: DataFrame, min_len: int = 2) -> DataFrame:
    """``text_id, tiled, long_enough, in_range, no_self, resolves``: is the coding well formed, and leads every symbol to a literal?"""
    w = Window.partitionBy("text_id").orderBy("dst")
    f = factors.withColumn("gap", F.col("dst") - F.coalesce(F.lag(F.col("dst") + F.col("len")).over(w), F.lit(1)))
    ref = F.col("src").isNotNull()
    per = f.groupBy("text_id").agg(
        F.bool_and(F.col("gap") == 0).alias("joined"),
        F.sum("len").alias("covered"),
        F.bool_and(~ref | (F.col("len") >= min_len)).alias("long_enough"),
        F.bool_and(~ref | (F.col("src") >= 1)).alias("low_ok"),
        F.max(F.when(ref, F.col("src") + F.col("len") - 1)).alias("top"),
        F.bool_and(~ref | (F.col("src") != F.col("dst"))).alias("no_self"),
    )
    from textfactor.operators.graph import resolves

    n = texts.select("text_id", F.length("text").cast("long").alias("n"))
    return n.join(per, "text_id", "left").join(resolves(factors), "text_id", "left").select(
        "text_id",
        (F.coalesce("joined", F.lit(True)) & (F.coalesce("covered", F.lit(0)) == F.col("n"))).alias("tiled"),
        F.coalesce("long_enough", F.lit(True)).alias("long_enough"),
        (F.coalesce("low_ok", F.lit(True)) & (F.coalesce("top", F.lit(0)) <= F.col("n"))).alias("in_range"),
        F.coalesce("no_self", F.lit(True)).alias("no_self"),
        F.coalesce("resolves", F.lit(True)).alias("resolves"),
    )


def check_occurrences(refs: DataFrame, texts: DataFrame) -> DataFrame:
    """``text_id, refs, equal``: how many references stand for the very string that is at their source. The references of a text
    meet it once, as one array."""
    kind = refs.schema["text_id"].dataType.simpleString()
    per = refs.groupBy("text_id").agg(F.collect_list(F.struct("dst", "len", "src")).alias("refs"))

    def run(it):
        for b in it:
            n, equal = [], []
            for text, found in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                n.append(len(found))
                equal.append(sum(text[r["dst"] - 1 : r["dst"] - 1 + r["len"]] == text[r["src"] - 1 : r["src"] - 1 + r["len"]] for r in found))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(equal, pa.int64())], ["text_id", "refs", "equal"])

    return texts.join(per, "text_id").select("text_id", "text", "refs").mapInArrow(run, f"text_id {kind}, refs long, equal long")


def is_unidirectional(refs: DataFrame) -> DataFrame:
    return refs.groupBy("text_id").agg(F.bool_and(F.col("src") < F.col("dst")).alias("unidirectional"))


def _varint(c: Column) -> Column:
    return F.greatest(F.lit(1), F.ceil(F.log2(c + 1) / 7)).cast("long")


def coding_bytes(factors: DataFrame) -> DataFrame:
    """``text_id, bytes`` with variable-length integers for lengths and sources and UTF-8 literals."""
    cost = F.when(F.col("src").isNotNull(), _varint(F.col("len") * 2) + _varint(F.abs(F.col("src") - F.col("dst")) * 2)).otherwise(
        _varint(F.col("len") * 2) + F.octet_length("literal")
    )
    return factors.groupBy("text_id").agg(F.sum(cost).cast("long").alias("bytes"))


def collect_coding(factors: DataFrame) -> DataFrame:
    """``text_id, coding``: one array of structs for each text."""
    part = F.struct("dst", "len", "src", "literal")
    return factors.groupBy("text_id").agg(F.array_sort(F.collect_list(part)).alias("coding"))


def explode_coding(nested: DataFrame) -> DataFrame:
    return nested.select("text_id", F.posexplode("coding").alias("i", "f")).select("text_id", (F.col("i") + 1).cast("long").alias("factor_no"), "f.*")


def summary(factors: DataFrame) -> DataFrame:
    """Share of literals, mean reference length and coverage over all texts."""
    ref = F.col("src").isNotNull()
    size = F.sum("len")
    return factors.agg(
        (F.sum(F.when(~ref, F.col("len")).otherwise(0)) / size).alias("literal_share"),
        F.avg(F.when(ref, F.col("len"))).alias("mean_reference"),
        (F.sum(F.when(ref, F.col("len")).otherwise(0)) / size).alias("coverage"),
    )
