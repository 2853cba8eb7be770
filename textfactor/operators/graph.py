"""Dependencies between factors: which factors hold the source of a reference.

Interval overlaps are equi-joins: both sides are cut on a grid of ``width`` positions, joined on (text, bucket), and an overlap is
kept in the bucket of its start.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textfactor.functions import kernels as K

WIDTH = 64


def buckets(start: str, size: str, width: int = WIDTH) -> Column:
    return F.explode(F.expr(f"sequence({start} div {width}, ({start} + {size} - 1) div {width})"))


def grid_width(pieces: DataFrame) -> int:
    """A grid for overlap joins: four mean lengths wide, so pieces are cut to at most a quarter more however long they are, and a
    bucket holds few of them."""
    mean = pieces.agg(F.avg("len")).first()[0] or 1.0
    return max(WIDTH, 1 << math.ceil(math.log2(4 * mean)))


def dependency_edges(factors: DataFrame, width: int | None = None) -> DataFrame:
    """``text_id, child_no, parent_no, ov_start, ov_len, contained``; ``contained``: the parent holds the whole source."""
    width = width or grid_width(factors)
    kids = factors.where("src IS NOT NULL").select(
        "text_id", F.col("factor_no").alias("child_no"), F.col("src").alias("s"), F.col("len").alias("n"), buckets("src", "len", width).alias("bucket")
    )
    folks = factors.select(
        "text_id", F.col("factor_no").alias("parent_no"), F.col("dst").alias("d"), F.col("len").alias("m"), buckets("dst", "len", width).alias("bucket")
    )
    start, end = F.greatest("s", "d"), F.least(F.col("s") + F.col("n"), F.col("d") + F.col("m"))
    both = kids.join(folks, ["text_id", "bucket"]).where((start < end) & (F.col("bucket") == F.expr(f"greatest(s, d) div {width}")))
    return both.select(
        "text_id", "child_no", "parent_no", start.alias("ov_start"), (end - start).alias("ov_len"),
        ((F.col("s") >= F.col("d")) & (F.col("s") + F.col("n") <= F.col("d") + F.col("m"))).alias("contained"),
    )


def multi_dependent(edges: DataFrame) -> DataFrame:
    """``text_id, child_no, parents`` of the references whose source meets more than one factor."""
    return edges.groupBy("text_id", "child_no").agg(F.count("*").alias("parents")).where("parents > 1")


def first_parent(edges: DataFrame) -> DataFrame:
    """``text_id, child_no, parent_no, contained``: the factor that holds the first symbol of the source."""
    pick = F.min_by(F.struct("parent_no", "contained"), "ov_start").alias("p")
    return edges.groupBy("text_id", "child_no").agg(pick).select("text_id", "child_no", F.col("p.parent_no").alias("parent_no"), F.col("p.contained").alias("contained"))


def nested_kernel(factors: DataFrame, schema: str, kernel) -> DataFrame:
    """``kernel(bounds, dst, size, src, literal)`` over batches of whole codings; ``bounds``: the factors of each text.

    ``src`` is -1 for literals; positions are 0-based within the text. Returns the columns behind ``text_id``.
    """
    part = F.struct("dst", "len", F.coalesce("src", F.lit(0)).alias("src"), F.coalesce("literal", F.lit("")).alias("literal"))
    nested = factors.groupBy("text_id").agg(F.array_sort(F.collect_list(part)).alias("coding"))
    schema = schema.format(id=factors.schema["text_id"].dataType.simpleString())
    names = [c.split()[0] for c in schema.split(", ")]

    def run(it):
        for b in it:
            col = b.column(1)
            flat, off = col.flatten(), col.offsets.to_numpy()
            bounds = (off - off[0]).astype(np.int64)
            dst, size, src = (flat.field(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(3))
            cols = kernel(bounds, dst - 1, size, src - 1, flat.field(3))
            yield pa.RecordBatch.from_arrays([b.column(0), *(c if isinstance(c, pa.Array) else pa.array(c) for c in cols)], names)

    return nested.mapInArrow(run, schema)


def batch_parents(bounds, dst, size, src, n=None) -> tuple[np.ndarray, np.ndarray]:
    """Parent of every position of a batch of texts laid end to end, and the n + 1 first positions."""
    if n is None:
        n = np.add.reduceat(size, bounds[:-1]) if len(size) else np.zeros(0, np.int64)
    first = np.concatenate([[0], np.cumsum(n)])
    base = np.repeat(first[:-1], np.diff(bounds))
    ref = src >= 0
    return K.char_parents(int(first[-1]), (dst + base)[ref], (src + base)[ref], size[ref]), first


def resolves(factors: DataFrame) -> DataFrame:
    """``text_id, resolves``: does every symbol lead to a literal inside the text, without a circle?"""

    def kernel(bounds, dst, size, src, literal):
        n = np.add.reduceat(size, bounds[:-1]) if len(size) else np.zeros(0, np.int64)
        whole = np.repeat(n, np.diff(bounds))
        inside = (dst >= 0) & (dst + size <= whole) & (src + size <= whole)
        text = np.repeat(np.arange(len(n)), np.diff(bounds))
        ok = np.bincount(text[~inside], minlength=len(n)) == 0
        parent, first = batch_parents(bounds, np.where(inside, dst, 0), np.where(inside, size, 0), np.where(inside, src, -1), n)
        lost = K.unresolved(parent)
        ok[np.searchsorted(first, lost, "right") - 1] = False
        return [pa.array(ok)]

    return nested_kernel(factors, "text_id {id}, resolves boolean", kernel)


def depths(factors: DataFrame) -> DataFrame:
    """``text_id, depth, mean_depth, factor_cycles``: steps from a symbol to its literal, and circles among first parents."""

    def kernel(bounds, dst, size, src, literal):
        parent, first = batch_parents(bounds, dst, size, src)
        hops = K.depths(parent)
        top = np.array([hops[a:b].max(initial=0) for a, b in zip(first[:-1], first[1:])], np.int64)
        mean = np.array([hops[a:b].mean() if b > a else 0.0 for a, b in zip(first[:-1], first[1:])])
        circles = []
        for u, v in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            s, d = src[u:v], dst[u:v]
            to = np.where(s >= 0, np.searchsorted(d, s, "right") - 1, np.arange(v - u))
            state = [0] * (v - u)
            found = 0
            for i in range(v - u):
                path = []
                while not state[i] and s[i] >= 0:
                    state[i] = 1
                    path.append(i)
                    i = int(to[i])
                if state[i] == 1:
                    found += 1
                for p in path:
                    state[p] = 2
            circles.append(found)
        return top, mean, np.array(circles, np.int64)

    return nested_kernel(factors, "text_id {id}, depth long, mean_depth double, factor_cycles long", kernel)
