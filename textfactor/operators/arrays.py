"""Text arrays of every text of a collection: suffix array, its inverse, transform, neighbours and common prefixes.

The kernel sorts all suffixes of a batch of texts together. Position n + 1 is the sentinel: it has rank 1, and, as it has no
predecessor in suffix order, points at itself.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from textfactor import schemas
from textfactor.functions import kernels as K
from textfactor.operators.runner import per_batch


def _with_sentinel(first: np.ndarray, values: np.ndarray, last: np.ndarray) -> np.ndarray:
    """One more entry behind each text's values."""
    return np.insert(values, first[1:], last)


def _frame(first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = np.diff(first) + 1
    row = np.repeat(np.arange(len(n)), n)
    pos = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + 1
    return row, pos, n


def build_arrays(texts: DataFrame, need: set[str] | None = None, unit: str = "codepoint") -> DataFrame:
    """``text_id, pos`` and those of ``isa, phi, plcp, bwt`` that are asked for (all by default); n + 1 rows for each text."""
    want = [c for c in ("isa", "phi", "plcp", "bwt") if need is None or c in need]

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        row, pos, _ = _frame(first)
        begin = first[:-1]
        n = np.diff(first)
        cols = [pos]
        phi = s.phi() if {"phi", "plcp"} & set(want) else None
        local = begin[s.text]
        for c in want:
            if c == "isa":
                # order is global and texts are contiguous in it, so the rank within the text is a difference
                rank = np.empty(s.n, np.int64)
                rank[s.order] = np.arange(s.n)
                cols.append(_with_sentinel(first, rank - local + 2, 1))
            elif c == "phi":
                cols.append(_with_sentinel(first, phi - local + 1, n + 1))
            elif c == "plcp":
                cols.append(_with_sentinel(first, s.plcp(phi), 0))
            else:
                order = np.full(int(n.sum()) + len(n), -1, np.int64)
                slot = np.arange(s.n) + s.text + 1
                order[slot] = s.order
                order[begin + np.arange(len(n))] = first[1:]
                opens = begin[np.repeat(np.arange(len(n)), n + 1)]
                before = np.where(order == opens, -1, order - 1)
                letters = np.array(list("".join(strings)) if unit == "codepoint" else [chr(x) for x in t.tolist()], dtype=object)
                cols.append(pa.array([letters[i] if i >= 0 else "$" for i in before.tolist()], pa.string()))
        return row, cols

    kinds = {"isa": "long", "phi": "long", "plcp": "long", "bwt": "string"}
    return per_batch(texts, "text_id {id}, pos long" + "".join(f", {c} {kinds[c]}" for c in want), kernel, unit)


def suffix_array(texts: DataFrame, unit: str = "codepoint") -> DataFrame:
    """``text_id, rank, pos``."""
    return build_arrays(texts, {"isa"}, unit).select("text_id", F.col("isa").alias("rank"), "pos")


def inverse(sa: DataFrame) -> DataFrame:
    """``text_id, pos, isa`` in text order from ``text_id, rank, pos``."""
    return sa.select("text_id", "pos", F.col("rank").alias("isa"))


def bwt(texts: DataFrame, unit: str = "codepoint") -> DataFrame:
    """``text_id, rank, bwt``: the symbol before the suffix of each rank, ``$`` for the sentinel."""
    return build_arrays(texts, {"bwt"}, unit).select("text_id", F.col("pos").alias("rank"), "bwt")


def phi_of(sa: DataFrame) -> DataFrame:
    """Predecessors in suffix order by a window over the suffix array; rank 1 points at itself."""
    w = Window.partitionBy("text_id").orderBy("rank")
    return sa.select("text_id", "pos", F.coalesce(F.lag("pos").over(w), "pos").alias("phi"))


def lcp(arrays: DataFrame) -> DataFrame:
    """``text_id, rank, lcp`` from ``isa`` and ``plcp``."""
    return arrays.select("text_id", F.col("isa").alias("rank"), F.col("plcp").alias("lcp"))


def plcp_phi_scan(texts: DataFrame, unit: str = "codepoint") -> DataFrame:
    """``text_id, pos, plcp`` from left to right, where the value before minus one is a lower bound; one text at a time."""

    def kernel(strings, t, first):
        phi = K.Suffixes(t, first).phi()
        out = np.zeros(len(t), np.int64)
        sym, to = t.tolist(), phi.tolist()
        for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
            k = 0
            for i in range(a, b):
                j = to[i]
                while i + k < b and j + k < b and sym[i + k] == sym[j + k]:
                    k += 1
                out[i] = k
                k = max(0, k - 1)
        row, pos, _ = _frame(first)
        return row, [pos, _with_sentinel(first, out, 0)]

    return per_batch(texts, "text_id {id}, pos long, plcp long", kernel, unit)


def lpf(texts: DataFrame, unit: str = "codepoint") -> DataFrame:
    """Longest previous factor of every position and the smaller of its neighbouring sources (null: none)."""

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        size, src = s.previous_factors()
        begin = first[:-1][s.text]
        return s.text, [np.arange(s.n) - begin + 1, size, pa.array(src - begin + 1, mask=src < 0)]

    return per_batch(texts, schemas.LPF, kernel, unit)


def reach_steps(texts: DataFrame, min_len: int = 1, unit: str = "codepoint") -> DataFrame:
    """Positions with a value of at least ``min_len`` at which position + value grows: a complete description of the values."""

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        v = s.plcp(s.phi())
        at = K.reach_steps(v, first)
        at = at[v[at] >= min_len]
        begin = first[:-1][s.text[at]] if s.n else at
        return s.text[at] if s.n else at, [at - begin + 1, at + v[at] - begin + 1]

    return per_batch(texts, schemas.REACH_STEPS, kernel, unit)


def bwt_runs(transform: DataFrame) -> DataFrame:
    """``text_id, runs`` of ``bwt``'s rows."""
    w = Window.partitionBy("text_id").orderBy("rank")
    changed = F.coalesce((F.lag("bwt").over(w) != F.col("bwt")).cast("long"), F.lit(1))
    return transform.withColumn("fresh", changed).groupBy("text_id").agg(F.sum("fresh").cast("long").alias("runs"))


def longest_repeat(arrays: DataFrame) -> DataFrame:
    """``text_id, pos, src, len``: the leftmost of the longest substrings that occur twice."""
    best = F.max_by(F.struct("pos", "phi", "plcp"), F.struct("plcp", -F.col("pos")))
    return arrays.groupBy("text_id").agg(best.alias("b")).where("b.plcp > 0").select(
        "text_id", F.col("b.pos").alias("pos"), F.col("b.phi").alias("src"), F.col("b.plcp").alias("len")
    )


def top_repeats(arrays: DataFrame, k: int) -> DataFrame:
    """The k longest repeats of all texts."""
    return longest_repeat(arrays).orderBy(F.desc("len"), "text_id").limit(k)


def peaks(texts: DataFrame, min_len: int = 2, unit: str = "codepoint") -> DataFrame:
    """The peaks before any factor is made, with their flags."""

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        v = s.plcp(s.phi())
        at = K.reach_steps(v, first)
        at = at[v[at] >= min_len]
        good, top = K.interesting_peaks(at, at + v[at]), np.zeros(len(at), bool)
        top[K.maximal_peaks(at, at + v[at])] = True
        # of equal neighbours only the first is a peak; the steps, which block others, have both
        if s.n:
            peak = (at == first[:-1][s.text[at]]) | (v[at] > v[np.maximum(at, 1) - 1])
            at, good, top = at[peak], good[peak], top[peak]
        row = s.text[at] if s.n else at
        return row, [at - first[:-1][row] + 1 if len(at) else at, v[at], good, top]

    return per_batch(texts, schemas.PEAKS, kernel, unit)


def islands(steps: DataFrame, min_len: int = 2) -> DataFrame:
    """``text_id, island, low, high, steps``: stretches that no reach crosses; they can be factorized apart from each other."""
    w = Window.partitionBy("text_id").orderBy("pos")
    s = steps.where(F.col("reach") - F.col("pos") >= min_len)
    opens = F.coalesce((F.col("pos") >= F.lag("reach").over(w)).cast("int"), F.lit(1))
    s = s.withColumn("opens", opens).withColumn("island", F.sum("opens").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return s.groupBy("text_id", "island").agg(F.min("pos").alias("low"), (F.max("reach") - 1).alias("high"), F.count("*").alias("steps"))
