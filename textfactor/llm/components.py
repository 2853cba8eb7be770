"""Connected components of an edge table by alternating star contractions, and a union-find for the links inside a task."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import Scratch


def connected_components(edges: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """``node, root`` (root: the smallest node) of every node of ``edges(u, v)``.

    A round first joins every node's larger neighbours with its smallest one, then its smaller ones; the number of rounds
    is logarithmic in the size of a component. Each round is written, and one row (count, checksum) tells whether it
    changed anything.
    """
    now = scratch.save(
        edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges"
    )
    seen = None
    for _ in range(max_rounds):
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or mark[0] == 0:
            break
        seen = mark
        both = now.select(F.col("u").alias("a"), F.col("v").alias("b")).union(now.select("v", "u"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = scratch.save(both.join(least, "a").where("b > a").select(F.col("b").alias("u"), F.col("m").alias("v")).distinct(), "large")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = scratch.save(small.union(least).distinct(), "small")
        scratch.drop(large)
        scratch.drop(now)
        now = new
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select("v", "v").distinct())


class LocalUnion:
    """Labels 0..n-1 that links join; ``rows`` and ``cols`` of any number of links at once."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def add(self, rows: np.ndarray, cols: np.ndarray) -> None:
        while True:
            a, b = self.label[rows], self.label[cols]
            differ = a != b
            if not differ.any():
                return
            rows, cols, a, b = rows[differ], cols[differ], a[differ], b[differ]
            low = np.arange(len(self.label))
            np.minimum.at(low, np.maximum(a, b), np.minimum(a, b))
            while True:
                nxt = low[low]
                if (nxt == low).all():
                    break
                low = nxt
            self.label = low[self.label]
