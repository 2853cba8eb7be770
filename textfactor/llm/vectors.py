"""Embedding near-duplicates by an exact metric range join.

Unit vectors with cosine >= c are at most r = sqrt(2 - 2 c) apart, a metric. Pivots, a bounded sample of the vectors, split the
space: a vector's home is the cell of its nearest pivot. By the triangle inequality a vector v may have a partner in cell j
only if d(v, p_j) <= R_j + r, with R_j the largest distance of a home vector from pivot j, and only if its distance from the
plane between its own pivot and p_j, (d(v, p_j)**2 - d(v, p_i)**2) / (2 d(p_i, p_j)), is at most r. It is replicated to
those cells. A cell then joins its home vectors with all it holds, independently of others, in tiles of bounded size: every
home vector meets all its partners there, so its number of links is complete, and the cell's links are handed on as a
spanning forest. A cell is cut into slices of home vectors and blocks of all its
vectors, both of bounded size; every slice meets every block in a task of its own.

Equal vectors are one node with a multiplicity, so copies are never expanded into pairs. Tiles are filtered in single
precision with a margin; the rest is decided in double precision on the stored components.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing; vectors of
different lengths never link; rows that repeat are copies; a null id never is a component's id unless all are null; an
empty table gives no row; other columns are ignored.
"""

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.components import LocalUnion, connected_components
from textfactor.llm.scratch import Scratch

COSINE = 0.9
CELL = 6000
MIN_PIVOTS, MAX_PIVOTS = 4, 512
SLICE = 8192
MET = 16_384
TILE = 2048
MARGIN = 1e-4


def _units(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt(np.einsum("ij,ij->i", x, x))[:, None]


def _rows(col) -> np.ndarray:
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(col), -1)


def _distances(x: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0.0, 2 - 2 * (x @ pivots.T)))


def _to_cells(nodes: DataFrame, dim: int, pivots: np.ndarray, r: float, reach: np.ndarray | None) -> DataFrame:
    """Without ``reach``: the farthest home vector of each cell. With it: nodes at home and, replicated, near other cells."""
    between = np.maximum(_distances(pivots, pivots), 1e-12)

    def run(batches):
        far = np.zeros(len(pivots))
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                b = batch.slice(at, 4096)
                d = _distances(_units(_rows(b.column("v"))), pivots)
                home = d.argmin(1)
                own = d[np.arange(len(d)), home]
                if reach is None:
                    np.maximum.at(far, home, own)
                    continue
                plane = (d**2 - own[:, None] ** 2) / (2 * between[home])
                go = (d <= reach[None, :] + r + 1e-6) & (plane <= r + 1e-6)
                go[np.arange(len(d)), home] = True
                row, cell = np.nonzero(go)
                take = pa.array(row)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(cell.astype(np.int32)), pa.array(cell == home[row]), b.column("node").take(take), b.column("copies").take(take), b.column("v").take(take)],
                    ["cell", "home", "node", "copies", "v"],
                )
        if reach is None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(far), dtype=np.int32)), pa.array(far)], ["cell", "far"])

    schema = "cell int, far double" if reach is None else "cell int, home boolean, node long, copies long, v array<double>"
    return nodes.where(F.size("v") == dim).select("node", "copies", "v").mapInArrow(run, schema)


def _join_cell(cosine: float):
    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A slice of home vectors against a block of the cell's vectors."""
        t = pa.Table.from_batches(list(batches))
        is_own = t["own"].to_numpy(zero_copy_only=False)
        x, node, copies = _rows(t["v"]), t["node"].to_numpy(), t["copies"].to_numpy()
        norm = np.sqrt(np.einsum("ij,ij->i", x, x))
        unit = (x / norm[:, None]).astype(np.float32)
        own, met = np.flatnonzero(is_own), np.flatnonzero(~is_own)
        # a vector of both sides is one label
        names, label = np.unique(node, return_inverse=True)
        links, union = np.zeros(len(x), np.int64), LocalUnion(len(names))
        for a in range(0, len(own), TILE):
            mine = own[a : a + TILE]
            for c in range(0, len(met), TILE):
                theirs = met[c : c + TILE]
                near = unit[mine] @ unit[theirs].T
                a_i, c_j = np.nonzero(near >= cosine - MARGIN)
                sure = near[a_i, c_j] >= cosine + MARGIN
                i, j = mine[a_i], theirs[c_j]
                other = node[i] != node[j]
                i, j, sure = i[other], j[other], sure[other]
                at = np.flatnonzero(~sure)
                for u in range(0, len(at), 1 << 16):
                    p = at[u : u + (1 << 16)]
                    sure[p] = np.einsum("ij,ij->i", x[i[p]], x[j[p]]) / (norm[i[p]] * norm[j[p]]) >= cosine
                i, j = i[sure], j[sure]
                np.add.at(links, i, copies[j])
                union.add(label[i], label[j])
        far = np.flatnonzero(union.label != np.arange(len(names)))
        some = own[links[own] > 0]
        none = np.zeros(len(far), np.int64)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(np.concatenate([node[some], names[far]])),
                pa.array(np.concatenate([links[some], none])),
                pa.array(np.concatenate([node[some], names[union.label[far]]])),
            ],
            ["node", "links", "other"],
        )

    return run


def link_vectors(vectors: DataFrame, cosine: float = COSINE, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``id, n_links, component_id, kept`` for every row."""
    spark = vectors.sparkSession
    scratch = Scratch(spark, "vectors")
    v = F.col(vector_col).cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    usable = v.isNotNull() & F.coalesce(finite, F.lit(False)) & F.coalesce(F.exists(v, lambda x: x != 0), F.lit(False))
    plain = F.transform(v, lambda x: F.when(x == 0, F.lit(0.0)).otherwise(x))
    rows = scratch.save(
        vectors.select(F.col(id_col).alias("id"), F.when(usable, plain).alias("v")).withColumn("node", F.when(F.col("v").isNotNull(), F.xxhash64("v"))), "rows"
    )
    nodes = rows.where(F.col("node").isNotNull()).groupBy("node").agg(F.count("*").alias("copies"), F.any_value("v").alias("v"))
    nodes = scratch.save(nodes, "nodes")
    r = float(np.sqrt(2 - 2 * cosine))
    parts = None
    for row in nodes.groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n")).collect():
        dim, n = row["dim"], row["n"]
        k = min(n, MAX_PIVOTS, max(MIN_PIVOTS, n // CELL))
        # a bounded sample: the k smallest node hashes, which are independent of the vectors' places
        sample = nodes.where(F.size("v") == dim).orderBy(F.xxhash64("node"), "node").limit(k).select("v").collect()
        pivots = _units(np.array([s["v"] for s in sample], np.float64))
        reach = np.zeros(k)
        for f in _to_cells(nodes, dim, pivots, r, None).groupBy("cell").agg(F.max("far").alias("far")).collect():
            reach[f["cell"]] = f["far"]
        cells = scratch.save(_to_cells(nodes, dim, pivots, r, reach), "cells")
        size = cells.groupBy("cell").agg(
            F.ceil(F.count_if("home") / SLICE).cast("int").alias("slices"), F.ceil(F.count("*") / MET).cast("int").alias("blocks")
        )
        cut = cells.join(F.broadcast(size), "cell")  # one row for each pivot
        place = lambda n: F.pmod(F.xxhash64("node"), F.col(n)).cast("int")
        every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        held = ["node", "copies", "v"]
        homes = cut.where("home").select("cell", place("slices").alias("slice"), every("blocks").alias("block"), F.lit(True).alias("own"), *held)
        met = cut.select("cell", every("slices").alias("slice"), place("blocks").alias("block"), F.lit(False).alias("own"), *held)
        got = homes.unionByName(met).groupBy("cell", "slice", "block").applyInArrow(_join_cell(cosine), "node long, links long, other long")
        parts = got if parts is None else parts.unionByName(got)
    if parts is None:
        parts = spark.createDataFrame([], "node long, links long, other long")
    found = scratch.save(parts, "found")
    roots = scratch.save(connected_components(found.where("node <> other").select(F.col("node").alias("u"), F.col("other").alias("v")), scratch), "roots")
    counts = found.groupBy("node").agg(F.sum("links").alias("links"))
    own = nodes.select("node", "copies").join(counts, "node", "left").join(roots, "node", "left")
    least = rows.where(F.col("node").isNotNull()).groupBy("node").agg(F.min("id").alias("least"))
    own = own.join(least, "node").select("node", "least", F.coalesce("root", "node").alias("root"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n"))
    best = own.groupBy("root").agg(F.min("least").alias("component_id"))
    named = own.join(best, "root").select("node", "n", "component_id")
    out = rows.join(named, "node", "left").select(
        F.col("id"), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "id").alias("component_id")
    )
    return out.withColumn("kept", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False))).withColumnRenamed("id", id_col)


def op9_embedding_near_dedup(spark, sf_dir: str) -> DataFrame:
    return link_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
