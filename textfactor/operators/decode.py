"""Decoders: by joins that double reference chains, by characters, and by kernels over whole codings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.operators.graph import WIDTH, batch_parents, buckets, grid_width, nested_kernel
from textfactor.plans.scratch import Scratch

MAX_ROUNDS = 4096


def _letters(literal: pa.Array) -> np.ndarray:
    return np.frombuffer("".join(literal.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32)


def decode_memory(factors: DataFrame) -> DataFrame:
    """``text_id, text``: a kernel follows all symbols of a batch of codings to their literals by doubling."""

    def kernel(bounds, dst, size, src, literal):
        parent, first = batch_parents(bounds, dst, size, src)
        root, _ = K.resolve(parent)
        sym = np.zeros(len(parent), np.uint32)
        sym[parent == np.arange(len(parent))] = _letters(literal)
        out = sym[root]
        return [pa.array([out[a:b].tobytes().decode("utf-32-le", "surrogatepass") for a, b in zip(first[:-1], first[1:])], pa.string())]

    return nested_kernel(factors, "text_id {id}, text string", kernel)


def decode_unidirectional(factors: DataFrame) -> DataFrame:
    """``text_id, text`` from left to right, phrase by phrase; fails if a source is not before its factor."""

    def kernel(bounds, dst, size, src, literal):
        if (src >= dst).any():
            raise ValueError("the coding is not unidirectional")
        words, out = literal.to_pylist(), []
        for u, v in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            text: list[str] = []
            for s, d, n, lit in zip(src[u:v].tolist(), dst[u:v].tolist(), size[u:v].tolist(), words[u:v]):
                if s < 0:
                    text.extend(lit)
                else:
                    while n:  # an overlapping source grows while it is copied
                        part = text[s : s + n]
                        text.extend(part)
                        s, n = s + len(part), n - len(part)
            out.append("".join(text))
        return [pa.array(out, pa.string())]

    return nested_kernel(factors, "text_id {id}, text string", kernel)


def make_tiles(factors: DataFrame) -> DataFrame:
    """``text_id, dst, src, len, final``: literals are their own sources, so tiles cover the text."""
    return factors.select("text_id", "dst", F.coalesce("src", "dst").alias("src"), "len", F.col("src").isNull().alias("final"))


def _on_grid(tiles: DataFrame, width: int) -> DataFrame:
    """Tiles cut so that each destination lies in one bucket."""
    cut = tiles.withColumn("bucket", buckets("dst", "len", width))
    a, b = F.greatest("dst", F.col("bucket") * width), F.least(F.col("dst") + F.col("len"), (F.col("bucket") + 1) * width)
    return cut.select("text_id", "bucket", a.alias("p_dst"), (F.col("src") + a - F.col("dst")).alias("p_src"), (b - a).alias("p_len"), F.col("final").alias("p_final"))


def advance(requests: DataFrame, parents: DataFrame, width: int = WIDTH) -> DataFrame:
    """One round: every request is moved to the sources of the tiles that hold its own source, and split where they end."""
    r = requests.withColumn("bucket", buckets("src", "len", width))
    start, end = F.greatest("src", "p_dst"), F.least(F.col("src") + F.col("len"), F.col("p_dst") + F.col("p_len"))
    return r.join(_on_grid(parents, width), ["text_id", "bucket"]).where(start < end).select(
        "text_id",
        (F.col("dst") + start - F.col("src")).alias("dst"),
        (F.col("p_src") + start - F.col("p_dst")).alias("src"),
        (end - start).alias("len"),
        F.col("p_final").alias("final"),
    )


def coalesce_pieces(tiles: DataFrame, stretch: int = 1 << 14) -> DataFrame:
    """Join neighbours with one shift, inside stretches of the text."""
    w = Window.partitionBy("text_id", F.expr(f"dst div {stretch}"), "final").orderBy("dst")
    joined = (F.lag(F.col("dst") + F.col("len")).over(w) == F.col("dst")) & (F.lag(F.col("src") + F.col("len")).over(w) == F.col("src"))
    t = tiles.withColumn("fresh", (~F.coalesce(joined, F.lit(False))).cast("int"))
    t = t.withColumn("run", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("part", F.expr(f"dst div {stretch}"))
    return t.groupBy("text_id", "part", "final", "run").agg(F.min("dst").alias("dst"), F.min("src").alias("src"), F.sum("len").alias("len")).select("text_id", "dst", "src", "len", "final")


def jump(factors: DataFrame, double: bool = True, merge: bool = True, width: int | None = None) -> tuple[DataFrame, list[dict]]:
    """Final tiles, whose sources are literals only, and what each round did.

    ``double``: requests are moved through the tiles of the round before, so distances double; otherwise always through
    the first ones, one step a round. Each round is written; one row of counts comes to the driver: of the requests of a round,
    the pieces that it finalized, and how many pieces splitting added.
    """
    scratch = Scratch(factors.sparkSession, "jump")
    start = scratch.save(make_tiles(factors), "tiles")
    tiles, rounds, old = start, [], None
    for k in range(MAX_ROUNDS):
        open_ = tiles.where("NOT final")
        n = open_.count()
        if not n:
            return tiles, rounds
        parents = tiles if double else start
        seen = Observation()
        moved = advance(open_, parents, width or grid_width(parents)).observe(
            seen, F.count(F.lit(1)).alias("made"), F.count_if("final").alias("finalized")
        )
        new = tiles.where("final").unionByName(moved)
        new = scratch.save(coalesce_pieces(new) if merge else new, "tiles")
        got = new.agg(F.count("*").alias("pieces"), F.count_if(~F.col("final")).alias("open")).first()
        rounds.append(
            {"round": k + 1, "requests": n, "finalized": seen.get["finalized"], "split": seen.get["made"] - n, "still_open": got["open"], "pieces": got["pieces"]}
        )
        if old is not None:
            scratch.drop(old)
        old = new
        tiles = new
    raise ValueError("the references run in a circle")


def assemble(tiles: DataFrame, factors: DataFrame, width: int | None = None) -> DataFrame:
    """``text_id, text`` of final tiles: cut their sources out of the literals and put the pieces in order."""
    return in_one(decoded_pieces(tiles, factors, width))


def in_one(pieces: DataFrame) -> DataFrame:
    """``text_id, text`` of the pieces ``(text_id, at, piece)`` of each text; for texts that fit a task."""
    return pieces.groupBy("text_id").agg(F.array_sort(F.collect_list(F.struct("at", "piece"))).alias("x")).select(
        "text_id", F.array_join(F.transform("x", lambda p: p["piece"]), "").alias("text")
    )


def decoded_pieces(tiles: DataFrame, factors: DataFrame, width: int | None = None) -> DataFrame:
    """``text_id, at, piece`` of final tiles, cut out of the literals; the pieces cover the texts."""
    width = width or grid_width(factors.where("src IS NULL"))
    lit = factors.where("src IS NULL").select("text_id", F.col("dst").alias("l_dst"), F.col("len").alias("l_len"), "literal", buckets("dst", "len", width).alias("bucket"))
    t = tiles.withColumn("bucket", buckets("src", "len", width))
    start = F.greatest("src", "l_dst", F.col("bucket") * width)
    end = F.least(F.col("src") + F.col("len"), F.col("l_dst") + F.col("l_len"), (F.col("bucket") + 1) * width)
    return t.join(lit, ["text_id", "bucket"]).where(start < end).select(
        "text_id", (F.col("dst") + start - F.col("src")).alias("at"),
        F.substring("literal", (start - F.col("l_dst") + 1).cast("int"), (end - start).cast("int")).alias("piece"),
    )


def cell_digests(pieces: DataFrame, cell: int = 1 << 14) -> DataFrame:
    """``cell, digest`` of one text given as pieces ``(at, piece)`` that tile it, by cells of ``cell`` symbols."""
    pieces = pieces.where("length(piece) > 0")
    pieces = pieces.select("at", "piece", F.explode(F.expr(f"sequence((at - 1) div {cell}, (at + length(piece) - 2) div {cell})")).alias("cell"))
    low, high = F.greatest("at", F.col("cell") * cell + 1), F.least(F.col("at") + F.length("piece"), (F.col("cell") + 1) * cell + 1)
    cut = pieces.select("cell", low.alias("at"), F.substring("piece", (low - F.col("at") + 1).cast("int"), (high - low).cast("int")).alias("piece"))
    body = cut.groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("at", "piece"))).alias("x"))
    return body.select("cell", F.md5(F.array_join(F.transform("x", lambda p: p["piece"]), "")).alias("digest"))


def decode_copies(factors: DataFrame) -> tuple[DataFrame, list[dict]]:
    """``text_id, text`` with recorded copies, and what each round did.

    The decoded part of the text is kept as strings. In a round, what of a request's source is decoded already is recorded as a
    copy and cut out of it at the end of the round; the rest jumps to the sources of the references that hold it. So a copy may
    come from any decoded symbols, not from literals only.
    """
    scratch = Scratch(factors.sparkSession, "copies")
    done = scratch.save(factors.where("src IS NULL").select("text_id", F.col("dst").alias("at"), "literal"), "decoded")
    open_ = scratch.save(make_tiles(factors.where("src IS NOT NULL")), "requests")
    rounds = []
    for k in range(MAX_ROUNDS):
        n = open_.count()
        if not n:
            return in_one(done.select("text_id", "at", F.col("literal").alias("piece"))), rounds
        known = done.select("text_id", F.col("at").alias("dst"), F.length("literal").cast("long").alias("len"), F.lit(None).cast("long").alias("src"), "literal")
        width = grid_width(open_)
        copied = scratch.save(decoded_pieces(open_, known, width).withColumnRenamed("piece", "literal"), "copies")
        moved = scratch.save(coalesce_pieces(advance(open_, open_, width)), "requests")
        rounds.append({"round": k + 1, "requests": n, "copies": copied.count()})
        new = scratch.save(done.unionByName(copied), "decoded")
        for x in (done, open_, copied):
            scratch.drop(x)
        done, open_ = new, moved
    raise ValueError("the references run in a circle")


def decode_jump(factors: DataFrame, double: bool = True, merge: bool = True) -> DataFrame:
    return assemble(jump(factors, double, merge)[0], factors)


def jump_rounds(factors: DataFrame, double: bool = True, merge: bool = True) -> DataFrame:
    """``round, requests, finalized, split, still_open, pieces``."""
    names = ["round", "requests", "finalized", "split", "still_open", "pieces"]
    rows = [tuple(r[c] for c in names) for r in jump(factors, double, merge)[1]]
    return factors.sparkSession.createDataFrame(rows, "round int, " + ", ".join(f"{c} long" for c in names[1:]))


def order_of_jumps(factors: DataFrame) -> DataFrame:
    """``text_id, parallel, in_order``: rounds of pointer jumping over symbols when all of a round see the state before it, and when
    they are taken in text order and see what was moved already."""

    def kernel(bounds, dst, size, src, literal):
        out = []
        for u, v in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            parent, _ = batch_parents(np.array([0, v - u]), dst[u:v], size[u:v], src[u:v])
            out.append((K.resolve(parent)[1], K.resolve_in_order(parent)))
        a, b = zip(*out) if out else ((), ())
        return np.array(a, np.int64), np.array(b, np.int64)

    return nested_kernel(factors, "text_id {id}, parallel long, in_order long", kernel)


def decode_chars(factors: DataFrame, direct_first: bool = False) -> DataFrame:
    """``text_id, text`` by splitting every factor into symbols and doubling their parents.

    ``direct_first``: references whose sources hold literals only are settled before the split.
    """
    scratch = Scratch(factors.sparkSession, "chars")
    if direct_first:
        tiles = advance(make_tiles(factors).where("NOT final"), make_tiles(factors))
        tiles = tiles.unionByName(make_tiles(factors).where("final"))
    else:
        tiles = make_tiles(factors)
    chars = tiles.select("text_id", F.explode(F.expr("sequence(0L, len - 1)")).alias("i"), "dst", "src").select(
        "text_id", (F.col("dst") + F.col("i")).alias("pos"), (F.col("src") + F.col("i")).alias("to")
    )
    now = scratch.save(chars, "chars")
    for _ in range(64):
        above = now.select("text_id", F.col("pos").alias("to"), F.col("to").alias("to2"))
        new = scratch.save(now.join(above, ["text_id", "to"]).select("text_id", "pos", F.col("to2").alias("to"), (F.col("to") != F.col("to2")).alias("moved")), "chars")
        scratch.drop(now)
        more = new.where("moved").limit(1).count()
        now = new
        if not more:
            break
    else:
        raise ValueError("the references run in a circle")
    lit = factors.where("src IS NULL").select("text_id", F.posexplode(F.split("literal", "")).alias("i", "c"), "dst")
    lit = lit.where("c <> ''").select("text_id", (F.col("dst") + F.col("i")).alias("to"), "c")
    return now.join(lit, ["text_id", "to"]).groupBy("text_id").agg(F.array_sort(F.collect_list(F.struct("pos", "c"))).alias("x")).select(
        "text_id", F.array_join(F.transform("x", lambda p: p["c"]), "").alias("text")
    )


def extract(factors: DataFrame, low: int, high: int) -> DataFrame:
    """``text_id, text``: the symbols low..high of every text (1-based, inclusive), following only their references."""
    scratch = Scratch(factors.sparkSession, "extract")
    whole = make_tiles(factors)
    a, b = F.greatest("dst", F.lit(low)), F.least(F.col("dst") + F.col("len"), F.lit(high + 1))
    tiles = scratch.save(whole.where((F.col("dst") <= high) & (F.col("dst") + F.col("len") > low)).select("text_id", a.alias("dst"), (F.col("src") + a - F.col("dst")).alias("src"), (b - a).alias("len"), "final"), "tiles")
    for _ in range(MAX_ROUNDS):
        if not tiles.where("NOT final").limit(1).count():
            return assemble(tiles, factors)
        new = scratch.save(coalesce_pieces(tiles.where("final").unionByName(advance(tiles.where("NOT final"), whole))), "tiles")
        scratch.drop(tiles)
        tiles = new
    raise ValueError("the references run in a circle")
