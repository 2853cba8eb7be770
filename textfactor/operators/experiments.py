"""The experiments over prefixes of one text: throughput, disk, factors and references of both schemes, and decoding.

A prefix of up to ``KERNEL_SYMBOLS`` symbols is one text in one kernel call, so one task; such prefixes are tasks side by side. A longer one
stays in blocks and runs over the cluster (``global_text``), one after another; counts are the same in both forms. Times are the median of
three runs and leave out the arrays' construction, which is a measure of its own; over the cluster, the previous factors are made once
and their time counts for each unidirectional parse, and a reference is written with its source.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.operators import coding, decode, factorize
from textfactor.operators.global_text import GlobalText
from textfactor.operators.measures import measure
from textfactor.operators.runner import symbol_batch
from textfactor.plans.scratch import Scratch
from textfactor.sources import corpus

MEASURES = "workload string, dataset string, prefix double, method string, min_len long, metric string, value double"
PARTS = (8, 4, 2, 1)
#: Symbols of the longest prefix that a kernel call takes, at about 110 bytes each.
KERNEL_SYMBOLS = 1 << 22


class Prefixes(NamedTuple):
    """``short``: ``text_id, text`` of the prefixes that a kernel call takes, text_id is the part; ``long``: blocks ``(start, body)`` and
    length of each of the others, by part."""

    short: DataFrame
    long: dict[int, tuple[DataFrame, int]]


def parted(texts: DataFrame, parts: tuple[int, ...] = PARTS, sep: str = "\n") -> Prefixes:
    """For each part p the first p-th of all texts joined in key order; no row holds a long one."""
    blocks = Scratch(texts.sparkSession, "prefixes").save(corpus.single_text(texts, sep), "blocks")
    n = blocks.agg(F.sum(F.length("body"))).first()[0] or 0
    head = lambda size: F.expr(f"substring(body, 1, cast(least(length(body), {size} - start + 1) AS int))").alias("body")
    heads = {p: blocks.where(F.col("start") <= n // p).select("start", head(n // p)) for p in parts}
    short = texts.sparkSession.createDataFrame([], "text_id long, text string")
    for p in parts:
        if 0 < n // p <= KERNEL_SYMBOLS:
            x = heads[p].agg(F.array_sort(F.collect_list(F.struct("start", "body"))).alias("x"))
            short = short.unionByName(x.select(F.lit(p).cast("long").alias("text_id"), F.array_join(F.transform("x", lambda s: s["body"]), "").alias("text")))
    return Prefixes(short, {p: (heads[p], n // p) for p in parts if n // p > KERNEL_SYMBOLS})


def prefixes(texts: DataFrame, parts: tuple[int, ...] = PARTS, sep: str = "\n") -> DataFrame:
    """``text_id, text``: for each part p the first p-th of all texts joined in key order, as one text; text_id is p."""
    whole = texts.withColumn("text", F.concat("text", F.lit(sep)))
    n = whole.agg(F.sum(F.length("text"))).first()[0] or 0
    cut = corpus.corpus_prefix(whole, n)
    sizes = F.explode(F.array(*(F.struct(F.lit(p).cast("long").alias("p"), F.lit(n // p).cast("long").alias("size")) for p in parts))).alias("s")
    at = corpus.assign_offsets(cut, ["text_id"], F.length("text"), 0).select("start", "text", sizes).where("start < s.size")
    piece = F.expr("substring(text, 1, cast(least(length(text), s.size - start) AS int))")
    per = at.groupBy(F.col("s.p").alias("text_id")).agg(F.array_sort(F.collect_list(F.struct("start", piece.alias("piece")))).alias("x"))
    return per.select("text_id", F.array_join(F.transform("x", lambda s: s["piece"]), "").alias("text"))


def _timed(action: Callable, repeat: int) -> tuple[float, object]:
    got = measure(action, repeat)
    return got["seconds"], got["result"]


def compress(texts: DataFrame, dataset: str, lengths: list[int], workload: str, repeat: int = 3) -> DataFrame:
    """Measures of both schemes on every text (its key: the part of the whole), for each minimum length."""

    def run(it):
        for b in it:
            for part, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                t, first = symbol_batch([text], "codepoint")
                out = []

                def put(method, m, **values):
                    out.extend((workload, dataset, 1.0 / part, method, m, k, float(v)) for k, v in values.items())

                a = time.perf_counter()
                s = K.Suffixes(t, first)
                order_s = time.perf_counter() - a
                phi = s.phi()
                v = s.plcp(phi)
                put("arrays", 0, symbols=len(t), suffix_order_s=order_s, plcp_s=time.perf_counter() - a - order_s)
                # what the unidirectional scheme needs besides: the values in suffix order
                lcp_s, _ = _timed(lambda: v[s.order], repeat)
                put("arrays", 0, lcp_s=lcp_s)
                gib = len(t) / 2**30
                for m in lengths:
                    seconds, (d, size) = _timed(lambda: K.rounds_factors(v, first, m), repeat)
                    ll = len(d) + len(t) - int(size.sum())
                    put("bidirectional", m, GiB_per_h=gib / seconds * 3600, references=len(d), factors=ll)

                    def parse():
                        lpf, src = s.previous_factors()
                        step = np.where(lpf >= m, lpf, 1)
                        at = K.greedy_parse(step, first)
                        return step[at]

                    seconds, step = _timed(parse, repeat)
                    put("unidirectional", m, GiB_per_h=gib / seconds * 3600, references=int((step > 1).sum()), factors=len(step))
                    put("bidirectional", m, factor_ratio=ll / max(1, len(step)))
                cols = list(zip(*out))
                kinds = [pa.string(), pa.string(), pa.float64(), pa.string(), pa.int64(), pa.string(), pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], [c.split()[0] for c in MEASURES.split(", ")])

    return texts.select("text_id", "text").repartition(len(PARTS), "text_id").mapInArrow(run, MEASURES)


def factor_counts(texts: DataFrame, min_len: int = 2) -> DataFrame:
    """``part, scheme, n_refs, n_factors`` of both schemes for the prefixes; without times, so the same in every run."""
    out = None
    for name, refs in (("bidirectional", factorize.factorize(texts, min_len)), ("unidirectional", factorize.parse_unidirectional(texts, min_len))):
        c = coding.reference_counts(refs, texts).select(F.col("text_id").alias("part"), F.lit(name).alias("scheme"), "n_refs", "n_factors")
        out = c if out is None else out.unionByName(c)
    return out


def _sizes(refs: DataFrame, n: int) -> tuple[int, int]:
    """References and factors of a parse of one text of ``n`` symbols."""
    r = refs.agg(F.count("*").alias("n_refs"), F.coalesce(F.sum("len"), F.lit(0)).alias("covered")).first()
    return r["n_refs"], r["n_refs"] + n - r["covered"]


def prefix_counts(prefixes: Prefixes, min_len: int = 2) -> DataFrame:
    """``factor_counts`` of the short prefixes by the kernels, of the long ones over the cluster."""
    rows = []
    for part, (blocks, n) in prefixes.long.items():
        g = GlobalText(blocks)
        for scheme, parse in (("bidirectional", g.factors), ("unidirectional", g.unidirectional)):
            rows.append((part, scheme, *_sizes(parse(min_len), n)))
        g.scratch.clear()
    rows = prefixes.short.sparkSession.createDataFrame(rows, "part long, scheme string, n_refs long, n_factors long")
    return factor_counts(prefixes.short, min_len).unionByName(rows)


def prefix_measures(prefixes: Prefixes, dataset: str, lengths: list[int], workload: str, repeat: int = 3) -> DataFrame:
    """``compress`` of the short prefixes; the same measures of the long ones over the cluster."""
    rows = []
    for part, (blocks, n) in prefixes.long.items():

        def put(method, m, **values):
            rows.extend((workload, dataset, 1.0 / part, method, m, k, float(v)) for k, v in values.items())

        order_s, g = _timed(lambda: GlobalText(blocks), 1)
        plcp_s, v = _timed(lambda: g.scratch.save(g.plcp(), "values"), 1)
        put("arrays", 0, symbols=n, suffix_order_s=order_s, plcp_s=plcp_s)
        in_order = v.join(g.ranks, "pos").select("rank", "plcp").repartitionByRange("rank").sortWithinPartitions("rank")
        put("arrays", 0, lcp_s=_timed(lambda: g.scratch.drop(g.scratch.save(in_order, "lcp")), repeat)[0])
        g.scratch.drop(v)
        previous_s, _ = _timed(lambda: g.previous(), 1)
        gib = n / 2**30
        for m in lengths:
            seconds, (refs, ll) = _timed(lambda: _sizes(g.factors(m), n), repeat)
            put("bidirectional", m, GiB_per_h=gib / seconds * 3600, references=refs, factors=ll)
            seconds, (refs, uni) = _timed(lambda: _sizes(g.unidirectional(m), n), repeat)
            put("unidirectional", m, GiB_per_h=gib / (previous_s + seconds) * 3600, references=refs, factors=uni)
            put("bidirectional", m, factor_ratio=ll / max(1, uni))
        g.scratch.clear()
    return compress(prefixes.short, dataset, lengths, workload, repeat).unionByName(prefixes.short.sparkSession.createDataFrame(rows, MEASURES))


def disk_of(spark: SparkSession, action: Callable) -> tuple[int, float, object]:
    """Bytes that the stages of an action wrote (tables, shuffles and spills; an upper bound of the peak), seconds, and its result."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages() -> dict[int, int]:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        found = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return {x.stageId(): x.outputBytes() + x.shuffleWriteBytes() + x.diskBytesSpilled() for x in (found.apply(i) for i in range(found.size()))}

    before = stages()
    a = time.perf_counter()
    got = action()
    seconds = time.perf_counter() - a
    return sum(v for k, v in stages().items() if k not in before), seconds, got


def decompress(spark: SparkSession, prefixes: Prefixes, dataset: str, min_len: int = 2) -> DataFrame:
    """Decoding by joins of the coding of each prefix: throughput in symbols and in factors, disk, rounds, and that the text is the same.

    A long prefix is coded over the cluster and compared by digests of cells, so no row holds it.
    """
    short = {r["text_id"]: r["n"] for r in prefixes.short.select("text_id", F.length("text").alias("n")).collect()}
    rows = []
    for part in sorted([*short, *prefixes.long], reverse=True):
        scratch = Scratch(spark, "decode")
        if part in short:
            t, n = prefixes.short.where(F.col("text_id") == part), short[part]
            f = scratch.save(coding.encode(factorize.factorize(t, min_len), t), "coding")
            factors = coding.factor_counts(f).first()["n_factors"]
        else:
            blocks, n = prefixes.long[part]
            g = GlobalText(blocks)
            refs = scratch.save(g.factors(min_len), "refs")
            f = scratch.save(coding.encode_blocks(refs, blocks).withColumn("text_id", F.lit(part).cast("long")), "coding")
            factors = _sizes(refs, n)[1]
            g.scratch.clear()

        def run():
            tiles, rounds = decode.jump(f)
            pieces = scratch.save(decode.decoded_pieces(tiles, f), "pieces")
            return pieces, len(rounds)

        disk, seconds, (pieces, rounds) = disk_of(spark, run)
        if part in short:
            same = t.join(decode.in_one(pieces).withColumnRenamed("text", "decoded"), "text_id").where("text = decoded").count()
        else:
            cells = decode.cell_digests(blocks.select(F.col("start").alias("at"), F.col("body").alias("piece")))
            both = cells.join(decode.cell_digests(pieces).withColumnRenamed("digest", "decoded"), "cell", "full")
            same = int(not both.where("NOT digest <=> decoded").limit(1).count())
        values = {"GiB_per_h": n / 2**30 / seconds * 3600, "factors_per_h": factors / seconds * 3600, "disk_bytes": disk, "rounds": rounds, "same": same}
        rows += [("decoding", dataset, 1.0 / part, "jump", min_len, k, float(v)) for k, v in values.items()]
        scratch.clear()
    return spark.createDataFrame(rows, MEASURES)
