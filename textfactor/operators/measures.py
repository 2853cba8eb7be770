"""Cost and size measures: entropies, counts, codec sizes, throughput and the I/O model; for disk see ``experiments``."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.operators import coding, factorize
from textfactor.operators.global_text import alphabet
from textfactor.operators.runner import batches_of, symbol_batch
from textfactor.plans.scratch import Scratch
from textfactor.sources import corpus


def context_counts(texts: DataFrame, order: int, unit: str = "codepoint") -> DataFrame:
    """``context, symbol, n``: how often a symbol follows a context of ``order`` symbols (hashed) inside a text.

    Batches are counted before the shuffle, so what moves are distinct pairs of each batch.
    """

    def run(it):
        for _, strings in batches_of(it):
            t, first = symbol_batch(strings, unit)
            n = len(t)
            ctx = np.zeros(max(0, n - order), np.uint64)
            with np.errstate(over="ignore"):
                for j in range(order):
                    ctx = (ctx ^ t[j : n - order + j].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
                    ctx ^= ctx >> np.uint64(29)
            ok = np.ones(len(ctx), bool)
            for e in first[1:-1].tolist():
                ok[max(0, e - order) : e] = False
            pairs = np.column_stack([ctx[ok].view(np.int64), t[order:][ok].astype(np.int64)]) if ok.any() else np.zeros((0, 2), np.int64)
            order_ = np.lexsort((pairs[:, 1], pairs[:, 0]))
            pairs = pairs[order_]
            new = np.ones(len(pairs), bool)
            new[1:] = (pairs[1:] != pairs[:-1]).any(axis=1)
            at = np.flatnonzero(new)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[at, 0]), pa.array(pairs[at, 1]), pa.array(np.diff(np.append(at, len(pairs))))], ["context", "symbol", "n"])

    return texts.select("text_id", "text").mapInArrow(run, "context long, symbol long, n long").groupBy("context", "symbol").agg(F.sum("n").alias("n"))


def empirical_entropy(texts: DataFrame, order: int, unit: str = "codepoint") -> DataFrame:
    """``k, symbols, entropy``: bits per symbol of order k, the sum over contexts divided by all symbols."""
    pairs = context_counts(texts, order, unit)
    per = pairs.groupBy("context").agg(F.sum("n").alias("m"), F.sum(F.col("n") * F.log2("n")).alias("s"))
    size = F.sum(F.length("text") if unit == "codepoint" else F.octet_length("text")).cast("long")
    bits = per.agg(F.sum(F.col("m") * F.log2("m") - F.col("s")).alias("bits"))
    # two single rows are added up instead of joined
    both = texts.agg(size.alias("symbols")).withColumn("bits", F.lit(0.0)).unionByName(bits.withColumn("symbols", F.lit(0).cast("long")))
    both = both.agg(F.sum("symbols").alias("symbols"), F.coalesce(F.sum("bits"), F.lit(0.0)).alias("bits"))
    return both.select(F.lit(order).alias("k"), "symbols", (F.col("bits") / F.col("symbols")).alias("entropy"))


def alphabet_size(texts: DataFrame) -> DataFrame:
    return context_counts(texts, 0).agg(F.countDistinct("symbol").alias("sigma"))


def scheme_counts(texts: DataFrame, refs: DataFrame, scheme: str, min_len: int) -> DataFrame:
    """One row: references, literal characters and factors of a scheme over all texts."""
    c = coding.reference_counts(refs, texts)
    return c.agg(*(F.coalesce(F.sum(x), F.lit(0)).cast("long").alias(x) for x in ("n", "n_refs", "n_literal_chars", "n_factors"))).select(
        F.lit(scheme).alias("scheme"), F.lit(min_len).alias("min_len"), "n", "n_refs", "n_literal_chars", "n_factors"
    )


def sweep(texts: DataFrame, lengths: list[int]) -> DataFrame:
    """Counts of the bidirectional scheme for each minimum length: one scan, and one sort of the suffixes per batch.

    References of all lengths come from one kernel call over the same arrays.
    """
    from textfactor.functions import kernels as K

    def run(it):
        for _, strings in batches_of(it):
            t, first = symbol_batch(strings, "codepoint")
            s = K.Suffixes(t, first)
            v = s.plcp(s.phi())
            rows = []
            for m in lengths:
                _, size = K.rounds_factors(v, first, m)
                rows.append((m, len(t), len(size), int(len(t) - size.sum())))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], ["min_len", "n", "n_refs", "n_literal_chars"])

    out = texts.select("text_id", "text").mapInArrow(run, "min_len long, n long, n_refs long, n_literal_chars long").groupBy("min_len")
    return out.agg(*(F.sum(c).cast("long").alias(c) for c in ("n", "n_refs", "n_literal_chars"))).withColumn("n_factors", F.col("n_refs") + F.col("n_literal_chars"))


def kernel_times(texts: DataFrame, min_len: int = 2) -> DataFrame:
    """Seconds and symbols of each step, added up over all batches: suffix order, neighbours, bidirectional and
    unidirectional factorization, the last two without the construction of their arrays' inputs."""
    from textfactor.functions import kernels as K

    names = ["n", "suffixes_s", "plcp_s", "bidirectional_s", "unidirectional_s", "refs", "uni_refs"]

    def run(it):
        for _, strings in batches_of(it):
            t, first = symbol_batch(strings, "codepoint")
            c = [time.perf_counter()]
            s = K.Suffixes(t, first)
            c.append(time.perf_counter())
            v = s.plcp(s.phi())
            c.append(time.perf_counter())
            d, _ = K.rounds_factors(v, first, min_len)
            c.append(time.perf_counter())
            size, _ = s.previous_factors()
            size = np.where(size >= min_len, size, 1)
            at = K.greedy_parse(size, first)
            c.append(time.perf_counter())
            yield pa.RecordBatch.from_arrays(
                [pa.array([float(x)]) for x in (len(t), *np.diff(c), len(d), int((size[at] >= min_len).sum()))], names
            )

    return texts.select("text_id", "text").mapInArrow(run, ", ".join(f"{n} double" for n in names)).agg(*(F.sum(n).alias(n) for n in names))


@dataclass(frozen=True)
class IoModel:
    """Block transfers for n items with a memory of ``memory`` and blocks of ``block`` items."""

    memory: int
    block: int

    def scan(self, n: float) -> float:
        return n / self.block

    def sort(self, n: float) -> float:
        if n <= self.memory:
            return self.scan(n)
        return n / self.block * max(1.0, math.ceil(math.log(n / self.block, self.memory / self.block)))

    def chain(self, n: float, refs: float) -> float:
        """Factorization from stored arrays: three scans and a sort of the references."""
        return 3 * self.scan(n) + self.sort(refs)

    def jump(self, n: float, depth: float, min_len: int) -> float:
        return max(1.0, math.log2(max(2.0, depth))) * self.sort(n / min_len)

    def compaction(self, factors: float) -> float:
        return self.sort(factors)


def measure(action, repeat: int = 3) -> dict:
    """Median seconds of an action, all of them, and what its last run returned."""
    seconds, got = [], None
    for _ in range(repeat):
        a = time.perf_counter()
        got = action()
        seconds.append(time.perf_counter() - a)
    return {"seconds": float(np.median(seconds)), "all": seconds, "result": got}


def compare_schemes(texts: DataFrame, min_len: int = 2) -> DataFrame:
    """Bidirectional and unidirectional counts side by side; ``ratio``: factors of a scheme to those of the unidirectional one."""
    a = scheme_counts(texts, factorize.factorize(texts, min_len), "bidirectional", min_len)
    b = scheme_counts(texts, factorize.parse_unidirectional(texts, min_len), "unidirectional", min_len)
    both = a.unionByName(b)
    base = both.where("scheme = 'unidirectional'").select("min_len", F.col("n_factors").alias("base"))
    return both.join(base, "min_len").withColumn("ratio", F.round(F.col("n_factors") / F.col("base"), 6)).drop("base")


#: Byte sizes of general codecs beside those of the codings; the library's default levels.
CODECS = ("zlib", "zstd", "lz4", "bz2")


def codec_bytes(texts: DataFrame) -> DataFrame:
    """``codec, raw_bytes, bytes``: all texts compressed one by one by window-bounded and block-sorting codecs."""

    def run(it):
        import bz2
        import zlib

        for b in it:
            total = dict.fromkeys(CODECS, 0)
            raw = 0
            for text in b.column(1).to_pylist():
                data = (text or "").encode("utf-8", "surrogatepass")
                raw += len(data)
                total["zlib"] += len(zlib.compress(data))
                total["bz2"] += len(bz2.compress(data))
                for name in ("zstd", "lz4"):
                    total[name] += len(pa.compress(data, codec=name, asbytes=True)) if data else 0
            yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([raw] * len(total)), pa.array(list(total.values()), pa.int64())], ["codec", "raw_bytes", "bytes"])

    got = texts.select("text_id", "text").mapInArrow(run, "codec string, raw_bytes long, bytes long")
    return got.groupBy("codec").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes"))


def entropies(texts: DataFrame, orders: list[int], unit: str = "codepoint") -> DataFrame:
    """``k, symbols, entropy`` for several orders from one pass over the texts."""

    def run(it):
        for _, strings in batches_of(it):
            t, first = symbol_batch(strings, unit)
            end = np.repeat(first[1:], np.diff(first))
            ctx = np.zeros(len(t), np.uint64)
            for k in range(max(orders) + 1):
                if k:  # the context of the symbol at i + k begins at i
                    with np.errstate(over="ignore"):
                        ctx = (ctx[: len(t) - k] ^ t[k - 1 : len(t) - 1].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
                        ctx ^= ctx >> np.uint64(29)
                if k not in orders:
                    continue
                ok = np.arange(len(ctx)) + k < end[: len(ctx)]
                c, x = ctx[ok].view(np.int64), t[k:][ok].astype(np.int64)
                by = np.lexsort((x, c))
                c, x = c[by], x[by]
                new = np.concatenate([[True], (c[1:] != c[:-1]) | (x[1:] != x[:-1])]) if len(c) else np.zeros(0, bool)
                at = np.flatnonzero(new)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(at), k)), pa.array(c[at]), pa.array(x[at]), pa.array(np.diff(np.append(at, len(c))))], ["k", "context", "symbol", "n"]
                )

    pairs = texts.select("text_id", "text").mapInArrow(run, "k long, context long, symbol long, n long")
    pairs = pairs.groupBy("k", "context", "symbol").agg(F.sum("n").alias("n"))
    per = pairs.groupBy("k", "context").agg(F.sum("n").alias("m"), F.sum(F.col("n") * F.log2("n")).alias("s"))
    bits = per.groupBy("k").agg(F.sum(F.col("m") * F.log2("m") - F.col("s")).alias("bits"))
    size = texts.agg(F.sum(F.length("text") if unit == "codepoint" else F.octet_length("text")).cast("long")).first()[0] or 0
    return bits.select("k", F.lit(size).cast("long").alias("symbols"), (F.col("bits") / size).alias("entropy"))


#: Symbols of a batch; different grams that a task adds up before it sends them; symbols for each bucket of grams.
GRAM_SYMBOLS, GRAM_ROWS, BUCKET_SYMBOLS = 1 << 21, 1 << 22, 1 << 20


def _added(cols: list[np.ndarray], counts: list[np.ndarray] | None = None) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Different rows of integer columns, by the last column first, and the sums of ``counts`` (or the number of rows) for each."""
    if len(cols) == 1 and counts is None:
        cols = [np.sort(cols[0])]
    else:
        by = np.lexsort(cols) if len(cols) > 1 else np.argsort(cols[0], kind="stable")
        cols, counts = [c[by] for c in cols], [n[by] for n in counts] if counts is not None else None
    size = len(cols[0])
    new = np.ones(size, bool)
    new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in cols])
    at = np.flatnonzero(new)
    return [c[at] for c in cols], [np.diff(np.append(at, size))] if counts is None else [np.add.reduceat(n, at) for n in counts]


def _pressed(values: np.ndarray) -> bytes:
    """Integers by byte planes, compressed."""
    return pa.compress(values.astype(np.int64).view(np.uint8).reshape(-1, 8).T.tobytes(), codec="zstd", asbytes=True)


def _released(data: bytes, rows: int) -> np.ndarray:
    raw = np.frombuffer(pa.decompress(data, decompressed_size=8 * rows, codec="zstd", asbytes=True), np.uint8)
    return raw.reshape(8, rows).T.copy().view(np.int64).reshape(-1)


def _n_log_n(n: np.ndarray) -> float:
    n = n[n > 0]
    return float((n * np.log2(n)).sum())


def prefix_entropies(texts: DataFrame, parts: tuple[int, ...], orders: list[int], sep: str = "\n") -> DataFrame:
    """``part, k, symbols, entropy``: for each part p and order k, bits per symbol of the first p-th of all texts joined in key order.

    No task holds a prefix. Every symbol is counted once, with as many symbols before it as the highest order has, in the smallest prefix
    that holds it; a larger prefix adds up. Lower orders follow from the sums of the next higher one without the oldest symbol. Grams move
    once, as sorted and compressed columns, to the bucket of the latest half of their context; a bucket has all of the higher orders'
    contexts that it has any of, the lower ones are few. Contexts are exact: ``bits`` for each symbol, in as many integers as it takes; 0
    stands before the first symbol.
    """
    top = max(orders)
    half = (top + 1) // 2
    placed, begins, n = corpus.placed_texts(texts, sep, top)
    sizes = sorted({n // p for p in parts} - {0})
    schema = "part long, k long, symbols long, entropy double"
    if not sizes:
        return texts.sparkSession.createDataFrame([], schema)
    kinds = np.array(alphabet(placed.select("body")), np.int64)
    bits = len(kinds).bit_length()
    per, mask = 62 // bits, (1 << bits) - 1
    width = top // per + 1
    keys = [f"c{i}" for i in range(width)]
    names, sums = [f"n{i}" for i in range(len(sizes))], [f"b{i}" for i in range(len(sizes))]
    buckets = min(4096, n // BUCKET_SYMBOLS + 1)

    def grams(pieces, code_of):
        """The integers of all symbols of pieces ``(pad, text)``, whose first ``top`` symbols, ``pad`` missing ones among them, only stand before."""
        fill = chr(int(kinds[0]))
        size = np.array([pad + len(x) for pad, x in pieces])
        start = np.cumsum(size) - size
        raw = "".join(fill * pad + x for pad, x in pieces).encode("utf-32-le", "surrogatepass")
        code = code_of[np.frombuffer(raw, np.uint32)]
        for at, (pad, _) in zip(start.tolist(), pieces):
            code[at : at + pad] = 0
        own = np.ones(len(code), bool)
        own[(start[:, None] + np.arange(top)).ravel()] = False
        cols = []
        for i in range(width):
            g = np.zeros(len(code), np.int64)
            for j in range(i * per, min(top + 1, (i + 1) * per)):
                g[j:] |= code[: len(code) - j] << (bits * (j - i * per))
            cols.append(g[own])
        return cols

    def symbol(cols, j):
        return (cols[j // per] >> (bits * (j % per))) & mask

    def count(it):
        code_of = np.zeros(int(kinds[-1]) + 1, np.int64)
        code_of[kinds] = np.arange(1, len(kinds) + 1)
        pieces, held, made = [[] for _ in sizes], 0, [[] for _ in sizes]

        def settle():
            for i, x in enumerate(pieces):
                if x:
                    made[i].append(_added(grams(x, code_of)))
                    x.clear()

        def send():
            for i, runs in enumerate(made):
                if not runs:
                    continue
                cols, (times,) = _added([np.concatenate(c) for c in zip(*(r[0] for r in runs))], [np.concatenate([r[1][0] for r in runs])])
                made[i] = []
                h = np.zeros(len(times), np.uint64)
                for j in range(1, half + 1):
                    h = (h + symbol(cols, j).view(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
                    h ^= h >> np.uint64(29)
                to = (h % np.uint64(buckets)).astype(np.int32)
                by = np.argsort(to, kind="stable")
                cols, times, to = [c[by] for c in cols], times[by], to[by]
                cuts = [0, *(np.flatnonzero(np.diff(to)) + 1).tolist(), len(to)]
                for a in range(0, len(cuts) - 1, 64):
                    out = [(int(to[x]), i, y - x, _pressed(times[x:y]), *(_pressed(np.diff(c[x:y], prepend=0)) for c in cols)) for x, y in zip(cuts[a : a + 64], cuts[a + 1 : a + 65])]
                    kinds_ = [pa.int32(), pa.int32(), pa.int64(), *[pa.binary()] * (1 + width)]
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds_)], ["bucket", "band", "rows", "n", *keys])

        for b in it:
            for part, off, before, body in zip(*(c.to_pylist() for c in b.columns)):
                base, tail = begins[part]
                at = base + off
                lead = (tail + before)[-top:] if top else ""
                text, zero = lead + body, at - len(lead)
                for i, (low, high) in enumerate(zip([0, *sizes], sizes)):
                    a, z = max(at, low), min(at + len(body), high)
                    if a < z:
                        begin = max(zero, a - top)
                        pieces[i].append((top - (a - begin), text[begin - zero : z - zero]))
                held += len(body)
                if held >= GRAM_SYMBOLS:
                    settle()
                    held = 0
                    if sum(len(r[1][0]) for runs in made for r in runs) >= GRAM_ROWS:
                        yield from send()
        settle()
        yield from send()

    def solve(table):
        """The sums of the higher orders' contexts in a bucket, one row for each order, and its grams of the highest of the others."""
        rows, band = table["rows"].to_pylist(), table["band"].to_pylist()
        times, *cols = ([_released(x, r) for x, r in zip(table[c].to_pylist(), rows)] for c in ["n", *keys])
        times, cols = np.concatenate(times), [np.concatenate([np.cumsum(x) for x in c]) for c in cols]
        band = np.repeat(np.array(band), rows)
        cols, counts = _added(cols, [np.where(band <= i, times, 0) for i in range(len(sizes))])
        got = []
        for k in range(top, half - 1, -1):
            ok = symbol(cols, k) > 0 if k else np.ones(len(cols[0]), bool)
            if k in orders and ok.any():
                own, mine = [cols[0][ok] & ~mask, *(c[ok] for c in cols[1:])], [x[ok] for x in counts]
                new = np.ones(len(own[0]), bool)
                new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in own])
                at = np.flatnonzero(new)
                got.append((k, *[0] * (width + 1), *(int(x.sum()) for x in mine), *(_n_log_n(np.add.reduceat(x, at)) - _n_log_n(x) for x in mine)))
            if k:
                cols[k // per] = cols[k // per] & ~(mask << (bits * (k % per)))
                cols, counts = _added(cols, counts)
        types = [pa.int64()] * (2 + width + len(sizes)) + [pa.float64()] * len(sizes)
        out = [pa.array(c, t) for c, t in zip(zip(*got), types)] if got else [pa.array([], t) for t in types]
        if half:
            zero = np.zeros(len(cols[0]))
            low = [np.full(len(zero), half - 1), cols[0] & ~mask, *cols[1:], cols[0] & mask, *counts, *[zero] * len(sizes)]
            out = [pa.chunked_array([a, pa.array(b, t)]) for a, b, t in zip(out, low, types)]
        return pa.table(dict(zip(["k", *keys, "s", *names, *sums], out)))

    scratch = Scratch(texts.sparkSession, "grams")
    sent = placed.select("part", "off", "before", "body").mapInArrow(count, "bucket int, band int, rows long, n binary, " + ", ".join(f"{c} binary" for c in keys))
    longs = ", ".join(f"{c} long" for c in ["k", *keys, "s", *names])
    solved = scratch.save(sent.groupBy("bucket").applyInArrow(solve, longs + "".join(f", {c} double" for c in sums)), "solved")
    found = {r["k"]: r for r in solved.where(F.col("k") >= half).groupBy("k").agg(*(F.sum(c).alias(c) for c in [*names, *sums])).collect()}
    now = solved.where(F.col("k") < half)
    for k in range(half - 1, -1, -1):
        key, shift = keys[k // per], bits * (k % per)
        now = scratch.save(now.groupBy(*keys, "s").agg(*(F.sum(c).alias(c) for c in names)), "pairs")
        if k in orders:
            valid = now.where(F.shiftright(key, shift).bitwiseAND(F.lit(mask)) > 0) if k else now
            of_context = [x for c in names for x in (F.sum(c).alias(c), F.sum(F.col(c) * F.log2(c)).alias(f"s{c}"))]
            both = [x for b, c in zip(sums, names) for x in (F.sum(c).alias(c), F.sum(F.col(c) * F.log2(c) - F.col(f"s{c}")).alias(b))]
            found[k] = valid.groupBy(*keys).agg(*of_context).agg(*both).first()
        now = now.withColumn(key, F.col(key).bitwiseAND(F.lit(~(mask << shift)))) if k else now
    at = {p: sizes.index(n // p) for p in parts if n // p}
    rows = [(p, k, n // p, r[sums[i]] / (n // p)) for k, r in found.items() for p, i in at.items() if r[names[i]]]
    return texts.sparkSession.createDataFrame(rows, schema)
