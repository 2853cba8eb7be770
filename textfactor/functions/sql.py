"""SQL surface: scalar functions and table functions over single texts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from textfactor.functions import kernels as K

_CODING = "array<struct<dst:bigint,len:bigint,src:bigint,literal:string>>"


def coding_of(text: str, min_len: int = 2) -> list[tuple[int, int, int | None, str | None]]:
    """(dst, len, src, literal) of one text, 1-based, literal runs included."""
    t, first = K.as_batch([K.symbols_of(text)])
    s = K.Suffixes(t, first)
    phi = s.phi()
    dst, size = K.rounds_factors(s.plcp(phi), first, min_len)
    out, at = [], 0
    for d, n in zip(dst.tolist(), size.tolist()):
        if d > at:
            out.append((at + 1, d - at, None, text[at:d]))
        out.append((d + 1, n, int(phi[d]) + 1, None))
        at = d + n
    if at < len(text):
        out.append((at + 1, len(text) - at, None, text[at:]))
    return out


def text_of(coding) -> str:
    n = sum(c["len"] for c in coding)
    refs = np.array([(c["dst"] - 1, c["src"] - 1, c["len"]) for c in coding if c["src"] is not None], np.int64).reshape(-1, 3)
    parent = K.char_parents(n, refs[:, 0], refs[:, 1], refs[:, 2])
    root, _ = K.resolve(parent)
    chars = np.zeros(n, np.uint32)
    for c in coding:
        if c["src"] is None:
            chars[c["dst"] - 1 : c["dst"] - 1 + c["len"]] = np.frombuffer(c["literal"].encode("utf-32-le"), np.uint32)
    return chars[root].tobytes().decode("utf-32-le")


def register(spark: SparkSession) -> None:
    """``bd_encode, bd_decode, bd_n_factors, bd_longest_repeat, bd_entropy, bd_group_factors`` and tables ``bd_factors, bd_arrays``."""

    @pandas_udf(_CODING)
    def bd_encode(text: pd.Series, min_len: pd.Series) -> pd.Series:
        return pd.Series([[dict(zip(("dst", "len", "src", "literal"), c)) for c in coding_of(t or "", int(m))] for t, m in zip(text, min_len)])

    @pandas_udf("string")
    def bd_decode(coding: pd.Series) -> pd.Series:
        return coding.map(text_of)

    @pandas_udf("bigint")
    def bd_n_factors(text: pd.Series, min_len: pd.Series) -> pd.Series:
        return pd.Series([sum(1 if c[2] is not None else c[1] for c in coding_of(t or "", int(m))) for t, m in zip(text, min_len)])

    @pandas_udf("string")
    def bd_longest_repeat(text: pd.Series) -> pd.Series:
        def one(t):
            x, first = K.as_batch([K.symbols_of(t or "")])
            s = K.Suffixes(x, first)
            v = s.plcp(s.phi())
            return t[int(v.argmax()) : int(v.argmax()) + int(v.max())] if len(v) else ""

        return text.map(one)

    @pandas_udf("double")
    def bd_entropy(text: pd.Series, order: pd.Series) -> pd.Series:
        def one(t, k):
            t = t or ""
            if len(t) <= k:
                return 0.0
            pairs = pd.Series([t[i : i + k + 1] for i in range(len(t) - k)]).value_counts()
            ctx = pairs.groupby(pairs.index.str[:k]).transform("sum")
            return float(-(pairs * np.log2(pairs / ctx)).sum() / len(t))

        return pd.Series([one(t, int(k)) for t, k in zip(text, order)])

    @pandas_udf("bigint")
    def bd_group_factors(text: pd.Series) -> int:
        return sum(1 if c[2] is not None else c[1] for c in coding_of("\n".join(text.fillna("")), 2))

    for f in (bd_encode, bd_decode, bd_n_factors, bd_longest_repeat, bd_entropy, bd_group_factors):
        spark.udf.register(f.__name__, f)

    @udtf(returnType="factor_no: bigint, dst: bigint, len: bigint, src: bigint, literal: string")
    class BdFactors:
        def eval(self, text: str, min_len: int) -> Iterator[tuple]:
            for i, c in enumerate(coding_of(text or "", min_len)):
                yield (i + 1, *c)

    @udtf(returnType="pos: bigint, isa: bigint, phi: bigint, plcp: bigint")
    class BdArrays:
        def eval(self, text: str) -> Iterator[tuple]:
            t, first = K.as_batch([K.symbols_of(text or "")])
            s = K.Suffixes(t, first)
            phi, n = s.phi(), len(t)
            v = s.plcp(phi)
            rank = np.empty(n, np.int64)
            rank[s.order] = np.arange(n) + 2
            for i in range(n):
                yield i + 1, int(rank[i]), int(phi[i]) + 1, int(v[i])
            yield n + 1, 1, n + 1, 0

    spark.udtf.register("bd_factors", BdFactors)
    spark.udtf.register("bd_arrays", BdArrays)
