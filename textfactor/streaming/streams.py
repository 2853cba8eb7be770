"""Streams: codings of arriving texts, event letters per window, and a stateful encoder of what a key has not said before.

A bidirectional factorization needs its whole text, so a stream has one per row or per closed window; over an unbounded
text only a unidirectional coding exists, which the stateful encoder makes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.operators.factorize import factorize


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def encode_stream(texts: DataFrame, min_len: int = 2) -> DataFrame:
    """References of arriving rows; stateless, append."""
    return factorize(texts, min_len)


def letters(events: DataFrame) -> DataFrame:
    """``ts, user_id, event_id, letter``; the letter is the first one of the type."""
    return events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_id", F.upper(F.substring("event_type", 1, 1)).alias("letter"))


def window_texts(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour", session: str | None = None) -> DataFrame:
    """``start, text``: the letters of a window in time order; a session window is kept per user. Works on streams and tables."""
    e = letters(events)
    if e.isStreaming:
        e = e.withWatermark("ts", late)
    keys = [F.session_window("ts", session).alias("w"), F.col("user_id")] if session else [(F.window("ts", size, slide) if slide else F.window("ts", size)).alias("w")]
    got = e.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "letter"))).alias("x"))
    text = F.array_join(F.transform("x", lambda s: s["letter"]), "").alias("text")
    return got.select(F.col("w.start").alias("start"), *(["user_id"] if session else []), text)


def incremental_parse(old: str, new: str, min_len: int = 2) -> list[tuple[int, int, int]]:
    """(dst, len, src) references of ``new`` to anything before, positions counted over old + new, 1-based."""
    t, first = K.as_batch([K.symbols_of(old + new)])
    size, src = K.Suffixes(t, first).previous_factors()
    i, out = len(old), []
    while i < len(t):
        n = int(size[i])
        if n >= min_len:
            out.append((i + 1, n, int(src[i]) + 1))
        i += n if n >= min_len else 1
    return out


def stateful_encode(rows: DataFrame, key: str, order: str, text: str, keep: int = 1 << 16) -> DataFrame:
    """``key, dst, len, src, n``: each micro-batch of a key is coded against the last ``keep`` symbols of its earlier text."""

    def run(k: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        old = state.get[0] if state.exists else ""
        base = state.get[1] if state.exists else 0
        pdf = pd.concat(list(parts)).sort_values("ord")
        new = "".join(pdf["txt"].fillna(""))
        refs = incremental_parse(old, new)
        whole = old + new
        cut = max(0, len(whole) - keep)
        state.update((whole[cut:], base + cut))
        out = np.array(refs, np.int64).reshape(-1, 3)
        yield pd.DataFrame({"key": k[0], "dst": out[:, 0] + base, "len": out[:, 1], "src": out[:, 2] + base})

    kind = rows.schema[key].dataType.simpleString()
    part = rows.select(F.col(key).alias("key"), F.col(order).alias("ord"), F.col(text).alias("txt"))
    return part.groupBy("key").applyInPandasWithState(run, f"key {kind}, dst long, len long, src long", "text string, base long", "append", "NoTimeout")
