"""Runs a batch kernel over a collection: one Arrow pass, no shuffle."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: Symbols that one kernel call holds at least, unless the texts end; a text longer than this is a call of its own.
BATCH_SYMBOLS = 1 << 20


def batches_of(it, limit: int = BATCH_SYMBOLS):
    """(ids, texts) in slices of about ``limit`` symbols."""
    for b in it:
        texts = pc.fill_null(b.column(1), "")
        sizes = np.cumsum(pc.utf8_length(texts).to_numpy(zero_copy_only=False), dtype=np.int64) // limit
        cuts = [0, *(np.flatnonzero(np.diff(sizes)) + 1).tolist(), b.num_rows]
        for a, z in zip(cuts[:-1], cuts[1:]):
            if z > a:
                yield b.column(0).slice(a, z - a), texts.slice(a, z - a).to_pylist()


def symbol_batch(texts: list[str], unit: str) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of all texts end to end and the n + 1 bounds."""
    if unit == "byte":
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        t = np.frombuffer(b"".join(raw), np.uint8)
    elif unit == "codepoint":
        raw = texts
        t = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    else:
        raise ValueError(f"unknown unit: {unit}")
    first = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(x) for x in raw], out=first[1:])
    return t, first


def per_batch(texts: DataFrame, schema: str, kernel, unit: str = "codepoint") -> DataFrame:
    """``kernel(texts, t, first)`` returns (row, columns): which text each output row belongs to, and its values.

    ``schema``: one of ``textfactor.schemas``; its first column is the text's key, of the type it has in ``texts``.
    """
    schema = schema.format(id=texts.schema["text_id"].dataType.simpleString())
    names = [c.split()[0] for c in schema.split(", ")]

    def run(it):
        for ids, strings in batches_of(it):
            row, cols = kernel(strings, *symbol_batch(strings, unit))
            arrays = [ids.take(pa.array(row, pa.int64())), *(c if isinstance(c, pa.Array) else pa.array(c) for c in cols)]
            yield pa.RecordBatch.from_arrays(arrays, names)

    return texts.select("text_id", "text").mapInArrow(run, schema)
