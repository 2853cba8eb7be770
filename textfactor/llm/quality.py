"""Quality classifier: hashed word and character n-gram vectors, averaged per document, softmax output.

Features of a text are its words, its byte n-grams (``GRAMS``) and its word pairs, each hashed into one of ``BUCKETS`` rows of
a vector table; row 0 is a bias that every text has. In a pair, a word that repeats the one before is written as a sign for
"the same", so that all repetitions share a row. Vectors and output weights are learned together by stochastic gradient descent
in numpy, one document a step. As the output is a softmax over an average, a trained model is folded into one
number per bucket, so a whole text is scored by a gather and a mean.

Training documents: at most ``bound`` labelled documents, those with the smallest hashes of their ids; every one is used
with its whole text as a sparse count vector (made on the executors, at most ``BUCKETS`` entries a document). Scoring covers
all documents and whole texts.

Defined cases: a null or empty text has the bias alone; a null id is hashed as an empty string; of several labels for one id
the largest counts and null labels are ignored; without labels of both kinds the score is the share of good labels, or
0.5 without labels; an empty table gives no row; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import bounded_batches
from textfactor.llm.textscan import Words, mix, pieces, text_bytes

BUCKETS = 1 << 17
GRAMS = (2, 4)
DIM = 12
BOUND = 4000
THRESHOLD = 0.3
_SLICE = 1 << 18
#: What stands for a pair of one word twice.
_SAME = np.uint64(0x5851F42D4C957F2D)


def fold_of(id_col: str, folds: int) -> Column:
    """crc32 of the id as text, modulo the number of folds."""
    return F.crc32(F.encode(F.coalesce(F.col(id_col).cast("string"), F.lit("")), "UTF-8")) % folds


def feature_rows(column: pa.Array):
    """For every row the buckets of its features, repeated as they occur; cases of letters are kept apart in n-grams."""
    data, off = text_bytes(column)
    words = Words(column)
    word_bucket = (words.hash % np.uint64(BUCKETS - 1)).astype(np.int32) + 1
    with np.errstate(over="ignore"):
        pair = mix(words.hash[:-1] * np.uint64(0xD6E8FEB86659FD93) + words.hash[1:], 21)
    pair = np.where(words.hash[1:] == words.hash[:-1], _SAME, pair)
    pair_bucket = np.zeros(len(word_bucket), np.int32)
    pair_bucket[1:] = (pair % np.uint64(BUCKETS - 1)).astype(np.int32) + 1
    bounds = off.tolist()
    for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:])):
        u, v = words.first[i], words.first[i + 1]
        yield i, _grams(data[a:b]), np.concatenate([word_bucket[u:v], pair_bucket[u + 1 : v]])


def _grams(raw: np.ndarray):
    """Buckets of all n-grams of a text, piece by piece."""
    for n in GRAMS:
        for a in range(0, max(0, len(raw) - n + 1), _SLICE):
            part = raw[a : a + _SLICE + n - 1].astype(np.uint32)
            code = part[: len(part) - n + 1].copy()
            for k in range(1, n):
                code |= part[k : k + len(code)] << np.uint32(8 * k)
            code *= np.uint32(0x9E3779B1)
            code ^= code >> np.uint32(15)
            code *= np.uint32(2 * n + 0x85EBCA6B)
            yield ((code >> np.uint32(8)) % np.uint32(BUCKETS - 1)).astype(np.int32) + 1


def pack(counts: np.ndarray) -> tuple[bytes, bytes]:
    """The buckets of a document, ascending, and their counts: 16 low bits each behind the number of those under 2**16, and as few
    bytes a count as the largest needs."""
    at = np.flatnonzero(counts)
    low = np.array([np.searchsorted(at, 1 << 16)], np.int32).tobytes()
    return low + at.astype(np.uint16).tobytes(), counts[at].astype(np.min_scalar_type(int(counts.max(initial=0)))).tobytes()


def unpack(buckets: bytes, counts: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The buckets and their shares of the document."""
    low = np.frombuffer(buckets[:4], np.int32)[0]
    at = np.frombuffer(buckets, np.uint16, offset=4).astype(np.int32)
    at[low:] += 1 << 16
    c = np.frombuffer(counts, f"u{len(counts) // len(at)}").astype(np.float32)
    return at, c / c.sum()


def sparse_counts(docs: DataFrame) -> DataFrame:
    """``id, label, text`` to ``id, label, buckets, counts``, the last two packed."""

    def run(batches):
        for batch in batches:
            cols = [[], []]
            for _, grams, words in feature_rows(batch.column("text")):
                c = np.bincount(words, minlength=BUCKETS)
                for g in grams:
                    c += np.bincount(g, minlength=BUCKETS)
                c[0] = 1
                for col, x in zip(cols, pack(c)):
                    col.append(x)
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), batch.column("label"), *(pa.array(x, pa.binary()) for x in cols)], ["id", "label", "buckets", "counts"]
            )

    kind = docs.schema["id"].dataType.simpleString()
    return docs.select("id", "label", "text").mapInArrow(run, f"id {kind}, label int, buckets binary, counts binary")


class Model:
    """``weight[b]``: what one feature of bucket b adds to the mean log odds of the good class."""

    def __init__(self, weight: np.ndarray):
        self.weight = weight

    def scores(self, column: pa.Array) -> np.ndarray:
        out = np.empty(len(column))
        for i, grams, words in feature_rows(column):
            total, n = float(self.weight[0]) + self.weight[words].sum(dtype=np.float64), 1 + len(words)
            for g in grams:
                total += self.weight[g].sum(dtype=np.float64)
                n += len(g)
            out[i] = 1.0 / (1.0 + np.exp(-np.clip(total / n, -50, 50)))
        return out


def loss_and_gradients(rows: np.ndarray, out: np.ndarray, y: int, x: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Log loss of a document with feature vectors ``rows`` of shares ``x``, and its gradients at ``out`` and at the average."""
    hidden = x @ rows
    z = out @ hidden
    p = np.exp(z - z.max())
    p /= p.sum()
    loss = -np.log(p[y])
    p[y] -= 1.0
    return float(loss), np.outer(p, hidden), p @ out


def train(rows: list[tuple[int, bytes, bytes]], epochs: int = 8, rate: float = 0.5, seed: int = 11) -> Model:
    """Stochastic gradient descent over (label, buckets, counts), the last two packed."""
    labels = np.array([r[0] for r in rows])
    share = labels.mean() if len(labels) else 0.5
    if len(set(labels.tolist())) < 2:
        p = min(max(share, 1e-6), 1 - 1e-6)
        return Model(np.full(BUCKETS, np.log(p / (1 - p)), np.float32))
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-1 / DIM, 1 / DIM, (BUCKETS, DIM)).astype(np.float32)
    out = rng.normal(0, 1, (2, DIM)).astype(np.float32)
    steps, t = epochs * len(rows), 0
    for _ in range(epochs):
        for i in rng.permutation(len(rows)):
            y, (b, x) = int(rows[i][0]), unpack(*rows[i][1:])
            step = rate * (1 - t / steps) + 1e-3
            t += 1
            _, at_out, at_hidden = loss_and_gradients(vectors[b], out, y, x)
            out -= step * at_out
            # the mean's gradient is shared by all its features; scaled so that a feature's step does not vanish with length
            vectors[b] -= (step * x * min(len(b), 400))[:, None] * at_hidden[None, :]
    return Model(vectors @ (out[1] - out[0]))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", folds: int = 5, bound: int = BOUND) -> Model:
    """Learn from labelled documents whose id is not in fold 0; at most ``bound`` of them."""
    bounded_batches(docs.sparkSession)
    known = (
        labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label"))
        .where(F.col("label").isNotNull() & (fold_of("id", folds) != 0))
        .groupBy("id")
        .agg(F.max("label").alias("label"))
        .orderBy(F.xxhash64("id"), "id")
        .limit(bound)
    )
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    # at most `bound` rows of two integers
    sample = texts.join(F.broadcast(known), "id")
    # what the driver holds is `bound` sparse vectors, as packed bytes
    rows = [(str(r["id"]), bytes(r["counts"]), bytes(r["buckets"]), r["label"]) for r in sparse_counts(sample).collect()]
    rows.sort(key=lambda r: r[:3])  # the order of partitions doesn't matter
    return train([(y, b, c) for _, c, b, y in rows])


def score(docs: DataFrame, model: Model, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All columns of ``docs`` and the score."""
    bounded_batches(docs.sparkSession)
    spark, names = docs.sparkSession, docs.columns
    sent = spark.sparkContext.broadcast(model.weight)  # BUCKETS numbers
    at = names.index(text_col)

    def run(batches):
        model = Model(sent.value)
        for b in (p for batch in batches for p in pieces(batch, at)):
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(model.scores(b.column(at)), pa.float64())], [*names, score_col])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(run, f"{kinds}, `{score_col}` double")


def op5_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    s = score(docs, model)
    return s.select(
        "doc_id", (fold_of("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )
