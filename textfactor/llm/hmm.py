"""Hidden Markov language model over word classes, and an additive unigram model as its base.

A word's class is a hash of its last bytes; the end of a text is a class of its own. Latent states emit classes, a class
emits its words with additive smoothing, so

    P(text) = P_hmm(classes of its tokens) * product of P(word | class),

a proper model of whole token sequences. Baum-Welch: the executors run forward and backward passes over the class sequences
of all training texts, cut into pieces of ``PIECE`` tokens, and their expected counts are added up by Spark; a fixed number of
rounds. A text's likelihood is computed by the scaled forward recursion over the whole text.

Word counts are exact over all training texts. Counts of at most ``HEAD`` frequent words travel to the executors; the
words of a text that are not among them are joined with the count table by a shuffle, which holds each word of a text once.

Defined cases: a null or empty text has the end as its only token; a null id is hashed as an empty string; rows that
repeat are separate texts; without training texts all counts are 0; an empty table gives no row; other columns are
ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import Scratch
from textfactor.llm.textscan import Words, pieces

STATES = 8
CLASSES = 1024  # class 0 is the end of a text
TAIL = 3
PIECE = 128
ROUNDS = 5
HEAD = 400_000
ADD = 0.1
END = 0x0E0D  # stands for the end among the word hashes


def _classes(w: Words) -> np.ndarray:
    return (w.tail % np.uint64(CLASSES - 1)).astype(np.uint16) + np.uint16(1)


def _word_counts(texts: DataFrame) -> DataFrame:
    """(h, cls, n) of the training texts, not yet added up."""

    def run(batches):
        for b in (p for batch in batches for p in pieces(batch, 0)):
            w = Words(b.column(0), tail=TAIL)
            h, first, n = np.unique(w.hash, return_index=True, return_counts=True)
            cls = _classes(w)[first]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.append(h.view(np.int64), END)),
                    pa.array(np.append(cls, 0).astype(np.int32)),
                    pa.array(np.append(n, b.num_rows).astype(np.int64)),
                ],
                ["h", "cls", "n"],
            )

    return texts.mapInArrow(run, "h long, cls int, n long")


def _class_sequences(texts: DataFrame) -> DataFrame:
    """Class sequences of whole texts, each with its end, as little-endian 16-bit numbers."""

    def run(batches):
        for b in (p for batch in batches for p in pieces(batch, 0)):
            w = Words(b.column(0), tail=TAIL)
            cls, first = _classes(w), w.first.tolist()
            end = np.zeros(1, np.uint16).tobytes()
            seq = [cls[u:v].tobytes() + end for u, v in zip(first[:-1], first[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(seq, pa.binary())], ["seq"])

    return texts.mapInArrow(run, "seq binary")


class Hmm:
    """``start`` (K), ``move`` (K x K) and ``emit`` (K x CLASSES), rows sum to 1; ``inside`` starts a piece within a text."""

    def __init__(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray, inside: np.ndarray):
        self.start, self.move, self.emit, self.inside = start, move, emit, inside

    @classmethod
    def initial(cls, class_counts: np.ndarray, states: int = STATES, seed: int = 5) -> "Hmm":
        rng = np.random.default_rng(seed)
        emit = (class_counts + 1.0)[None, :] * rng.gamma(1.0, size=(states, len(class_counts)))
        move = np.full((states, states), 0.1 / max(states - 1, 1))
        np.fill_diagonal(move, 0.9 if states > 1 else 1.0)
        even = np.full(states, 1.0 / states)
        return cls(even, move, emit / emit.sum(1, keepdims=True), even)

    def expected(self, pieces: np.ndarray, opens: np.ndarray, total: np.ndarray) -> None:
        """Add the expected counts of a (PIECE x n) block to ``total``; class CLASSES pads, ``opens``: starts a text."""
        k, (steps, n) = len(self.start), pieces.shape
        move = self.move.astype(np.float32)
        emit = np.vstack([self.emit.T, np.ones((1, k))]).astype(np.float32)
        alpha = np.empty((steps, n, k), np.float32)
        scale = np.empty((steps, n), np.float32)
        a = np.where(opens[:, None], self.start, self.inside).astype(np.float32)
        for t in range(steps):
            a = (a if t == 0 else a @ move) * emit[pieces[t]]
            c = np.maximum(a.sum(1), np.float32(1e-30))
            a = a / c[:, None]
            alpha[t], scale[t] = a, c
        at_start, at_inside, trans = total[:k], total[k : 2 * k], total[2 * k : 2 * k + k * k].reshape(k, k)
        beta = np.ones((n, k), np.float32)
        for t in range(steps - 1, 0, -1):
            e = emit[pieces[t]] * beta / scale[t][:, None]
            real = pieces[t] < CLASSES
            trans += self.move * (alpha[t - 1][real].T @ e[real])
            alpha[t] *= beta
            beta = e @ move.T
        alpha[0] *= beta
        at_start += alpha[0][opens].sum(0)
        at_inside += alpha[0][~opens].sum(0)
        flat = pieces.ravel()
        out = total[2 * k + k * k : -1].reshape(k, CLASSES)
        alpha = alpha.reshape(-1, k)
        for s in range(k):
            out[s] += np.bincount(flat, alpha[:, s], CLASSES + 1)[:CLASSES]
        total[-1] += np.log(scale[pieces < CLASSES]).sum(dtype=np.float64)

    def updated(self, total: np.ndarray) -> "Hmm":
        k = len(self.start)
        norm = lambda x, add: (x + add) / (x + add).sum(-1, keepdims=True)
        emit = total[2 * k + k * k : -1].reshape(k, CLASSES)
        return Hmm(norm(total[:k], 0.1), norm(total[2 * k : 2 * k + k * k].reshape(k, k), 0.1), norm(emit, 0.02), norm(emit.sum(1), 0.1))

    def log10(self, cls: np.ndarray, first: np.ndarray) -> np.ndarray:
        """log10 probability of every sequence ``cls[first[i]:first[i + 1]]`` by the scaled forward recursion."""
        length = np.diff(first)
        order = np.argsort(-length, kind="stable")
        begin, length = first[:-1][order], length[order]
        emit = np.ascontiguousarray(self.emit.T)
        out = np.zeros(len(order))
        a = np.broadcast_to(self.start, (len(order), len(self.start)))
        alive = np.searchsorted(-length, -np.arange(1, (length[0] if len(length) else 0) + 1), "right")
        for t, n in enumerate(alive.tolist()):
            a = (a[:n] if t == 0 else a[:n] @ self.move) * emit[cls[begin[:n] + t]]
            c = a.sum(1)
            a = a / c[:, None]
            out[:n] += np.log10(c)
        back = np.empty(len(order))
        back[order] = out
        return back


def _blocks(seqs, width: int = 2048):
    """(PIECE x n) blocks of pieces and their opening flags."""
    pieces, opens = [], []

    def block():
        out = np.full((len(pieces), PIECE), CLASSES, np.int64)
        for i, p in enumerate(pieces):
            out[i, : len(p)] = p
        flags = np.array(opens)
        pieces.clear(), opens.clear()
        return np.ascontiguousarray(out.T), flags

    for s in seqs:
        for u in range(0, len(s), PIECE):
            pieces.append(s[u : u + PIECE])
            opens.append(u == 0)
            if len(pieces) == width:
                yield block()
    if pieces:
        yield block()


def baum_welch(seqs: DataFrame, class_counts: np.ndarray, rounds: int = ROUNDS, states: int = STATES) -> tuple[Hmm, list[float]]:
    """The model after ``rounds`` rounds over all sequences, and the log likelihood that each round started from."""
    model = Hmm.initial(class_counts, states)
    size = 2 * states + states * states + states * CLASSES + 1
    trace = []
    for _ in range(rounds):

        def run(batches, model=model):
            total = np.zeros(size)
            for b in batches:
                found = (np.frombuffer(x.as_buffer(), np.uint16) for x in b.column(0))
                for block, opens in _blocks(found):
                    model.expected(block, opens, total)
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["i", "v"])

        total = np.zeros(size)
        for r in seqs.mapInArrow(run, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).toLocalIterator():
            total[r["i"]] = r["v"]
        trace.append(float(total[-1]))
        model = model.updated(total)
    return model, trace


def score_texts(docs: DataFrame, train_where, id_col: str = "doc_id", text_col: str = "text", rounds: int = ROUNDS, head: int = HEAD) -> DataFrame:
    """``id, held_out, n_tokens, n_known, train_tokens, base_score, score``; ``train_where``: a condition on ``docs``."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "hmm")
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), (~train_where).alias("held_out"))
    train = rows.where(~F.col("held_out")).select("text")
    vocab = scratch.save(_word_counts(train).groupBy("h").agg(F.min("cls").alias("cls"), F.sum("n").alias("n")), "vocab")
    in_class = np.zeros(CLASSES)
    kinds = np.zeros(CLASSES)
    for r in vocab.groupBy("cls").agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect():
        in_class[r["cls"]], kinds[r["cls"]] = r["n"], r["v"]
    n_train, n_kinds = int(in_class.sum()), int(kinds.sum())
    seqs = scratch.save(_class_sequences(train), "classes")
    model, _ = baum_welch(seqs, in_class, rounds)
    scratch.drop(seqs)

    # the lowest power of two such that the words at least so frequent fit the bound
    level = F.floor(F.log2("n")).cast("int")
    least, fits = 62, 0
    for r in vocab.groupBy(level.alias("b")).agg(F.count("*").alias("v")).orderBy(F.desc("b")).collect():
        if fits + r["v"] > head:
            break
        fits, least = fits + r["v"], r["b"]
    top = vocab.where(F.col("n") >= (1 << least)).select("h", "n").toPandas()  # at most `head` rows
    h, n = top["h"].to_numpy(np.int64), top["n"].to_numpy(np.int64)
    order = np.argsort(h)
    sent = spark.sparkContext.broadcast((h[order], np.log10(n[order] + ADD), model))
    class_norm = np.log10(in_class + ADD * (kinds + 1))

    def run(batches):
        keys, logs, model = sent.value
        part, seen = TaskContext.get().partitionId(), 0
        for batch in batches:
            for b in pieces(batch, 1, 6 << 20):
                w = Words(b.column("text"), tail=TAIL)
                m, first = b.num_rows, w.first
                cls = np.insert(_classes(w), first[1:], 0)
                bounds = first + np.arange(m + 1)
                model_log = model.log10(cls, bounds) - np.add.reduceat(class_norm[cls], bounds[:-1]) if m else np.zeros(0)
                hs = np.insert(w.hash.view(np.int64), first[1:], END)
                row = np.repeat(np.arange(m), np.diff(bounds))
                pos = np.searchsorted(keys, hs)
                pos[pos == len(keys)] = 0
                hit = keys[pos] == hs if len(keys) else np.zeros(len(hs), bool)
                log_head = np.bincount(row[hit], logs[pos[hit]], m) if len(keys) else np.zeros(m)
                known = np.bincount(row[hit], minlength=m)
                rest_h, rest_row = hs[~hit], row[~hit]
                o = np.lexsort((rest_h, rest_row))
                rest_h, rest_row = rest_h[o], rest_row[o]
                fresh = np.ones(len(o), bool)
                fresh[1:] = (rest_h[1:] != rest_h[:-1]) | (rest_row[1:] != rest_row[:-1])
                starts = np.flatnonzero(fresh)
                times = np.diff(np.append(starts, len(o)))
                cut = np.searchsorted(rest_row[starts], np.arange(m + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array((part << 36) + seen + np.arange(m)),
                        b.column("id"),
                        b.column("held_out"),
                        pa.array(np.diff(bounds)),
                        pa.array(known.astype(np.int64)),
                        pa.array(log_head),
                        pa.array(model_log),
                        pa.ListArray.from_arrays(pa.array(cut), pa.array(rest_h[starts])),
                        pa.ListArray.from_arrays(pa.array(cut), pa.array(times.astype(np.int32))),
                    ],
                    ["row", "id", "held_out", "n_tokens", "known", "log_head", "model_log", "rest", "times"],
                )
                seen += m

    kind = rows.schema["id"].dataType.simpleString()
    part = rows.mapInArrow(
        run, f"row long, id {kind}, held_out boolean, n_tokens long, known long, log_head double, model_log double, rest array<long>, times array<int>"
    )
    part = scratch.save(part, "scored")
    rest = part.select("row", F.explode(F.arrays_zip("rest", "times")).alias("w")).select("row", F.col("w.rest").alias("h"), F.col("w.times").alias("t"))
    rare = vocab.where(F.col("n") < (1 << least)).select("h", "n")
    tail = (
        rest.join(rare, "h", "left")
        .groupBy("row")
        .agg(
            F.sum(F.col("t") * F.log10(F.coalesce("n", F.lit(0)) + F.lit(ADD))).alias("log_tail"),
            F.sum(F.when(F.col("n").isNotNull(), F.col("t")).otherwise(0)).alias("known_tail"),
        )
    )
    words_log = F.col("log_head") + F.coalesce("log_tail", F.lit(0.0))
    norm = float(np.log10(n_train + ADD * (n_kinds + 1)))
    return (
        part.drop("rest", "times")
        .join(tail, "row", "left")
        .select(
            F.col("id").alias(id_col),
            "held_out",
            "n_tokens",
            (F.col("known") + F.coalesce("known_tail", F.lit(0))).cast("long").alias("n_known"),
            F.lit(n_train).cast("long").alias("train_tokens"),
            (words_log - F.col("n_tokens") * F.lit(norm)).alias("base_score"),
            (words_log + F.col("model_log")).alias("score"),
        )
    )


def op7_lm_scoring(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    fold = F.crc32(F.encode(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), "UTF-8")) % 10
    return score_texts(docs, fold != 0)
