"""Line deduplication over levelled sorted runs of line hashes.

The store keeps, for every line key seen, one row (128-bit hash, number of documents, largest document id) in exactly one
sorted run, a table in sorted buckets. A batch of documents is merge-anti-joined with the runs, where they lie: keys that no
run holds become the batch's own run of level 0; keys that some run holds go as increments into a ledger, which so has repeated
keys alone. ``FANOUT`` runs of a level are compacted into one of the next; their keys are disjoint, so nothing is added up.

At the end the repeated keys are sent to all executors while they are at most ``BROADCAST_KEYS``, and joined with the lines beyond
it; the result is the same.

A line's key is the line without ``[\\x20\\x09-\\x0D]`` at both ends and with A-Z lower-cased. Keys of at least ``min_chars``
code points that at least ``min_docs`` documents hold lose all their lines except in the largest document id holding it.

Defined cases: a null or empty text is one empty line; a null id counts as one document, smaller than all; rows of one id
are one document, and each keeps or loses its lines alike; an empty table gives no row; other columns are kept untouched.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.llm.scratch import Scratch, fresh, ordered_scans
from textfactor.llm.textscan import tidy

BATCHES = 5
FANOUT = 4
#: Keys whose set may be sent to all executors (24 bytes each); beyond it the lines are joined with the keys.
BROADCAST_KEYS = 400_000
_STRIP = b" \t\n\x0b\x0c\r"


def line_key(line: bytes, min_chars: int) -> bytes | None:
    """The 16-byte hash of the line's key, or None for short ones."""
    key = line.strip(_STRIP)
    if len(key) < min_chars:
        return None
    key = key.lower()
    if not key.isascii() and len(key.decode("utf-8")) < min_chars:
        return None
    return hashlib.blake2b(key, digest_size=16).digest()


def _no_null(id_col: str):
    return F.coalesce(F.col(id_col).cast("long"), F.lit(-(2**63)))


def line_hashes(docs: DataFrame, id_col: str, text_col: str, min_chars: int, batches: int) -> DataFrame:
    """``h1, h2, doc, batch``: the distinct long lines of every row."""

    def run(it):
        for b in it:
            ids, out_h, out_d = b.column(0).to_numpy(zero_copy_only=False), [], []
            for i, t in enumerate(b.column(1)):
                t = t.as_py()
                if t and len(t) >= min_chars:
                    found = {line_key(x, min_chars) for x in t.encode("utf-8").split(b"\n")}
                    found.discard(None)
                    out_h += found
                    out_d.append((ids[i], len(found)))
            h = np.frombuffer(b"".join(out_h), np.int64).reshape(-1, 2)
            d = np.repeat(np.array([x[0] for x in out_d], np.int64), [x[1] for x in out_d]) if out_d else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(h[:, 0].copy()), pa.array(h[:, 1].copy()), pa.array(d)], ["h1", "h2", "doc"])
            tidy()

    rows = docs.select(_no_null(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "h1 long, h2 long, doc long")
    return rows.withColumn("batch", F.pmod(F.xxhash64("doc"), F.lit(batches)).cast("int"))


KEYS = ["h1", "h2"]


class RunStore:
    """Levels of sorted runs and a ledger of repeated keys; all rows are (h1, h2, n, top).

    Runs, and a batch before it is compared, lie in buckets by the hash of their keys, each sorted. So a batch meets the runs of all
    levels in merge joins that neither move nor sort them; a compaction writes the runs of a level anew.
    """

    schema = "h1 long, h2 long, n long, top long"

    def __init__(self, spark: SparkSession, scratch: Scratch, fanout: int = FANOUT):
        self.spark, self.scratch, self.fanout = spark, scratch, fanout
        self.buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.levels: list[list[DataFrame]] = []
        self.ledger: list[DataFrame] = []
        self.merged: list[DataFrame] = []
        self.kept: list[DataFrame] = []

    def _sorted(self, df: DataFrame, name: str) -> DataFrame:
        with ordered_scans(self.spark):
            return self.scratch.save_sorted(df, name, KEYS, self.buckets)

    def _union(self, parts: list[DataFrame]) -> DataFrame:
        out = self.spark.createDataFrame([], self.schema) if not parts else parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def runs(self) -> list[DataFrame]:
        return [r for level in self.levels for r in level]

    def keys(self) -> DataFrame:
        return self._union(self.runs())

    def marked(self, batch: DataFrame) -> DataFrame:
        """A sorted batch and whether some run holds the key: one pass that merges the batch with all runs."""
        known = F.lit(False)
        for k, run in enumerate(self.runs()):
            batch = batch.join(run.select(*KEYS, F.lit(True).alias(f"in{k}")).hint("merge"), KEYS, "left")
            known = known | F.col(f"in{k}").isNotNull()
        return batch.select(*KEYS, "n", "top", known.alias("known"))

    def add(self, lines: DataFrame) -> DataFrame:
        """Take in a batch of (h1, h2, doc), doc ids that no earlier batch had; returns its keys that are new, to be read before the
        next batch."""
        while self.merged:
            self.scratch.drop(self.merged.pop())
        batch = self._sorted(lines.distinct().groupBy(*KEYS).agg(F.count("*").alias("n"), F.max("doc").alias("top")), "batch")
        run = batch
        if self.levels:
            both = self._sorted(self.marked(batch), "run0")
            self.scratch.drop(batch)
            self.ledger.append(both.where("known").drop("known"))
            run = both.where("not known").drop("known")
            # the ledger's rows lie in the run's files, so these stay
            self.kept.append(both)
        self._put(run, 0)
        return run

    def _put(self, run: DataFrame, level: int) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(run)
        if len(self.levels[level]) >= self.fanout:
            old = self.levels[level]
            self.levels[level] = []
            self._put(self._sorted(self._union(old).repartition(self.buckets, *KEYS), f"run{level + 1}"), level + 1)
            self.merged += [r for r in old if hasattr(r, "_scratch_path")]  # what add() has just returned may be among them

    def repeated(self, min_docs: int) -> DataFrame:
        """(h1, h2, top) of the keys that at least min_docs documents hold; a table."""
        more = self._union(self.ledger).groupBy(*KEYS).agg(F.sum("n").alias("n2"), F.max("top").alias("top2"))
        more = self._sorted(more, "repeated")
        found = []
        for run in self.runs():
            both = run.join(more.hint("merge"), KEYS, "left").where(F.col("n") + F.coalesce("n2", F.lit(0)) >= min_docs)
            found.append(both.select("h1", "h2", F.greatest("top", F.coalesce("top2", "top")).alias("top")))
        with ordered_scans(self.spark):
            return self.scratch.save(self._union(found) if found else self.spark.createDataFrame([], "h1 long, h2 long, top long"), "hot")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5, batches: int = BATCHES, n_lines: str | None = None, n_dropped: str | None = None, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """``docs`` with shortened texts and, if named, the numbers of lines before dropping and of dropped lines."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "linededup")
    lines = scratch.save(line_hashes(docs, id_col, text_col, min_chars, batches), "lines", partition_by="batch")
    store = RunStore(spark, scratch)
    for k in range(batches):
        store.add(lines.where(F.col("batch") == k).select("h1", "h2", "doc"))
    hot = store.repeated(min_docs)
    scratch.close()
    extra = [(c, "long") for c in (n_lines, n_dropped) if c]
    names, key, gone_col = docs.columns, fresh(docs, "key_of_row"), fresh(docs, "lines_to_drop")
    at, text_kind = names.index(text_col), docs.schema
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in text_kind) + "".join(f", `{c}` {k}" for c, k in extra)

    def rewrite(b, ids, doomed, extra_names):
        """``doomed(row, id, key)``: does the line go?"""
        texts, total, gone = [], [], []
        for i, t in enumerate(b.column(at)):
            t = t.as_py()
            if not t:
                texts.append(t), total.append(1), gone.append(0)
                continue
            parts = t.encode("utf-8").split(b"\n")
            kept = [x for x in parts if (h := line_key(x, min_chars)) is None or not doomed(i, ids[i], h)] if len(t) >= min_chars else parts
            texts.append(t if len(kept) == len(parts) else b"\n".join(kept).decode("utf-8"))
            total.append(len(parts)), gone.append(len(parts) - len(kept))
        cols = list(b.columns[: len(names)])
        cols[at] = pa.array(texts, pa.string())
        counts = {n_lines: total, n_dropped: gone}
        return pa.RecordBatch.from_arrays([*cols, *(pa.array(counts[c], pa.int64()) for c in extra_names)], [*names, *extra_names])

    extra_names = [c for c, _ in extra]
    if hot.count() <= broadcast_keys:
        sent = spark.sparkContext.broadcast({r[0].to_bytes(8, "little", signed=True) + r[1].to_bytes(8, "little", signed=True): r[2] for r in hot.collect()})

        def by_set(it):
            top = sent.value
            for b in it:
                ids = b.column(len(names)).to_pylist()
                yield rewrite(b, ids, lambda i, d, h: (t := top.get(h)) is not None and t != d, extra_names)

        return docs.withColumn(key, _no_null(id_col)).mapInArrow(by_set, kinds)

    doomed = (
        lines.join(hot, ["h1", "h2"])
        .where(F.col("top") != F.col("doc"))
        .groupBy("doc")
        .agg(F.collect_set(F.struct("h1", "h2")).alias(gone_col))  # a document's own lines
        .withColumnRenamed("doc", key)
    )

    def by_list(it):
        for b in it:
            gone = [
                {r["h1"].to_bytes(8, "little", signed=True) + r["h2"].to_bytes(8, "little", signed=True) for r in x or ()}
                for x in b.column(len(names)).to_pylist()
            ]
            yield rewrite(b, gone, lambda i, d, h: h in d, extra_names)

    both = docs.withColumn(key, _no_null(id_col)).join(doomed, key, "left")
    return both.select(*[F.col(f"`{c}`") for c in names], gone_col).mapInArrow(by_list, kinds)


def op6_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = dedup_lines(docs, n_lines="n_lines", n_dropped="n_dropped")
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.encode(F.coalesce("text", F.lit("")), "UTF-8"), 256).alias("kept_sha256"))


ORACLE = {
    "op6_line_dedup": r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents
), keyed AS (
  SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), hot AS (
  SELECT k, max(doc_id) AS top FROM keyed WHERE length(k) >= 40 GROUP BY k HAVING count(DISTINCT doc_id) >= 5
), marked AS (
  SELECT keyed.*, hot.k IS NOT NULL AND hot.top <> doc_id AS gone FROM keyed LEFT JOIN hot USING (k)
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
""",
}
