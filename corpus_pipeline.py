"""The corpus pipeline: five stages over ``documents``, each written as Parquet and reread as the next one's input.

Part of subpackage ``llm``; deleted with it. A stage takes (spark, docs, sf_dir) and returns the columns of ``docs``, the last
one the encoded documents. Nulls, empty texts, repeated rows and empty tables are as in the operators' docstrings.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.llm.bpe import encode_texts
from textfactor.llm.decontaminate import drop_contaminated
from textfactor.llm.jaccard import Rule, link_documents
from textfactor.llm.linededup import dedup_lines
from textfactor.llm.quality import THRESHOLD, fit, score
from textfactor.llm.scratch import Scratch, fresh, small_side


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go; it learns from the labelled documents outside of fold 0."""
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    name = fresh(docs, "score")
    return score(docs, model, score_col=name).where(F.col(name) >= THRESHOLD).drop(name)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Long lines that at least five documents hold stay in one of them; ``n_chars`` follows the text."""
    out = dedup_lines(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group linked by five-word shingles with a Jaccard similarity of 0.8 or more stays: the one with the
    smallest doc_id (null last), then the smallest hash of its text; of fully equal ones any. Rows without words are no group and stay."""
    scratch = Scratch(spark, "near-dedup")
    linked = link_documents(docs, Rule(k=5, num=80, den=100)).where(F.col("component").isNotNull())
    texts = linked.groupBy("component", "id", "text_hash").agg(F.count("*").alias("rows"))
    texts = texts.withColumn("place", F.struct(F.col("id").isNull(), "id", "text_hash"))
    best = texts.groupBy("component").agg(F.min("place").alias("best"))
    texts = texts.join(best, "component").withColumn("stays", F.col("place") == F.col("best")).where("not stays or rows > 1")
    id_, hash_, stays = fresh(docs, "id_of"), fresh(docs, "text_hash"), fresh(docs, "stays")
    marks = texts.select(F.col("id").alias(id_), F.col("text_hash").alias(hash_), F.col("stays").alias(stays))
    marks = scratch.save(marks, "marks")
    rows = docs.withColumn(hash_, F.xxhash64("text"))
    marked = rows.join(small_side(marks), hash_).where(F.col("doc_id").eqNullSafe(F.col(id_)))
    again = marked.where(stays).dropDuplicates(["doc_id", hash_])
    other = rows.join(small_side(marks), (rows[hash_] == marks[hash_]) & rows["doc_id"].eqNullSafe(marks[id_]), "left_anti")
    kept = other.select(*docs.columns)
    return kept.unionByName(again.select(*docs.columns)) if marks.where(stays).limit(1).count() else kept


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256, token_ids`` of every document that is left."""
    return encode_texts(docs)


STAGES = [
    ("quality classifier", quality_filter),
    ("line dedup", line_dedup),
    ("n-gram Jaccard join", near_dedup),
    ("benchmark decontamination", decontaminate),
    ("BPE encoding and decoding", bpe),
]

#: The classifier and the encoder cannot be written in SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = scratch.save(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
