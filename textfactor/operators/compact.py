"""Shorter reference chains: redirect references through factors that hold their whole source.

Edges to a holding factor form a forest. Pointer doubling finds, for every factor, the root of its tree and the sum of the
shifts (source minus destination) on the way, so all chains are redirected in logarithmically many joins. Borders and
literals stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.operators.graph import dependency_edges
from textfactor.plans.scratch import Scratch


def _holders(factors: DataFrame) -> DataFrame:
    """``text_id, factor_no, parent_no``: references to the reference that holds their whole source, themselves excluded."""
    refs = factors.where("src IS NOT NULL").select("text_id", F.col("factor_no").alias("parent_no"))
    edges = dependency_edges(factors).where("contained AND child_no <> parent_no")
    return edges.join(refs, ["text_id", "parent_no"], "left_semi").select("text_id", F.col("child_no").alias("factor_no"), "parent_no")


def _roots(factors: DataFrame, holders: DataFrame, scratch: Scratch) -> DataFrame:
    """``text_id, factor_no, anc, acc, hops``: root, shifts from the factor up to but without the root, and edges between."""
    shift = F.col("src") - F.col("dst")
    up = holders.withColumnRenamed("parent_no", "anc")
    now = factors.where("src IS NOT NULL").select("text_id", "factor_no", shift.alias("shift")).join(up, ["text_id", "factor_no"], "left")
    now = now.select(
        "text_id", "factor_no", F.coalesce("anc", "factor_no").alias("anc"),
        F.when(F.col("anc").isNull(), 0).otherwise(F.col("shift")).alias("acc"), F.col("anc").isNotNull().cast("long").alias("hops"),
    )
    now = scratch.save(now, "roots")
    for _ in range(64):
        above = now.select("text_id", F.col("factor_no").alias("anc"), F.col("anc").alias("anc2"), F.col("acc").alias("acc2"), F.col("hops").alias("hops2"))
        new = now.join(above, ["text_id", "anc"]).select(
            "text_id", "factor_no", F.col("anc2").alias("anc"), (F.col("acc") + F.col("acc2")).alias("acc"), (F.col("hops") + F.col("hops2")).alias("hops"),
            (F.col("anc") != F.col("anc2")).alias("moved"),
        )
        new = scratch.save(new, "roots")
        scratch.drop(now)
        moved = new.where("moved").limit(1).count()
        now = new.drop("moved")
        now._scratch_path = new._scratch_path
        if not moved:
            return now
    raise ValueError("the references run in a circle")


def compact(factors: DataFrame, through_multi: bool = False) -> DataFrame:
    """Redirected factors. Chains end at the root of their tree; ``through_multi`` also skips through a root that holds the
    source but has several parents itself, whose own source stays."""
    scratch = Scratch(factors.sparkSession, "compact")
    holders = scratch.save(_holders(factors), "holders")
    roots = _roots(factors, holders, scratch)
    at_parent = roots.select("text_id", F.col("factor_no").alias("parent_no"), "anc", "acc")
    moved = holders.join(at_parent, ["text_id", "parent_no"])
    if through_multi:
        own = factors.select("text_id", F.col("factor_no").alias("anc"), (F.col("src") - F.col("dst")).alias("root_shift"))
        moved = moved.join(own, ["text_id", "anc"]).withColumn("acc", F.col("acc") + F.col("root_shift"))
    moved = moved.select("text_id", "factor_no", "acc")
    out = factors.join(moved, ["text_id", "factor_no"], "left")
    return out.withColumn("src", F.col("src") + F.coalesce("acc", F.lit(0))).select(*factors.columns)


def tree_depths(factors: DataFrame) -> DataFrame:
    """``text_id, factor_no, hops``: edges from a reference to the root of its tree."""
    scratch = Scratch(factors.sparkSession, "trees")
    return _roots(factors, scratch.save(_holders(factors), "holders"), scratch).select("text_id", "factor_no", "hops")


def compact_layers(factors: DataFrame, through_multi: bool = False) -> DataFrame:
    """The same result layer by layer from the roots down: each factor hands its new source to those it holds."""
    scratch = Scratch(factors.sparkSession, "layers")
    holders = scratch.save(_holders(factors), "holders")
    layers = _roots(factors, holders, scratch).select("text_id", "factor_no", "hops")
    state = scratch.save(factors.where("src IS NOT NULL").select("text_id", "factor_no", "dst", "src").join(layers, ["text_id", "factor_no"]), "state")
    last = state.agg(F.max("hops")).first()[0] or 0
    for depth in range(1, last + 1):
        folks = state.select("text_id", F.col("factor_no").alias("parent_no"), (F.col("src") - F.col("dst")).alias("shift"), F.col("hops").alias("h"))
        step = holders.join(folks, ["text_id", "parent_no"]).where((F.col("h") == depth - 1) & ((F.col("h") > 0) | F.lit(through_multi)))
        step = step.select("text_id", "factor_no", "shift")
        new = state.join(step, ["text_id", "factor_no"], "left").withColumn("src", F.col("src") + F.when(F.col("hops") == depth, F.coalesce("shift", F.lit(0))).otherwise(0)).drop("shift")
        new = scratch.save(new, "state")
        scratch.drop(state)
        state = new
    new_src = state.select("text_id", "factor_no", F.col("src").alias("new_src"))
    return factors.join(new_src, ["text_id", "factor_no"], "left").withColumn("src", F.coalesce("new_src", "src")).select(*factors.columns)
