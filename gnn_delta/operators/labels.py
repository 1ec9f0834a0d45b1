"""Labels from the last layer, changes to announce, lookups."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import argmax, names
from ..plans.state import BatchResult, GraphState


def labels(last: DataFrame, d: int) -> DataFrame:
    """(vid, label): index of the largest entry, the smallest index on ties."""
    return last.select("vid", argmax([F.col(x) for x in names("h", d)]).alias("label"))


def changed_labels(old: DataFrame, new: DataFrame, d: int) -> DataFrame:
    """(vid, old_label, new_label) where two tables of last-layer rows disagree, for the vertices of ``new``."""
    before, after = labels(old, d).withColumnRenamed("label", "old_label"), labels(new, d).withColumnRenamed("label", "new_label")
    return after.join(before, "vid").where("not (old_label <=> new_label)").select("vid", "old_label", "new_label")


def label_changes(result: BatchResult, before: GraphState, d: int) -> DataFrame:
    """(vid, old_label, new_label) of vertices of the last hop whose label differs."""
    return changed_labels(before.layers[-1], result.rows[-1], d)


def lookup(last: DataFrame, vids: DataFrame, d: int) -> DataFrame:
    return labels(last.join(vids.select("vid"), "vid", "left_semi"), d)


def edge_scores(last: DataFrame, pairs: DataFrame, d: int) -> DataFrame:
    """(a, b, score): dot product of both end vectors, for edge-level tasks."""
    side = lambda n, p: last.select(F.col("vid").alias(n), *[F.col(f"h{i}").alias(f"{p}{i}") for i in range(d)])
    score = F.lit(0.0)
    for i in range(d):
        score = score + F.col(f"p{i}") * F.col(f"q{i}")
    return pairs.join(side("a", "p"), "a").join(side("b", "q"), "b").select("a", "b", score.alias("score"))
