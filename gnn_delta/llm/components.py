"""Connected components by Spark joins: neighbour minimum and pointer jumping until nothing changes.

Every round is written to the shared folder, so lineage stays short and a lost executor costs one round.
No set of nodes or links reaches the driver, only the count of changed labels.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, written


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, component (smallest node reachable) of every node that a link names."""
    both = links.select(F.col(a).alias("x"), F.col(b).alias("y")).where("x <> y")
    edges = written(both.union(both.select("y", "x")).distinct(), "links")
    labels = written(edges.groupBy(F.col("x").alias("node")).agg(F.min("y").alias("m")).select("node", F.least("node", "m").alias("component")), "labels")
    while True:
        near = edges.join(labels.withColumnRenamed("node", "y"), "y").groupBy(F.col("x").alias("node")).agg(F.min("component").alias("m"))
        step = labels.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "m").alias("component"))
        target = step.select(F.col("node").alias("component"), F.col("component").alias("further"))
        after = written(step.join(target, "component").select("node", F.least("component", "further").alias("component"), "old"), "labels")
        changed = after.where("component <> old").limit(1).count()
        forget(labels)
        if not changed:
            forget(edges)
            return after.select("node", "component")
        labels = after.select("node", "component")
        labels._written_at = after._written_at


def extended(labels: DataFrame, links: DataFrame) -> DataFrame:
    """``labels`` (node, component) after further links (a, b), which may name further nodes.

    Links are contracted to the components of their ends first: many links between two components count once."""
    one, two = (labels.select(F.col("node").alias(c), F.col("component").alias(f"c_{c}")) for c in ("a", "b"))
    ends = links.join(one, "a", "left").join(two, "b", "left").select(F.coalesce("c_a", "a").alias("x"), F.coalesce("c_b", "b").alias("y")).where("x <> y")
    moved = components(ends.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())
    old = labels.join(moved.select(F.col("node").alias("component"), F.col("component").alias("further")), "component", "left").select("node", F.coalesce("further", "component").alias("component"))
    return written(old.unionByName(moved.join(labels.select("node"), "node", "left_anti")), "labels")
