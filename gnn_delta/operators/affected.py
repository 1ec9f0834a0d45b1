"""Which vertices a batch can change, hop by hop (the propagation tree)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import ModelSpec
from ..plans.scratch import settled
from .netting import BROADCAST_UPDATES


def next_hop(edges_new: DataFrame, d_edges: DataFrame, before: DataFrame, self_dependent: bool) -> DataFrame:
    """Sinks of changed edges, out-neighbours of the hop before and, if the layer reads it, the hop itself."""
    touched = edges_new.join(before.withColumnRenamed("vid", "src"), "src", "left_semi")
    out = d_edges.select(F.col("dst").alias("vid")).unionByName(touched.select(F.col("dst").alias("vid")))
    if self_dependent:
        out = out.unionByName(before.select("vid"))
    return out.distinct()


def affected_sets(edges_new: DataFrame, d_edges: DataFrame, d_feats: DataFrame, model: ModelSpec, pin=lambda df: df) -> list[DataFrame]:
    """A_0 (feature changes) to A_L, each (vid)."""
    hops = [d_feats.select("vid").distinct()]
    changed_degree = None
    if any(x.agg == "norm" for x in model.layers):
        changed_degree = d_edges.select(F.col("dst").alias("vid")).distinct()
    for spec in model.layers:
        before = hops[-1] if spec.agg != "norm" else hops[-1].unionByName(changed_degree).distinct()
        hops.append(pin(next_hop(edges_new, d_edges, before, spec.self_dependent)))
    return hops


def affected_by(edges: DataFrame, d_edges: DataFrame, d_feats: DataFrame, model: ModelSpec, keys: list[str], pin=settled) -> DataFrame:
    """(keys.., vid), distinct: the vertices of all hops of several batches, told apart by ``keys``; a hop reads the edges once for all.

    ``edges`` are those before the batches. What a batch changes in them needs no overlay: the sinks of changed edges,
    added or deleted, belong to every hop."""
    changed = d_edges.select(*keys, F.col("dst").alias("vid"))
    hop = pin(d_feats.select(*keys, "vid").distinct())
    tree = hop
    for spec in model.layers:
        before = hop.unionByName(changed).distinct() if spec.agg == "norm" else hop
        few = before.limit(BROADCAST_UPDATES + 1).count() <= BROADCAST_UPDATES
        senders = before.withColumnRenamed("vid", "src")
        touched = edges.join(F.broadcast(senders) if few else senders.hint("shuffle_hash"), "src")
        out = touched.select(*keys, F.col("dst").alias("vid")).unionByName(changed)
        hop = pin((out.unionByName(hop) if spec.self_dependent else out).distinct())
        tree = tree.unionByName(hop)
    return tree.distinct()


def by_hop(hops: list[DataFrame]) -> DataFrame:
    """(hop, vid)."""
    out = None
    for i, a in enumerate(hops):
        rows = a.select(F.lit(i).cast("long").alias("hop"), "vid")
        out = rows if out is None else out.unionByName(rows)
    return out


def unaffected(vertices: DataFrame, hops: list[DataFrame]) -> DataFrame:
    return vertices.select("vid").join(by_hop(hops).select("vid").distinct(), "vid", "left_anti")
