"""Scoped layer-wise recompute: every affected vertex pulls all its in-neighbours again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import ModelSpec
from ..plans.state import BatchResult, GraphState, overlay, pinned
from .affected import affected_sets
from .layers import layer_forward
from .netting import NetEffect, edges_after, features_after


def scoped_hop(edges_new: DataFrame, before_new: DataFrame, targets: DataFrame, spec, degrees: DataFrame | None) -> DataFrame:
    """Layer rows of the affected vertices from all their in-neighbours."""
    pulled = edges_new.join(targets.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    return layer_forward(pulled, before_new, spec, targets, degrees)


def apply_scoped(state: GraphState, effect: NetEffect, model: ModelSpec, update_mode: str = "overlay", pin=pinned) -> BatchResult:
    """``update_mode='rebuild'`` mimics systems whose graph update is costly: the edge table is sorted and laid out anew.

    Otherwise the edge table is read with the batch laid over it, and not written."""
    edges_new = edges_after(state.edges, effect.d_edges, effect.small)
    if update_mode == "rebuild":
        edges_new = pin(edges_new.repartition("dst").sortWithinPartitions("dst", "src"))
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    hops = affected_sets(edges_new, effect.d_edges, effect.d_feats, model, pin)
    degrees = None
    if any(x.agg == "norm" for x in model.layers):
        degrees = edges_new.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    made = []
    for hop, spec in enumerate(model.layers, 1):
        rows = pin(scoped_hop(edges_new, layers[hop - 1], hops[hop], spec, degrees))
        made.append(rows.select(*state.layers[hop].columns))
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
    after = GraphState(state.vertices, edges_new, layers, state.version + 1)
    return BatchResult(after, hops, [], strategy=["scoped"] * model.depth, rows=made)
