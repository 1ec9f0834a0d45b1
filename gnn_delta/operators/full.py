"""Whole-graph layer-wise inference: the bootstrap, and the refresh baseline."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.model import ModelSpec
from ..plans.state import GraphState
from .layers import layer_forward


def infer_full(vertices: DataFrame, edges: DataFrame, features: DataFrame, model: ModelSpec, pin=lambda df: df) -> GraphState:
    """All layers of all vertices. ``features``: (vid, h0..). ``pin`` settles a layer before the next reads it."""
    layers = [features if hasattr(features, "_written_at") else pin(features)]
    degrees = None
    if any(x.agg == "norm" for x in model.layers):
        degrees = edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    for spec in model.layers:
        layers.append(pin(layer_forward(edges, layers[-1], spec, vertices, degrees, whole=True)))
    return GraphState(vertices, edges, layers)


def infer_outputs(vertices: DataFrame, edges: DataFrame, features: DataFrame, model: ModelSpec, pin=lambda df: df) -> DataFrame:
    """(vid, h0..) of the last layer alone: no aggregate is kept, and only layers that the next one reads twice are settled."""
    degrees = None
    if any(x.agg == "norm" for x in model.layers):
        degrees = edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    out = features
    for i, spec in enumerate(model.layers):
        before = pin(out) if i and (spec.self_dependent or spec.agg == "attention") else out
        out = layer_forward(edges, before, spec, vertices, degrees, whole=True).select("vid", *names("h", spec.d_out))
    return out


def refresh(state: GraphState, model: ModelSpec) -> GraphState:
    return infer_full(state.vertices, state.edges, state.layers[0], model)
