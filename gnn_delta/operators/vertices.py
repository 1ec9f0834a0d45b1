"""Vertices that join the graph: rows of zero aggregates in every layer; their edges then arrive as updates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.model import ModelSpec
from ..plans.state import GraphState
from .layers import transform


def insert(state: GraphState, fresh: DataFrame, model: ModelSpec) -> GraphState:
    """``fresh``: (vid, h0..) of new vertices; known ids are left as they are."""
    new = fresh.join(state.vertices.select("vid"), "vid", "left_anti")
    layers, before = [state.layers[0].unionByName(new.select(*state.layers[0].columns))], new
    for spec, layer in zip(model.layers, state.layers[1:], strict=True):
        zero = before.select("vid", F.lit(0).cast("long").alias("c"), *[F.lit(0.0).alias(s) for s in names("s", spec.d_in)], *[F.col(f"h{i}").alias(f"o{i}") for i in range(spec.d_in)])
        before = transform(zero, spec, ["vid", "c", *names("s", spec.d_in)])
        layers.append(layer.unionByName(before.select(*layer.columns)))
    return GraphState(state.vertices.select("vid").unionByName(new.select("vid")), state.edges, layers, state.version)
