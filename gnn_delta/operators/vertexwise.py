"""Vertex-wise inference: each target's computation tree on its own, whole or with a sampled fan-out."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mixes import edge_mix_sql
from ..functions.vectors import names
from ..plans.model import ModelSpec
from .layers import transform, weight


def sampled_edges(edges: DataFrame, fanout: int | None, seed: int, dsts: DataFrame | None = None) -> DataFrame:
    """At most ``fanout`` in-edges of each vertex (of ``dsts`` (vid) only, if given) by hash rank, with ``k``, its whole in-degree."""
    if dsts is not None:
        edges = edges.join(dsts.select(F.col("vid").alias("dst")).distinct(), "dst", "left_semi")
    if fanout is None:
        return edges
    by_dst = Window.partitionBy("dst")
    rank = F.row_number().over(by_dst.orderBy(F.expr(edge_mix_sql("src", "dst", seed)), "src"))
    return edges.withColumn("k", F.count("*").over(by_dst)).withColumn("r", rank).where(F.col("r") <= fanout).drop("r")


def infer_vertexwise(edges: DataFrame, features: DataFrame, targets: DataFrame, model: ModelSpec, fanouts: list[int | None] | None = None, seed: int = 0) -> DataFrame:
    """(vid, h0..) of the targets. Nothing is shared among targets: rows carry the target they serve.

    ``fanouts[l]`` bounds the in-neighbours read at layer l+1 (None: all). A sampled sum is scaled by
    in-degree over sample size, a sampled mean is the mean of the sample."""
    fanouts = fanouts or [None] * model.depth
    read = []
    need = [targets.select(F.col("vid").alias("target"), "vid")]  # needed at layer L, then L-1, ...
    for spec, fanout in zip(reversed(model.layers), reversed(fanouts), strict=True):
        inputs = sampled_edges(edges, fanout, seed, need[-1])
        read.append(inputs)
        source = inputs.join(need[-1].withColumnRenamed("vid", "dst"), "dst").select("target", F.col("src").alias("vid"))
        need.append((source.unionByName(need[-1]) if spec.self_dependent else source).distinct())
    need.reverse()
    read.reverse()
    h = need[0].join(features, "vid")
    for layer, spec in enumerate(model.layers):
        d = spec.d_in
        reach = read[layer].join(need[layer + 1].withColumnRenamed("vid", "dst"), "dst")
        near = reach.join(h.withColumnRenamed("vid", "src"), ["target", "src"])
        factor = weight(spec, "w")
        agg = near.groupBy("target", F.col("dst").alias("vid")).agg(
            F.count("*").alias("c"), *([F.first("k").alias("k")] if "k" in reach.columns else []),
            *[F.expr(f"sum(({factor}) * {x}) AS {s}") for x, s in zip(names("h", d), names("s", d), strict=True)],
        )
        if fanouts[layer] is not None and spec.agg in ("sum", "wsum"):
            agg = agg.select("target", "vid", "c", *[(F.col(s) * (F.col("k") / F.col("c"))).alias(s) for s in names("s", d)])
        full = need[layer + 1].join(agg, ["target", "vid"], "left").select("target", "vid", F.coalesce("c", F.lit(0)).alias("c"), *[F.coalesce(s, F.lit(0.0)).alias(s) for s in names("s", d)])
        if spec.self_dependent:
            full = full.join(h.select("target", "vid", *[F.col(f"h{i}").alias(f"o{i}") for i in range(d)]), ["target", "vid"])
        h = transform(full, spec, ["target", "vid"])
    return h.where("target = vid").select("vid", *names("h", model.layers[-1].d_out))


def tree_edges(edges: DataFrame, targets: DataFrame, model: ModelSpec) -> DataFrame:
    """(target, ops): edges of each target's computation tree, the cost of vertex-wise inference."""
    need = targets.select(F.col("vid").alias("target"), "vid")
    out = None
    for spec in reversed(model.layers):
        read = edges.join(need.withColumnRenamed("vid", "dst"), "dst").select("target", "src")
        count = read.groupBy("target").agg(F.count("*").alias("ops"))
        out = count if out is None else out.unionByName(count)
        source = read.select("target", F.col("src").alias("vid"))
        need = (source.unionByName(need) if spec.self_dependent else source).distinct()
    return out.groupBy("target").agg(F.sum("ops").alias("ops"))
