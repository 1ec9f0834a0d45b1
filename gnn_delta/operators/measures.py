"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.model import ModelSpec
from ..plans.state import GraphState
from .affected import by_hop
from .labels import labels
from .netting import NetEffect
from .vertexwise import tree_edges


def agg_ops(edges_old: DataFrame, edges_new: DataFrame, effect: NetEffect, hops: list[DataFrame], strategy: str) -> DataFrame:
    """(hop, ops): vector operations of aggregation. Recompute adds one vector per in-edge of an affected
    vertex; a delta subtracts and adds one per kept touched edge and moves one per changed edge."""
    out = None
    for hop in range(1, len(hops)):
        if strategy == "scoped":
            count = edges_new.join(hops[hop].withColumnRenamed("vid", "dst"), "dst", "left_semi").agg(F.count("*").alias("ops"))
        elif strategy == "incremental":
            kept = edges_new.join(effect.d_edges.select("src", "dst"), ["src", "dst"], "left_anti")
            touched = kept.join(hops[hop - 1].withColumnRenamed("vid", "src"), "src", "left_semi").agg(F.count("*").alias("t"))
            count = touched.crossJoin(effect.d_edges.agg(F.count("*").alias("e"))).select((2 * F.col("t") + F.col("e")).alias("ops"))
        elif strategy == "full":
            count = edges_new.agg(F.count("*").alias("ops"))
        else:
            raise ValueError(strategy)
        row = count.select(F.lit(hop).cast("long").alias("hop"), "ops")
        out = row if out is None else out.unionByName(row)
    return out


def agg_ops_vertexwise(edges_new: DataFrame, targets: DataFrame, model: ModelSpec) -> DataFrame:
    return tree_edges(edges_new, targets, model).agg(F.sum("ops").alias("ops"))


def affected_stats(hops: list[DataFrame], n: int) -> DataFrame:
    """(hop, cnt, share) per hop, hop -1 for all hops together."""
    rows = by_hop(hops)
    per_hop = rows.groupBy("hop").agg(F.count("*").alias("cnt"))
    union = rows.select("vid").distinct().agg(F.count("*").alias("cnt")).select(F.lit(-1).cast("long").alias("hop"), "cnt")
    return per_hop.unionByName(union).withColumn("share", F.col("cnt") / F.lit(n))


def state_bytes(state: GraphState) -> DataFrame:
    """(component, bytes): 8 per number of edges, layer outputs and stored aggregates."""
    out = state.edges.agg(F.count("*").alias("n")).select(F.lit("edges").alias("component"), (F.col("n") * 24).alias("bytes"))
    for i, layer in enumerate(state.layers):
        for part, prefix in (("h", "h"), ("agg", "s")):
            width = sum(1 for c in layer.columns if c[0] == prefix and c[1:].isdigit())
            if width:
                out = out.unionByName(layer.agg(F.count("*").alias("n")).select(F.lit(f"{part}{i}").alias("component"), (F.col("n") * 8 * width).alias("bytes")))
    return out


def max_abs_diff(state: GraphState, reference: GraphState, model: ModelSpec) -> DataFrame:
    """(layer, diff) between two states."""
    out = None
    for i, spec in enumerate(model.layers, 1):
        a, b = state.layers[i], reference.layers[i]
        other = b.select("vid", *[F.col(h).alias(f"r{j}") for j, h in enumerate(names("h", spec.d_out))])
        joined = a.join(other, "vid", "full_outer")
        diffs = [F.coalesce(F.abs(F.col(f"h{j}") - F.col(f"r{j}")), F.lit(float("inf"))) for j in range(spec.d_out)]
        worst = F.greatest(*diffs) if len(diffs) > 1 else diffs[0]
        row = joined.agg(F.max(worst).alias("diff")).select(F.lit(i).cast("long").alias("layer"), "diff")
        out = row if out is None else out.unionByName(row)
    return out


def agreement(sampled: DataFrame, exact: DataFrame, d: int) -> DataFrame:
    """(n, agree): targets, and those whose label is that of the exact prediction."""
    a, b = labels(sampled, d), labels(exact, d).withColumnRenamed("label", "exact")
    return a.join(b, "vid").agg(F.count("*").alias("n"), F.sum((F.col("label") == F.col("exact")).cast("long")).alias("agree"))


def throughput(cost: DataFrame) -> DataFrame:
    """(strategy, up_s) of rows (strategy, updates, seconds)."""
    return cost.groupBy("strategy").agg((F.sum("updates") / F.sum("seconds")).alias("up_s"))


def latency_stats(cost: DataFrame) -> DataFrame:
    q = lambda p: F.percentile("seconds", F.lit(p))
    return cost.groupBy("strategy").agg(q(0.5).alias("p50"), q(0.95).alias("p95"), q(0.99).alias("p99"))


def speedup(cost: DataFrame, base: str) -> DataFrame:
    """(strategy, speedup) of throughput over a base strategy."""
    rate = throughput(cost)
    return rate.crossJoin(rate.where(F.col("strategy") == base).select(F.col("up_s").alias("base"))).select("strategy", (F.col("up_s") / F.col("base")).alias("speedup"))


def scaling_efficiency(cost: DataFrame, base_p: int) -> DataFrame:
    """(p, speedup, efficiency) of rows (p, updates, seconds)."""
    rate = cost.groupBy("p").agg((F.sum("updates") / F.sum("seconds")).alias("up_s"))
    base = rate.where(F.col("p") == base_p).select(F.col("up_s").alias("base"))
    return rate.crossJoin(base).select("p", (F.col("up_s") / F.col("base")).alias("speedup"), (F.col("up_s") / F.col("base") * base_p / F.col("p")).alias("efficiency"))


def audit(state: GraphState, model: ModelSpec, share: float = 0.01) -> DataFrame:
    """(layer, diff) of a sample of vertices recomputed from stored neighbours: how far rounding has drifted."""
    from .layers import layer_forward

    out = None
    picked = state.vertices.where(F.abs(F.xxhash64("vid") % 1_000_000) < int(share * 1_000_000)).select("vid")
    degrees = state.edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    for i, spec in enumerate(model.layers, 1):
        pulled = state.edges.join(picked.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        fresh = layer_forward(pulled, state.layers[i - 1], spec, picked, degrees)
        other = state.layers[i].select("vid", *[F.col(h).alias(f"r{j}") for j, h in enumerate(names("h", spec.d_out))])
        joined = fresh.join(other, "vid")
        diffs = [F.abs(F.col(f"h{j}") - F.col(f"r{j}")) for j in range(spec.d_out)]
        row = joined.agg(F.max(F.greatest(*diffs) if len(diffs) > 1 else diffs[0]).alias("diff")).select(F.lit(i).cast("long").alias("layer"), "diff")
        out = row if out is None else out.unionByName(row)
    return out
