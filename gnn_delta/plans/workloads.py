"""Experiment workloads on the given tables: one function each, rows of measures as dictionaries.

Row columns where they apply: graph, model, layers, batch_size, strategy, partitions, updates, batches,
throughput_up_s, latency_median_s, latency_p95_s, latency_max_s, update_s, compute_s, affected_distinct,
affected_share, agg_ops, cross_part_vectors, cross_part_bytes, max_abs_diff_vs_full. ``batches`` bounds how many
batches are timed; the published experiments time 100.
"""

from __future__ import annotations

import time
import uuid
from statistics import median

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import affected as aff
from ..operators import measures as ms
from ..operators import partition as pt
from ..operators.full import refresh
from ..operators.hybrid import apply_hybrid
from ..operators.incremental import apply_incremental
from ..operators.netting import edges_after, features_after, net_effect, settled_effect
from ..operators.recompute import apply_scoped
from ..operators.vertexwise import infer_vertexwise
from ..sources.graphs import D
from ..streaming.apply import Engine
from .cases import Case, case
from .model import WORKLOADS, ModelSpec, make_model
from .scratch import settled, shared_dir
from .stage_metrics import measured
from .state import GraphState, pinned


def _vertexwise(state: GraphState, effect, model: ModelSpec) -> DataFrame:
    new = edges_after(state.edges, effect.d_edges, effect.small)
    hops = aff.affected_sets(new, effect.d_edges, effect.d_feats, model, pinned)
    return infer_vertexwise(new, features_after(state.layers[0], effect.d_feats, D, effect.small), hops[-1], model)


def _full(state: GraphState, effect, model: ModelSpec) -> DataFrame:
    features = features_after(state.layers[0], effect.d_feats, D, effect.small)
    return refresh(GraphState(state.vertices, edges_after(state.edges, effect.d_edges, effect.small), [features]), model).layers[-1]


#: each gives the rows of the last layer that it makes anew
STRATEGIES = {
    "incremental": lambda s, e, m: apply_incremental(s, e, m).rows[-1],
    "scoped": lambda s, e, m: apply_scoped(s, e, m).rows[-1],
    "rebuild": lambda s, e, m: apply_scoped(s, e, m, update_mode="rebuild").rows[-1],
    "hybrid": lambda s, e, m: apply_hybrid(s, e, m).rows[-1],
    "full": _full,
    "vertexwise": _vertexwise,
}


def _timed(f) -> float:
    began = time.time()
    f().write.format("noop").mode("overwrite").save()
    return time.time() - began


def timing(times: list[float], update_times: list[float], size: int) -> dict:
    ordered = sorted(times)
    return {
        "updates": size * len(times), "batches": len(times), "throughput_up_s": round(size * len(times) / sum(times), 2), "latency_median_s": round(median(times), 3),
        "latency_p95_s": round(ordered[min(len(ordered) - 1, int(0.95 * len(ordered)))], 3), "latency_max_s": round(max(times), 3),
        "update_s": round(median(update_times), 3), "compute_s": round(median(times) - median(update_times), 3),
    }


def run_strategy(c: Case, model: ModelSpec, size: int, strategy: str, batches: int = 2) -> dict:
    """Independent batches against the bootstrapped state (each from the snapshot), after one that is not timed."""
    state = c.state(model)
    times, update_times = [], []
    for b in [0, *range(batches)]:
        rows = settled(c.updates(f"seq > {b * size} and seq <= {(b + 1) * size}"))
        began = time.time()
        effect = settled_effect(net_effect(rows, state, D, size))
        update = time.time() - began
        update_times.append(update)
        times.append(update + _timed(lambda: STRATEGIES[strategy](state, effect, model)))  # noqa: B023
    return {"graph": c.graph, "model": model.name, "layers": model.depth, "batch_size": size, "strategy": strategy, **timing(times[1:], update_times[1:], size)}


def work_counts(c: Case, model: ModelSpec, size: int, parts: int = 4) -> dict:
    """Counts of one batch: affected vertices, aggregation operations and crossing vectors by strategy."""
    effect = c.effect(model, f"seq <= {size}")
    new = edges_after(c.stream.snapshot, effect.d_edges, effect.small)
    hops = aff.affected_sets(new, effect.d_edges, effect.d_feats, model, pinned)
    placed = settled(pt.place(c.stream.vertices, c.stream.snapshot, parts))
    union = aff.by_hop(hops).select("vid").distinct().count()
    out = {"graph": c.graph, "model": model.name, "batch_size": size, "partitions": parts, "affected_distinct": union, "affected_share": round(union / c.stream.vertices.count(), 4)}
    for st in ("incremental", "scoped", "full"):
        out[f"agg_ops_{st}"] = ms.agg_ops(c.stream.snapshot, new, effect, hops, st).agg(F.sum("ops")).first()[0]
    for st in ("incremental", "scoped"):
        r = pt.exchange_counts(c.stream.snapshot, effect, model, placed, st).agg(F.sum("vectors"), F.sum("bytes")).first()
        out[f"cross_part_vectors_{st}"], out[f"cross_part_bytes_{st}"] = r[0], r[1]
    return out


def shoot_out(spark: SparkSession, sf_dir: str, graph: str, kind: str, depth: int, sizes, strategies=("incremental", "scoped"), batches: int = 2) -> list[dict]:
    c, model = case(spark, sf_dir, graph), make_model(kind, depth)
    rows = [run_strategy(c, model, size, st, batches) for size in sizes for st in strategies]
    return rows + [work_counts(c, model, size) for size in sizes]


def sampling(spark: SparkSession, sf_dir: str, graph: str = "supplier_part", depth: int = 3, fanouts=(1, 2, 4, 8, 16, 32, None), seeds=(1, 2, 3, 4, 5), batch: int = 10) -> list[dict]:
    """Agreement with the exact prediction and time per vertex, by fan-out, for the vertices that a batch affects."""
    c, model = case(spark, sf_dir, graph), make_model("sage_mean", depth)
    effect = c.effect(model, f"seq <= {batch}")
    edges = settled(edges_after(c.stream.snapshot, effect.d_edges, effect.small))
    features = settled(features_after(c.features(), effect.d_feats, D, effect.small))
    targets = aff.affected_sets(edges, effect.d_edges, effect.d_feats, model, pinned)[-1]
    n = targets.count()
    exact = settled(apply_incremental(c.state(model), effect, model).rows[-1].join(targets, "vid", "left_semi"))
    rows = []
    for f in fanouts:
        shares, began = [], time.time()
        for seed in seeds if f is not None else seeds[:1]:
            r = ms.agreement(infer_vertexwise(edges, features, targets, model, [f] * depth, seed), exact, D).first()
            shares.append(r["agree"] / r["n"])
        spent = (time.time() - began) / len(shares)
        rows.append({"experiment": "sampling", "graph": graph, "fanout": f or "all", "agreement": round(sum(shares) / len(shares), 4), "spread": round(max(shares) - min(shares), 4), "ms_per_vertex": round(1000 * spent / n, 3)})
    return rows


def growth(spark: SparkSession, sf_dir: str, sizes=(1, 10, 100)) -> list[dict]:
    """Affected share and cost by batch size and in-degree (three-layer model with own vectors)."""
    return [{"experiment": "growth", **work_counts(case(spark, sf_dir, g), make_model("sage_sum", 3), b)} for g in ("order_part", "next_part") for b in sizes]


def kinds(spark: SparkSession, sf_dir: str) -> list[dict]:
    """Share affected by each kind of update: feature changes reach more."""
    c, model = case(spark, sf_dir), make_model("gc_sum", 2)
    rows = []
    for kind in ("edge_add", "edge_del", "feat_set"):
        e = c.effect(model, f"kind = '{kind}' and seq <= 300")
        hops = aff.affected_sets(edges_after(c.stream.snapshot, e.d_edges, e.small), e.d_edges, e.d_feats, model, pinned)
        rows.append({"experiment": "kinds", "kind": kind, "affected": aff.by_hop(hops).select("vid").distinct().count()})
    return rows


def scaling(spark: SparkSession, sf_dir: str, parts=(4, 8, 16), size: int = 100) -> list[dict]:
    """Crossing vectors and cut by number of parts on the mixed graph with half of its edges held out."""
    c, model = case(spark, sf_dir, "commerce", 0.5), make_model("gc_sum", 3)
    rows = []
    for p in parts:
        placed = settled(pt.place(c.stream.vertices, c.stream.snapshot, p))
        cut = pt.cut_stats(c.stream.snapshot, placed).agg(F.sum("out_cut"), F.sum("ghosts")).first()
        effect = c.effect(model, f"seq <= {size}")
        vectors = {st: pt.exchange_counts(c.stream.snapshot, effect, model, placed, st).agg(F.sum("vectors")).first()[0] for st in ("incremental", "scoped")}
        rows.append({"experiment": "scaling", "partitions": p, "edge_cut": cut[0], "ghosts": cut[1], **{f"vectors_{k}": v for k, v in vectors.items()}})
    return rows


def tree_latency(spark: SparkSession, sf_dir: str, graph: str = "next_part", depth: int = 2, updates: int = 20) -> list[dict]:
    """Latency of single updates against the size of their propagation trees, with the correlation."""
    c, model = case(spark, sf_dir, graph), make_model("gc_sum", depth)
    state, rows = c.state(model), []
    for strategy in ("incremental", "scoped"):
        points = []
        for seq in [1, *range(1, updates + 1)]:
            began = time.time()
            effect = settled_effect(net_effect(settled(c.updates(f"seq = {seq}")), state, D, 1))
            apply = apply_incremental if strategy == "incremental" else apply_scoped
            result = apply(state, effect, model)
            result.rows[-1].write.format("noop").mode("overwrite").save()
            spent = time.time() - began
            points.append((aff.by_hop(result.affected).select("vid").distinct().count(), spent))
        sizes, times = zip(*points[1:], strict=True)
        flat = len(set(sizes)) < 2
        rows.append({
            "experiment": "tree_latency", "graph": graph, "layers": depth, "strategy": strategy, "updates": updates, "affected_min": min(sizes), "affected_max": max(sizes),
            "latency_median_s": round(median(times), 3), "correlation": None if flat else round(float(np.corrcoef(sizes, times)[0, 1]), 3),
        })
    return rows


def plateau(spark: SparkSession, sf_dir: str, sizes=(1, 10, 100, 1000), batches: int = 2) -> list[dict]:
    """Throughput of the baseline whose graph update is costly, by batch size."""
    c, model = case(spark, sf_dir), make_model("gc_sum", 2)
    return [{"experiment": "plateau", **run_strategy(c, model, b, "rebuild", batches)} for b in sizes]


def worst_case(spark: SparkSession, sf_dir: str, graph: str = "copurchase", size: int = 1000) -> list[dict]:
    """Operations once a hop covers nearly all vertices: what the choice per hop is for."""
    c, model = case(spark, sf_dir, graph), make_model("gc_sum", 3)
    effect = c.effect(model, f"seq <= {size}")
    return [{"experiment": "worst_case", **work_counts(c, model, size), "chosen": apply_hybrid(c.state(model), effect, model).strategy}]


def distributed(spark: SparkSession, sf_dir: str, graph: str = "commerce", hold_out: float = 0.5, parts=(2, 4, 8, 16), size: int = 1000, depth: int = 3, kind: str = "gc_sum", method: str = "hash") -> list[dict]:
    """Both strategies with placed vertices: throughput, crossing vectors, time in tasks and in the exchange, routing."""
    c, model = case(spark, sf_dir, graph, hold_out), make_model(kind, depth)
    state, rows = c.state(model), []
    updates = settled(c.updates(f"seq <= {size}"))
    effect = settled_effect(net_effect(updates, state, D, size))
    for p in parts:
        placed = settled(pt.place(c.stream.vertices, c.stream.snapshot, p, method))
        located = pt.layout(state, placed, p)
        began = time.time()
        pt.route(updates, placed).write.format("noop").mode("overwrite").save()
        routing = time.time() - began
        for strategy, apply in (("incremental", pt.apply_partitioned), ("scoped", pt.apply_scoped_partitioned)):
            with measured(spark) as cost:
                began = time.time()
                got = apply(located, effect, model, placed, p)
                got.result.rows[-1].write.format("noop").mode("overwrite").save()
                spent = time.time() - began
            vectors = pt.exchange_counts(c.stream.snapshot, effect, model, placed, strategy).agg(F.sum("vectors"), F.sum("bytes")).first()
            rows.append({
                "experiment": "distributed", "graph": graph, "model": model.name, "batch_size": size, "partitions": p, "strategy": strategy, "throughput_up_s": round(size / spent, 1), "latency_s": round(spent, 2),
                "compute_task_s": round(cost.compute_s, 2), "exchange_task_s": round(cost.shuffle_s, 2), "shuffle_write_bytes": cost.shuffle_write_bytes, "cross_part_vectors": vectors[0], "cross_part_bytes": vectors[1], "routing_s": round(routing, 2),
            })
    return rows


def drift(spark: SparkSession, sf_dir: str, batches: int = 500, size: int = 6, every: int = 50) -> list[dict]:
    """Largest difference to recompute after a stream of small batches (mean: real-valued), through the engine."""
    c, model = case(spark, sf_dir), make_model("gc_mean", 2)
    engine = Engine(spark, f"{shared_dir(spark)}/drift-{uuid.uuid4().hex}", model, buckets=4)
    engine.bootstrap(c.state(model))
    rows = []
    for b in range(batches):
        engine.apply(c.updates(f"seq > {size * b} and seq <= {size * (b + 1)}"), b + 1)
        if (b + 1) % every == 0 or b + 1 == batches:
            rows.append({"experiment": "drift", "batches": b + 1, "max_abs_diff_vs_full": max(r["diff"] for r in ms.audit(engine.state(), model, 1.0).collect())})
    return rows


GRID_GRAPHS = ("order_part", "copurchase", "supplier_part")


def all_experiments(spark: SparkSession, sf_dir: str, batches: int = 100) -> list[dict]:
    """Every experiment as published, with ``batches`` timed batches each; hours at 100, so pass fewer for a look."""
    rows = sampling(spark, sf_dir) + sampling(spark, sf_dir, "knn") + growth(spark, sf_dir) + kinds(spark, sf_dir) + scaling(spark, sf_dir)
    for graph in ("order_part", "supplier_part"):
        rows += shoot_out(spark, sf_dir, graph, "gc_sum", 3, (10,), ("vertexwise", "rebuild", "scoped", "full", "incremental"), batches)
    for graph in GRID_GRAPHS:
        for kind in WORKLOADS:
            rows += shoot_out(spark, sf_dir, graph, kind, 2, (1, 10, 100, 1000), ("rebuild", "scoped", "incremental"), batches)
    for kind in WORKLOADS:
        rows += shoot_out(spark, sf_dir, "next_part", kind, 3, (1, 10, 100, 1000), ("rebuild", "scoped", "incremental"), batches)
    for depth in (2, 3):
        rows += tree_latency(spark, sf_dir, depth=depth, updates=batches)
    rows += plateau(spark, sf_dir, batches=batches) + worst_case(spark, sf_dir)
    for size in (10, 100, 1000):
        rows += distributed(spark, sf_dir, size=size)
    for graph in ("supplier_part", "order_part"):
        rows += distributed(spark, sf_dir, graph, 0.1, (2, 4, 8))
    return rows + drift(spark, sf_dir, 5 * batches)
