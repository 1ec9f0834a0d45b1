"""Per hop the cheaper of recompute and delta: deltas cost two operations per touched edge, recompute one per in-edge."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans.model import ModelSpec
from ..plans.state import BatchResult, GraphState, overlay, pinned
from .affected import next_hop
from .incremental import deltas, hop_step, new_vectors
from .netting import NetEffect, degree_delta, edges_after, features_after, out_edges
from .recompute import scoped_hop


def apply_hybrid(state: GraphState, effect: NetEffect, model: ModelSpec, pin=pinned) -> BatchResult:
    """Two counts per hop decide; both ways give the same rows. In-degrees are the stored ones of the targets."""
    edges_new = edges_after(state.edges, effect.d_edges, effect.small)
    moved = degree_delta(effect.d_edges).select("vid", "d_indeg")
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    changed, hops, how, inboxes, made = [effect.d_feats], [effect.d_feats.select("vid")], [], [], []
    for hop, spec in enumerate(model.layers, 1):
        senders = changed[-1].select("vid")
        near = out_edges(state, effect, senders)
        targets = pin(next_hop(near, effect.d_edges, senders, spec.self_dependent))
        touched = near.join(senders.withColumnRenamed("vid", "src"), "src", "left_semi").agg(F.count("*").alias("t"))
        indeg = targets.join(state.layer_of(hop, targets).select("vid", "c"), "vid").join(moved, "vid", "left")
        pulls = indeg.agg(F.sum(F.col("c") + F.coalesce("d_indeg", F.lit(0))).alias("p"))
        count = touched.crossJoin(pulls).first()
        if not spec.agg == "norm" and (2 * count["t"] > (count["p"] or 0) or spec.agg in ("max", "min", "attention")):
            fresh = scoped_hop(edges_new, layers[-1], targets, spec, None)
            old = state.layer_of(hop, targets).select("vid", *[F.col(f"h{i}").alias(f"p{i}") for i in range(spec.d_out)])
            rows = pin(fresh.join(old, "vid"))
            how.append("scoped")
        else:
            inbox, rows = hop_step(state, effect, changed[-1], new_vectors(changed[-1], spec.d_in), hop, spec, pin)
            rows = pin(rows)
            inboxes.append(inbox)
            how.append("incremental")
        made.append(rows.select(*state.layers[hop].columns))
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
        changed.append(deltas(rows, spec.d_out))
        hops.append(rows.select("vid"))
    return BatchResult(GraphState(state.vertices, edges_new, layers, state.version + 1), hops, changed, inboxes, how, made)
