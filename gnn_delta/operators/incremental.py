"""Incremental propagation: only differences of vectors move, along out-edges, hop by hop.

With S = E*H per layer, a batch gives dS = E_new*dH + dE*H_old. The first product joins the out-edges after
the update with the changed vectors, the second joins the changed edges with old vectors; together they
are new-minus-old for kept edges, the new vector for added and minus the old one for deleted edges. The
sums arrive in any order, so Spark's partial aggregation combines messages before they are shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.model import LayerSpec, ModelSpec
from ..plans.state import BatchResult, GraphState, overlay, pinned
from .layers import sent, transform, weight
from .netting import NetEffect, degree_delta, edges_after, features_after, out_edges, side


def changed_senders(changed: DataFrame, state: GraphState, hop: int, spec: LayerSpec, d_edges: DataFrame) -> DataFrame:
    """(vid, d0..): change of what each vertex sends at this hop.

    Degree-normalised layers send h/sqrt(degree), so a change of degree alone changes what is sent."""
    d = range(spec.d_in)
    if spec.agg != "norm":
        return changed.selectExpr("vid", *[f"new{i} - old{i} AS d{i}" for i in d])
    touched = changed.select("vid").unionByName(d_edges.select(F.col("dst").alias("vid")))
    degree = state.layer_of(1, touched).selectExpr("vid", "c AS c_old")
    moved = degree_delta(d_edges).where("d_indeg <> 0").select("vid", "d_indeg")
    still = state.layer_of(hop - 1, touched).join(moved.select("vid"), "vid", "left_semi").join(changed.select("vid"), "vid", "left_anti")
    both = changed.select("vid", *names("old", spec.d_in), *names("new", spec.d_in)).unionByName(
        still.selectExpr("vid", *[f"h{i} AS old{i}" for i in d], *[f"h{i} AS new{i}" for i in d])
    )
    both = both.join(degree, "vid").join(moved, "vid", "left").selectExpr("*", "c_old + coalesce(d_indeg, 0L) AS c_new")
    return both.selectExpr("vid", *[f"new{i} / sqrt(greatest(c_new, 1)) - old{i} / sqrt(greatest(c_old, 1)) AS d{i}" for i in d])


def old_sent(state: GraphState, hop: int, spec: LayerSpec, who: DataFrame) -> DataFrame:
    """(vid, g0..): what each vertex sent before the batch, for ``who`` at least."""
    h = state.layer_of(hop - 1, who)
    if spec.agg == "norm":
        h = h.select("vid", *names("h", spec.d_in)).join(state.layers[1].selectExpr("vid", "c AS degree"), "vid")
    return h.selectExpr("vid", *[f"{sent(spec, f'h{i}', 'degree')} AS g{i}" for i in range(spec.d_in)])


def messages(changed: DataFrame, state: GraphState, effect: NetEffect, hop: int, spec: LayerSpec, carry: tuple[str, ...] = ()) -> DataFrame:
    """(src, dst, kind, d_indeg, carry.., m0..): all messages into hop ``hop``, kinds changed, added, deleted, reweighted.

    Changed edges always speak, with zero vectors too, for they change degrees. Edges are read where senders
    have them, with the batch's own edges in place of the stored ones; no edge table is written."""
    d, d_edges, small = range(spec.d_in), effect.d_edges, effect.small
    senders = changed_senders(changed, state, hop, spec, d_edges)
    who = changed.select("vid") if spec.agg != "norm" else changed.select("vid").unionByName(d_edges.select(F.col("dst").alias("vid")))
    edges_new = out_edges(state, effect, who, carry)
    first = edges_new.join(senders.withColumnRenamed("vid", "src"), "src").selectExpr(
        "src", "dst", "'changed' AS kind", "0L AS d_indeg", *carry, *[f"({weight(spec, 'w')}) * d{i} AS m{i}" for i in d]
    )
    kind = "CASE WHEN w_old IS NULL THEN 'added' WHEN w_new IS NULL THEN 'deleted' ELSE 'reweighted' END AS kind"
    degree = "CAST(w_new IS NOT NULL AS BIGINT) - CAST(w_old IS NOT NULL AS BIGINT) AS d_indeg"
    more = f"(coalesce({weight(spec, 'w_new')}, 0D) - coalesce({weight(spec, 'w_old')}, 0D))"
    old = old_sent(state, hop, spec, d_edges.select(F.col("src").alias("vid")))
    second = old.join(side(d_edges.withColumnRenamed("src", "vid"), small), "vid").selectExpr(
        "vid AS src", "dst", kind, degree, *carry, *[f"{more} * g{i} AS m{i}" for i in d]
    )
    return first.unionByName(second)


def merge_inbox(messages_in: DataFrame, d: int) -> DataFrame:
    """(vid, d_indeg, n_msgs, m0..): one summed message per vertex, combined before and after the shuffle."""
    sums = [F.expr(f"sum({m}) AS {m}") for m in ("d_indeg", *names("m", d))]
    return messages_in.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("n_msgs"), *sums)


def apply_inbox(layer: DataFrame, inbox: DataFrame, own_new: DataFrame | None, also: DataFrame | None, spec: LayerSpec) -> DataFrame:
    """Rows of the vertices in the inbox (and ``also``): vid, c, s0.., h0.. (new), p0.. (old output).

    ``own_new``: new vectors of the layer before, for layers that read them."""
    d, out = spec.d_in, spec.d_out
    who = inbox if also is None else inbox.join(also, "vid", "full_outer")
    old = layer.selectExpr("vid", "c AS c_old", *names("s", d), *[f"h{i} AS p{i}" for i in range(out)])
    rows = old.join(who, "vid").selectExpr("*", "c_old + coalesce(d_indeg, 0L) AS c")
    # without in-neighbours the aggregate is exactly zero: this drops what rounding may have left
    rows = rows.selectExpr("vid", "c", *[f"CASE WHEN c = 0 THEN 0D ELSE s{i} + coalesce(m{i}, 0D) END AS s{i}" for i in range(d)], *names("p", out))
    keep = ["vid", "c", *names("s", d), *names("p", out)]
    if spec.self_dependent:
        rows = rows.join(own_new.selectExpr("vid", *[f"h{i} AS o{i}" for i in range(d)]), "vid")
    return transform(rows, spec, keep)


def hop_step(state: GraphState, effect: NetEffect, changed: DataFrame, own_new: DataFrame, hop: int, spec: LayerSpec, pin=pinned) -> tuple[DataFrame, DataFrame]:
    """(inbox, rows) of one hop. ``own_new``: changed vectors of the hop before (vid, h0..), over stored ones."""
    inbox = merge_inbox(messages(changed, state, effect, hop, spec), spec.d_in)
    if state.prunes:
        inbox = pin(inbox)
    also = changed.select("vid") if spec.self_dependent else None
    who = inbox.select("vid") if also is None else inbox.select("vid").unionByName(also)
    own = None
    if spec.self_dependent:
        own = overlay(state.layer_of(hop - 1, who).select("vid", *names("h", spec.d_in)), own_new, ["vid"])
    return inbox, apply_inbox(state.layer_of(hop, who), inbox, own, also, spec)


def new_vectors(changed: DataFrame, d: int) -> DataFrame:
    """(vid, h0..) after the batch of changed vertices (vid, old.., new..)."""
    return changed.selectExpr("vid", *[f"new{i} AS h{i}" for i in range(d)])


def deltas(rows: DataFrame, d: int) -> DataFrame:
    """(vid, old0.., new0..) of applied rows."""
    return rows.selectExpr("vid", *[f"p{i} AS old{i}" for i in range(d)], *[f"h{i} AS new{i}" for i in range(d)])


def differing(changed: DataFrame, d: int) -> DataFrame:
    """Only vertices whose vector differs; sending nothing for the rest is lossless."""
    return changed.where(" OR ".join(f"old{i} <> new{i}" for i in range(d)))


def apply_incremental(state: GraphState, effect: NetEffect, model: ModelSpec, prune_zero: bool = False, pin=pinned) -> BatchResult:
    """``pin`` is applied to what several later plans read (changed rows): persist, checkpoint or write."""
    for spec in model.layers:
        spec.require_inverse()
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    changed = [effect.d_feats]
    hops = [effect.d_feats.select("vid")]
    inboxes, made = [], []
    for hop, spec in enumerate(model.layers, 1):
        before = differing(changed[-1], spec.d_in) if prune_zero else changed[-1]
        inbox, rows = hop_step(state, effect, before, new_vectors(changed[-1], spec.d_in), hop, spec, pin)
        rows = pin(rows)
        inboxes.append(inbox)
        made.append(rows.select(*state.layers[hop].columns))
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
        changed.append(deltas(rows, spec.d_out))
        hops.append(rows.select("vid"))
    after = GraphState(state.vertices, edges_after(state.edges, effect.d_edges, effect.small), layers, state.version + 1)
    return BatchResult(after, hops, changed, inboxes, ["incremental"] * model.depth, made)
