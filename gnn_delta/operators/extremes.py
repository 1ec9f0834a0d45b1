"""Max and min aggregates kept up to date without an inverse.

A stored extreme stays right unless a value that equals it is lost (a deleted edge, a sender that changed) and
nothing gained reaches it. Then, and only then, the vertex pulls all its in-neighbours again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.model import LayerSpec, ModelSpec, NonInvertibleAggregator
from ..plans.state import BatchResult, GraphState, overlay, pinned
from .incremental import deltas
from .layers import layer_forward, transform
from .netting import NetEffect, degree_delta, edges_after, features_after, out_edges, side


def gains_and_losses(changed: DataFrame, state: GraphState, effect: NetEffect, hop: int, spec: LayerSpec) -> DataFrame:
    """(vid, g0.., l0..): the extreme of what receivers gain and of what they lose; null where nothing."""
    d, best = range(spec.d_in), spec.agg
    senders = changed.select("vid")
    vector = lambda df, prefix, to: df.selectExpr("vid AS src", *[f"{prefix}{i} AS {to}{i}" for i in d])
    none = lambda to: [f"CAST(NULL AS DOUBLE) AS {to}{i}" for i in d]
    after = out_edges(state, effect, senders).join(vector(changed, "new", "g"), "src").selectExpr("dst", *names("g", spec.d_in), *none("l"))
    before = state.edges_from(senders).join(vector(changed, "old", "l"), "src").selectExpr("dst", *none("g"), *names("l", spec.d_in))
    own = effect.d_edges.join(senders.withColumnRenamed("vid", "src"), "src", "left_anti")  # edges of senders that stay the same
    held = vector(state.layer_of(hop - 1, own.select(F.col("src").alias("vid"))), "h", "x").join(side(own, effect.small), "src")
    one = held.selectExpr("dst", *[f"CASE WHEN w_old IS NULL THEN x{i} END AS g{i}" for i in d], *[f"CASE WHEN w_new IS NULL THEN x{i} END AS l{i}" for i in d])
    both = after.unionByName(before).unionByName(one)
    return both.groupBy(F.col("dst").alias("vid")).agg(*[F.expr(f"{best}({c}) AS {c}") for c in (*names("g", spec.d_in), *names("l", spec.d_in))])


def apply_extreme(state: GraphState, effect: NetEffect, model: ModelSpec, pin=pinned) -> BatchResult:
    """Batches for models whose layers aggregate by max or min."""
    edges_new = edges_after(state.edges, effect.d_edges, effect.small)
    moved = degree_delta(effect.d_edges).select("vid", "d_indeg")
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    changed, hops, made, how = [effect.d_feats], [effect.d_feats.select("vid")], [], []
    for hop, spec in enumerate(model.layers, 1):
        if spec.agg not in ("max", "min") or spec.self_dependent:
            raise NonInvertibleAggregator(f"{spec.conv} {spec.agg}")
        d, out = range(spec.d_in), spec.d_out
        worst, better, pick = ("-Infinity", ">=", "greatest") if spec.agg == "max" else ("Infinity", "<=", "least")
        bound = lambda x: f"coalesce({x}, DOUBLE('{worst}'))"  # noqa: E731, B023
        news = gains_and_losses(changed[-1], state, effect, hop, spec)
        who = news.join(moved, "vid", "full_outer")
        rows = state.layer_of(hop, who.select("vid")).join(who, "vid").selectExpr(
            "vid", "c AS c_old", "c + coalesce(d_indeg, 0L) AS c", *[f"CASE WHEN c > 0 THEN s{i} ELSE DOUBLE('{worst}') END AS b{i}" for i in d],
            *[f"{bound(f'g{i}')} AS g{i}" for i in d], *[f"{bound(f'l{i}')} AS l{i}" for i in d], *[f"h{i} AS p{i}" for i in range(out)],
        )
        # a lost value that equals the stored extreme, and no gain that reaches it
        lost = " OR ".join(f"(c_old > 0 AND l{i} = b{i} AND NOT g{i} {better} b{i})" for i in d)
        rows = pin(rows.selectExpr("vid", "c", f"c > 0 AND ({lost}) AS again", *[f"CASE WHEN c = 0 THEN 0D ELSE {pick}(b{i}, g{i}) END AS s{i}" for i in d], *names("p", out)))
        keep = ["vid", "c", *names("s", spec.d_in), *names("p", out)]
        kept = transform(rows.where("not again").select(*keep), spec, keep)
        asked = rows.where("again").select("vid")
        pulled = edges_new.join(asked.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        fresh = layer_forward(pulled, layers[-1], spec, asked).join(rows.select("vid", *names("p", out)), "vid")
        rows = pin(kept.unionByName(fresh.select(*kept.columns)))
        made.append(rows.select(*state.layers[hop].columns))
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
        changed.append(deltas(rows, out))
        hops.append(rows.select("vid"))
        how.append("extreme")
    return BatchResult(GraphState(state.vertices, edges_new, layers, state.version + 1), hops, changed, [], how, made)
