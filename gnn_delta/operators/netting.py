"""Net effect of a batch of updates.

Updates act in ``seq`` order; per edge and per vertex the last one counts, so a batch equals its members
one at a time. Additions of an edge that exists with that weight, deletions of a missing edge, and feature
writes of the stored vector change nothing; they are ignored (and listed). Updates that name unknown
vertices, or features that are not finite, are set aside. Only the stored rows that a batch names are read.

Late updates: an update whose ``seq`` is not newer than the one last applied to its key is left out by
:func:`without_stale`.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import names
from ..plans.scratch import LOCAL_ROWS, forget, settled_batch
from ..plans.state import GraphState

UPDATE_SCHEMA = "seq BIGINT, ts TIMESTAMP, kind STRING, src BIGINT, dst BIGINT, w DOUBLE, feat ARRAY<DOUBLE>"
KINDS = ("edge_add", "edge_del", "feat_set")


@dataclass
class NetEffect:
    d_edges: DataFrame  # src, dst, w_old, w_new (null: absent)
    d_feats: DataFrame  # vid, old0.., new0..
    ignored: DataFrame  # seq, reason
    quarantined: DataFrame  # update rows
    small: bool = True  # whether the batch is small enough to be sent to all tasks
    size: int | None = None  # number of updates, where known


#: batches up to this many updates are broadcast, larger ones are joined by shuffle
BROADCAST_UPDATES = 500_000


def side(df: DataFrame, small: bool) -> DataFrame:
    return F.broadcast(df) if small else df


def last_writers(updates: DataFrame) -> DataFrame:
    """The last update of each edge, and of each vertex's features (ties on seq: the larger row wins)."""
    edge = F.col("kind") != "feat_set"
    order = Window.partitionBy(edge, "src", "dst").orderBy(F.desc("seq"), F.desc("kind"), F.desc("w"))
    return updates.withColumn("_n", F.row_number().over(order)).where("_n = 1").drop("_n")


def net_effect(updates: DataFrame, state: GraphState, d: int, size: int | None = None) -> NetEffect:
    """``size``: the number of updates where the caller knows it (else they are counted up to the bound)."""
    size = updates.limit(BROADCAST_UPDATES + 1).count() if size is None else size
    small, local = size <= BROADCAST_UPDATES, size <= LOCAL_ROWS
    if local:  # one partition: the steps below need no exchange
        updates = updates.coalesce(1)
    named = updates.select(F.explode(F.array("src", "dst")).alias("vid")).where("vid is not null").distinct()
    known = state.known(named).join(side(named, small), "vid", "left_semi")
    known = (settled_batch(known, size) if local else known).selectExpr("vid", "true AS known")
    finite = F.coalesce(~F.exists("feat", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False)) & (F.size("feat") == d)
    with_src = updates.join(side(known.selectExpr("vid AS src", "known AS has_src"), small), "src", "left")
    checked = with_src.join(side(known.selectExpr("vid AS dst", "known AS has_dst"), small), "dst", "left")
    good = F.coalesce(
        F.col("has_src") & F.when(F.col("kind") == "feat_set", finite).otherwise(F.col("has_dst") & F.col("kind").isin("edge_add", "edge_del")), F.lit(False)
    )
    checked = checked.withColumn("good", good)
    last = last_writers(checked.where("good")).select(*updates.columns)
    if local:
        last = settled_batch(last, size).coalesce(1)
    wanted = last.where("kind <> 'feat_set'").select("src", "dst", "seq", F.when(F.col("kind") == "edge_add", F.coalesce("w", F.lit(1.0))).alias("w_new"))
    senders = wanted.select(F.col("src").alias("vid"))
    stored = state.edges_from(senders).join(side(wanted.select("src", "dst"), small), ["src", "dst"], "left_semi").select("src", "dst", F.col("w").alias("w_old"))
    compared = wanted.join(stored, ["src", "dst"], "left").withColumn("same", F.col("w_old").eqNullSafe(F.col("w_new")))
    feats = last.where("kind = 'feat_set'").select(F.col("src").alias("vid"), "seq", "feat")
    old = state.layer_of(0, feats.select("vid")).join(side(feats, small), "vid")
    same = " AND ".join(f"h{i} = feat[{i}]" for i in range(d))
    d_feats = old.selectExpr("vid", *[f"h{i} AS old{i}" for i in range(d)], *[f"feat[{i}] AS new{i}" for i in range(d)])
    unchanged = compared.where("same").select("seq").unionByName(old.where(same).select("seq"))
    ignored = unchanged.select("seq", F.lit("no change").alias("reason")).unionByName(
        checked.where("good").join(last.select("seq", F.col("kind")), ["seq", "kind"], "left_anti").select("seq", F.lit("overwritten").alias("reason"))
    )
    return NetEffect(compared.where("not same").select("src", "dst", "w_old", "w_new"), d_feats, ignored, checked.where("not good").select(*updates.columns), small, size)


def settled_effect(effect: NetEffect) -> NetEffect:
    """The effect with its two tables made once, as several plans read them, without writes of the stored vector.

    The filter stands on a finished table: above the aliases of the old and new columns its derived constraints
    would double with each column."""
    raw = settled_batch(effect.d_feats, effect.size)
    differs = " OR ".join(f"{c} <> new{c[3:]}" for c in raw.columns if c.startswith("old"))
    d_feats = settled_batch(raw.where(differs), effect.size)
    forget(raw)
    return replace(effect, d_edges=settled_batch(effect.d_edges, effect.size), d_feats=d_feats)


def edges_after(edges: DataFrame, d_edges: DataFrame, small: bool = True, carry: tuple[str, ...] = ()) -> DataFrame:
    """The edge table with a batch laid over it: rows of changed pairs replaced (the batch side is small)."""
    kept = edges.join(side(d_edges.select("src", "dst"), small), ["src", "dst"], "left_anti")
    fresh = d_edges.where("w_new is not null").select("src", "dst", F.col("w_new").alias("w"), *carry)
    return kept.select("src", "dst", "w", *carry).unionByName(fresh)


def out_edges(state: GraphState, effect: NetEffect, senders: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    """The edges after the batch, read only where ``senders`` (vid) may have out-edges; nothing is written."""
    return edges_after(state.edges_from(senders), effect.d_edges, effect.small, carry)


def features_after(features: DataFrame, d_feats: DataFrame, d: int, small: bool = True) -> DataFrame:
    new = d_feats.selectExpr("vid", *[f"new{i} AS {h}" for i, h in enumerate(names("h", d))])
    kept = features.join(side(new.select("vid"), small), "vid", "left_anti")
    return kept.unionByName(new)


def degree_delta(d_edges: DataFrame) -> DataFrame:
    """(vid, d_indeg, d_wsum) of the sinks of changed edges."""
    return d_edges.groupBy(F.col("dst").alias("vid")).agg(
        F.sum(F.col("w_new").isNotNull().cast("long") - F.col("w_old").isNotNull().cast("long")).alias("d_indeg"),
        F.sum(F.coalesce("w_new", F.lit(0.0)) - F.coalesce("w_old", F.lit(0.0))).alias("d_wsum"),
    )


def seqs_of(updates: DataFrame) -> DataFrame:
    """(src, dst, last_seq) of the keys that updates write; dst is -1 for features."""
    return updates.groupBy("src", F.coalesce("dst", F.lit(-1)).alias("dst")).agg(F.max("seq").alias("last_seq"))


def without_stale(updates: DataFrame, applied: DataFrame) -> DataFrame:
    """Updates newer than the newest applied to their key. ``applied``: (src, dst, last_seq) as of :func:`seqs_of`."""
    known = applied.select(F.col("src").alias("a_src"), F.col("dst").alias("a_dst"), "last_seq")
    joined = updates.join(known, (F.col("src") == F.col("a_src")) & (F.coalesce("dst", F.lit(-1)) == F.col("a_dst")), "left")
    return joined.where("last_seq is null or seq > last_seq").select(*updates.columns)


def removal_updates(vertices: DataFrame, edges: DataFrame, first_seq: int) -> DataFrame:
    """Updates that take vertices out of the graph: deletion of every incident edge."""
    gone = vertices.select("vid")
    out = edges.join(gone.withColumnRenamed("vid", "src"), "src", "left_semi").unionByName(edges.join(gone.withColumnRenamed("vid", "dst"), "dst", "left_semi")).distinct()
    # one update for each edge: their order is free, so the key hash serves as seq
    seq = F.lit(first_seq) + F.abs(F.xxhash64("src", "dst") % (1 << 40))
    null = lambda t: F.lit(None).cast(t)
    return out.select(seq.alias("seq"), null("timestamp").alias("ts"), F.lit("edge_del").alias("kind"), "src", "dst", null("double").alias("w"), null("array<double>").alias("feat"))
