"""Partitioned execution: placement of vertices, routing of updates, exchange of vectors.

A column ``part`` says where a vertex lives. :func:`layout` stores every edge once with the parts of both its
ends, in files bucketed by its source's part; a batch reads them there. Incremental: messages are summed
beside their senders (one vector per receiver and part), the shuffle by the receiver's part is the exchange,
the stage boundary the barrier between hops. Scoped recompute: parts ask for the vectors of remote sources,
one per source and asking part, and aggregate at home.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mixes import hash_part
from ..functions.vectors import names
from ..plans.model import ModelSpec
from ..plans.scratch import settled_batch, shared_dir
from ..plans.state import BatchResult, GraphState, overlay, pinned
from .affected import affected_sets
from .incremental import apply_inbox, deltas, messages
from .layers import finish_rows, gather
from .netting import NetEffect, edges_after, features_after, side


def place(vertices: DataFrame, edges: DataFrame, parts: int, method: str = "hash", rounds: int = 4) -> DataFrame:
    """(vid, part): hash, range (equal ranks of ids), greedy or labelprop (both fewer cut edges), multilevel."""
    if method == "hash":
        placed = vertices.select("vid", hash_part(F.col("vid"), parts).alias("part"))
        placed._part_of = lambda vid: hash_part(vid, parts)
        return placed
    if method == "range":
        bounds = vertices.approxQuantile("vid", [i / parts for i in range(1, parts)], 0.0)
        part = F.lit(0)
        for b in bounds:
            part = part + (F.col("vid") > b).cast("int")
        return vertices.select("vid", part.cast("int").alias("part"))
    if method == "greedy":
        return improved(place(vertices, edges, parts, "range"), edges, parts, 1)
    if method == "labelprop":
        return improved(place(vertices, edges, parts, "hash"), edges, parts, rounds)
    if method == "multilevel":
        coarse = matched(vertices, edges)
        # parts of pairs that share their heaviest edge, refined as single vertices afterwards
        heads = coarse.select(F.col("head").alias("vid")).distinct()
        joined = edges.join(coarse.withColumnRenamed("vid", "src"), "src").withColumnRenamed("head", "a").join(coarse.withColumnRenamed("vid", "dst"), "dst").withColumnRenamed("head", "b")
        small = joined.where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("w").alias("w"))
        first = place(heads, small, parts, "labelprop", rounds)
        back = coarse.join(first.withColumnRenamed("vid", "head"), "head").select("vid", "part")
        return improved(back, edges, parts, 1)
    raise ValueError(method)


def matched(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """(vid, head): each vertex with the partner that it and that partner both prefer, else alone."""
    both = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).where("src <> dst")
    weight = both.groupBy("src", "dst").agg(F.count("*").alias("n"))
    best = weight.groupBy("src").agg(F.max_by("dst", F.struct("n", F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst")))).alias("dst"))
    mutual = best.alias("a").join(best.alias("b"), (F.col("a.dst") == F.col("b.src")) & (F.col("b.dst") == F.col("a.src"))).select(F.col("a.src").alias("vid"), F.least("a.src", "a.dst").alias("head"))
    return vertices.join(mutual, "vid", "left").select("vid", F.coalesce("head", "vid").alias("head"))


def improved(placed: DataFrame, edges: DataFrame, parts: int, rounds: int, slack: float = 1.1) -> DataFrame:
    """Capacity-bounded label propagation: vertices move to the part that holds most neighbours while it has room."""
    total = placed.count()
    room = int(total / parts * slack) + 1
    both = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    for r in range(rounds):
        near = both.join(placed.withColumnRenamed("vid", "dst"), "dst").groupBy("src", "part").agg(F.count("*").alias("n"))
        best = near.groupBy(F.col("src").alias("vid")).agg(F.max_by("part", F.struct("n", F.xxhash64("src", "part", F.lit(r)))).alias("wish"), F.max("n").alias("gain"))
        moves = placed.join(best, "vid", "left").withColumn("wish", F.coalesce("wish", "part"))
        stay = moves.where("wish = part").groupBy("part").agg(F.count("*").alias("held"))
        order = Window.partitionBy("wish").orderBy(F.desc("gain"), F.xxhash64("vid"))
        asked = moves.where("wish <> part").withColumn("rank", F.row_number().over(order)).join(F.broadcast(stay.withColumnRenamed("part", "wish")), "wish", "left")
        # half of the room each round, so that swapping pairs settle
        go = asked.withColumn("go", F.col("rank") * 2 <= F.lit(room) - F.coalesce("held", F.lit(0)))
        placed = moves.where("wish = part").select("vid", "part").unionByName(go.select("vid", F.when(F.col("go"), F.col("wish")).otherwise(F.col("part")).cast("int").alias("part")))
        placed = pinned(placed)
    return placed


def rebalance(placed: DataFrame, fresh: DataFrame, edges: DataFrame, parts: int, slack: float = 1.1) -> DataFrame:
    """Place new vertices (vid) beside their neighbours while there is room, else in the emptiest part."""
    total = placed.count() + fresh.count()
    room = int(total / parts * slack) + 1
    load = placed.groupBy("part").agg(F.count("*").alias("held"))
    both = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    votes = both.join(fresh.withColumnRenamed("vid", "src"), "src", "left_semi").join(placed.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid"), "part").agg(F.count("*").alias("n"))
    wish = votes.groupBy("vid").agg(F.max_by("part", "n").alias("part"))
    empty = load.agg(F.min_by("part", "held")).first()[0]
    asked = fresh.select("vid").join(wish, "vid", "left").withColumn("part", F.coalesce("part", F.lit(empty))).join(F.broadcast(load), "part", "left")
    rank = F.row_number().over(Window.partitionBy("part").orderBy(F.xxhash64("vid")))
    spread = F.pmod(F.xxhash64("vid"), F.lit(parts)).cast("int")
    return asked.withColumn("part", F.when(rank + F.col("held") <= room, F.col("part")).otherwise(spread).cast("int")).select("vid", "part")


def with_parts(edges: DataFrame, placed: DataFrame) -> DataFrame:
    """Edges with the parts p and q of their ends: computed from the ids where these place a vertex, else looked up."""
    if part_of := getattr(placed, "_part_of", None):
        return edges.withColumns({"p": part_of(F.col("src")), "q": part_of(F.col("dst"))})
    p, q = (placed.select(F.col("vid").alias(v), F.col("part").alias(c)) for v, c in (("src", "p"), ("dst", "q")))
    return edges.join(p, "src").join(q, "dst")


def route(updates: DataFrame, placed: DataFrame) -> DataFrame:
    """(seq, part, role): each update to the part of its hop-0 vertex; an edge whose sink lives elsewhere
    sends a topology-only request there too."""
    src = updates.join(placed.select(F.col("vid").alias("src"), F.col("part").alias("p_src")), "src")
    both = src.join(placed.select(F.col("vid").alias("dst"), F.col("part").alias("p_dst")), "dst", "left")
    compute = both.select("seq", F.col("p_src").alias("part"), F.lit("compute").alias("role"))
    topology = both.where("kind <> 'feat_set' and p_dst <> p_src").select("seq", F.col("p_dst").alias("part"), F.lit("topology_only").alias("role"))
    return compute.unionByName(topology)


def cut_stats(edges: DataFrame, placed: DataFrame) -> DataFrame:
    """(part, vertices, out_cut, ghosts): size, edges that leave, and remote sinks replicated as stubs."""
    cut = with_parts(edges, placed).where("p <> q").groupBy(F.col("p").alias("part")).agg(F.count("*").alias("out_cut"), F.countDistinct("dst").alias("ghosts"))
    size = placed.groupBy("part").agg(F.count("*").alias("vertices"))
    return size.join(cut, "part", "left").select(F.col("part").cast("long").alias("part"), "vertices", F.coalesce("out_cut", F.lit(0)).alias("out_cut"), F.coalesce("ghosts", F.lit(0)).alias("ghosts"))


def ghosts(edges: DataFrame, placed: DataFrame) -> DataFrame:
    """(vid, part): boundary vertices and the remote parts that hold a stub of them."""
    return with_parts(edges, placed).where("p <> q").select(F.col("dst").alias("vid"), F.col("p").cast("long").alias("part")).distinct()


PARTS = ("p", "q")  # part of an edge's source and of its sink


def layout(state: GraphState, placed: DataFrame, parts: int) -> GraphState:
    """The state with edges (src, dst, w, p, q) laid out beside their sources, once."""
    spark = placed.sparkSession
    p, q = (placed.select(F.col("vid").alias(v), F.col("part").cast("int").alias(c)) for v, c in (("src", "p"), ("dst", "q")))
    located = state.edges.join(p, "src").join(q, "dst").select("src", "dst", "w", *PARTS)
    name = f"located_{uuid.uuid4().hex}"
    located.repartition(parts, "p").write.bucketBy(parts, "p").sortBy("src").option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    return GraphState(state.vertices, spark.table(name), state.layers, state.version)


def located_effect(effect: NetEffect, placed: DataFrame) -> NetEffect:
    """The batch's edges with the parts of both ends: the batch is small, the map is read once."""
    near = placed.join(side(effect.d_edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), effect.small), "vid", "left_semi")
    p, q = (near.select(F.col("vid").alias(v), F.col("part").cast("int").alias(c)) for v, c in (("src", "p"), ("dst", "q")))
    return replace(effect, d_edges=settled_batch(effect.d_edges.join(p, "src").join(q, "dst"), effect.size))


def partial_sums(sent: DataFrame, d: int) -> DataFrame:
    """Messages summed per receiver inside the sender's part: what a stub collects. ``sent`` carries p and q."""
    sums = [F.sum(f"m{i}").alias(f"m{i}") for i in range(d)]
    return sent.groupBy("p", "dst", "q").agg(F.sum("d_indeg").alias("d_indeg"), F.count("*").alias("n"), *sums)


def exchange_inbox(partial: DataFrame, d: int, parts: int) -> DataFrame:
    """The inbox at the owners: partial sums go to the receiver's part and are summed there, without another shuffle."""
    sums = [F.sum(f"m{i}").alias(f"m{i}") for i in range(d)]
    home = partial.repartition(parts, "q").groupBy("q", F.col("dst").alias("vid"))
    return home.agg(F.sum("d_indeg").alias("d_indeg"), F.sum("n").alias("n_msgs"), *sums).drop("q")


@dataclass
class PartitionedResult:
    result: BatchResult
    partials: list[DataFrame]


def apply_partitioned(state: GraphState, effect: NetEffect, model: ModelSpec, placed: DataFrame, parts: int, pin=pinned) -> PartitionedResult:
    """Incremental propagation with placed vertices: local sums, exchange, apply at the owner, hop by hop."""
    if "p" not in state.edges.columns:
        state = layout(state, placed, parts)
    effect = located_effect(effect, placed)
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    changed, hops, partials, made = [effect.d_feats], [effect.d_feats.select("vid")], [], []
    for hop, spec in enumerate(model.layers, 1):
        spec.require_inverse()
        sent = messages(changed[-1], state, effect, hop, spec, PARTS)
        partial = partial_sums(sent, spec.d_in)
        partials.append(partial)
        inbox = exchange_inbox(partial, spec.d_in, parts)
        rows = pin(apply_inbox(state.layers[hop], inbox, layers[-1], changed[-1].select("vid") if spec.self_dependent else None, spec))
        made.append(rows)
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
        changed.append(deltas(rows, spec.d_out))
        hops.append(rows.select("vid"))
    after = GraphState(state.vertices, edges_after(state.edges, effect.d_edges, effect.small, PARTS), layers, state.version + 1)
    return PartitionedResult(BatchResult(after, hops, changed, [], ["partitioned"] * model.depth, made), partials)


def pull_requests(pulled: DataFrame) -> DataFrame:
    """(src, q): each source that a part needs, once per part, at home or remote."""
    return pulled.select("src", "q").distinct()


def apply_scoped_partitioned(state: GraphState, effect: NetEffect, model: ModelSpec, placed: DataFrame, parts: int, pin=pinned) -> PartitionedResult:
    """Scoped recompute with placed vertices: every affected vertex's part pulls all its sources, changed or not."""
    if "p" not in state.edges.columns:
        state = layout(state, placed, parts)
    effect = located_effect(effect, placed)
    edges_new = edges_after(state.edges, effect.d_edges, effect.small, PARTS)
    layers = [features_after(state.layers[0], effect.d_feats, model.layers[0].d_in, effect.small)]
    hops = affected_sets(edges_new, effect.d_edges, effect.d_feats, model, pin)
    answers, made = [], []
    for hop, spec in enumerate(model.layers, 1):
        if spec.agg in ("norm", "attention"):
            raise NotImplementedError(f"partitioned recompute of {spec.agg}")
        pulled = edges_new.join(hops[hop].withColumnRenamed("vid", "dst"), "dst", "left_semi")
        vectors = layers[hop - 1].select(F.col("vid").alias("src"), *names("h", spec.d_in))
        answer = pull_requests(pulled).join(vectors, "src").withColumnRenamed("src", "vid")
        answers.append(answer)
        moved = answer.repartition(parts, "q").withColumn("degree", F.lit(0))
        agg = gather(pulled, moved, spec, ("q",)).drop("q")
        rows = pin(finish_rows(hops[hop], agg, layers[hop - 1], spec))
        made.append(rows)
        layers.append(overlay(state.layers[hop], rows, ["vid"]))
    after = GraphState(state.vertices, edges_new, layers, state.version + 1)
    return PartitionedResult(BatchResult(after, hops, [], [], ["scoped_partitioned"] * model.depth, made), answers)


def exchange_counts(edges_old: DataFrame, effect: NetEffect, model: ModelSpec, placed: DataFrame, strategy: str, hops: list[DataFrame] | None = None) -> DataFrame:
    """(hop, vectors, bytes) that cross between parts.

    incremental: distinct (receiver, sending part) of remote messages. scoped: distinct (source, pulling
    part) over all in-edges of affected vertices, changed or not. ``hops``: the affected sets where the caller has them."""
    edges_new = edges_after(edges_old, effect.d_edges, effect.small)
    hops = hops or affected_sets(edges_new, effect.d_edges, effect.d_feats, model, pinned)
    out = None
    for hop, spec in enumerate(model.layers, 1):
        if strategy == "incremental":
            touched = edges_new.select("src", "dst").join(hops[hop - 1].withColumnRenamed("vid", "src"), "src", "left_semi").unionByName(effect.d_edges.select("src", "dst"))
            pairs = with_parts(touched, placed).where("p <> q").select("dst", "p").distinct()
        else:
            pulled = edges_new.select("src", "dst").join(hops[hop].withColumnRenamed("vid", "dst"), "dst", "left_semi")
            pairs = with_parts(pulled, placed).where("p <> q").select("src", "q").distinct()
        row = pairs.agg(F.count("*").alias("vectors")).select(F.lit(hop).cast("long").alias("hop"), "vectors", (F.col("vectors") * 8 * spec.d_in).alias("bytes"))
        out = row if out is None else out.unionByName(row)
    return out
