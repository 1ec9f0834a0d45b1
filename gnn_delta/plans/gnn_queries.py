"""Queries of the graph methods, each with an SQL oracle that recomputes on the final graph."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.mixes import edge_mix_sql, part_sql
from ..functions.vectors import names, tidy, to_long
from ..operators import affected as aff
from ..operators import incremental as inc
from ..operators import measures as ms
from ..operators import partition as pt
from ..operators.full import infer_full
from ..operators.hybrid import apply_hybrid
from ..operators.labels import edge_scores, label_changes, labels, lookup
from ..operators.extremes import apply_extreme
from ..operators.netting import edges_after, features_after, net_effect, removal_updates, settled_effect
from ..operators.recompute import apply_scoped
from ..operators.vertexwise import infer_vertexwise, sampled_edges
from ..operators.vertices import insert
from ..sources.graphs import D, GRAPHS, formula_features, graph_ctes, table, weighted
from ..sources.updates import assign_batches, stream_ctes
from . import oracle as o
from .cases import N_EACH_SQL, Case, case
from .model import WORKLOADS, ModelSpec, make_model, model_rows
from .state import pinned

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

BATCH = "seq <= 100"
PARTS = 4
UPDATE_TYPES = "seq BIGINT, ts TIMESTAMP, kind STRING, src BIGINT, dst BIGINT, w DOUBLE, feat ARRAY<DOUBLE>"


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def digits(model: ModelSpec) -> int | None:
    return None if model.exact else 6


def base_ctes(graph: str, second: bool = False, hold_out: float = 0.1) -> list[tuple[str, str]]:
    feats = (o.second_features_sql if second else o.features_sql)(D)
    return [*graph_ctes(graph), *stream_ctes(N_EACH_SQL, hold_out), ("h_0", feats)]


def new_ctes(graph: str, model: ModelSpec, where: str, old: bool = False, second: bool = False, hold_out: float = 0.1) -> list[tuple[str, str]]:
    ctes = [*base_ctes(graph, second, hold_out), *o.final_ctes(where), ("n_0", o.features_after_sql(D))]
    if old:
        ctes += o.full_ctes(model, "snap", "h_0", "h")
    return ctes + o.full_ctes(model, "e_new", "n_0", "n")


def final_sql(graph: str, model: ModelSpec, where: str, **kw) -> str:
    return o.with_sql(new_ctes(graph, model, where, **kw), o.long_select(f"n_{model.depth}", model.layers[-1].d_out, digits(model)))


def d_edge_ctes() -> tuple[str, str]:
    return ("d_e", "SELECT x.src, x.dst, e.w AS w_old, CASE WHEN x.kind = 'edge_add' THEN coalesce(x.w, 1.0) END AS w_new FROM last_e x LEFT JOIN snap e ON e.src = x.src AND e.dst = x.dst WHERE e.w IS DISTINCT FROM CASE WHEN x.kind = 'edge_add' THEN coalesce(x.w, 1.0) END")


def hop_ctes(model: ModelSpec) -> list[tuple[str, str]]:
    out = [d_edge_ctes(), ("a_0", "SELECT DISTINCT src AS vid FROM last_f")]
    for i, spec in enumerate(model.layers, 1):
        own = f" UNION SELECT vid FROM a_{i - 1}" if spec.self_dependent else ""
        out.append((f"a_{i}", f"SELECT dst AS vid FROM d_e UNION SELECT e.dst FROM e_new e JOIN a_{i - 1} a ON a.vid = e.src{own}"))
    return out


# --- graphs and streams ------------------------------------------------------------------------------

for _name in GRAPHS:
    query(f"graph_{_name}", o.with_sql(graph_ctes(_name), "SELECT src, dst, w FROM g"))(lambda s, d, n=_name: GRAPHS[n](s, d).select("src", "dst", "w"))


@query("degree_stats", " UNION ALL ".join(f"SELECT * FROM ({o.with_sql(graph_ctes(n), q)})" for n, q in [(n, f"SELECT '{n}' AS graph, (SELECT count(*) FROM (SELECT src FROM g UNION SELECT dst FROM g)) AS vertices, (SELECT count(*) FROM g) AS edges, (SELECT max(k) FROM (SELECT count(*) AS k FROM g GROUP BY dst)) AS max_indeg") for n in ("order_part", "supplier_part", "next_part", "turn_chain")]))
def degree_stats(s: SparkSession, d: str) -> DataFrame:
    out = None
    for n in ("order_part", "supplier_part", "next_part", "turn_chain"):
        e = GRAPHS[n](s, d)
        v = e.select(F.col("src").alias("vid")).unionByName(e.select(F.col("dst").alias("vid"))).agg(F.countDistinct("vid").alias("vertices"))
        k = e.groupBy("dst").agg(F.count("*").alias("k")).agg(F.sum("k").alias("edges"), F.max("k").alias("max_indeg"))
        row = v.crossJoin(k).select(F.lit(n).alias("graph"), "vertices", "edges", "max_indeg")
        out = row if out is None else out.unionByName(row)
    return out


def _with_stream(select: str, graph: str = "order_part") -> str:
    return o.with_sql(base_ctes(graph), select)


@query("stream_updates", _with_stream("SELECT seq, kind, src, coalesce(dst, -1) AS dst, coalesce(w, -1) AS w, coalesce(f0, -9) AS f0, coalesce(f7, -9) AS f7 FROM upd"))
def stream_updates(s, d):
    return case(s, d).stream.updates.select(
        "seq", "kind", "src", F.coalesce("dst", F.lit(-1)).alias("dst"), F.coalesce("w", F.lit(-1.0)).alias("w"), F.coalesce(F.col("feat")[0], F.lit(-9.0)).alias("f0"), F.coalesce(F.col("feat")[7], F.lit(-9.0)).alias("f7")
    )


@query("stream_batches", _with_stream("SELECT (seq - 1) // 10 AS batch_id, count(*) AS n, count(DISTINCT kind) AS kinds FROM upd GROUP BY 1"))
def stream_batches(s, d):
    return assign_batches(case(s, d).stream.updates, 10).groupBy("batch_id").agg(F.count("*").alias("n"), F.countDistinct("kind").alias("kinds"))


@query("stream_time_batches", _with_stream("SELECT (seq // 10) - (SELECT min(seq // 10) FROM upd) AS batch_id, count(*) AS n FROM upd GROUP BY 1"))
def stream_time_batches(s, d):
    return assign_batches(case(s, d).stream.updates, by="time", every="10 seconds").groupBy("batch_id").agg(F.count("*").alias("n"))


@query("net_effect", o.with_sql([*base_ctes("order_part"), *o.final_ctes(BATCH), d_edge_ctes()], "SELECT src, dst, coalesce(w_old, -1) AS w_old, coalesce(w_new, -1) AS w_new FROM d_e"))
def net_effect_query(s, d):
    c = case(s, d)
    found = c.effect(make_model("gc_sum", 2), BATCH).d_edges
    return found.select("src", "dst", *[F.coalesce(w, F.lit(-1.0)).alias(w) for w in ("w_old", "w_new")])


@query("stream_kind_counts", _with_stream("SELECT kind, count(*) AS n FROM upd GROUP BY kind"))
def stream_kind_counts(s, d):
    return case(s, d).stream.updates.groupBy("kind").agg(F.count("*").alias("n"))


@query("snapshot_edges", _with_stream("SELECT src, dst, w FROM snap"))
def snapshot_edges(s, d):
    return case(s, d).stream.snapshot


# --- bootstrap ---------------------------------------------------------------------------------------

def _full(kind: str, depth: int, graph: str = "order_part") -> None:
    model = make_model(kind, depth)
    sql = o.with_sql([*base_ctes(graph), *o.full_ctes(model, "snap")], o.long_select(f"h_{depth}", D, digits(model)))
    query(f"full_{'normalised' if kind == 'gc_norm' else kind}_{depth}l", sql)(lambda s, d: to_long(case(s, d, graph).outputs(model), "h", D, digits(model)))


for _kind in WORKLOADS:
    for _depth in (2, 3):
        _full(_kind, _depth)
for _kind in ("gc_norm", "sage_mean", "gc_sum_mean", "gc_max", "gc_min"):
    _full(_kind, 2)


@query("full_bias_2l", o.with_sql([*base_ctes("order_part"), *o.full_ctes(make_model("sage_sum", 2, bias=True), "snap")], o.long_select("h_2", D)))
def full_bias(s, d):
    return to_long(case(s, d).outputs(make_model("sage_sum", 2, bias=True)), "h", D)


@query("full_attention_2l", o.with_sql([*base_ctes("order_part"), *o.full_ctes(make_model("gc_attention", 2), "snap")], o.long_select("h_2", D, 4)))
def full_attention(s, d):
    return to_long(case(s, d).outputs(make_model("gc_attention", 2)), "h", D, 4)


@query("labels_2l", o.with_sql([*base_ctes("order_part"), *o.full_ctes(make_model("gc_sum", 2), "snap")], o.label_sql("h_2", D)))
def labels_2l(s, d):
    return labels(case(s, d).state(make_model("gc_sum", 2)).layers[-1], D)


SECOND_3L = make_model("gc_sum", 3, classes=7, weights="second")


@query("labels_second_3l", o.with_sql([*base_ctes("next_part", True), *o.full_ctes(SECOND_3L, "snap")], o.label_sql("h_3", 7)))
def labels_second(s, d):
    return labels(case(s, d, "next_part", second=True).state(SECOND_3L).layers[-1], 7)


# --- vertex-wise and sampled -------------------------------------------------------------------------

def stale(s: SparkSession, d: str, model: ModelSpec, graph: str = "order_part") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Edges and features after the batch, and the vertices whose last layer it can change: what vertex-wise inference answers."""
    c = case(s, d, graph)
    e = c.effect(model, BATCH)
    edges = edges_after(c.stream.snapshot, e.d_edges, e.small)
    targets = aff.affected_sets(edges, e.d_edges, e.d_feats, model, pinned)[-1]
    return edges, features_after(c.features(), e.d_feats, D, e.small), targets


def stale_ctes(model: ModelSpec, fanout: int | None = None) -> list[tuple[str, str]]:
    ctes = [*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(model), ("n_0", o.features_after_sql(D))]
    if fanout is None:
        return ctes + o.full_ctes(model, "e_new", "n_0", "n")
    return [*ctes, ("se", sampled_cte(fanout, 1, "e_new")), *o.full_ctes(model, "se", "n_0", "n")]


def stale_sql(model: ModelSpec, select: str, fanout: int | None = None) -> str:
    return o.with_sql(stale_ctes(model, fanout), f"SELECT * FROM ({select}) WHERE vid IN (SELECT vid FROM a_{model.depth})")


def _vertexwise(kind: str) -> None:
    model = make_model(kind, 2)

    def run(s, d):
        edges, features, targets = stale(s, d, model)
        return to_long(infer_vertexwise(edges, features, targets, model), "h", D, digits(model))

    query(f"vertexwise_{kind}_2l", stale_sql(model, o.long_select("n_2", D, digits(model))))(run)


_vertexwise("gc_sum")
_vertexwise("sage_sum")
_vertexwise("gc_mean")


def sampled_cte(fanout: int, seed: int, edges: str = "snap") -> str:
    return f"SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY {edge_mix_sql('src', 'dst', seed)}, src) AS r FROM {edges}) WHERE r <= {fanout}"


def _sampled(fanout: int) -> None:
    model = make_model("gc_mean", 2)

    def run(s, d):
        edges, features, targets = stale(s, d, model)
        return to_long(infer_vertexwise(edges, features, targets, model, [fanout] * 2, 1), "h", D, 6)

    query(f"sampled_f{fanout}_2l", stale_sql(model, o.long_select("n_2", D, 6), fanout))(run)


_sampled(2)
_sampled(8)


@query("sampled_edges_f4", o.with_sql([*base_ctes("supplier_part"), ("se", sampled_cte(4, 3))], "SELECT src, dst FROM se"))
def sampled_edges_query(s, d):
    return sampled_edges(case(s, d, "supplier_part").stream.snapshot, 4, 3).select("src", "dst")


FANOUTS = (1, 2, 4, 8, 64)


def _agreement_sql() -> str:
    model = make_model("gc_mean", 2)
    ctes = stale_ctes(model)
    parts = []
    rounded = lambda src: f"SELECT vid, {', '.join(f'round(h{i} + 3e-8, 6) AS h{i}' for i in range(D))} FROM {src}"
    ctes += [("hr", rounded("n_2")), ("le", o.label_sql("hr", D))]
    for f in FANOUTS:
        ctes += [(f"se{f}", sampled_cte(f, 1, "e_new")), *o.full_ctes(model, f"se{f}", "n_0", f"s{f}"), (f"sr{f}", rounded(f"s{f}_2")), (f"ls{f}", o.label_sql(f"sr{f}", D))]
        parts.append(f"SELECT CAST({f} AS BIGINT) AS fanout, count(*) AS n, CAST(sum(CASE WHEN a.label = b.label THEN 1 ELSE 0 END) AS BIGINT) AS agree FROM le a JOIN ls{f} b USING (vid) JOIN a_2 USING (vid)")
    return o.with_sql(ctes, " UNION ALL ".join(parts))


@query("sampled_agreement", _agreement_sql())
def sampled_agreement(s, d):
    model = make_model("gc_mean", 2)
    edges, features, targets = stale(s, d, model)
    rounded = lambda df: df.selectExpr("vid", *[f"round({h} + 3e-8D, 6) AS {h}" for h in names("h", D)])
    edges, features = pinned(edges), pinned(features)  # read by every fan-out
    exact = pinned(rounded(infer_vertexwise(edges, features, targets, model)))
    out = None
    for f in FANOUTS:
        got = pinned(rounded(infer_vertexwise(edges, features, targets, model, [f] * 2, 1)))
        row = ms.agreement(got, exact, D).select(F.lit(f).cast("long").alias("fanout"), "n", "agree")
        out = row if out is None else out.unionByName(row)
    return out


# --- affected sets -----------------------------------------------------------------------------------

AFFECTED = {
    "affected_add": ("gc_sum", 2, f"kind = 'edge_add' AND {BATCH}"), "affected_del": ("gc_sum", 2, f"kind = 'edge_del' AND {BATCH}"),
    "affected_feat": ("gc_sum", 2, f"kind = 'feat_set' AND {BATCH}"), "affected_mixed_3l": ("gc_sum", 3, BATCH), "affected_self_dep": ("sage_sum", 2, BATCH),
}


def _hops(c: Case, model: ModelSpec, where: str) -> list[DataFrame]:
    e = c.effect(model, where)
    return aff.affected_sets(edges_after(c.stream.snapshot, e.d_edges, e.small), e.d_edges, e.d_feats, model, pinned)


def _affected(name: str, kind: str, depth: int, where: str) -> None:
    model = make_model(kind, depth)
    ctes = [*base_ctes("order_part"), *o.final_ctes(where), *hop_ctes(model)]
    query(name, o.with_sql(ctes, " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS hop, vid FROM a_{i}" for i in range(depth + 1))))(lambda s, d: aff.by_hop(_hops(case(s, d), model, where)))


for _n, _a in AFFECTED.items():
    _affected(_n, *_a)


@query("affected_share", o.with_sql([*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(make_model("gc_sum", 3)), ("al", " UNION ALL ".join(f"SELECT {i} AS hop, vid FROM a_{i}" for i in range(4)))], "SELECT CAST(hop AS BIGINT) AS hop, count(*) AS cnt, round(count(*) / (SELECT count(*) FROM v), 9) AS share FROM al GROUP BY hop UNION ALL SELECT CAST(-1 AS BIGINT), count(DISTINCT vid), round(count(DISTINCT vid) / (SELECT count(*) FROM v), 9) FROM al"))
def affected_share(s, d):
    c = case(s, d)
    return ms.affected_stats(_hops(c, make_model("gc_sum", 3), BATCH), c.stream.vertices.count()).withColumn("share", F.round("share", 9))


@query("unaffected_vertices", o.with_sql([*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(make_model("gc_sum", 2))], "SELECT vid FROM v WHERE vid NOT IN (SELECT vid FROM a_0 UNION SELECT vid FROM a_1 UNION SELECT vid FROM a_2)"))
def unaffected_vertices(s, d):
    c = case(s, d)
    return aff.unaffected(c.stream.vertices, _hops(c, make_model("gc_sum", 2), BATCH))


# --- strategies over one batch -----------------------------------------------------------------------

def _strategy(name: str, kind: str, depth: int, apply, where: str = BATCH, graph: str = "order_part") -> None:
    model = make_model(kind, depth)

    def run(s, d):
        c = case(s, d, graph)
        result = apply(c.state(model), c.effect(model, where), model)
        return to_long(result.state.layers[-1], "h", D, digits(model))

    query(name, final_sql(graph, model, where))(run)


for _kind in (*WORKLOADS, "gc_max", "gc_norm"):
    _strategy(f"scoped_{_kind}_2l", _kind, 2, apply_scoped)
_strategy("scoped_gc_sum_3l", "gc_sum", 3, apply_scoped)
_strategy("scoped_rebuild_gc_sum", "gc_sum", 2, lambda st, e, m: apply_scoped(st, e, m, update_mode="rebuild"))
for _kind in WORKLOADS:
    for _depth in (2, 3):
        _strategy(f"incr_{_kind}_{_depth}l", _kind, _depth, lambda st, e, m: inc.apply_incremental(st, e, m))
for _kind in ("gc_norm", "sage_mean", "gc_sum_mean"):
    _strategy(f"incr_{_kind}_2l", _kind, 2, lambda st, e, m: inc.apply_incremental(st, e, m))
for _short, _k in (("add", "edge_add"), ("del", "edge_del"), ("feat", "feat_set")):
    _strategy(f"incr_{_short}_only", "gc_sum", 2, lambda st, e, m: inc.apply_incremental(st, e, m), f"kind = '{_k}' AND seq <= 300")
for _kind in ("gc_max", "gc_min"):
    _strategy(f"incr_{_kind}_2l", _kind, 2, lambda st, e, m: apply_extreme(st, e, m))
_strategy("incr_gc_smoothed_2l", "gc_smoothed", 2, lambda st, e, m: inc.apply_incremental(st, e, m))
_strategy("scoped_gc_smoothed_2l", "gc_smoothed", 2, apply_scoped)
_strategy("incr_prune_zero", "gc_sum", 2, lambda st, e, m: inc.apply_incremental(st, e, m, prune_zero=True))
_strategy("incr_hybrid", "gc_sum", 2, lambda st, e, m: apply_hybrid(st, e, m), graph="next_part")
_strategy("incr_next_part", "gc_sum", 2, lambda st, e, m: inc.apply_incremental(st, e, m), graph="next_part")
_strategy("incr_supplier_part", "gc_mean", 2, lambda st, e, m: inc.apply_incremental(st, e, m), graph="supplier_part")


def run_batches(c: Case, model: ModelSpec, size: int, count: int, apply=inc.apply_incremental):
    """Consecutive batches; what the next batch reads is pinned, the stored edges are read with the batches laid over them."""
    state = c.state(model)
    for b in range(count):
        effect = net_effect(c.updates(f"seq > {b * size} AND seq <= {(b + 1) * size}"), state, D)
        effect = settled_effect(effect)
        state = apply(state, effect, model).state.pinned(edges=False)
    return state


@query("incr_many_batches", final_sql("order_part", make_model("sage_sum", 2), "seq <= 60"))
def incr_many_batches(s, d):
    return to_long(run_batches(case(s, d), make_model("sage_sum", 2), 20, 3).layers[-1], "h", D)


# Custom update lists: (seq, kind, source of the pair, weight). Pairs are taken from the data by rank.

def _custom(name: str, kind: str, items_sql: str, model_depth: int = 2) -> None:
    """``items_sql``: rows seq, kind, src, dst, w over the tables snap, held, v, in SQL that both engines run."""
    model = make_model(kind, model_depth)
    feats = ", ".join(f"CASE WHEN kind = 'feat_set' THEN ((13 * src + 7 * seq + 5 * {k}) % 17 - 8) / CAST(8.0 AS DOUBLE) END AS f{k}" for k in range(D))
    items = f"SELECT seq, kind, src, dst, w, {feats} FROM ({items_sql})"
    ctes = [x for x in base_ctes("order_part") if x[0] not in ("upd",)]
    ctes = [*ctes, ("held", "SELECT src, dst, w FROM adds"), ("upd", items), *o.final_ctes(), ("n_0", o.features_after_sql(D)), *o.full_ctes(model, "e_new", "n_0", "n")]

    def run(s, d):
        c = case(s, d)
        c.stream.snapshot.createOrReplaceTempView("snap")
        c.updates("kind = 'edge_add'").select("src", "dst", "w").createOrReplaceTempView("held")
        c.stream.vertices.createOrReplaceTempView("v")
        rows = s.sql(items)
        ups = rows.select(
            F.col("seq").cast("long").alias("seq"), F.lit(None).cast("timestamp").alias("ts"), "kind", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("w").cast("double").alias("w"),
            F.when(F.col("kind") == "feat_set", F.array(*[F.col(f"f{k}") for k in range(D)])).alias("feat"),
        )
        state = c.state(model)
        return to_long(inc.apply_incremental(state, net_effect(ups, state, D), model).state.layers[-1], "h", D, digits(model))

    query(name, o.with_sql(ctes, o.long_select(f"n_{model.depth}", D, digits(model))))(run)


_NULLS = "CAST(NULL AS BIGINT) AS dst, CAST(NULL AS DOUBLE) AS w"
_S = "(SELECT src, dst, w, row_number() OVER (ORDER BY src, dst) AS r FROM snap)"
_H = "(SELECT src, dst, w, row_number() OVER (ORDER BY src, dst) AS r FROM held)"
_V = "(SELECT vid, row_number() OVER (ORDER BY vid) AS r FROM v)"
_custom("incr_reweight", "gc_wsum", f"SELECT r AS seq, 'edge_add' AS kind, src, dst, CAST(w + 0.25 AS DOUBLE) AS w FROM {_S} s WHERE r <= 20")
_custom(
    "incr_conflicts", "sage_sum",
    f"SELECT r AS seq, 'edge_add' AS kind, src, dst, w FROM {_H} a WHERE r <= 10"
    f" UNION ALL SELECT r + 100 AS seq, 'edge_del' AS kind, src, dst, CAST(NULL AS DOUBLE) AS w FROM {_H} b WHERE r <= 5"  # add then delete
    f" UNION ALL SELECT r + 200 AS seq, 'edge_del' AS kind, src, dst, CAST(NULL AS DOUBLE) AS w FROM {_S} c WHERE r <= 10"
    f" UNION ALL SELECT r + 300 AS seq, 'edge_add' AS kind, src, dst, w FROM {_S} d WHERE r <= 4"  # delete then add again
    f" UNION ALL SELECT r + 400 AS seq, 'edge_add' AS kind, src, dst, w FROM {_S} e WHERE r > 30 AND r <= 34"  # present already
    f" UNION ALL SELECT r + 500 AS seq, 'edge_del' AS kind, src, dst, CAST(NULL AS DOUBLE) AS w FROM {_H} f WHERE r > 20 AND r <= 24"  # missing
    f" UNION ALL SELECT r + 600 AS seq, 'feat_set' AS kind, vid AS src, {_NULLS} FROM {_V} g WHERE r <= 6"
    f" UNION ALL SELECT r + 700 AS seq, 'feat_set' AS kind, vid AS src, {_NULLS} FROM {_V} h WHERE r <= 3"  # twice
    f" UNION ALL SELECT r + 800 AS seq, 'edge_add' AS kind, vid AS src, vid AS dst, CAST(1.0 AS DOUBLE) AS w FROM {_V} i WHERE r <= 3",  # self loops
)
_custom("incr_zero_degree", "gc_mean", "SELECT row_number() OVER (ORDER BY src, dst) AS seq, 'edge_del' AS kind, src, dst, CAST(NULL AS DOUBLE) AS w FROM snap WHERE dst IN (SELECT vid FROM (SELECT dst AS vid, row_number() OVER (ORDER BY count(*), dst) AS r FROM snap GROUP BY dst) q WHERE r <= 5)")


@query("vertex_removal", o.with_sql([*base_ctes("order_part"), ("gone", "SELECT vid FROM v WHERE vid % 3200 = 1"), ("e_new", "SELECT * FROM snap WHERE src NOT IN (SELECT vid FROM gone) AND dst NOT IN (SELECT vid FROM gone)"), *o.full_ctes(make_model("gc_sum", 2), "e_new", "h_0", "n")], f"SELECT * FROM ({o.long_select('n_2', D)}) WHERE vid % 3200 <> 1"))
def vertex_removal(s, d):
    c, model = case(s, d), make_model("gc_sum", 2)
    gone = c.stream.vertices.where("vid % 3200 = 1")
    state = c.state(model)
    result = inc.apply_incremental(state, net_effect(removal_updates(gone, c.stream.snapshot, 1), state, D), model)
    return to_long(result.state.layers[-1].join(gone, "vid", "left_anti"), "h", D)


def _insertion_sql() -> str:
    model = make_model("sage_sum", 2)
    more = "SELECT src AS vid FROM g UNION SELECT dst FROM g UNION SELECT dst + 5 FROM g WHERE dst % 1600 = 1"
    ctes = [(n, more if n == "v" else q) for n, q in base_ctes("order_part")]
    ctes.append(("e_new", "SELECT * FROM snap UNION ALL SELECT DISTINCT dst + 5, dst, 1.0::DOUBLE FROM g WHERE dst % 1600 = 1"))
    return o.with_sql([*ctes, *o.full_ctes(model, "e_new", "h_0", "n")], o.long_select("n_2", D))


@query("vertex_insertion", _insertion_sql())
def vertex_insertion(s, d):
    c, model = case(s, d), make_model("sage_sum", 2)
    hosts = c.stream.vertices.where("vid % 1600 = 1")
    fresh = hosts.select((F.col("vid") + 5).alias("vid"))
    state = insert(c.state(model), formula_features(fresh), model).pinned()
    rows = hosts.select(F.col("vid").alias("seq"), F.lit(None).cast("timestamp").alias("ts"), F.lit("edge_add").alias("kind"), (F.col("vid") + 5).alias("src"), F.col("vid").alias("dst"), F.lit(1.0).alias("w"), F.lit(None).cast("array<double>").alias("feat"))
    return to_long(inc.apply_incremental(state, net_effect(rows, state, D), model).state.layers[-1], "h", D)


# --- inboxes and messages ----------------------------------------------------------------------------

def _inbox(hop: int) -> None:
    model = make_model("gc_sum", 2)
    sums = lambda p: f"SELECT v.vid, {', '.join(f'coalesce({p}_{hop}_a.s{i}, 0) AS s{i}' for i in range(D))} FROM v LEFT JOIN {p}_{hop}_a ON {p}_{hop}_a.vid = v.vid"
    ctes = [*new_ctes("order_part", model, BATCH, old=True), *hop_ctes(model), ("so", sums("h")), ("sn", sums("n"))]
    ctes.append(("m", f"SELECT so.vid, {', '.join(f'sn.s{i} - so.s{i} AS h{i}' for i in range(D))} FROM so JOIN sn ON so.vid = sn.vid JOIN a_{hop} a ON a.vid = so.vid"))

    def run(s, d):
        c = case(s, d)
        result = inc.apply_incremental(c.state(model), c.effect(model, BATCH), model)
        return to_long(result.inboxes[hop - 1], "m", D)

    query(f"inbox_hop{hop}", o.with_sql(ctes, o.long_select("m", D)))(run)


_inbox(1)
_inbox(2)


@query("messages_by_kind", o.with_sql([*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(make_model("gc_sum", 2))], " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS hop, 'changed' AS kind, count(*) AS n FROM e_new e JOIN a_{i - 1} a ON a.vid = e.src UNION ALL SELECT {i}, CASE WHEN w_old IS NULL THEN 'added' ELSE 'deleted' END, count(*) FROM d_e GROUP BY 2" for i in (1, 2))))
def messages_by_kind(s, d):
    c, model = case(s, d), make_model("gc_sum", 2)
    effect = c.effect(model, BATCH)
    result = inc.apply_incremental(c.state(model), effect, model)
    out = None
    for hop, spec in enumerate(model.layers, 1):
        sent = inc.messages(result.changed[hop - 1], c.state(model), effect, hop, spec)
        rows = sent.groupBy("kind").agg(F.count("*").alias("n")).select(F.lit(hop).cast("long").alias("hop"), "kind", "n")
        out = rows if out is None else out.unionByName(rows)
    return out


# --- labels, triggers, lookups -----------------------------------------------------------------------

def _changes_ctes() -> list[tuple[str, str]]:
    return [*new_ctes("order_part", make_model("gc_sum", 2), BATCH, old=True), ("lo", o.label_sql("h_2", D)), ("ln", o.label_sql("n_2", D)), ("ch", "SELECT lo.vid, lo.label AS old_label, ln.label AS new_label FROM lo JOIN ln USING (vid) WHERE lo.label <> ln.label")]


def _changes(s, d) -> DataFrame:
    c, model = case(s, d), make_model("gc_sum", 2)
    return label_changes(inc.apply_incremental(c.state(model), c.effect(model, BATCH), model), c.state(model), D)


query("label_changes", o.with_sql(_changes_ctes(), "SELECT * FROM ch"))(_changes)
query("label_change_counts", o.with_sql(_changes_ctes(), "SELECT old_label, new_label, count(*) AS n FROM ch GROUP BY 1, 2"))(lambda s, d: _changes(s, d).groupBy("old_label", "new_label").agg(F.count("*").alias("n")))


@query("lookup_labels", stale_sql(make_model("gc_sum", 2), o.label_sql("n_2", D)))
def lookup_labels(s, d):
    """Request-based: the labels of all vertices that the batch may have changed, from the stored outputs."""
    c, model = case(s, d), make_model("gc_sum", 2)
    result = inc.apply_incremental(c.state(model), c.effect(model, BATCH), model)
    return lookup(result.state.layers[-1], result.affected[-1], D)


@query("lookup_lazy", stale_sql(make_model("gc_sum", 2), o.label_sql("n_2", D)))
def lookup_lazy(s, d):
    """Pull-based: stale vertices are inferred vertex-wise when asked for."""
    model = make_model("gc_sum", 2)
    edges, features, targets = stale(s, d, model)
    return labels(infer_vertexwise(edges, features, targets, model), D)


EDGE_SCORES = " + ".join(f"p.h{i} * q.h{i}" for i in range(D))


@query("edge_scores", o.with_sql(
    [*base_ctes("order_part"), *o.full_ctes(make_model("gc_sum", 2), "snap"), ("sc", f"SELECT s.src AS a, s.dst AS b, {EDGE_SCORES} AS t FROM snap s JOIN h_2 p ON p.vid = s.src JOIN h_2 q ON q.vid = s.dst")],
    "SELECT a, b, CASE WHEN t = 0 THEN 0.0 ELSE t END AS score FROM sc"))
def edge_scores_query(s, d):
    c = case(s, d)
    pairs = c.stream.snapshot.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return edge_scores(c.state(make_model("gc_sum", 2)).layers[-1], pairs, D).withColumn("score", tidy(F.col("score")))


@query("customer_label_report", o.with_sql([*base_ctes("customer_part"), *o.full_ctes(make_model("gc_sum", 2), "snap"), ("l", o.label_sql("h_2", D))], "SELECT r_name, n_name, label, count(*) AS n, CAST(round(sum(c_acctbal) * 100) AS BIGINT) AS cents FROM l JOIN customer ON 8 * c_custkey + 3 = vid JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2, 3"))
def customer_label_report(s, d):
    c = case(s, d, "customer_part")
    l = labels(c.state(make_model("gc_sum", 2)).layers[-1], D)
    people = table(s, d, "customer").withColumn("vid", F.col("c_custkey") * 8 + 3)
    places = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    joined = l.join(people, "vid").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("r_name", "n_name", "label").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal") * 100).cast("long").alias("cents"))


# --- partitioned -------------------------------------------------------------------------------------

_P = ("p", f"SELECT vid, CAST({part_sql('vid', PARTS, 'duckdb')} AS BIGINT) AS part FROM v")


def _placed(c: Case, method: str = "hash", parts: int = PARTS) -> DataFrame:
    return pt.place(c.stream.vertices, c.stream.snapshot, parts, method)


query("part_hash", o.with_sql([*base_ctes("order_part"), _P], "SELECT vid, part FROM p"))(lambda s, d: _placed(case(s, d)).select("vid", F.col("part").cast("long").alias("part")))
query("part_range", o.with_sql(base_ctes("order_part"), f"SELECT vid, CAST(ntile({PARTS}) OVER (ORDER BY vid) - 1 AS BIGINT) AS part FROM v"))(
    lambda s, d: case(s, d).stream.vertices.select("vid", (F.expr(f"ntile({PARTS}) over (order by vid)") - 1).cast("long").alias("part"))
)
for _m in ("range", "greedy", "labelprop", "multilevel"):
    query(f"part_{_m}_stats")(lambda s, d, m=_m: pt.cut_stats(case(s, d).stream.snapshot, _placed(case(s, d), m)))

_CUT = ("ce", "SELECT e.src, e.dst, a.part AS ps, b.part AS pd FROM snap e JOIN p a ON a.vid = e.src JOIN p b ON b.vid = e.dst")


@query("cut_stats", o.with_sql([*base_ctes("order_part"), _P, _CUT], "SELECT part, count(*) AS vertices, coalesce(max(out_cut), 0) AS out_cut, coalesce(max(gh), 0) AS ghosts FROM p LEFT JOIN (SELECT ps, count(*) AS out_cut, count(DISTINCT dst) AS gh FROM ce WHERE ps <> pd GROUP BY ps) q ON q.ps = p.part GROUP BY part"))
def cut_stats(s, d):
    return pt.cut_stats(case(s, d).stream.snapshot, _placed(case(s, d)))


@query("ghosts", o.with_sql([*base_ctes("order_part"), _P, _CUT], "SELECT DISTINCT dst AS vid, ps AS part FROM ce WHERE ps <> pd"))
def ghosts(s, d):
    return pt.ghosts(case(s, d).stream.snapshot, _placed(case(s, d)))


_ROUTED = ("ro", f"SELECT seq, a.part, 'compute' AS role FROM upd JOIN p a ON a.vid = upd.src WHERE {BATCH} UNION ALL SELECT seq, b.part, 'topology_only' FROM upd JOIN p a ON a.vid = upd.src JOIN p b ON b.vid = upd.dst WHERE {BATCH} AND a.part <> b.part")


def _routed(s, d) -> DataFrame:
    return pt.route(case(s, d).updates(BATCH), _placed(case(s, d))).select("seq", F.col("part").cast("long").alias("part"), "role")


query("route_updates", o.with_sql([*base_ctes("order_part"), _P, _ROUTED], "SELECT seq, part, role FROM ro"))(_routed)
query("topology_only_requests", o.with_sql([*base_ctes("order_part"), _P, _ROUTED], "SELECT part, count(*) AS n FROM ro WHERE role = 'topology_only' GROUP BY part"))(
    lambda s, d: _routed(s, d).where("role = 'topology_only'").groupBy("part").agg(F.count("*").alias("n"))
)


@query("incr_partitioned_gc_sum", final_sql("order_part", make_model("gc_sum", 2), BATCH))
def incr_partitioned(s, d):
    c, model = case(s, d), make_model("gc_sum", 2)
    got = pt.apply_partitioned(c.state(model), c.effect(model, BATCH), model, _placed(c), PARTS)
    return to_long(got.result.state.layers[-1], "h", D)


@query("incr_partitioned_commerce", final_sql("commerce", make_model("gc_sum", 2), BATCH, hold_out=0.5))
def incr_partitioned_commerce(s, d):
    c, model = case(s, d, "commerce", 0.5), make_model("gc_sum", 2)
    got = pt.apply_partitioned(c.state(model), c.effect(model, BATCH), model, _placed(c, parts=8), 8)
    return to_long(got.result.state.layers[-1], "h", D)


def _scoped_partitioned(name: str, kind: str, graph: str, hold_out: float, parts: int) -> None:
    model = make_model(kind, 2)

    def run(s, d):
        c = case(s, d, graph, hold_out)
        got = pt.apply_scoped_partitioned(c.state(model), c.effect(model, BATCH), model, _placed(c, parts=parts), parts)
        return to_long(got.result.state.layers[-1], "h", D, digits(model))

    query(name, final_sql(graph, model, BATCH, hold_out=hold_out))(run)


for _kind in ("gc_sum", "sage_sum", "gc_mean"):
    _scoped_partitioned(f"scoped_partitioned_{_kind}", _kind, "order_part", 0.1, PARTS)
_scoped_partitioned("scoped_partitioned_commerce", "gc_sum", "commerce", 0.5, 8)


def _exchange(strategy: str) -> None:
    model = make_model("gc_sum", 2)
    ctes = [*base_ctes("order_part"), _P, *o.final_ctes(BATCH), *hop_ctes(model)]
    if strategy == "incremental":
        one = lambda i: f"SELECT DISTINCT t.dst, a.part FROM (SELECT e.src, e.dst FROM e_new e JOIN a_{i - 1} x ON x.vid = e.src UNION ALL SELECT src, dst FROM d_e) t JOIN p a ON a.vid = t.src JOIN p b ON b.vid = t.dst WHERE a.part <> b.part"
    else:
        one = lambda i: f"SELECT DISTINCT t.src, b.part FROM (SELECT e.src, e.dst FROM e_new e JOIN a_{i} x ON x.vid = e.dst) t JOIN p a ON a.vid = t.src JOIN p b ON b.vid = t.dst WHERE a.part <> b.part"
    sql = o.with_sql(ctes, " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS hop, count(*) AS vectors, count(*) * {8 * D} AS bytes FROM ({one(i)})" for i in (1, 2)))

    def run(s, d):
        c = case(s, d)
        return pt.exchange_counts(c.stream.snapshot, c.effect(model, BATCH), model, _placed(c), strategy)

    query(f"exchange_vectors_{strategy}", sql)(run)


_exchange("incremental")
_exchange("scoped")


# --- measures ----------------------------------------------------------------------------------------

def _ops(strategy: str) -> None:
    model = make_model("gc_sum", 2)
    ctes = [*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(model)]
    sql = {
        "scoped": lambda i: f"SELECT count(*) FROM e_new e JOIN a_{i} a ON a.vid = e.dst",
        "incremental": lambda i: f"SELECT 2 * (SELECT count(*) FROM e_new e JOIN a_{i - 1} a ON a.vid = e.src WHERE NOT EXISTS (SELECT 1 FROM d_e x WHERE x.src = e.src AND x.dst = e.dst)) + (SELECT count(*) FROM d_e)",
        "full": lambda i: "SELECT count(*) FROM e_new",
    }[strategy]

    def run(s, d):
        c = case(s, d)
        e = c.effect(model, BATCH)
        new = edges_after(c.stream.snapshot, e.d_edges, e.small)
        return ms.agg_ops(c.stream.snapshot, new, e, aff.affected_sets(new, e.d_edges, e.d_feats, model, pinned), strategy)

    query(f"agg_ops_{strategy}", o.with_sql(ctes, " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS hop, ({sql(i)}) AS ops" for i in (1, 2))))(run)


for _st in ("scoped", "incremental", "full"):
    _ops(_st)


@query("agg_ops_vertexwise", o.with_sql(
    [*base_ctes("order_part"), *o.final_ctes(BATCH), *hop_ctes(make_model("gc_sum", 2)), ("n1", "SELECT e.dst AS target, e.src AS vid FROM e_new e JOIN a_2 a ON a.vid = e.dst"),
     ("n2", "SELECT n1.target, e.src FROM (SELECT DISTINCT target, vid FROM n1) n1 JOIN e_new e ON e.dst = n1.vid")],
    "SELECT CAST((SELECT count(*) FROM n1) + (SELECT count(*) FROM n2) AS BIGINT) AS ops"))
def agg_ops_vertexwise(s, d):
    edges, _, targets = stale(s, d, make_model("gc_sum", 2))
    return ms.agg_ops_vertexwise(edges, targets, make_model("gc_sum", 2))


@query("state_bytes", _with_stream(f"SELECT 'edges' AS component, (SELECT count(*) FROM snap) * 24 AS bytes UNION ALL SELECT x, (SELECT count(*) FROM v) * {8 * D} FROM (SELECT unnest(['h0', 'h1', 'agg1', 'h2', 'agg2']) AS x)"))
def state_bytes(s, d):
    return ms.state_bytes(case(s, d).state(make_model("gc_sum", 2)))


@query("memory_overhead", _with_stream(f"SELECT (SELECT count(*) FROM v) * {8 * D} * 2 AS aggregate_bytes, (SELECT count(*) FROM v) * {8 * D} * 3 AS output_bytes"))
def memory_overhead(s, d):
    """What incremental keeps beyond recompute: the stored aggregates."""
    b = ms.state_bytes(case(s, d).state(make_model("gc_sum", 2)))
    pick = lambda p: F.sum(F.when(F.col("component").startswith(p), F.col("bytes")).otherwise(0))
    return b.agg(pick("agg").alias("aggregate_bytes"), pick("h").alias("output_bytes"))


@query("exactness", "SELECT CAST(x AS BIGINT) AS layer, 0.0::DOUBLE AS diff FROM (SELECT unnest([1, 2]) AS x)")
def exactness(s, d):
    c, model = case(s, d), make_model("gin_sum", 2)
    result = inc.apply_incremental(c.state(model), c.effect(model, BATCH), model)
    fresh = infer_full(c.stream.vertices, result.state.edges, result.state.layers[0], model, pinned)
    return ms.max_abs_diff(result.state, fresh, model)


@query("drift_audit", "SELECT CAST(x AS BIGINT) AS layer, true AS within FROM (SELECT unnest([1, 2]) AS x)")
def drift_audit(s, d):
    c, model = case(s, d), make_model("gc_mean", 2)
    state = run_batches(c, model, 50, 2)
    return ms.audit(state, model, 0.2).select("layer", (F.col("diff") < 1e-9).alias("within"))


@query("model_table", "SELECT CAST(l AS BIGINT) AS layer, 'w' AS role, CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, ((7 * i + 3 * j + 5 * l) % 11 - 5) / 8.0::DOUBLE AS w FROM (SELECT unnest(range(2)) AS l), (SELECT unnest(range(8)) AS i), (SELECT unnest(range(8)) AS j)")
def model_table(s, d):
    return s.createDataFrame(model_rows(make_model("gc_sum", 2)), "layer long, role string, i long, j long, w double")


@query("worked_example", "SELECT * FROM (VALUES (1, 'A'), (2, 'A'), (2, 'B'), (2, 'D')) t(hop, name)")
def worked_example(s, d):
    """Six-edge example: adding C to A reaches A, then A, B and D."""
    ids = {n: i for i, n in enumerate("ABCDE")}
    e = s.createDataFrame([(ids[a], ids[b]) for a, b in ("BA", "DA", "AB", "AD", "DB", "CD")], "src long, dst long").transform(weighted)
    change = s.createDataFrame([(ids["C"], ids["A"], None, 1.0)], "src long, dst long, w_old double, w_new double")
    none = s.createDataFrame([], "vid long")
    hops = aff.affected_sets(edges_after(e, change), change, none, make_model("gc_sum", 2))
    named = F.element_at(F.array(*[F.lit(n) for n in "ABCDE"]), (F.col("vid") + 1).cast("int"))
    return aff.by_hop(hops).select(F.col("hop").cast("int").alias("hop"), named.alias("name"))


def flagship(s: SparkSession, d: str) -> DataFrame:
    c, model = case(s, d), make_model("gc_sum", 2)
    return label_changes(inc.apply_incremental(c.state(model), c.effect(model, "seq <= 10"), model), c.state(model), D)
