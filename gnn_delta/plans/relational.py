"""Relational, function and stream queries around the graph methods, each with an SQL oracle."""

from __future__ import annotations

from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import PandasUDFType

from ..functions import vectors as vec
from ..functions.vectors import names, tidy
from ..operators.labels import labels
from ..operators.netting import last_writers
from ..sources.graphs import D, graph_ctes, table
from ..sources.updates import assign_batches, stream_ctes
from . import oracle as o
from .cases import N_EACH_SQL, case
from .gnn_queries import BATCH, _hops, base_ctes, d_edge_ctes, hop_ctes, new_ctes, query
from .model import make_model
from .scratch import shared_dir

GC2 = make_model("gc_sum", 2)
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _layers(s, d):
    return case(s, d).state(GC2).layers


def _sql(select: str, extra: list[tuple[str, str]] = ()) -> str:
    return o.with_sql([*base_ctes("order_part"), *extra], select)


_FULL = o.full_ctes(GC2, "snap")
_LABELS = [*_FULL, ("l", o.label_sql("h_2", D))]
_DEG = ("deg", "SELECT dst AS vid, count(*) AS k FROM snap GROUP BY dst")


def _degrees(s, d) -> DataFrame:
    return case(s, d).stream.snapshot.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("k"))


# --- sources and sinks -------------------------------------------------------------------------------

@query("scan_row_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_row_counts(s, d):
    out = None
    for t in TABLES:
        row = table(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("scan_csv_updates", _sql("SELECT f AS format, kind, count(*) AS n FROM upd, (SELECT unnest(['csv', 'json', 'orc']) AS f) GROUP BY 1, 2"))
def scan_csv_updates(s, d):
    import uuid

    flat = case(s, d).stream.updates.select("seq", "kind", "src", "dst", "w")
    out = None
    for form in ("csv", "json", "orc"):
        path = f"{shared_dir(s)}/log-{uuid.uuid4().hex}"
        flat.write.format(form).save(path)
        back = s.read.schema("seq BIGINT, kind STRING, src BIGINT, dst BIGINT, w DOUBLE").format(form).load(path)
        row = back.groupBy("kind").agg(F.count("*").alias("n")).select(F.lit(form).alias("format"), "kind", "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("source_update_replay", _sql("SELECT seq, kind, src, coalesce(dst, -1) AS dst FROM upd"))
def source_update_replay(s, d):
    import uuid

    from ..sources.replay import UpdateSource

    path = f"{shared_dir(s)}/replay-{uuid.uuid4().hex}"
    case(s, d).stream.updates.select("seq", "kind", "src", "dst", "w").write.json(path)
    s.dataSource.register(UpdateSource)
    lines = [r[0] for r in s.read.text(path).orderBy("value").collect()]
    return s.read.format("gnn_updates").option("lines", "\n".join(lines)).option("parts", "3").load().select("seq", "kind", "src", F.coalesce("dst", F.lit(-1)).alias("dst"))


@query("sink_state_roundtrip", _sql(f"SELECT vid, k, x FROM ({o.long_select('h_1', D)})", _FULL))
def sink_state_roundtrip(s, d):
    import uuid

    from .state import StateStore

    store = StateStore(s, f"{shared_dir(s)}/store-{uuid.uuid4().hex}", 4)
    store.bootstrap(case(s, d).state(GC2))
    picked = store.table("layer1", touched=[0, 1]).unionByName(store.table("layer1", touched=[2, 3]))
    return vec.to_long(picked, "h", D)


# --- filters and joins -------------------------------------------------------------------------------

@query("filter_update_kind", _sql("SELECT seq, src FROM upd WHERE kind = 'feat_set' AND src IN (SELECT vid FROM deg WHERE k > (SELECT avg(k) FROM deg))", [_DEG]))
def filter_update_kind(s, d):
    k = _degrees(s, d)
    hubs = k.crossJoin(F.broadcast(k.agg(F.avg("k").alias("m")))).where("k > m").select(F.col("vid").alias("src"))
    return case(s, d).updates("kind = 'feat_set'").join(hubs, "src", "left_semi").select("seq", "src")


@query("join_inner_part_label", _sql("SELECT vid, label, p_brand, p_type FROM l JOIN part ON vid = 8 * p_partkey + 1", _LABELS))
def join_inner_part_label(s, d):
    parts = table(s, d, "part").select((F.col("p_partkey") * 8 + 1).alias("vid"), "p_brand", "p_type")
    return labels(_layers(s, d)[-1], D).join(parts, "vid").select("vid", "label", "p_brand", "p_type")


_HOPS = [*o.final_ctes(BATCH), *hop_ctes(GC2)]


@query("join_left_missing_inbox", _sql("SELECT v.vid FROM v LEFT JOIN a_1 ON a_1.vid = v.vid WHERE a_1.vid IS NULL", _HOPS))
def join_left_missing_inbox(s, d):
    c = case(s, d)
    hit = _hops(c, GC2, BATCH)[1].withColumn("hit", F.lit(True))
    return c.stream.vertices.join(hit, "vid", "left").where("hit is null").select("vid")


@query("join_semi_touched", _sql("SELECT src, dst FROM snap WHERE src IN (SELECT vid FROM a_1)", _HOPS))
def join_semi_touched(s, d):
    c = case(s, d)
    return c.stream.snapshot.join(_hops(c, GC2, BATCH)[1].withColumnRenamed("vid", "src"), "src", "left_semi").select("src", "dst")


@query("join_anti_unaffected", _sql("SELECT vid FROM v WHERE vid NOT IN (SELECT vid FROM a_1 UNION SELECT vid FROM a_2)", _HOPS))
def join_anti_unaffected(s, d):
    c = case(s, d)
    hops = _hops(c, GC2, BATCH)
    return c.stream.vertices.join(hops[1], "vid", "left_anti").join(hops[2], "vid", "left_anti").select("vid")


@query("join_full_state_diff", o.with_sql([*new_ctes("order_part", GC2, BATCH, old=True), ("lo", o.label_sql("h_2", D)), ("ln", o.label_sql("n_2", D))], "SELECT coalesce(lo.vid, ln.vid) AS vid, lo.label IS NOT DISTINCT FROM ln.label AS same FROM lo FULL JOIN ln ON lo.vid = ln.vid"))
def join_full_state_diff(s, d):
    from ..operators.incremental import apply_incremental

    c = case(s, d)
    after = labels(apply_incremental(c.state(GC2), c.effect(GC2, BATCH), GC2).state.layers[-1], D).withColumnRenamed("label", "after")
    return labels(_layers(s, d)[-1], D).join(after, "vid", "full_outer").select("vid", F.col("label").eqNullSafe(F.col("after")).alias("same"))


@query("join_broadcast_range_part", _sql("SELECT vid, CAST(CASE WHEN vid < 1000 THEN 0 WHEN vid < 5000 THEN 1 ELSE 2 END AS BIGINT) AS part FROM v"))
def join_broadcast_range_part(s, d):
    bounds = s.createDataFrame([(0, 999, 0), (1000, 4999, 1), (5000, 1 << 60, 2)], "lo long, hi long, part long")
    v = case(s, d).stream.vertices
    return v.join(F.broadcast(bounds), v["vid"].between(bounds["lo"], bounds["hi"])).select("vid", "part")


@query("join_asof_feature", "SELECT event_id, (SELECT max_by(b.value, b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND (b.ts, b.event_id) < (a.ts, a.event_id)) AS value FROM events a WHERE event_type = 'purchase'")
def join_asof_feature(s, d):
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    value = F.last(F.when(F.col("event_type") == "view", F.col("value")), ignorenulls=True).over(before)
    return table(s, d, "events").withColumn("v", value).where("event_type = 'purchase'").select("event_id", F.col("v").alias("value"))


@query("join_interval_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval_events(s, d):
    e = table(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), hour.alias("h"))
    return a.join(b, ["user_id", "h"]).where("tb > ta and tb <= ta + interval 1 hour").select("a", "b")


@query("join_cross_weights", "SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, ((7 * i + 3 * j) % 11 - 5) / 8.0::DOUBLE AS w FROM (SELECT unnest(range(8)) AS i), (SELECT unnest(range(8)) AS j)")
def join_cross_weights(s, d):
    i, j = s.range(8).withColumnRenamed("id", "i"), s.range(8).withColumnRenamed("id", "j")
    return i.crossJoin(F.broadcast(j)).select("i", "j", (((7 * F.col("i") + 3 * F.col("j")) % 11 - 5) / 8).alias("w"))


# --- aggregations ------------------------------------------------------------------------------------

@query("agg_label_histogram", _sql("SELECT vid % 8 AS kind, label, count(*) AS n FROM l GROUP BY 1, 2", _LABELS))
def agg_label_histogram(s, d):
    return labels(_layers(s, d)[-1], D).groupBy((F.col("vid") % 8).alias("kind"), "label").agg(F.count("*").alias("n"))


query("agg_distinct_sources", _sql("SELECT dst, count(DISTINCT src) AS n FROM snap GROUP BY dst"))(lambda s, d: case(s, d).stream.snapshot.groupBy("dst").agg(F.countDistinct("src").alias("n")))
query("agg_approx_sources")(lambda s, d: case(s, d).stream.snapshot.groupBy("dst").agg(F.approx_count_distinct("src").alias("n")))


@query("agg_rollup_degree", "SELECT r_name, n_name, c_mktsegment, count(*) AS n, CAST(sum(k) AS BIGINT) AS orders FROM (SELECT r_name, n_name, c_mktsegment, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS k FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) GROUP BY ROLLUP (r_name, n_name, c_mktsegment)")
def agg_rollup_degree(s, d):
    k = table(s, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("k"))
    places = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = table(s, d, "customer").join(k, "c_custkey", "left").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.rollup("r_name", "n_name", "c_mktsegment").agg(F.count("*").alias("n"), F.sum(F.coalesce("k", F.lit(0))).alias("orders"))


query("agg_cube_updates", _sql("SELECT coalesce(kind, 'all') AS kind, coalesce(CAST(src % 8 AS BIGINT), -1) AS tag, count(*) AS n FROM upd GROUP BY CUBE (kind, src % 8)"))(
    lambda s, d: case(s, d).stream.updates.withColumn("tag", F.col("src") % 8).cube("kind", "tag").agg(F.count("*").alias("n")).select(F.coalesce("kind", F.lit("all")).alias("kind"), F.coalesce("tag", F.lit(-1)).alias("tag"), "n")
)


@query("agg_grouping_sets_cost", _sql("SELECT coalesce(b, -1) AS b, coalesce(kind, 'all') AS kind, count(*) AS n FROM (SELECT (seq - 1) // 10 AS b, kind FROM upd) GROUP BY GROUPING SETS ((b), (kind), ())"))
def agg_grouping_sets_cost(s, d):
    assign_batches(case(s, d).stream.updates, 10).createOrReplaceTempView("cost_rows")
    return s.sql("SELECT coalesce(batch_id, -1) AS b, coalesce(kind, 'all') AS kind, count(*) AS n FROM cost_rows GROUP BY GROUPING SETS ((batch_id), (kind), ())")


@query("agg_stats_embedding", "SELECT k, round(avg(x), 6) AS mean, round(stddev_pop(x), 6) AS sd, min(x) AS low, max(x) AS high, round(median(x), 6) AS mid FROM (SELECT CAST(unnest(range(64)) AS BIGINT) AS k, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY k")
def agg_stats_embedding(s, d):
    rows = table(s, d, "embeddings").select(F.posexplode("embedding").alias("k", "x")).select(F.col("k").cast("long").alias("k"), F.col("x").cast("double").alias("x"))
    return rows.groupBy("k").agg(F.round(F.avg("x"), 6).alias("mean"), F.round(F.stddev_pop("x"), 6).alias("sd"), F.min("x").alias("low"), F.max("x").alias("high"), F.round(F.percentile("x", F.lit(0.5)), 6).alias("mid"))


# --- windows, top-k, sets ----------------------------------------------------------------------------

query("win_last_writer", _sql("SELECT src, coalesce(dst, -1) AS dst, seq FROM (SELECT *, row_number() OVER (PARTITION BY src, dst, kind = 'feat_set' ORDER BY seq DESC) AS r FROM upd) WHERE r = 1"))(
    lambda s, d: last_writers(case(s, d).stream.updates).select("src", F.coalesce("dst", F.lit(-1)).alias("dst"), "seq")
)


@query("win_rank_hubs", _sql("SELECT vid, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr FROM deg WINDOW w AS (PARTITION BY vid % 8 ORDER BY k DESC)", [_DEG]))
def win_rank_hubs(s, d):
    w = Window.partitionBy(F.col("vid") % 8).orderBy(F.desc("k"))
    return _degrees(s, d).select("vid", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("win_running_updates", _sql("SELECT seq, count(*) OVER (PARTITION BY kind ORDER BY seq) AS n, CAST(sum(src) OVER (PARTITION BY kind ORDER BY seq ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS moving FROM upd"))
def win_running_updates(s, d):
    w = Window.partitionBy("kind").orderBy("seq")
    return case(s, d).stream.updates.select("seq", F.count("*").over(w).alias("n"), F.sum("src").over(w.rowsBetween(-9, 0)).alias("moving"))


@query("win_range_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_events(s, d):
    e = table(s, d, "events").withColumn("t", F.col("ts").cast("timestamp").cast("double"))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)).alias("n"))


@query("win_lag_interarrival", "SELECT event_id, coalesce(CAST(epoch(ts) - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS DOUBLE), -1) AS gap FROM events")
def win_lag_interarrival(s, d):
    t = F.col("ts").cast("timestamp").cast("double")
    before = F.lag(t).over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return table(s, d, "events").select("event_id", F.coalesce(t - before, F.lit(-1.0)).alias("gap"))


query("win_ntile_parts", _sql("SELECT vid, CAST(ntile(8) OVER (PARTITION BY vid % 8 ORDER BY vid) AS BIGINT) AS part FROM v"))(
    lambda s, d: case(s, d).stream.vertices.select("vid", F.ntile(8).over(Window.partitionBy(F.col("vid") % 8).orderBy("vid")).cast("long").alias("part"))
)


@query("topk_changed", o.with_sql([*new_ctes("order_part", GC2, BATCH, old=True)], "SELECT h_2.vid, " + " + ".join(f"abs(n_2.h{i} - h_2.h{i})" for i in range(D)) + " AS change FROM h_2 JOIN n_2 ON h_2.vid = n_2.vid ORDER BY change DESC, h_2.vid LIMIT 20"))
def topk_changed(s, d):
    from ..operators.incremental import apply_incremental

    c = case(s, d)
    last = apply_incremental(c.state(GC2), c.effect(GC2, BATCH), GC2).changed[-1]
    change = F.abs(F.col("new0") - F.col("old0"))
    for i in range(1, D):
        change = change + F.abs(F.col(f"new{i}") - F.col(f"old{i}"))
    return last.select("vid", change.alias("change")).orderBy(F.desc("change"), "vid").limit(20)


@query("topk_classes", _sql(f"SELECT vid, k, r FROM (SELECT vid, k, row_number() OVER (PARTITION BY vid ORDER BY x DESC, k) AS r FROM ({o.long_select('h_2', D)})) WHERE r <= 3 AND vid % 8 = 1", _FULL))
def topk_classes(s, d):
    rows = vec.to_long(_layers(s, d)[-1].where("vid % 8 = 1"), "h", D)
    return rows.withColumn("r", F.row_number().over(Window.partitionBy("vid").orderBy(F.desc("x"), "k"))).where("r <= 3").select("vid", "k", F.col("r").cast("long").alias("r"))


@query("set_intersect_hops", _sql("SELECT vid FROM a_1 INTERSECT SELECT vid FROM a_2", _HOPS))
def set_intersect_hops(s, d):
    hops = _hops(case(s, d), GC2, BATCH)
    return hops[1].intersect(hops[2])


@query("set_union_messages", _sql("SELECT src, dst, 'kept' AS kind FROM e_new WHERE src IN (SELECT vid FROM a_0) UNION ALL SELECT src, dst, CASE WHEN w_new IS NULL THEN 'deleted' ELSE 'added' END FROM d_e", _HOPS))
def set_union_messages(s, d):
    from ..operators.netting import edges_after

    c = case(s, d)
    e = c.effect(GC2, BATCH)
    kept = edges_after(c.stream.snapshot, e.d_edges).join(e.d_feats.select(F.col("vid").alias("src")), "src", "left_semi").select("src", "dst", F.lit("kept").alias("kind"))
    return kept.unionByName(e.d_edges.select("src", "dst", F.when(F.col("w_new").isNull(), "deleted").otherwise("added").alias("kind")))


@query("set_except_edges", _sql("SELECT src, dst FROM snap EXCEPT SELECT src, dst FROM e_new", _HOPS))
def set_except_edges(s, d):
    from ..operators.netting import edges_after

    c = case(s, d)
    return c.stream.snapshot.select("src", "dst").subtract(edges_after(c.stream.snapshot, c.effect(GC2, BATCH).d_edges).select("src", "dst"))


@query("set_exceptall_lines", "SELECT l_orderkey, l_partkey FROM lineitem EXCEPT ALL SELECT DISTINCT l_orderkey, l_partkey FROM lineitem")
def set_exceptall_lines(s, d):
    lines = table(s, d, "lineitem").select("l_orderkey", "l_partkey")
    return lines.exceptAll(lines.distinct())


@query("pivot_kind_by_batch", _sql("SELECT (seq - 1) // 10 AS batch_id, count(*) FILTER (kind = 'edge_add') AS edge_add, count(*) FILTER (kind = 'edge_del') AS edge_del, count(*) FILTER (kind = 'feat_set') AS feat_set FROM upd GROUP BY 1"))
def pivot_kind_by_batch(s, d):
    kinds = ["edge_add", "edge_del", "feat_set"]
    return assign_batches(case(s, d).stream.updates, 10).groupBy("batch_id").pivot("kind", kinds).count().na.fill(0, kinds)


@query("unpivot_vector", _sql("SELECT vid, unnest(['h0', 'h1', 'h2']) AS name, unnest([h0, h1, h2]) AS x FROM h_0"))
def unpivot_vector(s, d):
    return case(s, d).features().unpivot(["vid"], ["h0", "h1", "h2"], "name", "x")


# --- vector functions, UDFs --------------------------------------------------------------------------

def _arrays(s, d) -> DataFrame:
    l = _layers(s, d)
    a = l[0].select("vid", F.array(*names("h", D)).alias("a"))
    return a.join(l[1].select("vid", F.array(*names("h", D)).alias("b")), "vid")


_A, _B = [f"h_0.h{i}" for i in range(D)], [f"h_1.h{i}" for i in range(D)]
_Z = lambda x: f"CASE WHEN ({x}) = 0 THEN 0.0 ELSE ({x}) END"


@query("vec_arith", _sql(f"SELECT h_0.vid, {_Z(f'{_A[3]} + {_B[3]}')} AS added, {_Z(f'{_A[3]} - {_B[3]}')} AS less, {_Z(f'{_A[3]} * 2.5')} AS scaled, {_Z(' + '.join(f'{a} * {b}' for a, b in zip(_A, _B, strict=True)))} AS dot, {' + '.join(f'abs({a})' for a in _A)} AS l1, round(sqrt({' + '.join(f'{a} * {a}' for a in _A)}), 6) AS l2, greatest({_A[3]}, 0.0) AS pos, CAST(list_position([{', '.join(_A)}], greatest({', '.join(_A)})) - 1 AS BIGINT) AS top, round(exp({_A[3]} - greatest({', '.join(_A)})) / ({' + '.join('exp(' + a + ' - greatest(' + ', '.join(_A) + '))' for a in _A)}), 6) AS soft, CAST(16 AS BIGINT) AS wide FROM h_0 JOIN h_1 ON h_0.vid = h_1.vid", _FULL))
def vec_arith(s, d):
    a, b = F.col("a"), F.col("b")
    return _arrays(s, d).select(
        "vid", tidy(vec.vec_add(a, b)[3]).alias("added"), tidy(vec.vec_sub(a, b)[3]).alias("less"), tidy(vec.vec_scale(a, F.lit(2.5))[3]).alias("scaled"), tidy(vec.vec_dot(a, b)).alias("dot"), vec.vec_norm(a, 1).alias("l1"),
        F.round(vec.vec_norm(a), 6).alias("l2"), vec.vec_relu(a)[3].alias("pos"), vec.vec_argmax(a).alias("top"), F.round(vec.vec_softmax(a)[3], 6).alias("soft"), F.size(vec.vec_concat(a, b)).cast("long").alias("wide"),
    )


@query("vec_sql_functions", _sql(f"SELECT h_0.vid, {_Z(' + '.join(f'{a} * {b}' for a, b in zip(_A, _B, strict=True)))} AS dot FROM h_0 JOIN h_1 ON h_0.vid = h_1.vid", _FULL))
def vec_sql_functions(s, d):
    vec.register_sql(s)
    _arrays(s, d).createOrReplaceTempView("two_layers")
    return s.sql("SELECT vid, CASE WHEN vec_dot(a, b) = 0 THEN 0D ELSE vec_dot(a, b) END AS dot FROM two_layers")


@query("vec_quantise_embeddings", "WITH q AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(x::DOUBLE * 64 + 0.5) AS BIGINT)) AS q FROM embeddings) SELECT a.vec_id, CAST(list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2])) AS BIGINT) AS dot FROM q a, q b WHERE b.vec_id = 0")
def vec_quantise_embeddings(s, d):
    q = table(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * 64 + 0.5)).alias("q"))
    first = q.where("vec_id = 0").select(F.col("q").alias("z"))
    return q.crossJoin(F.broadcast(first)).select("vec_id", F.aggregate(F.zip_with("q", "z", lambda a, b: a * b), F.lit(0).cast("long"), lambda t, x: t + x).alias("dot"))


@query("vec_sum_udaf", _sql("SELECT vid % 8 AS kind, sum(h0) AS x0, sum(h5) AS x5 FROM h_0 GROUP BY 1"))
def vec_sum_udaf(s, d):
    import numpy as np

    def total(v: pd.Series) -> Any:
        return np.sum(np.stack(v.to_numpy()), axis=0).tolist()

    vec_sum = F.pandas_udf(total, "array<double>", PandasUDFType.GROUPED_AGG)
    rows = case(s, d).features().select((F.col("vid") % 8).alias("kind"), F.array(*names("h", D)).alias("h"))
    return rows.groupBy("kind").agg(vec_sum("h").alias("x")).select("kind", F.col("x")[0].alias("x0"), F.col("x")[5].alias("x5"))


@query("udf_matmul", _sql(o.long_select("h_1", D), _FULL))
def udf_matmul(s, d):
    """The Arrow path of the transform gives what literal arithmetic gives."""
    from ..operators.layers import _by_matrix

    rows = _layers(s, d)[1].select("vid", "c", *names("s", D))
    return vec.to_long(_by_matrix(rows, GC2.layers[0], ["vid"], names("s", D), [], names("h", D)), "h", D)


@query("udtf_neighbourhood", _sql("SELECT root, vid, CAST(min(hop) AS BIGINT) AS hop FROM (SELECT vid AS root, vid, 0 AS hop FROM r5 UNION ALL SELECT r5.vid, dst, 1 FROM r5 JOIN snap ON src = r5.vid UNION ALL SELECT r5.vid, b.dst, 2 FROM r5 JOIN snap a ON a.src = r5.vid JOIN snap b ON b.src = a.dst) GROUP BY 1, 2", [("r5", "SELECT vid FROM v ORDER BY vid LIMIT 5")]))
def udtf_neighbourhood(s, d):
    from pyspark.sql.functions import udtf

    c = case(s, d)
    roots = c.stream.vertices.orderBy("vid").limit(5)
    one = c.stream.snapshot.join(roots.withColumnRenamed("vid", "src"), "src", "left_semi")
    near = one.unionByName(c.stream.snapshot.join(one.select(F.col("dst").alias("src")).distinct(), "src", "left_semi")).distinct()
    out_edges = {r["src"]: r["to"] for r in near.groupBy("src").agg(F.collect_list("dst").alias("to")).collect()}  # two hops of five roots

    @udtf(returnType="vid bigint, hop bigint")
    class Neighbourhood:
        def eval(self, root: int, depth: int):
            seen, front = {root: 0}, [root]
            for hop in range(1, depth + 1):
                front = [x for v in front for x in out_edges.get(v, []) if x not in seen and not seen.update({x: hop})]
            yield from seen.items()

    s.udtf.register("neighbourhood", Neighbourhood)
    roots.createOrReplaceTempView("roots")
    return s.sql("SELECT r.vid AS root, n.vid, n.hop FROM roots r, LATERAL neighbourhood(r.vid, 2) n")


# --- json, strings, dates, maps, arrays, SQL ---------------------------------------------------------

query("json_event_props", "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY 1")(
    lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.sum(F.from_json("props", "k BIGINT")["k"]).alias("k"))
)


@query("str_page_hosts", r"""SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, CAST(len(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS BIGINT) AS links FROM pages""")
def str_page_hosts(s, d):
    return table(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).cast("long").alias("links"))


query("date_update_buckets", "SELECT strftime(ts, '%Y-%m-%d') AS day, CAST(hour(ts) AS BIGINT) AS hour, count(*) AS n FROM events GROUP BY 1, 2")(
    lambda s, d: table(s, d, "events").groupBy(F.date_format(F.date_trunc("day", F.col("ts").cast("timestamp")), "yyyy-MM-dd").alias("day"), F.hour("ts").cast("long").alias("hour")).agg(F.count("*").alias("n"))
)


@query("map_out_edges", _sql("SELECT src, count(*) AS n, max(w) AS top FROM snap WHERE src % 8 = 1 GROUP BY src"))
def map_out_edges(s, d):
    m = case(s, d).stream.snapshot.where("src % 8 = 1").groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", "w"))).alias("out"))
    return m.select("src", F.size("out").cast("long").alias("n"), F.array_max(F.map_values("out")).alias("top"))


@query("array_adjacency", _sql("SELECT src, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS pos, dst FROM snap"))
def array_adjacency(s, d):
    a = case(s, d).stream.snapshot.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("out"))
    return a.select("src", F.posexplode("out").alias("pos", "dst")).select("src", F.col("pos").cast("long").alias("pos"), "dst")


@query("sql_label_report", _sql("SELECT label, count(*) AS n FROM l WHERE EXISTS (SELECT 1 FROM snap e WHERE e.dst = l.vid AND e.w > 0.5) GROUP BY label", _LABELS))
def sql_label_report(s, d):
    labels(_layers(s, d)[-1], D).createOrReplaceTempView("vertex_labels")
    case(s, d).stream.snapshot.createOrReplaceTempView("edge")
    return s.sql("SELECT label, count(*) AS n FROM vertex_labels l WHERE EXISTS (SELECT 1 FROM edge e WHERE e.dst = l.vid AND e.w > 0.5) GROUP BY label")


_CP = [*graph_ctes("customer_part"), *stream_ctes(N_EACH_SQL)]


@query("customer_2hop_parts", o.with_sql([*_CP, ("c10", "SELECT DISTINCT src FROM snap WHERE src % 8 = 3 ORDER BY src LIMIT 10")], "SELECT c10.src AS customer, count(DISTINCT c.dst) AS parts FROM c10 JOIN snap a ON a.src = c10.src JOIN snap b ON b.src = a.dst JOIN snap c ON c.src = b.dst GROUP BY 1"))
def customer_2hop_parts(s, d):
    e = case(s, d, "customer_part").stream.snapshot.select("src", "dst")
    front = e.where("src % 8 = 3").select(F.col("src").alias("customer")).distinct().orderBy("customer").limit(10).withColumn("vid", F.col("customer"))
    for _ in range(3):
        front = front.join(e, F.col("vid") == F.col("src")).select("customer", F.col("dst").alias("vid")).distinct()
    return front.groupBy("customer").agg(F.countDistinct("vid").alias("parts"))
