"""Graph methods against NumPy, algebra of batches, worked examples, costs, storage, streaming."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from gnn_delta.functions.vectors import names, to_long
from gnn_delta.operators import affected as aff
from gnn_delta.operators import measures as ms
from gnn_delta.operators import partition as pt
from gnn_delta.operators.full import infer_full
from gnn_delta.operators.hybrid import apply_hybrid
from gnn_delta.operators.incremental import apply_incremental, merge_inbox, messages
from gnn_delta.operators.labels import label_changes, labels
from gnn_delta.operators.extremes import apply_extreme
from gnn_delta.operators.netting import UPDATE_SCHEMA, edges_after, net_effect, settled_effect
from gnn_delta.operators.recompute import apply_scoped
from gnn_delta.operators.vertexwise import infer_vertexwise
from gnn_delta.plans.model import WORKLOADS, LinearAggregator, ModelSpec, NonInvertibleAggregator, make_model, register_aggregator
from gnn_delta.plans.scratch import settled
from gnn_delta.plans.state import StateStore
from gnn_delta.sources.graphs import formula_features, second_features, vertices_of, weighted
from gnn_delta.functions.mixes import MIX
from gnn_delta.sources import updates as up
from gnn_delta.sources.updates import assign_batches, next_batch_size
from gnn_delta.streaming.apply import ROW, Engine, stream_chained

D = 4
LETTERS = {n: i for i, n in enumerate("ABCDEF")}
WORKED = ["BA", "DA", "AB", "AD", "DB", "CD", "DC", "DE"]


def graph(spark, pairs):
    return spark.createDataFrame([(LETTERS[a], LETTERS[b]) for a, b in pairs], "src long, dst long").transform(weighted)


def updates(spark, rows):
    full = [(seq, None, kind, src, dst, w, feat) for seq, kind, src, dst, w, feat in rows]
    return spark.createDataFrame(full, UPDATE_SCHEMA)


@pytest.fixture(scope="module")
def random_graph(spark):
    rng = np.random.default_rng(3)
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, 14, (45, 2)) if a != b}
    edges = settled(spark.createDataFrame(sorted(pairs), "src long, dst long").transform(weighted))
    vertices = settled(spark.range(16).withColumnRenamed("id", "vid"))  # 14 and 15 are isolated
    return vertices, edges, settled(formula_features(vertices, D)), pairs


def batch(spark, pairs):
    missing = [(a, b) for a in range(14) for b in range(14) if a != b and (a, b) not in pairs]
    there = sorted(pairs)
    feat = [0.5, -0.25, 1.0, 0.125]
    return updates(spark, [
        (1, "edge_add", *missing[3], 0.5, None), (2, "edge_del", *there[0], None, None), (3, "edge_del", *there[7], None, None), (4, "feat_set", 2, None, None, feat),
        (5, "edge_add", 14, 1, 1.0, None), (6, "edge_add", *there[9], 0.75, None), (7, "edge_del", *missing[8], None, None), (8, "edge_add", *missing[20], 1.0, None), (9, "edge_del", *missing[20], None, None),
        (10, "edge_add", 99, 1, 1.0, None), (11, "feat_set", 3, None, None, [float("nan"), 0.0, 0.0, 0.0]), (12, "edge_add", 5, 5, 1.0, None),
    ])


def dense(edges, h, model):
    """The same model by dense matrices."""
    n = len(h)
    rows = [(r.src, r.dst, r.w) for r in edges.collect()]
    one, w = np.zeros((n, n)), np.zeros((n, n))
    for a, b, x in rows:
        one[b, a], w[b, a] = 1, x
    c = one.sum(1, keepdims=True)
    for spec in model.layers:
        if spec.agg == "norm":
            x = (one @ (h / np.sqrt(np.maximum(c, 1)))) / np.sqrt(np.maximum(c, 1))
        elif spec.agg == "max":
            x = np.array([h[one[v] > 0].max(0) if c[v] else np.zeros(h.shape[1]) for v in range(n)])
        else:
            total = (w if spec.agg == "wsum" else one) @ h
            mean = np.where(c > 0, total / np.maximum(c, 1), 0)
            x = {"mean": mean, "sum_mean": np.concatenate([total, mean], 1)}.get(spec.agg, total)
        if spec.conv == "gin":
            z = np.maximum((x + (1 + spec.eps) * h) @ np.array(spec.w), 0) @ np.array(spec.w_self)
        else:
            z = x @ np.array(spec.w) + (h @ np.array(spec.w_self) if spec.conv == "sage" else 0)
        h = np.maximum(z, 0) if spec.act == "relu" else z
    return h


def matrix(df, d=D):
    return np.array([[r[f"h{i}"] for i in range(d)] for r in df.orderBy("vid").collect()])


@pytest.mark.parametrize("kind", [*WORKLOADS, "gc_norm", "gc_sum_mean"])
def test_strategies_agree_with_numpy(spark, random_graph, kind):
    vertices, edges, feats, pairs = random_graph
    model = make_model(kind, 2, D)
    state = infer_full(vertices, edges, feats, model, settled)
    assert np.allclose(matrix(state.layers[-1]), dense(edges, matrix(feats), model), rtol=1e-12, atol=1e-12)
    effect = net_effect(batch(spark, pairs), state, D)
    assert effect.quarantined.count() == 2
    results = {"incremental": apply_incremental(state, effect, model), "scoped": apply_scoped(state, effect, model), "pruned": apply_incremental(state, effect, model, prune_zero=True)}
    if kind != "gc_norm":
        results["hybrid"] = apply_hybrid(state, effect, model)
    want = dense(results["scoped"].state.edges, matrix(results["scoped"].state.layers[0]), model)
    for name, r in results.items():
        got = matrix(r.state.layers[-1])
        assert len(got) == 16
        if model.exact:
            assert (got == want).all(), name
        else:
            assert np.allclose(got, want, rtol=1e-12, atol=1e-12), name
    targets = vertices.where("vid < 5")
    if kind not in ("gc_norm", "gc_sum_mean"):
        alone = infer_vertexwise(results["scoped"].state.edges, results["scoped"].state.layers[0], targets, model)
        assert np.allclose(matrix(alone), want[:5], rtol=1e-12, atol=1e-12)


def test_batch_equals_one_by_one_and_split(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    model = make_model("sage_sum", 2, D)
    rows = batch(spark, pairs)
    whole = apply_incremental((s := infer_full(vertices, edges, feats, model, settled)), net_effect(rows, s, D), model)
    state = s
    for lo, hi in ((0, 3), (3, 8), (8, 12)):
        state = apply_incremental(state, net_effect(rows.where(f"seq > {lo} and seq <= {hi}"), state, D), model).state.pinned()
    assert (matrix(state.layers[-1]) == matrix(whole.state.layers[-1])).all()
    stored = state.edges.join(state.layers[1].withColumnRenamed("vid", "src"), "src").groupBy("dst").agg(F.sum("h1").alias("s"))
    both = state.layers[2].join(stored, F.col("vid") == F.col("dst"), "left").select(F.abs(F.coalesce("s", F.lit(0.0)) - F.col("s1")).alias("x")).agg(F.max("x")).first()[0]
    assert both == 0


def test_add_then_delete_restores(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    model = make_model("gin_sum", 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    there = apply_incremental(s, net_effect(updates(spark, [(1, "edge_add", 14, 2, 1.0, None)]), s, D), model).state.pinned()
    back = apply_incremental(there, net_effect(updates(spark, [(2, "edge_del", 14, 2, None, None)]), there, D), model).state
    assert (matrix(there.layers[-1]) != matrix(s.layers[-1])).any()
    assert (matrix(back.layers[-1]) == matrix(s.layers[-1])).all()


def hops_of(spark, edges, rows, model):
    vertices = vertices_of(edges)
    state = infer_full(vertices, edges, formula_features(vertices, D), model, settled)
    effect = net_effect(updates(spark, rows), state, D)
    hops = aff.affected_sets(edges_after(edges, effect.d_edges), effect.d_edges, effect.d_feats, model)
    back = {i: n for n, i in LETTERS.items()}
    return ["".join(sorted(back[r.vid] for r in h.collect())) for h in hops], state, effect


def test_worked_example_of_hops(spark):
    model = make_model("gc_sum", 3, D)
    edges = graph(spark, WORKED)
    hops, state, effect = hops_of(spark, edges, [(1, "edge_add", LETTERS["C"], LETTERS["A"], 1.0, None)], model)
    assert hops == ["", "A", "ABD", "ABCDE"]
    result = apply_incremental(state, effect, model)
    sent = messages(result.changed[1], state, effect, 2, model.layers[1])
    to_d = sent.where(f"dst = {LETTERS['D']} and src = {LETTERS['A']}").first()
    old, new = (matrix(x.layers[1].where("vid = 0"))[0] for x in (state, result.state))
    assert [to_d[f"m{i}"] for i in range(D)] == (new - old).tolist()
    feat, _, _ = hops_of(spark, graph(spark, [*WORKED, "CA"]), [(1, "feat_set", LETTERS["C"], None, None, [0.5] * D)], model)
    assert feat[:2] == ["C", "AD"]


def test_worked_example_of_unaffected(spark):
    hops, state, effect = hops_of(spark, graph(spark, ["AB", "AC", "AD", "FB", "EF"]), [(1, "edge_add", LETTERS["E"], LETTERS["A"], 1.0, None)], make_model("gc_sum", 2, D))
    assert hops == ["", "A", "ABCD"]


def test_messages_combine_in_any_order(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    model = make_model("gc_sum", 1, D)
    s = infer_full(vertices, edges, feats, model, settled)
    effect = net_effect(batch(spark, pairs), s, D)
    sent = messages(effect.d_feats, s, effect, 1, model.layers[0])
    a, b = (merge_inbox(x, D).orderBy("vid").collect() for x in (sent, sent.repartition(7)))
    assert a == b


def test_non_invertible_raises(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    for kind in ("gc_max", "gc_min", "gc_attention"):
        model = make_model(kind, 2, D)
        s = infer_full(vertices, edges, feats, model, settled)
        effect = net_effect(batch(spark, pairs), s, D)
        with pytest.raises(NonInvertibleAggregator):
            apply_incremental(s, effect, model)
        got = apply_scoped(s, effect, model).state
        fresh = infer_full(vertices, got.edges, got.layers[0], model)
        assert np.allclose(matrix(got.layers[-1]), matrix(fresh.layers[-1]))


def test_partitions_do_not_change_results(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    model = make_model("gc_sum", 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    effect = net_effect(batch(spark, pairs), s, D)
    want = matrix(apply_scoped(s, effect, model).state.layers[-1])
    for method in ("hash", "labelprop"):
        placed = settled(pt.place(vertices, edges, 3, method))
        assert placed.count() == placed.select("vid").distinct().count() == 16
        assert (matrix(pt.apply_scoped_partitioned(s, effect, model, placed, 3).result.state.layers[-1]) == want).all()
        assert (matrix(pt.apply_partitioned(s, effect, model, placed, 3).result.state.layers[-1]) == want).all()
    one = vertices.withColumn("part", F.lit(0))
    assert {r.vectors for r in pt.exchange_counts(edges, effect, model, one, "incremental").collect()} == {0}
    routed = pt.route(batch(spark, pairs).where("seq < 5"), settled(pt.place(vertices, edges, 3)))
    assert routed.where("role = 'compute'").count() == 4
    fresh = spark.createDataFrame([(20,), (21,)], "vid long")
    more = edges.unionByName(spark.createDataFrame([(20, 1, 1.0), (3, 20, 1.0)], edges.schema))
    near = {r.vid: r.part for r in settled(pt.place(vertices, edges, 3)).collect()}
    got = {r.vid: r.part for r in pt.rebalance(settled(pt.place(vertices, edges, 3)), fresh, more, 3, slack=3.0).collect()}
    assert set(got) == {20, 21} and got[20] in (near[1], near[3]) and 0 <= got[21] < 3


def test_costs_match_hand_counts(spark):
    model = make_model("gc_sum", 2, D)
    edges = graph(spark, WORKED)
    _, state, effect = hops_of(spark, edges, [(1, "edge_add", LETTERS["C"], LETTERS["A"], 1.0, None)], model)
    new = edges_after(edges, effect.d_edges)
    hops = aff.affected_sets(new, effect.d_edges, effect.d_feats, model)
    ops = lambda st: [r.ops for r in ms.agg_ops(edges, new, effect, hops, st).orderBy("hop").collect()]
    assert ops("scoped") == [3, 7]  # A has three in-edges; A, B and D have seven
    assert ops("incremental") == [1, 5]  # the new edge; twice A's two out-edges and the new edge
    assert ops("full") == [9, 9]


def test_sampling_reaches_the_exact_result(spark, random_graph):
    vertices, edges, feats, _ = random_graph
    model = make_model("gc_sum", 2, D)
    exact = matrix(infer_full(vertices, edges, feats, model).layers[-1])
    assert (matrix(infer_vertexwise(edges, feats, vertices, model, [50, 50], 1)) == exact).all()
    a, b = (matrix(infer_vertexwise(edges, feats, vertices, model, [2, 2], 5)) for _ in range(2))
    assert (a == b).all() and (a != exact).any()


def test_large_matrices_go_through_arrow(spark):
    d = 20
    vertices = spark.range(6).withColumnRenamed("id", "vid")
    edges = weighted(spark.createDataFrame([(i, (i + 1) % 6) for i in range(6)] + [(0, 3)], "src long, dst long"))
    for kind in ("sage_sum", "gin_sum", "gc_mean"):
        model = make_model(kind, 2, d)
        feats = formula_features(vertices, d)
        assert np.allclose(matrix(infer_full(vertices, edges, feats, model).layers[-1], d), dense(edges, matrix(feats, d), model))


def test_store_and_engine(spark, random_graph, tmp_path):
    vertices, edges, feats, pairs = random_graph
    model = make_model("sage_sum", 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    engine = Engine(spark, str(tmp_path / "state"), model, buckets=3, compact_every=3)
    engine.bootstrap(s)
    rows = batch(spark, pairs)
    changes = engine.apply(rows.where("seq <= 4"), 1)
    result = apply_incremental(s, net_effect(rows.where("seq <= 4"), s, D), model)
    assert sorted((r.vid, r.new_label) for r in changes.collect()) == sorted((r.vid, r.new_label) for r in label_changes(result, s, D).collect())
    engine.apply(rows.where("seq > 4"), 2, "scoped")
    engine.apply(rows.where("seq > 4"), 2, "incremental")  # a batch that runs again replaces itself
    want = matrix(apply_incremental(s, net_effect(rows, s, D), model).state.layers[-1])
    assert (matrix(engine.state().layers[-1]) == want).all()
    assert (matrix(engine.state(as_of=0).layers[-1]) == matrix(s.layers[-1])).all()
    engine.store.compact()
    assert (matrix(engine.store.state().layers[-1]) == want).all()
    assert engine.labels().count() == labels(engine.state().layers[-1], D).count() == 16
    one = engine.store.table("layer1", touched=[0])
    assert "PartitionFilters: [isnotnull(bucket" in one._jdf.queryExecution().executedPlan().toString()
    assert 0 < one.count() < 16


def changed(rows):
    return sorted((r.batch_id, r.vid, r.old_label, r.new_label) for r in rows.collect())


@pytest.fixture()
def engine(spark, random_graph, tmp_path):
    vertices, edges, feats, _ = random_graph
    model = make_model("sage_sum", 2, D)
    engine = Engine(spark, str(tmp_path / "state"), model, buckets=2, compact_every=100)
    engine.bootstrap(infer_full(vertices, edges, feats, model, settled))
    return engine


def test_replay_after_compaction(spark, random_graph, engine):
    """The last batch runs again with the same notifications and the same state, before and after compaction."""
    rows = batch(spark, random_graph[3])
    engine.apply(rows.where("seq <= 3"), 1)
    first = changed(engine.apply(rows.where("seq > 3"), 2))
    want = matrix(engine.state().layers[-1])
    for _ in range(2):
        engine.store.compact()
        assert changed(engine.apply(rows.where("seq > 3"), 2)) == first and first
        assert (matrix(engine.state().layers[-1]) == want).all()
    assert engine.state().vertices.count() == 16
    with pytest.raises(ValueError):
        engine.apply(rows, 1)
    with pytest.raises(ValueError):
        engine.state(as_of=0)


def test_manifest_appears_at_once(spark, random_graph, engine):
    """A crash before the rename leaves the state before it; tables without any manifest are an error."""
    rows = batch(spark, random_graph[3])
    before = matrix(engine.state().layers[-1])
    store, rename = engine.store, StateStore._publish
    StateStore._publish = lambda self, manifest: (_ for _ in ()).throw(RuntimeError("crash"))
    try:
        with pytest.raises(RuntimeError):
            engine.apply(rows, 1)
    finally:
        StateStore._publish = rename
    assert (matrix(engine.state().layers[-1]) == before).all()
    engine.apply(rows, 1)
    assert (matrix(engine.state().layers[-1]) != before).any()
    store._delete(["manifests"])
    with pytest.raises(FileNotFoundError):
        store.manifest()


def test_late_updates_do_not_overwrite(spark, random_graph, engine):
    new, late = [0.5] * D, [0.25] * D
    engine.apply(updates(spark, [(10, "feat_set", 2, None, None, new), (11, "edge_add", 14, 3, 1.0, None)]), 1)
    engine.apply(updates(spark, [(5, "feat_set", 2, None, None, late), (6, "edge_del", 14, 3, None, None), (12, "feat_set", 4, None, None, late)]), 2)
    state = engine.state()
    assert matrix(state.layers[0].where("vid = 2"))[0].tolist() == new and matrix(state.layers[0].where("vid = 4"))[0].tolist() == late
    assert state.edges.where("src = 14 and dst = 3").count() == 1


def test_many_buckets_prune(spark, random_graph, tmp_path):
    vertices, edges, feats, pairs = random_graph
    model = make_model("sage_sum", 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    engine = Engine(spark, str(tmp_path / "many"), model, buckets=20)
    engine.bootstrap(s)
    rows = batch(spark, pairs)
    engine.apply(rows.where("seq <= 5"), 1)
    engine.apply(rows.where("seq > 5"), 2)
    want = matrix(apply_incremental(s, net_effect(rows, s, D), model).state.layers[-1])
    assert (matrix(engine.state().layers[-1]) == want).all()


def test_batches_write_no_edge_table(spark, random_graph):
    """What a batch writes are the rows of its hops; edges are scanned and laid over, never written."""
    vertices, edges, feats, pairs = random_graph
    model = make_model("gc_sum", 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    for apply in (apply_incremental, apply_scoped, apply_hybrid):
        pinned = []
        apply(s, settled_effect(net_effect(batch(spark, pairs), s, D)), model, pin=lambda df: pinned.append(df.columns) or settled(df))  # noqa: B023
        assert pinned and not any("src" in columns for columns in pinned)


def test_writes_of_the_stored_vector_change_nothing(spark, random_graph):
    vertices, edges, feats, _ = random_graph
    model = make_model("gc_sum", 1, D)
    s = infer_full(vertices, edges, feats, model, settled)
    same = matrix(feats.where("vid = 3"))[0].tolist()
    effect = net_effect(updates(spark, [(1, "feat_set", 3, None, None, same), (2, "feat_set", 4, None, None, [0.5] * D)]), s, D)
    assert [r.vid for r in settled_effect(effect).d_feats.collect()] == [4]
    assert [(r.seq, r.reason) for r in effect.ignored.collect()] == [(1, "no change")]


@pytest.mark.parametrize("kind", ["gc_max", "gc_min"])
def test_extremes_without_inverse(spark, random_graph, kind):
    vertices, edges, feats, pairs = random_graph
    model = make_model(kind, 2, D)
    s = infer_full(vertices, edges, feats, model, settled)
    effect = settled_effect(net_effect(batch(spark, pairs), s, D))
    got, want = apply_extreme(s, effect, model).state, apply_scoped(s, effect, model).state
    assert (matrix(got.layers[-1]) == matrix(want.layers[-1])).all()


def test_aggregator_of_ones_own(spark, random_graph):
    vertices, edges, feats, pairs = random_graph
    register_aggregator("thirds", LinearAggregator("{w} / 3", "{s} / sqrt({c})"))
    model = ModelSpec("own", (replace(make_model("gc_sum", 1, D).layers[0], agg="thirds"),))
    s = infer_full(vertices, edges, feats, model, settled)
    h, rows = matrix(feats), [(r.src, r.dst, r.w) for r in edges.collect()]
    total, c = np.zeros((16, D)), np.zeros((16, 1))
    for a, b, w in rows:
        total[b] += w / 3 * h[a]
        c[b] += 1
    z = np.where(c > 0, total / np.sqrt(np.maximum(c, 1)), 0) @ np.array(model.layers[0].w)
    assert np.allclose(matrix(s.layers[1]), z)
    effect = net_effect(batch(spark, pairs), s, D)
    assert np.allclose(matrix(apply_incremental(s, effect, model).state.layers[1]), matrix(apply_scoped(s, effect, model).state.layers[1]))
    with pytest.raises(ValueError):
        register_aggregator("sum", LinearAggregator())


def test_chained_form_refuses_what_it_cannot_keep(spark):
    rows = spark.createDataFrame([], ROW)
    for kind in ("gc_max", "gc_attention", "gc_norm"):
        with pytest.raises(NonInvertibleAggregator):
            stream_chained(rows, make_model(kind, 2, D))


def test_store_is_empty_without_manifest(spark, tmp_path):
    assert StateStore(spark, str(tmp_path / "none")).manifest()["batches"] == []


def test_batching(spark):
    rows = updates(spark, [(i, "edge_del", 0, 1, None, None) for i in range(1, 8)])
    assert [r.batch_id for r in assign_batches(rows, 3).orderBy("seq").collect()] == [0, 0, 0, 1, 1, 1, 2]
    assert next_batch_size([(10, 1.0), (20, 1.5), (40, 2.5)], 5.0) == pytest.approx(90, abs=1)
    assert next_batch_size([], 1.0) == 1


def test_plan_has_partial_sums_and_no_python(spark, random_graph):
    vertices, edges, feats, _ = random_graph
    plan = infer_full(vertices, edges, feats, make_model("gc_sum", 1, D)).layers[-1]._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "Arrow" not in plan and "Python" not in plan


def test_measures(spark):
    cost = spark.createDataFrame([("a", 4, 10, 1.0), ("a", 4, 10, 3.0), ("b", 8, 10, 1.0)], "strategy string, p int, updates int, seconds double")
    assert {r.strategy: r.up_s for r in ms.throughput(cost).collect()} == {"a": 5.0, "b": 10.0}
    assert {r.strategy: r.speedup for r in ms.speedup(cost, "a").collect()} == {"a": 1.0, "b": 2.0}
    assert {r.p: r.efficiency for r in ms.scaling_efficiency(cost, 4).collect()} == {4: 1.0, 8: 1.0}
    assert {r.strategy: r.p50 for r in ms.latency_stats(cost).collect()}["a"] == 2.0
    assert names("h", 2) == ["h0", "h1"]


def test_second_features_of_large_ids(spark):
    """Products beyond 2^53 stay whole numbers."""
    got = second_features(spark.range(380_001, 960_001, 8).toDF("vid")).toPandas().astype({"vid": "int64"})
    for k in range(8):
        want = ((got["vid"] + 1) * (2 * k + 3) * 2654435761 // 4096 % 257 - 128) / 64
        assert (got[f"h{k}"] == want).all(), k


def test_stream_ranks_without_one_task(spark, monkeypatch):
    """Ranks by ranges and histograms are those of one sorted list; the snapshot's plan has no window over all edges."""
    pairs = sorted({(a * 7 % 113, a * a % 97) for a in range(900)})
    edges = spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "src long, dst long, w double")
    h = lambda k, x: (MIX[k][0] * x + MIX[k][1]) % MIX[k][2]
    keep = len(pairs) - int(len(pairs) * 0.1)
    order = sorted(range(1, len(pairs) + 1), key=lambda n: h(1, n))
    stay = order[:keep]
    dels = sorted(stay, key=lambda n: h(2, n))[:20]
    vids = sorted({x for p in pairs for x in p})
    sets = sorted(range(1, len(vids) + 1), key=lambda n: h(3, n))[:20]
    items = [(i, 0, *pairs[n - 1]) for i, n in enumerate(order[keep : keep + 20])] + [(i, 1, *pairs[n - 1]) for i, n in enumerate(dels)] + [(i, 2, vids[n - 1], None) for i, n in enumerate(sets)]
    want = [(c, a, b) for _, c, a, b in sorted(items, key=lambda x: h(4, 3 * x[0] + x[1]))]
    for at_once, buckets in ((up.KEYS_AT_ONCE, up.BUCKETS), (10, 4)):
        monkeypatch.setattr(up, "KEYS_AT_ONCE", at_once)
        monkeypatch.setattr(up, "BUCKETS", buckets)
        s = up.make_stream(edges, 20)
        assert sorted((r.src, r.dst) for r in s.snapshot.collect()) == sorted(pairs[n - 1] for n in stay)
        assert sorted(r.vid for r in s.vertices.collect()) == vids
        kinds = {"edge_add": 0, "edge_del": 1, "feat_set": 2}
        assert [(kinds[r.kind], r.src, r.dst) for r in s.updates.orderBy("seq").collect()] == want
        assert "Window" not in s.snapshot._jdf.queryExecution().executedPlan().toString()
    none = up.make_stream(edges.limit(0), 20)
    assert none.snapshot.count() == none.updates.count() == none.vertices.count() == 0


def test_bounds_on_hashes_are_counted():
    """The k-th smallest hash of 1 .. n without listing the hashes."""
    for h, (a, c, m) in MIX.items():
        for n in (1, 2, 1000, 30_011):
            keys = sorted((a * i + c) % m for i in range(1, n + 1))
            assert [up.smallest_mix(h, k, n) for k in (0, 1, n // 2 + 1, n)] == [-1, keys[0], keys[n // 2], keys[-1]]


def test_pairs_are_numbered_by_one_shuffle(spark, monkeypatch):
    """Repeated pairs become distinct in the shuffle that numbers them; of a graph that holds each edge both ways sources are all vertices."""
    half = [(a % 31, 100 + a * a % 29) for a in range(400)]
    edges = spark.createDataFrame(half + [(b, a) for a, b in half], "src long, dst long").transform(weighted)
    want = up.make_stream(settled(edges), 20)
    plans = []
    written = up.settled
    monkeypatch.setattr(up, "settled", lambda df, *a: plans.append(df._jdf.queryExecution().executedPlan().toString()) or written(df, *a))
    got = up.make_stream(edges, 20, mutual=True)
    assert len(plans) == 2 and plans[0].split("Initial Plan")[-1].count("Exchange") == 1
    for a, b in ((got.vertices, want.vertices), (got.snapshot, want.snapshot), (got.updates, want.updates)):
        assert sorted(map(str, a.select(b.columns).collect())) == sorted(map(str, b.collect()))


def test_features_by_formula_are_not_looked_up(spark, random_graph):
    """The first layer over a whole graph joins only targets with sums; listed features give the same rows."""
    vertices, edges, features, _ = random_graph
    for kind in ("gc_wsum", "sage_sum"):
        model = make_model(kind, 2, D)
        by_formula = infer_full(vertices, edges, formula_features(vertices, D), model)
        assert by_formula.layers[1]._jdf.queryExecution().optimizedPlan().toString().count("Join") == 1
        listed = infer_full(vertices, edges, features, model)
        for a, b in zip(by_formula.layers[1:], listed.layers[1:], strict=True):
            assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_batches_in_a_row_pin_no_edges(spark, random_graph):
    """Layers become tables of their own, edges stay the stored ones; affected sets that the caller has are not found again."""
    vertices, edges, features, pairs = random_graph
    model = make_model("gc_sum", 2, D)
    state = infer_full(vertices, edges, features, model, settled)
    kept = state.pinned(edges=False)
    assert kept.edges is state.edges and kept.layers[1]._written_at != state.layers[1]._written_at
    effect = settled_effect(net_effect(batch(spark, pairs), state, D))
    hops = aff.affected_sets(edges_after(edges, effect.d_edges), effect.d_edges, effect.d_feats, model, settled)
    placed = pt.place(vertices, edges, 3)
    for st in ("incremental", "scoped"):
        found, given = (pt.exchange_counts(edges, effect, model, placed, st, h) for h in (None, hops))
        assert sorted(map(tuple, found.collect())) == sorted(map(tuple, given.collect()))


def test_hash_placement_is_not_looked_up(spark, random_graph):
    vertices, edges, _, _ = random_graph
    placed = pt.place(vertices, edges, 3)
    plan = pt.with_parts(edges, placed)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan
    listed = settled(placed)
    for f in (pt.cut_stats, pt.ghosts):
        assert sorted(map(tuple, f(edges, placed).collect())) == sorted(map(tuple, f(edges, listed).collect()))


@pytest.mark.parametrize("scale", [3, 1 << 20])
def test_neighbours_by_groups_and_tiles(spark, monkeypatch, scale):
    """Held queries and streamed tiles give the neighbours that whole rows give, ties to the smaller id."""
    from gnn_delta.sources import graphs

    rng = np.random.default_rng(5)
    q = rng.integers(-scale, scale, (90, 3))
    q[40:60] = q[40]  # copies: ties
    rows = [(int(v), [int(x) for x in row]) for v, row in zip(rng.permutation(1000)[:90], q, strict=True)]
    got = {}
    for queries, tile in ((4096, 512), (7, 4)):
        monkeypatch.setattr(graphs, "QUERIES", queries)
        monkeypatch.setattr(graphs, "TILE", tile)
        got[queries] = {(r.src, r.dst) for r in graphs.knn_edges(spark.createDataFrame(rows, "v long, q array<long>"), 7).collect()}
    want = set()
    for v, x in rows:
        best = sorted((-sum(a * b for a, b in zip(x, y, strict=True)), u) for u, y in rows if u != v)[:7]
        want |= {(u, v) for _, u in best}
    assert got[4096] == got[7] == want


def test_neighbour_tasks_hold_tiles(spark):
    """No group of the plan collects vectors into one row."""
    from gnn_delta.sources import graphs

    rows = [(v, [v % 7, v % 5]) for v in range(50)]
    plan = graphs.knn_edges(spark.createDataFrame(rows, "v long, q array<long>"), 7)._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" not in plan


def test_last_layer_alone(spark, random_graph):
    """Outputs without a kept state: the same vectors, only layers that are read twice are written, generated methods stay below
    the 8,000 bytes that the JVM compiles (means inside each term of the matrix took 9,593)."""
    from gnn_delta.operators.full import infer_outputs

    vertices, edges, features, _ = random_graph
    code = spark._jvm.org.apache.spark.sql.execution.debug.__getattr__("package$").__getattr__("MODULE$")
    for kind, depth, writes in (("gc_mean", 2, 0), ("gc_min", 2, 0), ("gc_max", 2, 0), ("gc_wsum", 3, 0), ("gin_sum", 2, 1), ("gc_sum_mean", 2, 0), ("gc_norm", 2, 0)):
        model, written = make_model(kind, depth), []
        pin = lambda df: written.append(settled(df)) or written[-1]  # noqa: B023, E731
        got = infer_outputs(vertices, edges, formula_features(vertices), model, pin)
        want = infer_full(vertices, edges, settled(formula_features(vertices)), model, settled).layers[-1]
        a, b = (np.array(sorted(map(tuple, x.select("vid", *names("h", 8)).collect()))) for x in (got, want))
        assert len(written) == writes
        assert np.array_equal(a, b) if model.exact else np.allclose(a, b, rtol=1e-12, atol=1e-12)
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        try:
            parts = code.codegenStringSeq(infer_full(vertices, edges, formula_features(vertices), model).layers[1]._jdf.queryExecution().executedPlan())
        finally:
            spark.conf.set("spark.sql.adaptive.enabled", "true")
        assert max(parts.apply(i)._3().maxMethodCodeSize() for i in range(parts.size())) < 8000


def test_rounding_without_decimal_texts(spark):
    """Like scaled doubles in other SQL engines, halves away from zero, and null, NaN and infinities as they are."""
    import duckdb

    from gnn_delta.functions.vectors import rounded

    xs = [float(x) for x in np.random.default_rng(1).uniform(-1, 1, 500) * 10.0 ** np.random.default_rng(2).integers(-8, 9, 500)] + [k / 2e6 for k in range(-99, 99)] + [-0.0, 1e300, None]
    df = spark.createDataFrame(list(enumerate(xs)), "i long, x double")
    got = [r["r"] for r in df.selectExpr("i", f"{rounded('x', 6)} AS r").orderBy("i").collect()]
    rows = ", ".join(f"({i}, {'NULL' if x is None else repr(x)}::DOUBLE)" for i, x in enumerate(xs))
    assert got == [r[0] for r in duckdb.sql(f"SELECT round(x, 6) FROM (VALUES {rows}) t(i, x) ORDER BY i").fetchall()]
    odd = spark.sql(f"SELECT {rounded('x', 6)} AS r FROM VALUES (double('NaN')), (double('Infinity')), (double('-Infinity')) AS t(x)").collect()
    assert str([r["r"] for r in odd]) == "[nan, inf, -inf]"
    plan = to_long(spark.createDataFrame([(1, 0.5)], "vid long, h0 double"), "h", 1, 6)._jdf.queryExecution().optimizedPlan().toString()
    assert "FLOOR" in plan


@pytest.mark.parametrize("kind", ["gc_sum", "sage_sum", "gc_norm"])
def test_affected_by_reads_the_edges_once_for_all(spark, random_graph, monkeypatch, kind):
    """Several batches at once reach what each reaches alone over the edges after it, also where senders are not broadcast."""
    vertices, edges, features, pairs = random_graph
    model, ups = make_model(kind, 3, D), batch(spark, pairs)
    state = infer_full(vertices, edges, features, model, settled)
    alone, d_edges, d_feats = set(), None, None
    for b in (1, 3, 6):
        e = settled_effect(net_effect(ups.where(f"seq <= {b}"), state, D))
        hops = aff.affected_sets(edges_after(edges, e.d_edges), e.d_edges, e.d_feats, model, settled)
        alone |= {(b, r["vid"]) for h in hops for r in h.collect()}
        de, df = e.d_edges.withColumn("batch", F.lit(b)), e.d_feats.withColumn("batch", F.lit(b))
        d_edges, d_feats = (de, df) if d_edges is None else (d_edges.unionByName(de), d_feats.unionByName(df))
    for bound in (500_000, 0):
        monkeypatch.setattr(aff, "BROADCAST_UPDATES", bound)
        plans = []
        pin = lambda df: plans.append(df) or settled(df)  # noqa: B023, E731
        got = aff.affected_by(edges, d_edges, d_feats, model, ["batch"], pin)
        assert sorted(map(tuple, got.select("batch", "vid").collect())) == sorted(alone)
        assert len(plans) == model.depth + 1  # hops, not hops of each batch


def test_pairs_are_numbered_as_one_long_where_they_fit(spark, monkeypatch):
    """Small ids are packed into one key, others are not; ranks and pairs are the same."""
    pairs = [(a * 7 % 40, a * 11 % 60) for a in range(300)] * 2
    top = (1 << 31) - 1
    plans = []
    monkeypatch.setattr(up, "settled", lambda df, what="step": plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or settled(df, what))
    for extra, fits in (((top, top), True), ((0, top), True), ((0, top + 1), False), ((-1, 0), False), ((1 << 40, 3), False)):
        rows = pairs + [extra]
        table, total = up.numbered(spark.createDataFrame(rows, "src long, dst long"), "src", "dst", repeats=True, plain=True)
        want = [(a, b, n) for n, (a, b) in enumerate(sorted(set(rows)), 1)]
        assert total == len(want) and sorted(map(tuple, table.select("src", "dst", "n").collect())) == want
        assert ("shiftleft" in plans[-1]) == fits
    assert not up.fit_one_long(spark.createDataFrame([(1, None)], "src long, dst long"), "src", "dst")
    assert up.numbered(spark.createDataFrame([], "src long, dst long"), "src", "dst", repeats=True, plain=True)[1] == 0
