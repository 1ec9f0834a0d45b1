"""Counts of the experiments and the measures over cost tables, as queries with SQL oracles.

Times differ from run to run; what the experiments explain them by does not: affected vertices, aggregation
operations and crossing vectors by batch size, kind of update, graph and number of parts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.mixes import part_sql
from ..operators import affected as aff
from ..operators import measures as ms
from ..operators import partition as pt
from ..operators.netting import edges_after
from ..sources.graphs import table
from . import oracle as o
from .cases import Case, case
from .gnn_queries import base_ctes, hop_ctes, query
from .model import ModelSpec, make_model
from .state import pinned


def _union(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def _hops(c: Case, model: ModelSpec, where: str) -> list[DataFrame]:
    e = c.effect(model, where)
    return aff.affected_sets(edges_after(c.stream.snapshot, e.d_edges, e.small), e.d_edges, e.d_feats, model, pinned)


def _reached(c: Case, model: ModelSpec, batches: dict, within: str) -> DataFrame:
    """(batch, affected): how many vertices each batch reaches, none included."""
    d_edges, d_feats = c.effects_of(batches, within)
    tree = aff.affected_by(c.stream.snapshot, d_edges, d_feats, model, ["batch"])
    counts = {r["batch"]: r["affected"] for r in tree.groupBy("batch").agg(F.count("*").alias("affected")).collect()}
    kind = "string" if isinstance(next(iter(batches)), str) else "long"
    return c.spark.createDataFrame([(b, counts.get(b, 0)) for b in batches], f"batch {kind}, affected long")


def _tree_sql(graph: str, model: ModelSpec, where: str, select: str) -> str:
    """``select`` over ``tree`` (vid), the vertices of all hops."""
    tree = " UNION ".join(f"SELECT vid FROM a_{i}" for i in range(model.depth + 1))
    return o.with_sql([*base_ctes(graph), *o.final_ctes(where), *hop_ctes(model), ("tree", tree)], select)


GC2, SAGE3 = make_model("gc_sum", 2), make_model("sage_sum", 3)
KINDS = ("edge_add", "edge_del", "feat_set")


@query("exp_kinds", " UNION ALL ".join(f"SELECT * FROM ({_tree_sql('order_part', GC2, f'kind = {k!r} AND seq <= 300', f'SELECT {k!r} AS kind, count(*) AS affected FROM tree')})" for k in KINDS))
def exp_kinds(s, d):
    """How many vertices each kind of update reaches: feature changes reach more than edge changes."""
    return _reached(case(s, d), GC2, {k: f"kind = '{k}'" for k in KINDS}, "seq <= 300").withColumnRenamed("batch", "kind")


GROWTH = [(g, b) for g in ("order_part", "next_part") for b in (1, 10, 100)]


@query("exp_growth", " UNION ALL ".join(f"SELECT * FROM ({_tree_sql(g, SAGE3, f'seq <= {b}', f'SELECT {g!r} AS graph, CAST({b} AS BIGINT) AS batch_size, count(*) AS affected, round(count(*) / (SELECT count(*) FROM v), 9) AS share FROM tree')})" for g, b in GROWTH))
def exp_growth(s, d):
    """Share of affected vertices by batch size, on a sparse and a dense graph, for a three-layer model with own vectors."""
    rows = []
    for g in dict.fromkeys(g for g, _ in GROWTH):
        c, sizes = case(s, d, g), [b for h, b in GROWTH if h == g]
        n = c.stream.vertices.count()
        reached = _reached(c, SAGE3, {b: f"seq <= {b}" for b in sizes}, f"seq <= {max(sizes)}")
        rows.append(reached.select(F.lit(g).alias("graph"), F.col("batch").cast("long").alias("batch_size"), "affected", F.round(F.col("affected") / n, 9).alias("share")))
    return _union(rows)


SIZES = (1, 10, 100)


def _ops_sql(b: int) -> str:
    kept = "SELECT count(*) FROM e_new e JOIN a_{0} a ON a.vid = e.src WHERE NOT EXISTS (SELECT 1 FROM d_e x WHERE x.src = e.src AND x.dst = e.dst)"
    parts = {
        "scoped": " + ".join(f"(SELECT count(*) FROM e_new e JOIN a_{i} a ON a.vid = e.dst)" for i in (1, 2)),
        "incremental": " + ".join(f"2 * ({kept.format(i - 1)}) + (SELECT count(*) FROM d_e)" for i in (1, 2)),
        "full": "2 * (SELECT count(*) FROM e_new)",
    }
    select = " UNION ALL ".join(f"SELECT CAST({b} AS BIGINT) AS batch_size, '{k}' AS strategy, CAST({q} AS BIGINT) AS ops" for k, q in parts.items())
    return o.with_sql([*base_ctes("order_part"), *o.final_ctes(f"seq <= {b}"), *hop_ctes(GC2)], select)


@query("exp_ops_by_size", " UNION ALL ".join(f"SELECT * FROM ({_ops_sql(b)})" for b in SIZES))
def exp_ops_by_size(s, d):
    """Aggregation operations of each strategy by batch size."""
    c, rows = case(s, d), []
    for b in SIZES:
        e, hops = c.effect(GC2, f"seq <= {b}"), _hops(c, GC2, f"seq <= {b}")
        new = edges_after(c.stream.snapshot, e.d_edges, e.small)
        for st in ("scoped", "incremental", "full"):
            ops = ms.agg_ops(c.stream.snapshot, new, e, hops, st).agg(F.sum("ops").alias("ops"))
            rows.append(ops.select(F.lit(b).cast("long").alias("batch_size"), F.lit(st).alias("strategy"), "ops"))
    return _union(rows)


PARTS = (4, 8, 16)


def _vectors_sql(p: int) -> str:
    placed = ("p", f"SELECT vid, {part_sql('vid', p, 'duckdb')} AS part FROM v")
    one = lambda i: f"SELECT DISTINCT t.dst, a.part FROM (SELECT e.src, e.dst FROM e_new e JOIN a_{i - 1} x ON x.vid = e.src UNION ALL SELECT src, dst FROM d_e) t JOIN p a ON a.vid = t.src JOIN p b ON b.vid = t.dst WHERE a.part <> b.part"
    two = lambda i: f"SELECT DISTINCT t.src, b.part FROM (SELECT e.src, e.dst FROM e_new e JOIN a_{i} x ON x.vid = e.dst) t JOIN p a ON a.vid = t.src JOIN p b ON b.vid = t.dst WHERE a.part <> b.part"
    total = lambda f: " + ".join(f"(SELECT count(*) FROM ({f(i)}))" for i in (1, 2))
    select = f"SELECT CAST({p} AS BIGINT) AS parts, 'incremental' AS strategy, CAST({total(one)} AS BIGINT) AS vectors UNION ALL SELECT {p}, 'scoped', CAST({total(two)} AS BIGINT)"
    return o.with_sql([*base_ctes("order_part"), placed, *o.final_ctes("seq <= 100"), *hop_ctes(GC2)], select)


@query("exp_scaling_vectors", " UNION ALL ".join(f"SELECT * FROM ({_vectors_sql(p)})" for p in PARTS))
def exp_scaling_vectors(s, d):
    """Vectors that cross between parts, by number of parts and strategy."""
    c, rows = case(s, d), []
    effect, hops = c.effect(GC2, "seq <= 100"), _hops(c, GC2, "seq <= 100")
    for p in PARTS:
        placed = pt.place(c.stream.vertices, c.stream.snapshot, p)
        for st in ("incremental", "scoped"):
            v = pt.exchange_counts(c.stream.snapshot, effect, GC2, placed, st, hops).agg(F.sum("vectors").alias("vectors"))
            rows.append(v.select(F.lit(p).cast("long").alias("parts"), F.lit(st).alias("strategy"), "vectors"))
    return _union(rows)


# --- measures over a cost table: order lines as batches (strategy, parts, updates, seconds) ------------------

_COST = "SELECT l_returnflag AS strategy, 2 + l_linenumber % 3 * 2 AS p, l_quantity AS updates, l_extendedprice / 1000 AS seconds FROM lineitem"


def _cost(s, d) -> DataFrame:
    return table(s, d, "lineitem").selectExpr("l_returnflag AS strategy", "2 + l_linenumber % 3 * 2 AS p", "l_quantity AS updates", "l_extendedprice / 1000 AS seconds")


def _rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


query("measure_throughput", f"SELECT strategy, round(sum(updates) / sum(seconds), 6) AS up_s FROM ({_COST}) GROUP BY strategy")(lambda s, d: _rounded(ms.throughput(_cost(s, d)), "up_s"))
query("measure_latency", f"SELECT strategy, round(quantile_cont(seconds, 0.5), 6) AS p50, round(quantile_cont(seconds, 0.95), 6) AS p95, round(quantile_cont(seconds, 0.99), 6) AS p99 FROM ({_COST}) GROUP BY strategy")(
    lambda s, d: _rounded(ms.latency_stats(_cost(s, d)), "p50", "p95", "p99")
)
query("measure_speedup", f"WITH r AS (SELECT strategy, sum(updates) / sum(seconds) AS up_s FROM ({_COST}) GROUP BY strategy) SELECT strategy, round(up_s / (SELECT up_s FROM r WHERE strategy = 'A'), 6) AS speedup FROM r")(
    lambda s, d: _rounded(ms.speedup(_cost(s, d), "A"), "speedup")
)
query("measure_scaling", f"WITH r AS (SELECT p, sum(updates) / sum(seconds) AS up_s FROM ({_COST}) GROUP BY p), b AS (SELECT up_s AS base FROM r WHERE p = 2) SELECT CAST(p AS BIGINT) AS p, round(up_s / base, 6) AS speedup, round(up_s / base * 2 / p, 6) AS efficiency FROM r, b")(
    lambda s, d: _rounded(ms.scaling_efficiency(_cost(s, d), 2).withColumn("p", F.col("p").cast("long")), "speedup", "efficiency")
)
