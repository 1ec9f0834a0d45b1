"""Update streams: held-out edges return as additions, snapshot edges are deleted, features change, in equal thirds."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mixes import MIX, mix, mix_sql
from ..plans.scratch import settled
from .graphs import D, vertices_of, with_weight


@dataclass(frozen=True)
class Stream:
    vertices: DataFrame
    snapshot: DataFrame  # edges before the stream
    updates: DataFrame  # seq, ts, kind, src, dst, w, feat


def feature_value(vid: Column, seq: Column, k: int) -> Column:
    return ((13 * vid + 7 * seq + 5 * k) % 17 - 8) / 8


#: keys that reach the driver at once, and buckets of the histogram that comes before where there are more
KEYS_AT_ONCE, BUCKETS = 100_000, 4096


def smallest(keys: DataFrame, k: int, total: int, space: int) -> int:
    """The k-th smallest of ``total`` distinct keys (column key) in [0, space), -1 for k = 0: histograms narrow the range."""
    if k <= 0:
        return -1
    low, width = 0, space
    while total > KEYS_AT_ONCE:
        width = -(-width // BUCKETS)
        counts = dict(keys.groupBy(F.expr(f"(key - {low}L) div {width}L")).count().toPandas().itertuples(index=False, name=None))
        at = 0
        while k > counts.get(at, 0):
            k -= counts.get(at, 0)
            at += 1
        low, total = low + at * width, counts[at]
        keys = keys.where(f"key >= {low}L and key < {low + width}L")
    return int(np.sort(keys.toArrow().column("key").to_numpy())[k - 1])


def floor_sum(n: int, m: int, a: int, b: int) -> int:
    """Sum of (a i + b) div m over i = 0 .. n - 1."""
    total = 0
    while n > 0:
        total += n * (n - 1) // 2 * (a // m) + n * (b // m)
        a, b = a % m, b % m
        top = a * n + b
        n, b, m, a = top // m, top % m, a, m
    return total


def smallest_mix(h: int, k: int, n: int) -> int:
    """The k-th smallest of the hashes ``h`` of 1 .. n, -1 for k = 0: as the hash is linear, those up to a bound are counted, not listed."""
    a, c, m = MIX[h]
    if k <= 0:
        return -1
    low, high = 0, m - 1
    while low < high:
        mid = (low + high) // 2
        if floor_sum(n, m, a, a + c) - floor_sum(n, m, a, a + c + m - mid - 1) + n >= k:
            high = mid
        else:
            low = mid + 1
    return low


def fit_one_long(rows: DataFrame, *by: str) -> bool:
    """Whether both keys are in [0, 2^31) in every row, so that one long orders and tells apart the pairs: its sort is by radix."""
    row = rows.agg(F.expr(f"bool_and({' AND '.join(f'coalesce({k} BETWEEN 0 AND {(1 << 31) - 1}L, false)' for k in by)})").alias("fit")).first()
    return bool(row["fit"])


def numbered(rows: DataFrame, *by: str, repeats: bool = False, plain: bool = False) -> tuple[DataFrame, int]:
    """``rows``, whose keys ``by`` are distinct, with their rank n from 1, and their number: ranges are sorted apart and counted.

    ``repeats``: rows of keys alone that may repeat; equal ones fall into one range and are made distinct there.
    ``plain``: they are read from a table without joins or windows, so that one more look at them is cheap."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if repeats and plain and len(by) == 2 and fit_one_long(rows, *by):
        packed = rows.select(F.expr(f"shiftleft({by[0]}, 32) | {by[1]}").alias("key"))
        keys = packed.repartitionByRange(parts, "key").distinct().sortWithinPartitions("key")
        dealt = keys.selectExpr(f"shiftright(key, 32) AS {by[0]}", f"key & {(1 << 32) - 1}L AS {by[1]}")
    else:
        dealt = rows.repartitionByRange(parts, *by)
        dealt = (dealt.distinct() if repeats else dealt).sortWithinPartitions(*by)
    table = settled(dealt.withColumn("at", F.monotonically_increasing_id()), "numbered")
    sizes = dict(table.groupBy(F.expr("shiftright(at, 33)")).count().toPandas().itertuples(index=False, name=None))
    before = np.cumsum([1, *(sizes.get(i, 0) for i in range(max(sizes, default=0)))]).tolist()
    out = table.selectExpr(*rows.columns, f"array({', '.join(f'{x}L' for x in before)})[CAST(shiftright(at, 33) AS INT)] + (at & {(1 << 33) - 1}L) AS n")
    out._written_at = table._written_at
    return out, sum(sizes.values())


def make_stream(edges: DataFrame, n_each: int, hold_out: float = 0.1, d: int = D, mutual: bool = False) -> Stream:
    """Exact ranks by hash. Edges and vertices are numbered in ranges; as their numbers are 1, 2, .. and the hashes of
    these are distinct (up to 2^31 rows), bounds on the hash follow from the numbers alone. Only updates are ranked in one task.

    Weighted pairs are made distinct by the shuffle that numbers them. ``mutual``: every edge is there both ways."""
    spark = edges.sparkSession
    pairs = getattr(edges, "_pairs", None)
    links, total = numbered(edges.select("src", "dst", "w"), "src", "dst") if pairs is None else numbered(pairs.select("src", "dst"), "src", "dst", repeats=True, plain=getattr(edges, "_plain", False))
    written = links._written_at
    links = links if pairs is None else with_weight(links)
    people, n_people = numbered(links.select(F.col("src").alias("vid")).distinct() if mutual else vertices_of(links), "vid")
    keep = total - int(total * hold_out)
    kept, back, told = smallest_mix(1, keep, total), smallest_mix(1, min(keep + n_each, total), total), smallest_mix(3, min(n_each, n_people), n_people)
    # as many as are wanted lie below this one, even if all that are held out do
    most = smallest_mix(2, min(n_each, keep) + total - keep, total)
    among = spark.range(1, total + 1).where((mix(1, F.col("id")) <= kept) & (mix(2, F.col("id")) <= most))
    gone = smallest(among.select(mix(2, F.col("id")).alias("key")), min(n_each, keep), keep, most + 1)
    stays = mix(1, F.col("n")) <= kept
    rank = lambda h: (F.row_number().over(Window.orderBy(mix(h, F.col("n")))) - 1).cast("long")
    none = F.lit(None)
    adds = links.where(~stays & (mix(1, F.col("n")) <= back)).select(rank(1).alias("i"), F.lit(0).alias("c"), "src", "dst", "w")
    dels = links.where(stays & (mix(2, F.col("n")) <= gone)).select(rank(2).alias("i"), F.lit(1).alias("c"), "src", "dst", none.cast("double").alias("w"))
    sets = people.where(mix(3, F.col("n")) <= told).select(rank(3).alias("i"), F.lit(2).alias("c"), F.col("vid").alias("src"), none.cast("long").alias("dst"), none.cast("double").alias("w"))
    items = adds.unionByName(dels).unionByName(sets)
    seq = F.row_number().over(Window.orderBy(mix(4, 3 * F.col("i") + F.col("c")))).cast("long")
    everything, snapshot = people.select("vid"), links.where(stays).select("src", "dst", "w")
    everything._written_at, snapshot._written_at = people._written_at, written
    return Stream(everything, snapshot, _finish(items.withColumn("seq", seq), d))


def _finish(items: DataFrame, d: int) -> DataFrame:
    feat = F.when(F.col("c") == 2, F.array(*[feature_value(F.col("src"), F.col("seq"), k) for k in range(d)]))
    kind = F.when(F.col("c") == 0, "edge_add").when(F.col("c") == 1, "edge_del").otherwise("feat_set")
    ts = F.timestamp_seconds(F.lit(1704067200) + F.col("seq"))
    return items.select("seq", ts.alias("ts"), kind.alias("kind"), "src", "dst", "w", feat.alias("feat"))


def make_stream_by_threshold(edges: DataFrame, share_each: float, hold_out: float = 0.1, d: int = D) -> Stream:
    """The same for any size: hash thresholds choose edges and vertices, no global rank; seq is a hash."""
    unit = lambda *c: F.abs(F.xxhash64(*c) % 1_000_000) / 1_000_000.0
    held = unit("src", "dst", F.lit(1)) < hold_out
    snapshot, out = edges.where(~held), edges.where(held)
    adds = out.where(unit("src", "dst", F.lit(2)) < share_each / hold_out).select(F.lit(0).alias("c"), "src", "dst", "w")
    dels = snapshot.where(unit("src", "dst", F.lit(3)) < share_each).select(F.lit(1).alias("c"), "src", "dst", F.lit(None).cast("double").alias("w"))
    people = vertices_of(edges)
    feats = people.where(unit("vid", F.lit(4)) < share_each).select(F.lit(2).alias("c"), F.col("vid").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(None).cast("double").alias("w"))
    items = adds.unionByName(dels).unionByName(feats)
    return Stream(people, snapshot, _finish(items.withColumn("seq", F.abs(F.xxhash64("c", "src", "dst") % (1 << 50))), d))


def assign_batches(updates: DataFrame, size: int = 10, by: str = "count", every: str = "10 seconds") -> DataFrame:
    """Add ``batch_id``: by fixed count of updates, or by windows of event time."""
    if by == "count":
        return updates.withColumn("batch_id", F.floor((F.col("seq") - 1) / size).cast("long"))
    start = F.window("ts", every)["start"]
    return updates.withColumn("batch_id", F.dense_rank().over(Window.orderBy(start)).cast("long") - 1)


def next_batch_size(history: list[tuple[int, float]], deadline: float, least: int = 1, most: int = 100_000) -> int:
    """Batch size that should meet a latency deadline, from (size, seconds) of past batches: latency = a + b*size."""
    if not history:
        return least
    if len({n for n, _ in history}) < 2:
        n, seconds = history[-1]
        return max(least, min(most, int(n * 2 if seconds < deadline else n / 2)))
    mean_n = sum(n for n, _ in history) / len(history)
    mean_s = sum(s for _, s in history) / len(history)
    slope = sum((n - mean_n) * (s - mean_s) for n, s in history) / sum((n - mean_n) ** 2 for n, _ in history)
    if slope <= 0:
        return most
    return max(least, min(most, int(mean_n + (deadline - mean_s) / slope)))


# --- SQL twins for oracles ---------------------------------------------------------------------------

def stream_ctes(n_each: int, hold_out: float = 0.1, d: int = D) -> list[tuple[str, str]]:
    """CTEs v, snap, upd (seq, kind, src, dst, w, f0..) after g (src, dst, w)."""
    feats = ", ".join(f"CASE WHEN c = 2 THEN ((13 * src + 7 * seq + 5 * {k}) % 17 - 8) / 8.0::DOUBLE END AS f{k}" for k in range(d))
    return [
        ("v", "SELECT src AS vid FROM g UNION SELECT dst FROM g"),
        ("numbered", "SELECT *, row_number() OVER (ORDER BY src, dst) AS n FROM g"),
        ("cut", f"SELECT count(*) - CAST(floor(count(*) * {hold_out}) AS BIGINT) AS keep FROM g"),
        ("ranked", f"SELECT *, row_number() OVER (ORDER BY {mix_sql(1, 'n')}) AS r FROM numbered"),
        ("snapn", "SELECT ranked.* FROM ranked, cut WHERE r <= keep"),
        ("snap", "SELECT src, dst, w FROM snapn"),
        ("adds", f"SELECT r - keep - 1 AS i, 0 AS c, src, dst, w FROM ranked, cut WHERE r > keep AND r <= keep + {n_each}"),
        ("dels", f"SELECT i, 1 AS c, src, dst, NULL::DOUBLE AS w FROM (SELECT *, row_number() OVER (ORDER BY {mix_sql(2, 'n')}) - 1 AS i FROM snapn) WHERE i < {n_each}"),
        ("vn", "SELECT vid, row_number() OVER (ORDER BY vid) AS n FROM v"),
        ("fsets", f"SELECT i, 2 AS c, vid AS src, NULL::BIGINT AS dst, NULL::DOUBLE AS w FROM (SELECT *, row_number() OVER (ORDER BY {mix_sql(3, 'n')}) - 1 AS i FROM vn) WHERE i < {n_each}"),
        ("items", "SELECT * FROM adds UNION ALL SELECT * FROM dels UNION ALL SELECT * FROM fsets"),
        ("seqd", f"SELECT *, row_number() OVER (ORDER BY {mix_sql(4, '3 * i + c')}) AS seq FROM items"),
        ("upd", f"SELECT seq, CASE c WHEN 0 THEN 'edge_add' WHEN 1 THEN 'edge_del' ELSE 'feat_set' END AS kind, src, dst, w, {feats} FROM seqd"),
    ]
