"""Graphs over the given tables: (src, dst, w) with tagged ids (order 8k, part 8k+1, supplier 8k+2, customer 8k+3)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vectors import names

D = 8


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _tag(column: str, tag: int):
    return (F.col(column) * 8 + tag).cast("long")


def _pairs(df: DataFrame, a, b) -> DataFrame:
    return df.select(a.alias("src"), b.alias("dst"))


def _both_ways(pairs: DataFrame) -> DataFrame:
    return pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def with_weight(pairs: DataFrame) -> DataFrame:
    return pairs.withColumn("w", (1 + (7 * F.col("src") + 3 * F.col("dst")) % 4) / 4)


def weighted(pairs: DataFrame, plain: bool = False) -> DataFrame:
    """Distinct pairs with the dyadic weight (1 + (7 src + 3 dst) mod 4) / 4; the pairs before stay at hand as ``_pairs``.

    ``plain``: they are columns of a table, cheap to read again."""
    out = with_weight(pairs.distinct())
    out._pairs, out._plain = pairs, plain
    return out


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return weighted(_both_ways(_pairs(table(spark, d, "lineitem"), _tag("l_orderkey", 0), _tag("l_partkey", 1))), plain=True)


def supplier_part(spark: SparkSession, d: str) -> DataFrame:
    return weighted(_both_ways(_pairs(table(spark, d, "lineitem"), _tag("l_suppkey", 2), _tag("l_partkey", 1))), plain=True)


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", _tag("l_partkey", 1).alias("p")).distinct()
    other = lines.select("l_orderkey", F.col("p").alias("q"))
    return weighted(lines.join(other, "l_orderkey").where("p <> q").select(F.col("p").alias("src"), F.col("q").alias("dst")))


def next_part(spark: SparkSession, d: str) -> DataFrame:
    line = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    lines = table(spark, d, "lineitem").select(_tag("l_partkey", 1).alias("src"), F.lead(_tag("l_partkey", 1)).over(line).alias("dst"))
    return weighted(lines.where("dst is not null and src <> dst"))


def commerce(spark: SparkSession, d: str) -> DataFrame:
    lines, orders = table(spark, d, "lineitem"), table(spark, d, "orders")
    known = lines.select(F.col("l_orderkey").alias("o_orderkey")).distinct()
    pairs = _pairs(lines, _tag("l_orderkey", 0), _tag("l_partkey", 1)).unionByName(_pairs(lines, _tag("l_suppkey", 2), _tag("l_partkey", 1)))
    pairs = pairs.unionByName(_pairs(orders, _tag("o_custkey", 3), _tag("o_orderkey", 0)))
    return weighted(_both_ways(pairs))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    lines, orders = table(spark, d, "lineitem"), table(spark, d, "orders")
    joined = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])
    return weighted(_both_ways(_pairs(joined, _tag("o_custkey", 3), _tag("l_partkey", 1))))


def user_hops(spark: SparkSession, d: str) -> DataFrame:
    """User of an event to user of the next one; the order is global, so hours are ordered apart and joined at their edges."""
    events = table(spark, d, "events").select("event_id", "ts", "user_id", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour"))
    inner = Window.partitionBy("hour").orderBy("ts", "event_id")
    edges = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(inner).alias("dst"))
    ends = events.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    # one row per hour is left: an order of hours is small at any scale
    across = ends.select(F.col("last").alias("src"), F.lead("first").over(Window.orderBy("hour")).alias("dst"))
    return weighted(edges.unionByName(across).where("dst is not null and src <> dst"))


def knn(spark: SparkSession, d: str, k: int = 7) -> DataFrame:
    """Each vector from its k nearest by integer dot product of quantised vectors; the queries are all vectors, in blocks."""
    vectors = table(spark, d, "embeddings").select(F.col("vec_id").alias("v"), F.transform("embedding", lambda x: F.floor(x.cast("double") * 64 + 0.5).cast("long")).alias("q"))
    return knn_edges(vectors, k)


#: vectors whose neighbours one group looks for, and vectors it is compared with at once (a tile of 16 MB)
QUERIES, TILE = 4096, 512
LOWEST = -(1 << 63)


def knn_edges(vectors: DataFrame, k: int) -> DataFrame:
    """Rows (v, q) compared with all others, exactly: groups of queries are held, all vectors stream past in order of v."""
    import numpy as np
    import pyarrow as pa

    size = vectors.agg(F.count("*").alias("n"), F.max(F.array_max(F.transform("q", lambda x: F.abs(x)))).alias("top")).first()
    blocks = max(4, -(-size["n"] // QUERIES))
    small = vectors.select("v", F.col("q").cast("array<smallint>").alias("q")) if (size["top"] or 0) < 1 << 15 else vectors.select("v", "q")
    asked = small.select(F.pmod(F.xxhash64("v"), F.lit(blocks)).cast("int").alias("block"), F.lit(0).alias("role"), "v", "q")
    shown = small.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.lit(1).alias("role"), "v", "q")
    dealt = asked.unionByName(shown).repartition(int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")), "block").sortWithinPartitions("block", "role", "v")

    def matrix(column: pa.Array) -> np.ndarray:
        return column.flatten().to_numpy().reshape(len(column), -1).astype(np.int64)

    class Group:
        def __init__(self):
            self.v, self.q, self.floor = [], [], None

        def hold(self) -> None:
            self.v, self.q = np.concatenate(self.v), np.concatenate(self.q)
            self.floor = np.full(len(self.v), LOWEST)
            self.row, self.src, self.dot = (np.zeros(0, np.int64) for _ in range(3))

        def show(self, v: np.ndarray, q: np.ndarray) -> None:
            """Later vectors lose ties, so only those above the k-th best so far can enter."""
            exact = float(np.abs(self.q).max()) * float(np.abs(q).max()) * q.shape[1] < 1 << 53
            dots = (self.q.astype(float) @ q.T.astype(float)).astype(np.int64) if exact else self.q @ q.T
            other = self.v[:, None] != v[None, :]
            able = other & (dots > self.floor[:, None])
            if len(v) > k:
                able &= dots >= np.partition(np.where(other, dots, LOWEST), len(v) - k, axis=1)[:, len(v) - k, None]
            row, at = np.nonzero(able)
            if not len(row):
                return
            row, src, dot = np.concatenate([self.row, row]), np.concatenate([self.src, v[at]]), np.concatenate([self.dot, dots[row, at]])
            order = np.lexsort((src, -dot, row))
            row, src, dot = row[order], src[order], dot[order]
            place = np.arange(len(row)) - np.searchsorted(row, row)
            self.row, self.src, self.dot = row[place < k], src[place < k], dot[place < k]
            last = place == k - 1
            self.floor[row[last]] = dot[last]

        def links(self) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(self.src), pa.array(self.v[self.row])], names=["src", "dst"])

    def nearest(batches):
        current, group = None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            block, role = batch.column("block").to_numpy(), batch.column("role").to_numpy()
            change = (np.flatnonzero((block[1:] != block[:-1]) | (role[1:] != role[:-1])) + 1).tolist()
            for a, b in zip([0, *change], [*change, len(block)], strict=True):
                if block[a] != current:
                    if group is not None and group.floor is not None:
                        yield group.links()
                    current, group = block[a], Group()
                for at in range(a, b, TILE):
                    v, q = (batch.column(c).slice(at, min(TILE, b - at)) for c in ("v", "q"))
                    if role[a] == 0:
                        group.v.append(v.to_numpy().copy())
                        group.q.append(matrix(q))
                    elif len(group.v):
                        if group.floor is None:
                            group.hold()
                        group.show(v.to_numpy(), matrix(q))
        if group is not None and group.floor is not None:
            yield group.links()

    return weighted(dealt.mapInArrow(nearest, "src long, dst long"))


def turn_chain(spark: SparkSession, d: str) -> DataFrame:
    turns = table(spark, d, "conversations").select("conv_id", "turn").distinct()
    following = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.lit(1).alias("has"))
    vid = (F.col("conv_id") * 1000 + F.col("turn")).cast("long")
    return weighted(turns.join(following, ["conv_id", "turn"]).select(vid.alias("src"), (vid + 1).alias("dst")))


def page_word(spark: SparkSession, d: str) -> DataFrame:
    """Page and link word both ways; words are numbered in order (their number is bounded by the vocabulary of links)."""
    hrefs = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("word"))
    words = hrefs.select("word").distinct().withColumn("n", F.row_number().over(Window.orderBy("word")))
    return weighted(_both_ways(_pairs(hrefs.join(words, "word"), _tag("page_id", 4), _tag("n", 5))))


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (order_part, supplier_part, copurchase, next_part, commerce, customer_part, user_hops, knn, turn_chain, page_word)
}

#: graphs that hold every edge both ways, so that each vertex is a source
MUTUAL = ("order_part", "supplier_part", "copurchase", "commerce", "customer_part", "page_word")


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()


def computed(vertices: DataFrame, of: Callable[[str], list[str]]) -> DataFrame:
    """Features that are a function of the id, given as SQL texts: ``_of`` stays at hand, as they need no look-up."""
    vectors = of("vid")
    out = vertices.selectExpr("vid", *[f"{x} AS {n}" for x, n in zip(vectors, names("h", len(vectors)), strict=True)])
    out._of = of
    return out


def formula_features(vertices: DataFrame, d: int = D) -> DataFrame:
    return computed(vertices, lambda vid: [f"((31 * {vid} + {7 * k}) % 17 - 8) / 8" for k in range(d)])


def second_features(vertices: DataFrame, d: int = D) -> DataFrame:
    """The second feature set, of many distinct vectors, for label tests on dense graphs."""
    # whole numbers throughout: as doubles, products beyond 2^53 round over a border of 4096
    return computed(vertices, lambda vid: [f"(({vid} + 1) * {2 * k + 3} * 2654435761L div 4096 % 257 - 128) / 64D" for k in range(d)])


# --- the same graphs as SQL for oracles (DuckDB) -----------------------------------------------------

_W = "(1 + (7 * src + 3 * dst) % 4) / 4.0::DOUBLE"


def _sql_both(a: str, b: str, rest: str) -> str:
    return f"SELECT {a} AS src, {b} AS dst {rest} UNION SELECT {b}, {a} {rest}"


PAIRS_SQL = {
    "order_part": _sql_both("8 * l_orderkey", "8 * l_partkey + 1", "FROM lineitem"),
    "supplier_part": _sql_both("8 * l_suppkey + 2", "8 * l_partkey + 1", "FROM lineitem"),
    "copurchase": "SELECT DISTINCT 8 * a.l_partkey + 1 AS src, 8 * b.l_partkey + 1 AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey",
    "next_part": "SELECT DISTINCT src, dst FROM (SELECT 8 * l_partkey + 1 AS src, lead(8 * l_partkey + 1) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS dst FROM lineitem) WHERE dst IS NOT NULL AND src <> dst",
    "commerce": _sql_both("8 * l_orderkey", "8 * l_partkey + 1", "FROM lineitem") + " UNION " + _sql_both("8 * l_suppkey + 2", "8 * l_partkey + 1", "FROM lineitem") + " UNION " + _sql_both("8 * o_custkey + 3", "8 * o_orderkey", "FROM orders"),
    "customer_part": _sql_both("8 * o_custkey + 3", "8 * l_partkey + 1", "FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "user_hops": "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
    "knn": """SELECT src, dst FROM (SELECT b.vec_id AS src, a.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2])) DESC, b.vec_id) AS r
        FROM (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(x::DOUBLE * 64 + 0.5) AS BIGINT)) AS q FROM embeddings) a JOIN (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(x::DOUBLE * 64 + 0.5) AS BIGINT)) AS q FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE r <= 7""",
    "turn_chain": "SELECT DISTINCT 1000 * a.conv_id + a.turn AS src, 1000 * a.conv_id + a.turn + 1 AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "page_word": "SELECT 8 * page_id + 4 AS src, 8 * n + 5 AS dst FROM pw UNION SELECT 8 * n + 5, 8 * page_id + 4 FROM pw",
}


def graph_ctes(name: str) -> list[tuple[str, str]]:
    """CTEs that end with g (src, dst, w), all BIGINT, BIGINT, DOUBLE."""
    ctes = []
    if name == "page_word":
        ctes.append(("hw", """SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS word FROM pages"""))
        ctes.append(("pw", "SELECT page_id, dense_rank() OVER (ORDER BY word) AS n FROM hw"))
    ctes.append(("pairs", PAIRS_SQL[name]))
    ctes.append(("g", f"SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST({_W} AS DOUBLE) AS w FROM pairs"))
    return ctes
