"""Exact deduplication by a log-structured merge index over text digests, with DataFrame functions only.

* Memtable and flush: every input task turns its rows into (digest, id, count) and writes a sorted run: a
  Parquet file whose digest column carries a Bloom filter and min/max statistics, so that point lookups
  (:meth:`DigestIndex.lookup`) skip runs and row groups.
* Compaction: a level that holds ``fanout`` runs is merged into one run of the next level by partial
  aggregation; each digest keeps the smallest identifier (or the largest, by parameter) and its count.
* Hits: digests seen more than once fill a Bloom filter of bounded size, one array of words sent to all
  tasks. Only rows that pass it are shuffled with their texts.
* Byte verification: the rows of digests seen more than once are grouped by digest and whole text, so
  equality is decided on bytes; a digest shared by different texts would split into its texts.

Defined cases: a null text counts as empty; where ids are null or repeat, rows are told apart by a row
number in order of (id, text), so that one row of each group stays whatever its id, and null ids never win
over others; of rows equal in id and text any one stays; very long texts are one value each (the digest is
what is sorted); an empty table gives an empty result; extra columns are not read, :func:`dedup` keeps them.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import forget, ids_identify, lower_ascii, numbered, rows_without, shared_dir, written

#: digests that hold more than this share of all rows (so at most 1/share of them) are joined apart
HOT_SHARE = 1 / 200
#: runs of a level that are merged into one run of the next
FANOUT = 4
#: bits of the filter of hits: about ten for each, between these bounds (the upper one is 32 MB)
FILTER_BITS = (1 << 13, 1 << 28)
PROBES = 4


def normalised(text: Column) -> Column:
    return F.coalesce(lower_ascii(text), F.lit(""))


def digest(text: Column) -> Column:
    return F.unhex(F.sha2(text, 256))


@dataclass
class DigestIndex:
    """Sorted digest runs by level: level 0 as flushed, higher ones merged."""

    spark: SparkSession
    path: str
    keep: str = "smallest"
    fanout: int = FANOUT
    levels: list[list[str]] = field(default_factory=list)

    @classmethod
    def create(cls, spark: SparkSession, keep: str = "smallest", fanout: int = FANOUT) -> DigestIndex:
        return cls(spark, f"{shared_dir(spark)}/digest-index-{uuid.uuid4().hex}", keep, fanout)

    def _best(self) -> Column:
        return F.min("id") if self.keep == "smallest" else F.max("id")

    def _run(self, df: DataFrame, level: int) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        path = f"{self.path}/level{level}-{uuid.uuid4().hex}"
        rows = df.select("digest", "id", F.col("n").cast("long").alias("n")).sortWithinPartitions("digest")
        rows.write.option("parquet.bloom.filter.enabled#digest", "true").option("parquet.bloom.filter.adaptive.enabled", "true").parquet(path)
        self.levels[level].append(path)

    def flush(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> None:
        """Add rows: a run with one sorted file per task."""
        self._run(docs.select(digest(normalised(F.col(text_col))).alias("digest"), F.col(id_col).alias("id"), F.lit(1).alias("n")), 0)

    def _merge(self, paths: list[str]) -> DataFrame:
        return self.spark.read.parquet(*paths).groupBy("digest").agg(self._best().alias("id"), F.sum("n").alias("n"))

    def compact(self, whole: bool = False) -> None:
        """Merge levels that are full; ``whole``: all runs into one."""
        level = 0
        while level < len(self.levels):
            paths = list(self.levels[level]) if not whole else [p for runs in self.levels for p in runs]
            if len(paths) >= (1 if whole else self.fanout):
                self._run(self._merge(paths), len(self.levels) if whole else level + 1)
                self._forget(paths)
            if whole:
                return
            level += 1

    def entries(self) -> DataFrame:
        """digest, id that stays, count over all runs."""
        paths = [p for runs in self.levels for p in runs]
        if len(paths) == 1 and not self.levels[0]:
            return self.spark.read.parquet(*paths)
        return self._merge(paths)

    def lookup(self, digests: list[bytes]) -> DataFrame:
        """Entries of some digests; equality filters reach Bloom filters and statistics of the files."""
        paths = [p for runs in self.levels for p in runs]
        found = self.spark.read.parquet(*paths).where(F.col("digest").isin([F.lit(bytearray(d)) for d in digests]))
        return found.groupBy("digest").agg(self._best().alias("id"), F.sum("n").alias("n"))

    def verified(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """digest, text, keep_id, n for groups of two or more rows, equal byte by byte."""
        hits = self.entries().where("n > 1").select("digest")
        text = normalised(F.col(text_col))
        rows = docs.select(F.col(id_col).alias("id"), digest(text).alias("digest"), text.alias("text"))
        return passing(rows, hits, hits.count()).groupBy("digest", "text").agg(self._best().alias("keep_id"), F.count("*").alias("n"))

    def _forget(self, paths: list[str]) -> None:
        for path in paths:
            table = self.spark.createDataFrame([], "x int")
            table._written_at = path
            forget(table)
            for runs in self.levels:
                if path in runs:
                    runs.remove(path)

    def drop(self) -> None:
        self._forget([p for runs in self.levels for p in runs])


def probes(key: Column, bits: int) -> Column:
    """The bits of a key."""
    return F.array(*[F.pmod(F.xxhash64(key, F.lit(k)), F.lit(bits)) for k in range(PROBES)])


def passing(rows: DataFrame, hits: DataFrame, n: int) -> DataFrame:
    """``rows`` whose digest is among the ``n`` of ``hits``, or passes their filter by mistake (a group of one)."""
    bits = min(max(FILTER_BITS[0], 1 << (10 * n).bit_length()), FILTER_BITS[1])
    marked = hits.select(F.explode(probes(F.col("digest"), bits)).alias("p"))
    words = marked.groupBy(F.expr("shiftright(p, 6)").alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(p & 63 AS INT))")).alias("w"))
    every = hits.sparkSession.range(bits // 64).withColumnRenamed("id", "at").join(words, "at", "left")
    # one row of bounded size
    ordered = F.array_sort(F.collect_list(F.struct("at", F.coalesce("w", F.lit(0).cast("long")).alias("w"))))
    sieve = every.agg(F.transform(ordered, lambda x: x["w"]).alias("words"))
    asked = rows.withColumn("at", probes(F.col("digest"), bits)).join(F.broadcast(sieve))
    tests = [F.expr(f"words[CAST(shiftright(at[{k}], 6) AS INT)] & shiftleft(1L, CAST(at[{k}] & 63 AS INT)) <> 0") for k in range(PROBES)]
    for t in tests:
        asked = asked.where(t)
    return asked.select(*rows.columns)


def groups(docs: DataFrame, id_col: str, text_col: str, keep: str) -> tuple[DigestIndex, DataFrame, bool]:
    """Index, verified groups of two or more rows, and whether a digest is shared by different texts."""
    index = DigestIndex.create(docs.sparkSession, keep)
    index.flush(docs, id_col, text_col)
    # the text itself is kept only for digests with several texts
    found = index.verified(docs, id_col, text_col)
    per_digest = found.groupBy("digest").agg(
        F.count("*").alias("texts"), F.first("keep_id").alias("keep_id"), F.first("n").alias("n"),
    )
    table = written(per_digest.where("texts > 1 or n > 1"), "copies")
    return index, table, table.where("texts > 1").limit(1).count() > 0


def joined(rows: DataFrame, table: DataFrame, total: int) -> DataFrame:
    """Left join on digest; the few hot digests (bounded by HOT_SHARE) are broadcast."""
    bound = max(2, int(total * HOT_SHARE))
    hot = table.where(F.col("n") >= bound).select("digest", F.col("keep_id").alias("hot_keep"), F.col("n").alias("hot_n"))
    rest = table.where(F.col("n") < bound).select("digest", F.col("keep_id").alias("rest_keep"), F.col("n").alias("rest_n"))
    first = rows.drop("n").join(F.broadcast(hot), "digest", "left")
    second = first.where("hot_n is null").join(rest, "digest", "left")
    held = first.where("hot_n is not null").withColumns({"rest_keep": F.lit(None).cast("long"), "rest_n": F.lit(None).cast("long")})
    return held.unionByName(second).select(
        "id", "digest", F.coalesce("hot_keep", "rest_keep").alias("keep_id"), F.coalesce("hot_n", "rest_n").alias("n"),
    )


def mark(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256 of the normalised text."""
    if ids_identify(docs, id_col):
        return _mark(docs, id_col, text_col, keep)
    table, row = numbered(docs, id_col, text_col, "last" if keep == "smallest" else "first")
    found = _mark(table.select(F.col(row).alias("id"), F.col(text_col).alias("text")), "id", "text", keep)
    names = table.select(F.col(row).alias("id"), F.col(id_col).alias("own_id"))
    kept = names.select(F.col("id").alias("keep_id"), F.col("own_id").alias("kept_id"))
    out = found.join(names, "id").join(kept, "keep_id")
    return out.select(F.col("own_id").alias(id_col), F.col("kept_id").alias("keep_id"), "group_size", "kept", "text_sha256")


def _mark(docs: DataFrame, id_col: str, text_col: str, keep: str) -> DataFrame:
    index, table, collided = groups(docs, id_col, text_col, keep)
    if collided:
        return _mark_by_text(docs, id_col, text_col, keep)
    rows = index.spark.read.parquet(*index.levels[0])
    out = joined(rows, table, rows.count())
    return out.select(
        F.col("id").alias(id_col),
        F.when(F.col("n").isNull(), F.col("id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        (F.col("n").isNull() | F.col("id").eqNullSafe(F.col("keep_id"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def _mark_by_text(docs: DataFrame, id_col: str, text_col: str, keep: str) -> DataFrame:
    """The same by whole texts, for tables where two texts share a digest."""
    text = normalised(F.col(text_col))
    best = F.min("id") if keep == "smallest" else F.max("id")
    rows = docs.select(F.col(id_col).alias("id"), text.alias("text"))
    table = rows.groupBy("text").agg(best.alias("keep_id"), F.count("*").alias("n"))
    return rows.join(table, "text").select(
        F.col("id").alias(id_col), "keep_id", F.col("n").cast("long").alias("group_size"), F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"), F.sha2("text", 256).alias("text_sha256"),
    )


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows of ``docs`` (all columns) that stay: one of each group of equal texts."""

    def copies(rows: DataFrame) -> DataFrame:
        return written(_mark(rows, "id", "text", keep).where("not kept").select(F.col("id").alias("dropped_id")), "dropped")

    return rows_without(docs, id_col, text_col, copies, "last" if keep == "smallest" else "first")
