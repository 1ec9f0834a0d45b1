"""What the two substring deduplicators share: anchors, hash buckets, spans with sources, removal.

Units are words or bytes. A *span* says that ``n`` consecutive windows of document ``doc`` from unit
``start`` equal the ``n`` windows of ``src_doc`` from ``src_start``, which start earlier. Anchors are the
least hashes of short unit runs inside each window: equal windows choose equal anchors, so windows meet by
anchor, and windows whose anchor occurs once need not be looked at.

Rows between tasks are blobs: one binary per input slice and hash bucket, read back as NumPy arrays.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import vec
from .common import forget, partitions, written

SPAN = "start long, n long, src_doc long, src_start long"


def bucket_count(docs: DataFrame, bytes_each: int = 10 << 20) -> int:
    """Hash buckets for a table: its text bytes (summed in one scan) by ``bytes_each``, at least the shuffle partitions."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(partitions(docs.sparkSession), size // bytes_each)


def sliding_least(codes: np.ndarray, width: int) -> np.ndarray:
    """Place of the least code (leftmost on ties of the leading bits) in each stretch of ``width`` codes."""
    bits = np.uint64(max(24, int(len(codes)).bit_length()))
    keyed = (codes >> bits << bits) | np.arange(len(codes), dtype=np.uint64)
    span, least = 1, keyed
    while 2 * span <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < width:
        rest = width - span
        least = np.minimum(least[: len(least) - rest], least[rest:])
    return (least & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)


def ids_of(batch: pa.RecordBatch) -> np.ndarray:
    """Document ids; null sorts before all others."""
    import pyarrow.compute as pc

    return pc.fill_null(batch.column("doc_id").cast(pa.int64()), -(1 << 63)).to_numpy(zero_copy_only=False)


def dealt(bucket: np.ndarray, columns: list[np.ndarray]) -> Iterator[tuple[int, bytes]]:
    """(bucket, blob) of equally long columns."""
    order = np.argsort(bucket, kind="stable")
    sorted_bucket = bucket[order]
    columns = [c[order] for c in columns]
    for a, b in runs(sorted_bucket):
        yield int(sorted_bucket[a]), np.int64(b - a).tobytes() + b"".join(c[a:b].tobytes() for c in columns)


def runs(sorted_keys: np.ndarray) -> list[tuple[int, int]]:
    if not len(sorted_keys):
        return []
    cut = np.flatnonzero(sorted_keys[1:] != sorted_keys[:-1]) + 1
    edges = [0, *cut.tolist(), len(sorted_keys)]
    return list(zip(edges[:-1], edges[1:], strict=True))


def gathered(blobs: list[bytes], dtypes: list[str]) -> list[np.ndarray]:
    parts: list[list[np.ndarray]] = [[] for _ in dtypes]
    for blob in blobs:
        n, at = int(np.frombuffer(blob, np.int64, 1)[0]), 8
        for part, dtype in zip(parts, dtypes, strict=True):
            part.append(np.frombuffer(blob, dtype, n, at))
            at += n * np.dtype(dtype).itemsize
    return [np.concatenate(p) if p else np.zeros(0, d) for p, d in zip(parts, dtypes, strict=True)]


#: blobs of one bucket beyond so many bytes are not held in one task (a hot anchor)
HELD = 96 << 20


def by_bucket(rows: DataFrame, count: int, work: Callable[[list[bytes]], Iterator[pa.RecordBatch]], schema: str, spread: Callable[[bytes], Iterator[pa.RecordBatch]] | None = None, limit: int = HELD) -> DataFrame:
    """Run ``work`` on all blobs of each bucket (rows bucket, blob).

    Where a bucket has more than ``limit`` bytes, ``spread`` turns its blobs one by one into rows that are dealt anew."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, held, size, over = None, [], 0, False
        for batch in batches:
            for bucket, blob in zip(batch.column("bucket").to_pylist(), batch.column("blob").to_pylist(), strict=True):
                if bucket != current:
                    if held:
                        yield from work(held)
                    current, held, size, over = bucket, [], 0, False
                size += len(blob)
                if spread is not None and size > limit:
                    for earlier in held:
                        yield from spread(earlier)
                    held, over = [], True
                if over:
                    yield from spread(blob)
                else:
                    held.append(blob)
        if held:
            yield from work(held)
        vec.give_back()

    return rows.repartition(count, "bucket").sortWithinPartitions("bucket").mapInArrow(run, schema)


def met_by_name(rows: DataFrame) -> DataFrame:
    """Spans of single windows (doc, start; name in hi, lo): every place of a name but the first, with the first as source.

    The first places are found by partial aggregation, and the join splits hot names (adaptive skew join)."""
    first = rows.groupBy("hi", "lo").agg(F.min(F.struct("doc", "start")).alias("s"), F.count("*").alias("c")).where("c > 1")
    later = rows.join(first, ["hi", "lo"]).where("not (doc = s.doc and start = s.start)")
    return later.select("doc", "start", F.lit(1).cast("long").alias("n"), F.col("s.doc").alias("src_doc"), F.col("s.start").alias("src_start"))


def compacted(spans: DataFrame) -> DataFrame:
    """Spans of a document that continue each other in document and source become one span."""
    order = Window.partitionBy("doc").orderBy("start", "n", "src_doc", "src_start").rowsBetween(Window.unboundedPreceding, 0)
    one = Window.partitionBy("doc").orderBy("start", "n", "src_doc", "src_start")
    before = lambda c: F.lag(c).over(one)
    goes_on = (F.col("start") <= before("start") + before("n")) & (F.col("src_doc") == before("src_doc")) & (F.col("src_start") - F.col("start") == before("src_start") - before("start"))
    marked = spans.withColumn("new", F.when(goes_on, 0).otherwise(1)).withColumn("path", F.sum("new").over(order))
    joined = marked.groupBy("doc", "path").agg(
        F.min("start").alias("start"), (F.max(F.col("start") + F.col("n")) - F.min("start")).alias("n"), F.first("src_doc").alias("src_doc"), F.min("src_start").alias("src_start"),
    )
    return joined.groupBy("doc").agg(F.sort_array(F.collect_list(F.struct("start", "n", "src_doc", "src_start"))).alias("spans"))


def id_key(doc_id: Column) -> Column:
    return F.coalesce(doc_id.cast("long"), F.lit(-(1 << 63)))


def beside(docs: DataFrame, lists: DataFrame, column: str, how: str) -> DataFrame:
    """doc_id, text and the list ``column`` of each document (``lists``: doc, column), joined by shuffle at any size."""
    rows = docs.select("doc_id", "text", id_key(F.col("doc_id")).alias("doc"))
    return rows.join(lists.hint("shuffle_merge"), "doc", how).select("doc_id", "text", column)


def unit_parts(text: str | None, words: bool):
    raw = (text or "").encode()
    return raw.split() if words else raw


def covered(parts_len: int, spans: list[dict], window: int) -> np.ndarray:
    gone = np.zeros(parts_len + 1, dtype=np.int64)
    for s in spans:
        a, b = min(s["start"], parts_len), min(s["start"] + s["n"] + window - 1, parts_len)
        gone[a] += 1
        gone[b] -= 1
    return np.cumsum(gone[:-1]) > 0


def digest_of(parts, a: int, b: int) -> bytes:
    piece = parts[a:b]
    return hashlib.blake2b(b" ".join(piece) if isinstance(piece, list) else piece, digest_size=16).digest()


REMOVED = "doc_id {kind}, units long, removed long, runs long, kept_sha256 string, kept binary, checks array<struct<src_doc:long,src_start:long,len:long,digest:binary>>"


def removal(docs: DataFrame, lists: DataFrame, window: int, words: bool, with_text: bool = False) -> DataFrame:
    """Per document: units, removed units, maximal removed runs, digest of what is kept, checks to make on sources."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    check = pa.list_(pa.struct([("src_doc", pa.int64()), ("src_start", pa.int64()), ("len", pa.int64()), ("digest", pa.binary())]))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            out: list[tuple] = []
            for text, spans in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
                parts = unit_parts(text, words)
                n, removed, stretches, checks = len(parts), 0, 0, []
                kept = b" ".join(parts) if words else parts
                if spans:
                    gone = covered(n, spans, window)
                    removed = int(gone.sum())
                    stretches = int((gone & ~np.concatenate([[False], gone[:-1]])).sum())
                    kept = b" ".join([p for p, g in zip(parts, gone.tolist(), strict=True) if not g]) if words else np.frombuffer(parts, np.uint8)[~gone].tobytes()
                    for s in spans:
                        length = s["n"] + window - 1
                        checks.append({"src_doc": s["src_doc"], "src_start": s["src_start"], "len": length, "digest": digest_of(parts, s["start"], s["start"] + length)})
                out.append((n, removed, stretches, hashlib.sha256(kept).hexdigest(), kept if with_text else None, checks))
            units, removed, stretches, sha, kept, checks = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(units, pa.int64()), pa.array(removed, pa.int64()), pa.array(stretches, pa.int64()), pa.array(sha), pa.array(kept, pa.binary()), pa.array(checks, check)],
                names=["doc_id", "units", "removed", "runs", "kept_sha256", "kept", "checks"],
            )

    return beside(docs, lists, "spans", "left").mapInArrow(rows, REMOVED.format(kind=kind))


def false_matches(docs: DataFrame, removed: DataFrame, words: bool) -> int:
    """Checks that the text at the source coordinates fails: 0 unless two different windows share hashes."""
    wanted = removed.select(F.explode("checks").alias("c")).select("c.*").distinct()
    lists = written(wanted.groupBy(F.col("src_doc").alias("doc")).agg(F.collect_list(F.struct("src_start", "len", "digest")).alias("asked")), "checks")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            bad = 0
            for text, asked in zip(batch.column("text").to_pylist(), batch.column("asked").to_pylist(), strict=True):
                parts = unit_parts(text, words)
                bad += sum(digest_of(parts, a["src_start"], a["src_start"] + a["len"]) != a["digest"] for a in asked)
            yield pa.RecordBatch.from_arrays([pa.array([bad], pa.int64())], names=["bad"])

    bad = beside(docs, lists, "asked", "inner").mapInArrow(rows, "bad long").agg(F.sum("bad")).first()[0] or 0
    forget(lists)
    return bad


def verified(docs: DataFrame, spans_for: Callable[[int], DataFrame], window: int, words: bool, with_text: bool, tries: int = 4) -> DataFrame:
    """Removal by spans whose sources all verify; with another seed if a hash has brought unequal windows together."""
    for seed in range(tries):
        lists = written(compacted(spans_for(seed)), "spans")
        out = written(removal(docs, lists, window, words, with_text), "removed")
        bad = false_matches(docs, out, words)
        forget(lists)
        if not bad:
            return out
        forget(out)
    raise ArithmeticError(f"unequal windows share a hash under {tries} seeds: is doc_id unique?")


def by_row(docs: DataFrame, run: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``run`` over (doc_id, text); where ids are null or repeat, rows are numbered in order of (id, text) first."""
    rows = docs.select("doc_id", "text")
    if not rows.groupBy("doc_id").count().where("doc_id is null or count > 1").limit(1).count():
        return run(rows)
    order = rows.repartitionByRange(partitions(docs.sparkSession), "doc_id", "text").sortWithinPartitions("doc_id", "text")
    numbered = written(order.withColumn("row", F.monotonically_increasing_id()), "numbered")
    found = run(numbered.select(F.col("row").alias("doc_id"), "text")).withColumnRenamed("doc_id", "row")
    return numbered.select("row", "doc_id").join(found, "row").drop("row")
