"""Repeated byte strings by suffix arrays in shards.

1. Every window of ``window`` bytes has an anchor, the least hash of ``anchor`` bytes inside it. Anchors
   meet in hash buckets together with a hash of their context: all bytes of the consecutive windows that
   have this anchor. An anchor that occurs once belongs to no repeat. Of equal contexts all but the first repeat
   it whole, without looking at bytes again.
2. Contexts that share an anchor but differ (at the ends of copies and around edits) are cut out of their
   documents and dealt by anchor: the shards. Equal windows share their anchor, so they share a shard.
3. Each shard's suffixes are sorted by external induced sorting (:mod:`suffix`), whose common-prefix
   values tell which windows are equal; the first place by (doc_id, start) stays.
4. Bytes at the source of every joined span are compared before anything is removed.

What a large share of all documents carries is never held in one task: a bucket beyond :data:`repeats.HELD` bytes
is dealt anew, anchors by anchor and context, contexts window by window under 128-bit names; so is one anchor's
group of contexts beyond ``GROUP`` bytes, whose suffix sort would not fit.

Defined cases: null counts as empty; texts shorter than a window lose nothing; a null id counts as smaller
than all others, and rows that repeat an id are ordered by their texts; extra columns are not read; what is kept are bytes (a cut may
fall inside a character).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vec
from .common import forget, written
from .debruijn import of_kind, path_rows
from .repeats import HELD, beside, bucket_count, by_bucket, by_row, dealt, gathered, ids_of, met_by_name, runs, sliding_least, verified
from .suffix import FIRST, SEPARATOR, suffix_array

WINDOW = 100
ANCHOR = 24
#: text bytes that one suffix sort takes, if its anchors' groups allow
SHARD = 1 << 20
#: contexts of one anchor beyond so many bytes are not sorted in one task (a sort takes some 75 bytes for each)
GROUP = 8 << 20
#: contexts whose windows are named at a time
NAMED = 4096
SEEN = ["<u8", "<u8", "<i8", "<i8", "<i4", "<i4"]  # anchor, context, document, place, bytes before, bytes from it
PIECES = "kind int, doc long, start long, n long, src_doc long, src_start long"


def anchors(docs: DataFrame, window: int, anchor: int, buckets: int, seed: int) -> DataFrame:
    """(bucket, blob): the anchors of all windows with their contexts' hashes."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            data, offsets = vec.buffers(batch.column("text"))
            if len(data) < window:
                continue
            sums = vec.prefix(data, seed)
            at = np.arange(len(data) - anchor + 1)
            code = vec.ranges(sums, at, at + anchor)
            chosen = sliding_least(code, window - anchor + 1)
            size = np.diff(offsets)
            inside = np.zeros(len(data) + 1, dtype=np.int64)
            long = size >= window
            np.add.at(inside, offsets[:-1][long], 1)
            np.add.at(inside, offsets[1:][long] - window + 1, -1)
            begin = np.flatnonzero(np.cumsum(inside[:-1])[: len(chosen)] > 0)
            if not len(begin):
                continue
            picked = chosen[begin]
            head_at = np.flatnonzero(np.concatenate([[True], (picked[1:] != picked[:-1]) | (begin[1:] != begin[:-1] + 1)]))
            place, first = picked[head_at], begin[head_at]
            final = begin[np.append(head_at[1:], len(begin)) - 1]
            doc = np.searchsorted(offsets, place, "right") - 1
            before, after = place - first, final + window - place
            context = vec.mix(vec.ranges(sums, place - before, place + after) ^ (before.astype(np.uint64) << np.uint64(32)))
            head = code[place]
            columns = [head.astype("<u8"), context.astype("<u8"), ids_of(batch)[doc].astype("<i8"), (place - offsets[doc]).astype("<i8"), before.astype("<i4"), after.astype("<i4")]
            got = list(dealt((head % np.uint64(buckets)).astype(np.int64), columns))
            yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in got], pa.int32()), pa.array([x for _, x in got], pa.binary())], names=["bucket", "blob"])

    return docs.select("doc_id", "text").mapInArrow(rows, "bucket int, blob binary")


def meet(window: int):
    """Spans of repeated contexts (kind 0), and contexts to compare by their bytes (kind 1: anchor in src_doc)."""

    def work(blobs: list[bytes]) -> Iterator[pa.RecordBatch]:
        head, context, doc, place, before, after = gathered(blobs, SEEN)
        order = np.lexsort((place, doc, context, head))
        head, context, doc, place, before, after = (x[order] for x in (head, context, doc, place, before, after))
        new_head = np.concatenate([[True], head[1:] != head[:-1]])
        new = new_head | np.concatenate([[True], context[1:] != context[:-1]])
        source = np.maximum.accumulate(np.where(new, np.arange(len(head)), 0))
        start = place - before
        later = ~new & ~((doc == doc[source]) & (place == place[source]))
        kinds_of_head = np.bincount(np.cumsum(new_head) - 1, new)[np.cumsum(new_head) - 1]
        differ = new & (kinds_of_head > 1)
        yield pa.RecordBatch.from_arrays(
            [pa.array(x) for x in (
                np.concatenate([np.zeros(later.sum(), np.int32), np.ones(differ.sum(), np.int32)]),
                np.concatenate([doc[later], doc[differ]]),
                np.concatenate([start[later], start[differ]]),
                np.concatenate([(before + after - window + 1)[later], (before + after)[differ]]).astype(np.int64),
                np.concatenate([doc[source][later], head[differ].view(np.int64)]),
                np.concatenate([start[source][later], np.zeros(differ.sum(), np.int64)]),
            )],
            names=["kind", "doc", "start", "n", "src_doc", "src_start"],
        )

    return work


def single_anchors(blob: bytes) -> Iterator[pa.RecordBatch]:
    """The anchors of a blob one by one (kind 2): lengths before and from the anchor packed in n, then anchor and context."""
    head, context, doc, place, before, after = gathered([blob], SEEN)
    packed = before.astype(np.int64) << 32 | after
    columns = (np.full(len(head), 2, np.int32), doc, place, packed, head.view(np.int64), context.view(np.int64))
    yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["kind", "doc", "start", "n", "src_doc", "src_start"])


def met_by_context(rows: DataFrame, window: int) -> tuple[DataFrame, DataFrame]:
    """What :func:`meet` finds, for anchors dealt one by one: spans of repeated contexts, and contexts to compare.

    The first place of a context is found by partial aggregation; the joins split hot keys (adaptive skew join)."""
    seen = rows.selectExpr("src_doc AS head", "src_start AS context", "doc", "start AS place", "shiftright(n, 32) AS before", "n & 4294967295 AS after")
    first = seen.groupBy("head", "context").agg(F.min(F.struct("doc", "place", "before", "after")).alias("f"), F.count("*").alias("c"))
    later = seen.join(first.where("c > 1"), ["head", "context"]).where("not (doc = f.doc and place = f.place)")
    spans = later.selectExpr("doc", "place - before AS start", f"before + after - {window - 1} AS n", "f.doc AS src_doc", "f.place - f.before AS src_start")
    torn = first.groupBy("head").agg(F.count("*").alias("kinds")).where("kinds > 1").select("head")
    differ = first.join(torn, "head").selectExpr("f.doc AS doc", "f.place - f.before AS start", "f.before + f.after AS n", "head")
    return spans, differ


def contexts(docs: DataFrame, lists: DataFrame, buckets: int) -> DataFrame:
    """(bucket, blob): bytes of the contexts listed per document, dealt by anchor."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            data, offsets = vec.buffers(batch.column("text"))
            places = batch.column("places")
            count = np.diff(places.offsets.to_numpy())
            flat = places.flatten()
            start, n, head = (flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(3))
            owner = np.repeat(np.arange(batch.num_rows), count)
            from_ = offsets[owner] + start
            good = from_ + n <= offsets[owner + 1]  # else rows repeat an id
            from_, n, head, owner, start = from_[good], n[good], head[good], owner[good], start[good]
            bucket = (head.view(np.uint64) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            from_, n, head, owner, start, bucket = (x[order] for x in (from_, n, head, owner, start, bucket))
            ids = ids_of(batch)[owner]
            ends = np.concatenate([[0], np.cumsum(n)])
            body = data[np.repeat(from_ - ends[:-1], n) + np.arange(ends[-1])]
            got, blobs = [], []
            for a, b in runs(bucket):
                got.append(int(bucket[a]))
                blobs.append(np.int64(b - a).tobytes() + b"".join(x[a:b].astype("<i8").tobytes() for x in (head, ids, start, n)) + body[ends[a] : ends[b]].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(got, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "blob"])

    return beside(docs, lists, "places", "inner").mapInArrow(rows, "bucket int, blob binary")


EDGES = "kind int, doc long, start long, n long, src_doc long, src_start long"
LISTED = ["<i8"] * 4  # anchor, document, start, bytes


def bodies(blobs: list[bytes]) -> np.ndarray:
    """Bytes of the contexts, behind the count and the listed columns of each blob."""
    return np.concatenate([np.frombuffer(b, np.uint8, offset=8 + 8 * len(LISTED) * int(np.frombuffer(b, np.int64, 1)[0])) for b in blobs])


def compare(window: int, seed: int, shard: int = SHARD, group_limit: int = GROUP):
    """Spans among the contexts of one bucket (kind 0), by suffix arrays of whole anchor groups; windows of larger groups (kind 1)."""

    def work(blobs: list[bytes]) -> Iterator[pa.RecordBatch]:
        head, doc, start, n = gathered(blobs, LISTED)
        body = bodies(blobs)
        at = np.cumsum(n) - n
        order = np.argsort(head, kind="stable")
        held: list[np.ndarray] = []
        size = 0
        for a, b in runs(head[order]):
            members = order[a:b]
            own = int(n[members].sum())
            if own > group_limit:
                yield from named_windows(body, at[members], n[members], doc[members], start[members], window, seed)
                continue
            if held and size + own > group_limit:
                yield sorted_spans(body, at, n, doc, start, held, window)
                held, size = [], 0
            held.append(members)
            size += own
            if size >= shard:
                yield sorted_spans(body, at, n, doc, start, held, window)
                held, size = [], 0
        if held:
            yield sorted_spans(body, at, n, doc, start, held, window)

    return work


def sorted_spans(body: np.ndarray, at: np.ndarray, n: np.ndarray, doc: np.ndarray, start: np.ndarray, held: list[np.ndarray], window: int) -> pa.RecordBatch:
    members = np.concatenate(held)
    return of_kind(0, repeats_in(body, at[members], n[members], doc[members], start[members], window))


def single_windows(window: int, seed: int):
    """The windows of a blob of contexts one by one (kind 1)."""

    def spread(blob: bytes) -> Iterator[pa.RecordBatch]:
        _, doc, start, n = gathered([blob], LISTED)
        yield from named_windows(bodies([blob]), np.cumsum(n) - n, n, doc, start, window, seed)

    return spread


def named_windows(body: np.ndarray, at: np.ndarray, n: np.ndarray, doc: np.ndarray, start: np.ndarray, window: int, seed: int) -> Iterator[pa.RecordBatch]:
    """Every window of the contexts with a 128-bit name in the source columns (kind 1), some contexts at a time."""
    for k in range(0, len(n), NAMED):
        size, begin = n[k : k + NAMED], at[k : k + NAMED]
        own = np.cumsum(size) - size
        inner = np.arange(int(size.sum())) - np.repeat(own, size)
        data = body[np.repeat(begin, size) + inner]
        first = np.flatnonzero(inner + window <= np.repeat(size, size))
        who, offset = np.repeat(np.arange(len(size)), size)[first] + k, inner[first]
        high, low = (vec.ranges(vec.prefix(data, 2 * seed + part), first, first + window).view(np.int64) for part in (101, 102))
        columns = (doc[who], start[who] + offset, np.ones(len(first), np.int64), high, low)
        yield of_kind(1, pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["doc", "start", "n", "src_doc", "src_start"]))


def repeats_in(body: np.ndarray, at: np.ndarray, n: np.ndarray, doc: np.ndarray, start: np.ndarray, window: int) -> pa.RecordBatch:
    ends = np.cumsum(n + 1)
    begin = ends - (n + 1)
    text = np.full(int(ends[-1]) + 1, SEPARATOR, dtype=np.uint16)
    text[-1] = 0
    step = np.repeat(np.arange(len(n)), n)
    inner = np.arange(len(step)) - np.repeat(np.cumsum(n) - n, n)
    text[begin[step] + inner] = body[at[step] + inner].astype(np.uint16) + np.uint16(FIRST)
    order, common = suffix_array(text, window)
    same = np.cumsum(common < window)
    owner = np.searchsorted(ends, order, "right")
    owner_in = np.minimum(owner, len(n) - 1)
    offset = order - begin[owner_in]
    valid = (owner < len(n)) & (offset + window <= n[owner_in])
    same, owner, offset = same[valid], owner_in[valid], offset[valid]
    w_doc, w_start = doc[owner], start[owner] + offset
    sort = np.lexsort((w_start, w_doc, same))
    same, w_doc, w_start = same[sort], w_doc[sort], w_start[sort]
    new = np.concatenate([[True], same[1:] != same[:-1]]) if len(same) else np.zeros(0, bool)
    source = np.maximum.accumulate(np.where(new, np.arange(len(same)), 0)) if len(same) else np.zeros(0, np.int64)
    later = ~((w_doc == w_doc[source]) & (w_start == w_start[source]))
    return path_rows(w_doc[later], w_start[later], w_doc[source][later], w_start[source][later])


def dedup(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR, with_text: bool = False, held: int = HELD, group: int = GROUP) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and what is kept) of every row."""
    return by_row(docs, lambda rows: _dedup(rows, window, anchor, with_text, held, group))


def _dedup(docs: DataFrame, window: int, anchor: int, with_text: bool, held: int, group: int) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and the kept bytes) of every row."""
    buckets = bucket_count(docs)
    made: list[DataFrame] = []

    def spans(seed: int) -> DataFrame:
        found = written(by_bucket(anchors(docs, window, anchor, buckets, seed), buckets, meet(window), PIECES, single_anchors, held), "anchors")
        columns = ["doc", "start", "n", "src_doc", "src_start"]
        whole, differ = met_by_context(found.where("kind = 2"), window)
        differ = found.where("kind = 1").select("doc", "start", "n", F.col("src_doc").alias("head")).unionByName(differ)
        lists = written(differ.groupBy("doc").agg(F.collect_list(F.struct("start", "n", "head")).alias("places")), "places")
        edges = written(by_bucket(contexts(docs, lists, buckets), buckets, compare(window, seed, group_limit=group), EDGES, single_windows(window, seed), held), "edges")
        made.extend([found, lists, edges])
        single = edges.where("kind = 1").select("doc", "start", F.col("src_doc").alias("hi"), F.col("src_start").alias("lo"))
        return found.where("kind = 0").select(*columns).unionByName(whole).unionByName(edges.where("kind = 0").select(*columns)).unionByName(met_by_name(single))

    out = verified(docs, spans, window, False, with_text)
    forget(*made)
    columns = [F.col("units").alias("n_bytes"), F.col("removed").alias("n_removed"), F.col("runs").alias("n_spans"), "kept_sha256"]
    return out.select("doc_id", *columns, *(["kept"] if with_text else []))
