"""Repeated word spans by De Bruijn compaction.

The words of all documents form a De Bruijn graph: each window of ``window`` words is an edge from its
first to its last ``window - 1`` words, named by 80 bits of hash. An edge seen more than once is a repeat;
following edges that repeat together, in a document and at the same distance in the source (the first place
of the edge), form a nonbranching path. Edges meet by the anchor of their window, in hash buckets; runs of
edges that share anchor and source leave a bucket as one piece of path; a join by document puts pieces that
continue each other together (:func:`repeats.compacted`), and the words at the source coordinates of every
path are compared before anything is removed. A bucket beyond :data:`repeats.HELD` bytes (a phrase that a
large share of all documents carries) is dealt anew edge by edge, by name.

Defined cases: null and empty texts have no words; documents shorter than a window lose nothing; of equal
windows the one with the smallest (doc_id, start) stays; a null id counts as smaller than all others, and
rows that repeat an id are ordered by their texts; texts of any length are read whole; an empty table gives
an empty result; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vec
from .common import forget, written
from .repeats import HELD, bucket_count, by_bucket, by_row, ids_of, met_by_name, runs, sliding_least, verified

WINDOW = 20
ANCHOR = 6
#: per run of windows with one anchor: anchor, document, first word, windows; then 80 bits of each window
RUN = ["<u8", "<i8", "<u4", "<u1"]


def edges(docs: DataFrame, window: int, anchor: int, buckets: int, seed: int) -> DataFrame:
    """(bucket, blob): every window of every document, dealt by anchor."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            data, offsets = vec.buffers(batch.column("text"))
            starts, ends, first = vec.tokens(data, offsets)
            if len(starts) < window:
                continue
            token = vec.ranges(vec.prefix(data, seed), starts, ends)
            sums = vec.prefix(token)
            at = np.arange(len(token) - anchor + 1)
            code = vec.ranges(sums, at, at + anchor)
            chosen = sliding_least(code, window - anchor + 1)
            owner = vec.owners(first)
            begin = np.arange(len(chosen))
            whole = owner[begin] == owner[begin + window - 1]
            begin, chosen = begin[whole], chosen[whole]
            if not len(begin):
                continue
            name = vec.mix(vec.ranges(sums, begin, begin + window) ^ np.uint64(0x5BD1E995))
            more = vec.ranges(vec.prefix(vec.mix(token ^ np.uint64(0x2545F4914F6CDD1D))), begin, begin + window).astype("<u2")
            new = np.concatenate([[True], (chosen[1:] != chosen[:-1]) | (begin[1:] != begin[:-1] + 1)])
            head = np.flatnonzero(new)
            count = np.diff(np.concatenate([head, [len(begin)]]))
            doc = owner[begin[head]]
            head_anchor = code[chosen[head]]
            bucket = (head_anchor % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            columns = [head_anchor[order], ids_of(batch)[doc[order]].astype("<i8"), (begin[head] - first[doc])[order].astype("<u4"), count[order].astype("<u1")]
            take = np.repeat(head[order] - (np.cumsum(count[order]) - count[order]), count[order]) + np.arange(len(begin))
            low, high = name[take].astype("<u8"), more[take]
            ends_at = np.concatenate([[0], np.cumsum(count[order])])
            got, blobs = [], []
            for a, b in runs(bucket[order]):
                x, y = ends_at[a], ends_at[b]
                got.append(int(bucket[order[a]]))
                blobs.append(b"".join([np.array([b - a, y - x], "<i8").tobytes(), *(c[a:b].tobytes() for c in columns), low[x:y].tobytes(), high[x:y].tobytes()]))
            yield pa.RecordBatch.from_arrays([pa.array(got, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "blob"])

    return docs.select("doc_id", "text").mapInArrow(rows, "bucket int, blob binary")


def read(blobs: list[bytes]) -> tuple[np.ndarray, ...]:
    runs_of, lows, highs = [[] for _ in RUN], [], []
    for blob in blobs:
        n, w = np.frombuffer(blob, "<i8", 2).tolist()
        at = 16
        for part, dtype in zip(runs_of, RUN, strict=True):
            part.append(np.frombuffer(blob, dtype, n, at))
            at += n * np.dtype(dtype).itemsize
        lows.append(np.frombuffer(blob, "<u8", w, at))
        highs.append(np.frombuffer(blob, "<u2", w, at + 8 * w))
    return *(np.concatenate(p) for p in runs_of), np.concatenate(lows), np.concatenate(highs)


def pieces(blobs: list[bytes]) -> Iterator[pa.RecordBatch]:
    """Path pieces of one bucket: later places of repeated edges with their source."""
    anchor, doc, start, count, low, high = read(blobs)
    _, inverse, times = np.unique(anchor, return_inverse=True, return_counts=True)
    again = times[inverse] > 1
    if not again.any():
        return
    per_edge = np.repeat(again, count)
    run = np.repeat(np.arange(len(count)), count)[per_edge]
    step = (np.arange(len(low)) - np.repeat(np.cumsum(count, dtype=np.int64) - count, count))[per_edge]
    name, more = low[per_edge], high[per_edge]
    e_doc, e_start = doc[run], start[run].astype(np.int64) + step
    order = np.lexsort((e_start, e_doc, more, name))
    name, more, e_doc, e_start = name[order], more[order], e_doc[order], e_start[order]
    new = np.concatenate([[True], (name[1:] != name[:-1]) | (more[1:] != more[:-1])])
    source = np.maximum.accumulate(np.where(new, np.arange(len(name)), 0))
    later = ~((e_doc == e_doc[source]) & (e_start == e_start[source]))
    yield of_kind(0, path_rows(e_doc[later], e_start[later], e_doc[source][later], e_start[source][later]))


def of_kind(kind: int, rows: pa.RecordBatch) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(rows.num_rows, kind, np.int32)), *rows.columns], names=["kind", *rows.schema.names])


def single_edges(blob: bytes) -> Iterator[pa.RecordBatch]:
    """The edges of a blob one by one (kind 1), their names in the source columns."""
    _, doc, start, count, low, high = read([blob])
    run = np.repeat(np.arange(len(count)), count)
    step = np.arange(len(low)) - np.repeat(np.cumsum(count, dtype=np.int64) - count, count)
    columns = (doc[run], start[run].astype(np.int64) + step, np.ones(len(low), np.int64), low.view(np.int64), high.astype(np.int64))
    yield of_kind(1, pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=["doc", "start", "n", "src_doc", "src_start"]))


def path_rows(doc: np.ndarray, start: np.ndarray, src_doc: np.ndarray, src_start: np.ndarray) -> pa.RecordBatch:
    """Consecutive windows with consecutive sources as one row each."""
    order = np.lexsort((start, doc))
    doc, start, src_doc, src_start = doc[order], start[order], src_doc[order], src_start[order]
    if len(doc):
        once = np.concatenate([[True], (doc[1:] != doc[:-1]) | (start[1:] != start[:-1])])
        doc, start, src_doc, src_start = doc[once], start[once], src_doc[once], src_start[once]
        new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (start[1:] != start[:-1] + 1) | (src_doc[1:] != src_doc[:-1]) | (src_start[1:] != src_start[:-1] + 1)])
        head = np.flatnonzero(new)
    else:
        head = np.zeros(0, np.int64)
    n = np.diff(np.concatenate([head, [len(doc)]]))
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (doc[head], start[head], n, src_doc[head], src_start[head])], names=["doc", "start", "n", "src_doc", "src_start"])


def dedup(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR, with_text: bool = False, held: int = HELD) -> DataFrame:
    """doc_id, n_words, n_removed, n_spans, kept_sha256 (and what is kept) of every row."""
    return by_row(docs, lambda rows: _dedup(rows, window, anchor, with_text, held))


PIECES = "kind int, doc long, start long, n long, src_doc long, src_start long"


def _dedup(docs: DataFrame, window: int, anchor: int, with_text: bool, held: int) -> DataFrame:
    """doc_id, n_words, n_removed, n_spans, kept_sha256 (and the kept words) of every row."""
    buckets = bucket_count(docs)
    made: list[DataFrame] = []

    def spans(seed: int) -> DataFrame:
        found = written(by_bucket(edges(docs, window, anchor, buckets, seed), buckets, pieces, PIECES, single_edges, held), "pieces")
        made.append(found)
        single = found.where("kind = 1").select("doc", "start", F.col("src_doc").alias("hi"), F.col("src_start").alias("lo"))
        return found.where("kind = 0").drop("kind").unionByName(met_by_name(single))

    out = verified(docs, spans, window, True, with_text)
    forget(*made)
    columns = [F.col("units").alias("n_words"), F.col("removed").alias("n_removed"), F.col("runs").alias("n_spans"), "kept_sha256"]
    return out.select("doc_id", *columns, *([F.col("kept").cast("string").alias("kept")] if with_text else []))
