"""Benchmark decontamination by the q-gram lemma and banded alignment.

A benchmark text is cut into overlapping windows of at most ``window`` bytes. A region within e edits of a
window of m bytes shares at least (m - q + 1) - e*q of its q-grams, at places whose diagonals (place in the
document minus place in the window) differ by at most e. So per document: all q-gram positions are looked
up in a table of the benchmark's q-grams; stretches too poor in hits for any window are dropped; in the
rest hits are counted per window in overlapping bands of diagonals; bands that reach the bound are
verified by banded alignment. Only those pairs that align within the budget are results. Windows begin at
every ``stride`` bytes, so each excerpt of ``window + stride`` bytes holds a whole one. The budget admits a
replaced word: a stretch of b changed bytes spoils at most b + q - 1 q-grams, fewer than b single edits.

The benchmark is the query set: it is read in blocks of a fixed size, each sent to all tasks, so what is
broadcast never exceeds ``block_bytes`` of text.

Defined cases: null and empty texts on either side match nothing; benchmark texts shorter than a q-gram
are matched as whole texts between separators; repeated rows and repeated items give their own results;
letters A-Z and white space signs are compared as equal to a-z and a blank.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vec

FOLD = vec.LOWER.copy()
FOLD[[9, 10, 11, 12, 13]] = 32


@dataclass(frozen=True)
class LeakConfig:
    """``edits``: scattered edits as a share of the window; ``word``: the same for one replaced stretch, in
    windows of ``least_word`` bytes or more; ``window`` and ``stride`` in bytes."""

    q: int = 12
    window: int = 60
    stride: int = 4
    edits: float = 0.04
    word: float = 0.2
    least_word: int = 40
    slots: int = 1 << 22
    block_bytes: int = 4 << 20

    def scattered(self, m: int) -> int:
        return int(m * self.edits)

    def replaced(self, m: int) -> int:
        return int(m * self.word) if m >= self.least_word else 0

    def budget(self, m: int) -> int:
        return max(self.scattered(m), self.replaced(m))

    def bound(self, m: int) -> int:
        spoilt = max(self.scattered(m) * self.q, self.replaced(m) + self.q - 1 if self.replaced(m) else 0)
        return max(1, m - self.q + 1 - spoilt)


def codes(data: np.ndarray, q: int) -> np.ndarray:
    """Hash of the q bytes (8 to 16) that start at each place."""
    n = len(data) - q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    words = np.ndarray(shape=(len(data),), dtype="<u8", buffer=padded, strides=(1,))
    return words[:n] * np.uint64(0x9E3779B97F4A7C15) + (words[q - 8 : q - 8 + n] ^ np.uint64(0x5851F42D4C957F2D)) * np.uint64(0xC2B2AE3D27D4EB4F)


class Patterns:
    """One block of the benchmark: its windows and the table of their q-grams."""

    def __init__(self, items: list[tuple[object, str]], config: LeakConfig):
        self.config = config
        self.windows: list[tuple[object, bytes]] = []
        self.tiny: list[tuple[object, bytes]] = []
        self.starts: list[int] = []
        texts, first, lasts = [], [], []
        for item, text in items:
            raw = FOLD[np.frombuffer((text or "").strip().encode(), np.uint8)].tobytes()
            if len(raw) < config.q:
                if raw:
                    self.tiny.append((item, raw))
                continue
            last = max(0, len(raw) - config.window)
            starts = [*range(0, last, config.stride), last]
            texts.append(np.frombuffer(raw, np.uint8))
            first.append(len(self.windows))
            lasts.append(last)
            self.windows += [(item, raw[s : s + config.window]) for s in starts]
            self.starts += starts
        grams = [codes(t, config.q) for t in texts]
        code = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        owner = np.repeat(np.arange(len(grams)), [len(g) for g in grams])
        place = np.concatenate([np.arange(len(g)) for g in grams]) if grams else np.zeros(0, np.int64)
        order = np.argsort(code, kind="stable")
        self.code, self.owner, self.place = code[order], owner[order], place[order]
        self.first, self.last = np.array(first, np.int64), np.array(lasts, np.int64)
        self.starts = np.array(self.starts, np.int64)
        self.present = np.zeros(config.slots, dtype=bool)
        self.shift = np.uint64(64 - (config.slots.bit_length() - 1))
        self.present[(self.code >> self.shift).astype(np.int64)] = True
        sizes = np.array([len(w) for _, w in self.windows] or [0])
        self.bounds = np.array([config.bound(m) for m in sizes])
        self.least, self.longest = int(self.bounds.min()), int(sizes.max()) + config.budget(int(sizes.max()))

    def windows_of(self, entry: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For table entries: positions in ``entry`` and the windows that hold the q-gram whole."""
        owner, place = self.owner[entry], self.place[entry]
        last, stride = self.last[owner], self.config.stride
        regular = -(-last // stride)  # windows before the last one
        low = np.maximum(0, -(-(place - self.config.window + self.config.q) // stride))
        count = np.maximum(0, np.minimum(place // stride + 1, regular) - low)
        at = np.repeat(np.arange(len(entry)), count)
        k = np.repeat(low, count) + np.arange(len(at)) - np.repeat(np.cumsum(count) - count, count)
        end = np.flatnonzero(place >= last)
        return np.concatenate([at, end]), np.concatenate([self.first[owner[at]] + k, self.first[owner[end]] + regular[end]])

    def search(self, texts: pa.Array) -> Iterator[tuple[int, object, int, int, int]]:
        """(row, item, edits, start, length) of every verified region, best first per row and item."""
        config, q = self.config, self.config.q
        raw, offsets = vec.buffers(texts)
        data = FOLD[raw] if len(raw) else raw
        if self.tiny:
            yield from self._tiny(data, offsets)
        code = codes(data, q)
        if not len(code) or not self.windows:
            return
        hit = self.present[(code >> self.shift).astype(np.int64)]
        for end in offsets[1:-1]:
            hit[max(0, int(end) - q + 1) : int(end)] = False
        at = np.flatnonzero(hit)
        found = np.searchsorted(self.code, code[at])
        found[found == len(self.code)] = 0
        at = at[self.code[found] == code[at]]
        if len(at) < self.least:
            return
        # a region of a window holds `least` hits within `longest` places: keep hits of such stretches
        reach = np.searchsorted(at, at + self.longest, "right") - np.arange(len(at))
        rich = np.flatnonzero(reach >= self.least)
        keep = np.zeros(len(at) + 1, dtype=np.int64)
        np.add.at(keep, rich, 1)
        np.add.at(keep, np.minimum(rich + reach[rich], len(at)), -1)
        at = at[np.cumsum(keep[:-1]) > 0]
        if not len(at):
            return
        low, high = np.searchsorted(self.code, code[at], "left"), np.searchsorted(self.code, code[at], "right")
        times = high - low
        where = np.repeat(at, times)
        entry = np.repeat(low, times) + np.arange(len(where)) - np.repeat(np.cumsum(times) - times, times)
        use, window = self.windows_of(entry)
        where = where[use]
        diagonal = where - self.place[entry[use]] + self.starts[window]
        row = np.searchsorted(offsets, where, "right") - 1
        width = max(1, config.budget(config.window))
        best: dict[tuple[int, object], tuple[int, int, int]] = {}
        seen: set[tuple[int, int]] = set()
        for half in (0, 1):  # bands of 2*width diagonals, each overlapping the next by width
            band = (diagonal + half * width) // (2 * width)
            keys = np.stack([window, band, row], axis=1)
            kinds, first, count = np.unique(keys, axis=0, return_index=True, return_counts=True)
            full = np.array([len(self.windows[w][1]) - q + 1 for w in kinds[:, 0].tolist()])
            fewest = np.maximum(0, -(-(full - count) // q))  # edits at least, by the lemma
            begins = diagonal[first]
            for k in np.lexsort((begins, fewest)).tolist():
                w, _, r = kinds[k].tolist()
                if count[k] < self.bounds[w]:
                    continue
                start = int(begins[k])
                if (w, start) in seen:
                    continue
                seen.add((w, start))
                if (r, self.windows[w][0]) in best and best[r, self.windows[w][0]][0] <= fewest[k]:
                    continue
                item, pattern = self.windows[w]
                slack = 2 * width
                begin = max(int(offsets[r]), start - slack)
                region = data[begin : min(int(offsets[r + 1]), start + len(pattern) + slack)].tobytes()
                match = align(pattern, region, config.budget(len(pattern)))
                if match is None:
                    continue
                edits, a, b = match
                found_at = (edits, begin - int(offsets[r]) + a, b - a)
                if (r, item) not in best or found_at < best[r, item]:
                    best[r, item] = found_at
        for (r, item), (edits, start, length) in best.items():
            yield r, item, edits, start, length

    def _tiny(self, data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, object, int, int, int]]:
        for r in range(len(offsets) - 1):
            text = data[offsets[r] : offsets[r + 1]].tobytes()
            for item, word in self.tiny:
                place = f" {text.decode(errors='replace')} ".find(f" {word.decode(errors='replace')} ")
                if place >= 0:
                    yield r, item, 0, place, len(word)


def align(pattern: bytes, region: bytes, budget: int) -> tuple[int, int, int] | None:
    """(edits, start, end) of the best place of ``pattern`` in ``region`` within ``budget`` edits, else None.

    The region is little longer than the pattern, so its free start and end already bound the band."""
    exact = region.find(pattern)
    if exact >= 0:
        return 0, exact, exact + len(pattern)
    n = len(region)
    text = np.frombuffer(region, np.uint8)
    places = np.arange(n + 1)
    cost, origin = np.zeros(n + 1, np.int64), places.copy()
    for i, sign in enumerate(pattern):
        diagonal = cost[:-1] + (text != sign)
        above = cost[1:] + 1
        new = np.concatenate([[i + 1], np.minimum(diagonal, above)])
        came = np.concatenate([[0], np.where(diagonal <= above, origin[:-1], origin[1:])])
        # insertions run along the row: the least of cost minus place so far
        level = new - places
        lowest = np.minimum.accumulate(level)
        source = np.maximum.accumulate(np.where(level == lowest, places, 0))
        cost, origin = lowest + places, came[source]
        if cost.min() > budget:
            return None
    end = int(cost.argmin())
    return int(cost[end]), int(origin[end]), end


def blocks_of(benchmark: DataFrame, id_col: str, text_col: str, limit: int) -> Iterator[list[tuple[object, str]]]:
    """The benchmark in blocks of at most ``limit`` text bytes (or one item), a partition at a time."""
    block, size = [], 0
    for r in benchmark.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).where("t is not null").toLocalIterator():
        length = len(r["t"].encode())
        if block and size + length > limit:
            yield block
            block, size = [], 0
        block.append((r["i"], r["t"]))
        size += length
    if block:
        yield block


def leaks(docs: DataFrame, benchmark: DataFrame, config: LeakConfig = LeakConfig()) -> DataFrame:
    """doc_id, item_id, edits, start, length (bytes) of the best region of each contaminated pair."""
    spark = docs.sparkSession
    id_kind, item_kind = docs.schema["doc_id"].dataType.simpleString(), benchmark.schema["item_id"].dataType.simpleString()
    schema = f"doc_id {id_kind}, item_id {item_kind}, edits int, start long, length long"
    out = None
    for block in blocks_of(benchmark, "item_id", "text", config.block_bytes):
        shared = spark.sparkContext.broadcast(block)

        def rows(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            patterns = Patterns(shared.value, config)
            for batch in vec.slices(batches, "text"):
                ids = batch.column("doc_id")
                found = list(patterns.search(batch.column("text")))
                if found:
                    row, item, edits, start, length = zip(*found, strict=True)
                    yield pa.RecordBatch.from_pydict({
                        "doc_id": ids.take(pa.array(row)), "item_id": pa.array(item), "edits": pa.array(edits, pa.int32()),
                        "start": pa.array(start, pa.int64()), "length": pa.array(length, pa.int64()),
                    })

        part = docs.select("doc_id", "text").mapInArrow(rows, schema)
        out = part if out is None else out.unionByName(part)
    return out if out is not None else spark.createDataFrame([], schema)


def clean(docs: DataFrame, benchmark: DataFrame, config: LeakConfig = LeakConfig()) -> DataFrame:
    """The rows of ``docs`` (all columns) in which no benchmark window is found, one scan per block."""
    out = docs
    for block in blocks_of(benchmark, "item_id", "text", config.block_bytes):
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def rows(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            patterns = Patterns(shared.value, config)
            for batch in vec.slices(batches, "text"):
                keep = np.ones(batch.num_rows, dtype=bool)
                keep[[r for r, *_ in patterns.search(batch.column("text"))]] = False
                yield batch.filter(pa.array(keep))

        out = out.mapInArrow(rows, docs.schema)
    return out
