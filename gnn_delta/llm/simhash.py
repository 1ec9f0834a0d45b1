"""SimHash fingerprints of word shingles and their links, by pivot distance tables.

Links join fingerprints that differ in at most ``radius`` bits. Candidates meet where they agree on a
combination of bit blocks (with ``blocks`` blocks and ``radius`` differing bits at least
``blocks - radius`` blocks agree, so no link is missed). Each fingerprint carries its Hamming distances
to reference fingerprints; by the triangle inequality a pair whose largest coordinate difference exceeds
``radius`` is discarded, and the survivors are verified on all bits. Only links needed to connect a
block's members leave a task: never all pairs of a group. Equal fingerprints count once.

Pivot distances alone are no index here: fingerprints of unrelated texts all lie about 32 bits from any
pivot, so each pivot lets half of all pairs pass; hence the blocks before them.

Defined cases: null and empty texts have fingerprint zero and link like others; fewer words than a
shingle make one shingle; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import vec
from .common import forget, partitions, rows_without, written
from .components import components, extended
from .exact_dedup import HOT_SHARE

SEED = 42
N_PIVOTS = 24
MAX_LANES = 8
#: reference fingerprints, and the multipliers that make further 64-bit lanes of a shingle hash
PIVOTS = np.random.default_rng(SEED).integers(0, 1 << 64, (N_PIVOTS, MAX_LANES), dtype=np.uint64)
LANE = np.random.default_rng(SEED + 1).integers(0, 1 << 64, MAX_LANES, dtype=np.uint64) | np.uint64(1)
RADIUS = 4
BLOCKS = 7
#: runs up to this length are compared by shifts over the whole partition at once, up to the next as a matrix
SHORT, MIDDLE = 12, 1024


def fingerprint(text: bytes, width: int, lanes: int = 1, digest=xxhash.xxh64_digest) -> bytes:
    """Majority bits over the shingle hashes, 64 for each lane, big-endian."""
    words = text.lower().split()
    if not words:
        return bytes(8 * lanes)
    line = b" ".join(words)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(size) - 1
    last = min(width, len(words)) - 1
    starts = (ends - size + 1)[: len(words) - last].tolist()
    packed = b"".join([digest(line[a:b], SEED) for a, b in zip(starts, ends[last:].tolist(), strict=True)])
    if lanes > 1:
        first = np.frombuffer(packed, ">u8").astype(np.uint64)
        more = [first, *(vec.mix(first * LANE[k]) for k in range(1, lanes))]
        packed = np.stack(more, axis=1).astype(">u8").tobytes()
    bits = np.unpackbits(np.frombuffer(packed, np.uint8).reshape(-1, 8 * lanes), axis=1)
    blocks = len(bits) // 255  # sums of 255 rows fit a byte
    ones = bits[255 * blocks :].sum(axis=0, dtype=np.int64)
    if blocks:
        ones += bits[: 255 * blocks].reshape(blocks, 255, -1).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return np.packbits(2 * ones > len(bits)).tobytes()


def lane_names(lanes: int) -> list[str]:
    return [f"f{k}" for k in range(lanes)]


def fingerprints(docs: DataFrame, width: int = 4, lanes: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and the lanes f0, f1, ... (64 bits each as signed longs) of every row."""
    kind = docs.schema[id_col].dataType.simpleString()
    names = lane_names(lanes)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            packed = b"".join(fingerprint((t or "").encode(), width, lanes) for t in batch.column("text").to_pylist())
            out = np.frombuffer(packed, ">i8").astype(np.int64).reshape(-1, lanes)
            yield pa.RecordBatch.from_arrays([batch.column("id"), *(pa.array(out[:, k]) for k in range(lanes))], names=["id", *names])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(rows, f"id {kind}, " + ", ".join(f"{n} long" for n in names))


def pivot_table(fp: np.ndarray) -> np.ndarray:
    """Distances of fingerprints to the reference fingerprints, one row each."""
    table = np.zeros((len(fp), N_PIVOTS), dtype=np.int16)
    for k in range(fp.shape[1]):
        table += np.bitwise_count(fp[:, k, None] ^ PIVOTS[None, :, k])
    return table


def distance(fp: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    return np.bitwise_count(fp[left] ^ fp[right]).sum(axis=1, dtype=np.int64)


def near(fp: np.ndarray, table: np.ndarray, left: np.ndarray, right: np.ndarray, radius: int) -> np.ndarray:
    """Which pairs of positions link: by pivot coordinates first, survivors on all bits."""
    alive = np.arange(len(left))
    for part in range(0, N_PIVOTS, 8):
        apart = np.abs(table[left[alive], part : part + 8] - table[right[alive], part : part + 8]).max(axis=1, initial=0)
        alive = alive[apart <= radius]
    return alive[distance(fp, left[alive], right[alive]) <= radius]


def pairs_of_run(fp: np.ndarray, table: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """All links of a run of moderate length, or, where they are many, links that connect as they do."""
    close = np.triu(np.ones((len(fp), len(fp)), dtype=bool), 1)
    for column in table.T[:8]:
        if int(column.max()) - int(column.min()) > radius:
            close &= np.abs(column[:, None] - column[None, :]) <= radius
    left, right = np.nonzero(close)
    good = distance(fp, left, right) <= radius
    left, right = left[good], right[good]
    return (left, right) if len(left) <= 8 * len(fp) else connect_run(fp, table, radius)


def connect_run(fp: np.ndarray, table: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect the members of one long run as all its links would: a breadth-first search.

    Each member is compared once with the members not yet reached, so dense groups cost little more
    than their size."""
    rest = np.arange(1, len(fp))
    frontier, left, right = [0], [], []
    while True:
        if not frontier:
            if not len(rest):
                break
            frontier, rest = [int(rest[0])], rest[1:]
            continue
        at = frontier.pop()
        close = near(fp, table, np.full(len(rest), at), rest, radius)
        if len(close):
            found = rest[close]
            left.append(np.full(len(found), at))
            right.append(found)
            frontier += found.tolist()
            rest = np.delete(rest, close)
    empty = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (empty, empty)


def links_of_run(key: np.ndarray, fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links among members with equal key; ``key`` is sorted."""
    change = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    length = np.diff(np.concatenate([change, [len(key)]]))
    run = np.repeat(length, length)
    table = pivot_table(fp)
    left, right = [], []
    for shift in range(1, min(SHORT, len(key) - 1) + 1):
        at = np.flatnonzero((key[shift:] == key[:-shift]) & (run[:-shift] <= SHORT))
        good = near(fp, table, at, at + shift, radius)
        left.append(at[good])
        right.append(at[good] + shift)
    for begin, n in zip(change[length > SHORT].tolist(), length[length > SHORT].tolist(), strict=True):
        a, b = (pairs_of_run if n <= MIDDLE else connect_run)(fp[begin : begin + n], table[begin : begin + n], radius)
        left.append(a + begin)
        right.append(b + begin)
    empty = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (empty, empty)


def stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One link from each node to the smallest node that these links connect it with."""
    nodes, place = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right = place[: len(a)], place[len(a) :]
    label = np.arange(len(nodes))
    while True:
        before = label.copy()
        least = np.minimum(label[left], label[right])
        np.minimum.at(label, left, least)
        np.minimum.at(label, right, least)
        label = label[label]
        if (label == before).all():
            break
    off = label != np.arange(len(nodes))
    return nodes[label[off]], nodes[off]


def block_masks(blocks: int, radius: int) -> list[int]:
    """One bit mask for each combination of blocks that some pair within the radius must agree on."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    masks = [((1 << (b - a)) - 1) << a for a, b in zip(edges[:-1], edges[1:], strict=True)]
    return [sum(c) for c in combinations(masks, blocks - radius)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def agreement_keys(radius: int, blocks: int) -> Column:
    """Keys of which a pair within the radius shares at least one, for one lane: no link is missed."""
    masks = block_masks(blocks, radius)
    return F.array(*[F.xxhash64(F.lit(i), F.col("f0").bitwiseAND(F.lit(signed(m)))) for i, m in enumerate(masks)])


def links(distinct: DataFrame, keys: Column, radius: int, lanes: int = 1) -> DataFrame:
    """Pairs (a, b) of representatives (column rep) of distinct fingerprints that connect all within the radius."""
    names = lane_names(lanes)
    keyed = distinct.select(*names, "rep", F.explode(keys).alias("key")).repartition(partitions(distinct.sparkSession), "key").sortWithinPartitions("key")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def close(ready: list[pa.RecordBatch]) -> pa.RecordBatch:
            key, rep, *fp = (np.concatenate([b.column(c).to_numpy() for b in ready]) for c in ("key", "rep", *names))
            a, b = links_of_run(key, np.stack(fp, axis=1).view(np.uint64), radius)
            low, high = stars(rep[a], rep[b])
            return pa.RecordBatch.from_arrays([pa.array(low), pa.array(high)], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("key").to_numpy()
            cut = int(np.searchsorted(key, key[-1]))  # the last key may go on in the next batch
            if cut or (held and held[-1].column("key")[-1].as_py() != int(key[-1])):
                yield close([*held, batch.slice(0, cut)])
                held = []
            held.append(batch.slice(cut))
        if held:
            yield close(held)

    return keyed.mapInArrow(rows, "a long, b long").distinct()


def cluster(prints: DataFrame, keys: Column, radius: int, lanes: int = 1) -> DataFrame:
    """id, lanes, component (smallest id reachable by links) of every row of ``prints``."""
    names = lane_names(lanes)
    table = written(prints, "fingerprints")
    distinct = written(table.groupBy(*names).agg(F.min("id").alias("rep"), F.count("*").alias("n")), "distinct")
    labels = components(links(distinct.where("rep is not null").select(*names, "rep"), keys, radius, lanes))
    known = distinct.join(labels, distinct["rep"] == labels["node"], "left").select(*names, "n", F.coalesce("component", "rep").alias("component"), "rep")
    known = written(known.where("n > 1 or component <> rep").select(*names, "n", "component"), "groups")
    forget(distinct)
    bound = max(2, int(table.count() * HOT_SHARE))
    hot = known.where(F.col("n") >= bound).select(*names, F.col("component").alias("hot"))
    rest = known.where(F.col("n") < bound).select(*names, F.col("component").alias("usual"))
    first = table.join(F.broadcast(hot), names, "left")
    second = first.where("hot is null").join(rest, names, "left")
    return first.where("hot is not null").select("id", *names, F.col("hot").alias("component")).unionByName(second.select("id", *names, F.coalesce("usual", "id").alias("component")))


def near_duplicates(docs: DataFrame, width: int = 4, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits), component_id of every row."""
    found = cluster(fingerprints(docs, width), agreement_keys(radius, BLOCKS), radius)
    return found.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("f0"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))


#: near-dedup: sets of five-word shingles at Jaccard similarity SIMILAR or more. Candidates share one of
#: BANDS keys of ROWS minima (missed at 0.8: (1 - 0.8^4)^24 = 3e-6), differ in at most NEAR_RADIUS of 512
#: bits (expected 78 at 0.8, deviation 8; TINY_RADIUS for sets under TINY shingles, whose bits vary more)
#: and agree in the low bytes of at least LEAST_MINIMA of their 96 minima (expected 77, deviation 4); the mean
#: of the similarities that both suggest (deviation 0.03) is at least LEAST_ESTIMATE
NEAR_WIDTH, NEAR_LANES, NEAR_RADIUS, TINY_RADIUS, TINY = 5, 8, 112, 144, 16
SIMILAR = (4, 5)
BANDS, ROWS, LEAST_MINIMA, LEAST_ESTIMATE = 24, 4, 60, 0.69
MINIMA = np.random.default_rng(SEED + 2).integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
#: radii of the searches that connect most members of a long run before its other pairs are looked at
CONNECT = (64, 96)
MARKS = BANDS * ROWS // 8


def shingle_set(text: bytes, width: int = NEAR_WIDTH) -> np.ndarray:
    """Sorted distinct hashes of the shingles."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    width = min(width, len(words))
    packed = b"".join([xxhash.xxh64_digest(b" ".join(words[i : i + width]), SEED) for i in range(len(words) - width + 1)])
    return np.unique(np.frombuffer(packed, ">u8").astype(np.uint64))


def set_bits(shingles: np.ndarray, lanes: int = NEAR_LANES) -> bytes:
    """Majority bits over a set of shingles, little-endian lanes."""
    hashes = np.stack([shingles, *(vec.mix(shingles * LANE[k]) for k in range(1, lanes))], axis=1)
    bits = np.unpackbits(hashes.view(np.uint8), axis=1)
    return np.packbits(2 * bits.sum(axis=0, dtype=np.int64) > len(shingles)).tobytes()


def minima(shingles: np.ndarray) -> np.ndarray:
    low = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 2048):
        np.minimum(low, (shingles[at : at + 2048, None] * MINIMA).min(axis=0), out=low)
    return low


def band_keys(low: np.ndarray) -> np.ndarray:
    """One key for each band of minima over the set."""
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for column in low.reshape(BANDS, ROWS).T:
        key = vec.mix(key ^ column)
    return key


def marks(low: np.ndarray) -> bytes:
    """A byte of each minimum."""
    return (vec.mix(low) & np.uint64(255)).astype(np.uint8).tobytes()


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether the Jaccard similarity of two sorted sets is at least SIMILAR, in whole numbers."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * SIMILAR[1] >= (len(a) + len(b) - both) * SIMILAR[0]


def sketches(docs: DataFrame) -> DataFrame:
    """id, name (128-bit digest) and size of the shingle set, bits and marks, band keys of every row (id, text)."""
    kind = docs.schema["id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            sets = [shingle_set((t or "").encode()) for t in batch.column("text").to_pylist()]
            low = [minima(s) for s in sets]
            yield pa.RecordBatch.from_pydict({
                "id": batch.column("id"), "name": pa.array([xxhash.xxh128_digest(s.tobytes()) for s in sets], pa.binary()), "n": pa.array([len(s) for s in sets], pa.int32()),
                "fp": pa.array([set_bits(s) + marks(m) for s, m in zip(sets, low, strict=True)], pa.binary()), "keys": pa.array([band_keys(m).view(np.int64) for m in low], pa.list_(pa.int64())),
            })

    return docs.select("id", "text").mapInArrow(rows, f"id {kind}, name binary, n int, fp binary, keys array<long>")


class Members:
    """Sketches of the members of some runs: sizes, bits, marks, pivot distances."""

    def __init__(self, n: np.ndarray, fp: list[bytes]):
        self.n = n.astype(np.int64)
        packed = np.frombuffer(b"".join(fp), np.uint64).reshape(len(n), -1)
        self.bits, self.marks = packed[:, :NEAR_LANES], packed[:, NEAR_LANES:].copy().view(np.uint8)
        self.table = pivot_table(self.bits)

    def within(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Which pairs may be similar: by size, pivots, bits and marks."""
        n = self.n
        few, many = np.minimum(n[left], n[right]), np.maximum(n[left], n[right])
        alive = np.flatnonzero(few * SIMILAR[1] >= many * SIMILAR[0])
        alive = alive[near(self.bits, self.table, left[alive], right[alive], TINY_RADIUS)]
        limit = np.where(few[alive] < TINY, TINY_RADIUS, NEAR_RADIUS)
        alive = alive[distance(self.bits, left[alive], right[alive]) <= limit]
        agree = (self.marks[left[alive]] == self.marks[right[alive]]).sum(axis=1)
        alive, agree = alive[agree >= LEAST_MINIMA], agree[agree >= LEAST_MINIMA]
        small = few[alive] < TINY
        return alive[small | (self.estimate(left[alive], right[alive], agree) >= LEAST_ESTIMATE)]

    def estimate(self, left: np.ndarray, right: np.ndarray, agree: np.ndarray) -> np.ndarray:
        """Similarity by both sketches: the mean of what differing bits and what agreeing minima suggest."""
        cosine = np.cos(np.pi * distance(self.bits, left, right) / (64 * NEAR_LANES))
        both = cosine * np.sqrt(self.n[left] * self.n[right])
        by_bits = both / (self.n[left] + self.n[right] - both)
        by_marks = (agree / (BANDS * ROWS) - 1 / 256) / (1 - 1 / 256)
        return (by_bits + by_marks) / 2


def first_pairs(key: np.ndarray, members: Members) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All candidates of short runs; of a long run pairs that connect its close members, and each member with itself."""
    change = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    length = np.diff(np.concatenate([change, [len(key)]]))
    run = np.repeat(length, length)
    for shift in range(1, min(SHORT, len(key) - 1) + 1):
        at = np.flatnonzero((key[shift:] == key[:-shift]) & (run[:-shift] <= SHORT))
        at = at[members.within(at, at + shift)]
        yield at, at + shift
    for begin, size in zip(change[length > SHORT].tolist(), length[length > SHORT].tolist(), strict=True):
        end = begin + size
        yield np.arange(begin, end), np.arange(begin, end)
        for radius in CONNECT:
            a, b = connect_run(members.bits[begin:end], members.table[begin:end], radius)
            yield a + begin, b + begin


class Joined:
    """Which labels the links found so far connect (least label of each set)."""

    def __init__(self):
        self.least: dict[int, int] = {}

    def find(self, x: int) -> int:
        root = x
        while (up := self.least.get(root, root)) != root:
            root = up
        while x != root:
            self.least[x], x = root, self.least.get(x, x)
        return root

    def join(self, x: int, y: int) -> None:
        x, y = self.find(x), self.find(y)
        self.least[max(x, y)] = min(x, y)

    def links(self) -> list[tuple[int, int]]:
        """One link for each label that is not the least of its set."""
        return [(self.find(x), x) for x in list(self.least) if self.find(x) != x]


def join_across(one: list[tuple], two: list[tuple], joined: Joined) -> None:
    """Join the labels of similar members (rep, n, fp, shingles, label) of two lists; joined labels are not compared again."""
    if not one or not two:
        return
    members = Members(np.array([m[1] for m in one + two]), [m[2] for m in one + two])
    step = max(1, 400_000 // len(one))
    for at in range(0, len(two), step):
        label = np.array([joined.find(m[4]) for m in one + two])
        right = np.arange(at, min(at + step, len(two))) + len(one)
        left, right = np.repeat(np.arange(len(one)), len(right)), np.tile(right, len(one))
        torn = label[left] != label[right]
        left, right = left[torn], right[torn]
        for k in members.within(left, right).tolist():
            x, y = one[left[k]], two[right[k] - len(one)]
            if joined.find(x[4]) != joined.find(y[4]) and similar(np.frombuffer(x[3], np.uint64), np.frombuffer(y[3], np.uint64)):
                joined.join(x[4], y[4])


def links_of_hot_runs(members: DataFrame, docs: DataFrame) -> DataFrame:
    """(a, b): labels to join, as members of long runs (rep, n, fp, keys, label) are similar.

    Of each run the members outside its largest component come first and are held; the rest streams past them,
    so neither pairs nor the whole run are laid out. A run gives less links than it has labels."""
    keyed = members.select("rep", "label", F.explode("keys").alias("key"))
    count = keyed.groupBy("key", "label").agg(F.count("*").alias("c"))
    torn = count.groupBy("key").agg(F.max_by("label", F.struct("c", "label")).alias("large"), F.count("*").alias("kinds")).where("kinds > 1").select("key", "large")
    met = written(keyed.join(torn, "key").selectExpr("rep", "key", "label", "label = large AS major"), "torn")
    sets = shingle_sets(docs, met.select(F.col("rep").alias("id")).distinct())
    rows = met.join(members.select("rep", "n", "fp").join(sets.withColumnRenamed("id", "rep"), "rep"), "rep")
    rows = rows.repartition(partitions(docs.sparkSession), "key").sortWithinPartitions("key", "major")

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, held, joined = None, [], Joined()

        def links_found() -> pa.RecordBatch:
            x, y = (np.array([pair[i] for pair in joined.links()], np.int64) for i in (0, 1))
            return pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = {c: batch.column(c).to_pylist() for c in ("rep", "n", "fp", "shingles", "label")}
            everyone = list(zip(*columns.values(), strict=True))
            key, major = batch.column("key").to_numpy(), batch.column("major").to_numpy(zero_copy_only=False).astype(bool)
            cut = np.flatnonzero((key[1:] != key[:-1]) | (major[1:] != major[:-1])) + 1
            for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(key)], strict=True):
                if key[a] != current:
                    if current is not None:
                        yield links_found()
                    current, held, joined = key[a], [], Joined()
                part = everyone[a:b]
                join_across(held, part, joined)
                if not major[a]:
                    join_across(part, part, joined)
                    held = held + part
                else:
                    held = [m for m in held if joined.find(m[4]) != joined.find(part[0][4])]
        if current is not None:
            yield links_found()

    out = written(rows.mapInArrow(links, "a long, b long").distinct(), "hot")
    forget(met)
    return out


def candidates(distinct: DataFrame) -> DataFrame:
    """Pairs (a, b, apart) of representatives that :func:`first_pairs` names in runs of equal band keys.

    Keys alone are dealt first; sketches follow only to members of keys that several share."""
    keyed = distinct.select("rep", F.explode("keys").alias("key"))
    shared = keyed.groupBy("key").agg(F.count("*").alias("c")).where("c > 1").select("key")
    met = keyed.join(shared.hint("shuffle_hash"), "key", "left_semi")
    keyed = met.join(distinct.select("rep", "n", "fp"), "rep")
    keyed = keyed.repartition(partitions(distinct.sparkSession), "key").sortWithinPartitions("key")

    def close(ready: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(ready)
        key, rep, n = (table.column(c).to_numpy() for c in ("key", "rep", "n"))
        members = Members(n, table.column("fp").to_pylist())
        for a, b in first_pairs(key, members):
            if len(a):
                turn = rep[a] > rep[b]
                x, y = np.where(turn, rep[b], rep[a]), np.where(turn, rep[a], rep[b])
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y), pa.array(distance(members.bits, a, b).astype(np.int32))], names=["a", "b", "apart"])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column("key").to_numpy()
            cut = int(np.searchsorted(key, key[-1]))  # the last key may go on in the next batch
            if cut or (held and held[-1].column("key")[-1].as_py() != int(key[-1])):
                yield from close([*held, batch.slice(0, cut)])
                held = []
            held.append(batch.slice(cut))
        if held:
            yield from close(held)

    return keyed.mapInArrow(rows, "a long, b long, apart int").distinct()


def nearest(pairs: DataFrame) -> DataFrame:
    """Of each member the pair with the closest other one."""
    both = pairs.select(F.col("a").alias("x"), F.col("b").alias("y"), "apart").unionByName(pairs.select(F.col("b").alias("x"), F.col("a").alias("y"), "apart"))
    best = both.groupBy("x").agg(F.min_by("y", F.struct("apart", "y")).alias("y"))
    return best.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def apart(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """The pairs whose members are not connected yet."""
    one, two = (labels.select(F.col("node").alias(c), F.col("component").alias(f"c_{c}")) for c in ("a", "b"))
    joined = pairs.join(one, "a", "left").join(two, "b", "left")
    return joined.where("coalesce(c_a, a) <> coalesce(c_b, b)").select(*pairs.columns)


def shingle_sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(id, shingles) of the wanted rows (id) of ``docs`` (id, text)."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            packed = [shingle_set((t or "").encode()).tobytes() for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id").cast(pa.int64()), pa.array(packed, pa.binary())], names=["id", "shingles"])

    return docs.join(wanted, "id", "left_semi").mapInArrow(sets, "id long, shingles binary")


def verified(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """The pairs (a, b) whose shingle sets are similar; sets of hot hubs are broadcast. ``docs``: (id, text)."""
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (batch.column(c).to_pylist() for c in ("x", "y"))
            good = [similar(np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)) for p, q in zip(x, y, strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    held = written(shingle_sets(docs, wanted), "shingles")
    # a pair is laid out from its busier member, so that the sets of few hubs go to many pairs
    ends = pairs.select(F.explode(F.array("a", "b")).alias("hub")).groupBy("hub").count()
    busy = ends.where(F.col("count") >= max(2 * BANDS * SHORT, int(pairs.count() * HOT_SHARE)))
    hubs = [r["hub"] for r in busy.collect()]  # at most 2 / HOT_SHARE
    of_hub = F.col("a").isin(hubs)
    usual = pairs.select(F.when(F.col("b").isin(hubs) & ~of_hub, F.col("b")).otherwise(F.col("a")).alias("a"), F.when(F.col("b").isin(hubs) & ~of_hub, F.col("a")).otherwise(F.col("b")).alias("b"))
    right = usual.join(held.select(F.col("id").alias("b"), F.col("shingles").alias("y")), "b")
    left = held.select(F.col("id").alias("a"), F.col("shingles").alias("x"))
    near_hub = right.where(of_hub).join(F.broadcast(left.where(of_hub)), "a")
    others = right.where(~of_hub).join(left, "a")
    columns = ["a", "b", "x", "y"]
    out = written(near_hub.select(columns).unionByName(others.select(columns)).mapInArrow(rows, "a long, b long"), "similar")
    forget(held)
    return out


def dedup(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` (all columns) that stay: the smallest id of each group of near copies.

    Groups are the connected components of all candidates whose sets of five-word shingles have a Jaccard
    similarity of 0.8 or more, computed from the texts; equal sets count once. Pairs are verified nearest
    first: a pair whose members are connected already adds nothing and is left out. In long runs of one key
    (a hot group of near copies) most members are connected by few pairs, then the pairs of what is still
    apart are all verified."""
    return rows_without(docs, "doc_id", "text", near_copies)


def near_copies(docs: DataFrame) -> DataFrame:
    """dropped_id of the rows (id, text; ids identify) that go."""
    table = written(sketches(docs), "sketches")
    distinct = written(table.groupBy("name").agg(F.min("id").alias("rep"), *(F.first(c).alias(c) for c in ("n", "fp", "keys"))).where("rep is not null"), "distinct")
    pairs = written(candidates(distinct), "pairs")
    real = pairs.where("a <> b")
    good = verified(written(nearest(real), "nearest"), docs)
    labels = components(good)
    rest = written(apart(real, labels), "rest")
    if rest.limit(1).count():
        labels = extended(labels, verified(rest, docs))
    long = distinct.join(pairs.where("a = b").select(F.col("a").alias("rep")), "rep", "left_semi")
    lone = long.join(labels, long["rep"] == labels["node"], "left").withColumn("label", F.coalesce("component", "rep"))
    more = links_of_hot_runs(lone.select("rep", "n", "fp", "keys", "label"), docs)
    if more.limit(1).count():
        labels = extended(labels, more)
    equal = table.select(F.col("id").alias("dropped_id")).join(distinct.select(F.col("rep").alias("dropped_id")), "dropped_id", "left_anti")
    dropped = written(equal.unionByName(labels.where("component <> node").select(F.col("node").alias("dropped_id"))).distinct(), "dropped")
    forget(table, distinct, pairs, more, rest)
    return dropped
