"""Factorisation machine over hashed terms and structure statistics of whole texts.

Terms get parameters on marginal evidence (the label rate among rows with the term) or on evidence of a
pair (the label rate among rows with both terms lies outside the rates of either term alone), so terms that
matter only together are kept. Repeated rows, empty and very long texts need no special case: a text is a
set of terms and some shares.

score(x) = sigmoid(b + sum w_i x_i + 1/2 sum_f ((sum v_if x_i)^2 - sum v_if^2 x_i^2)), x binary: the
pairwise part costs one pass over the active features. Features are computed by executors in Arrow
batches; a bounded sample of labelled rows (``max_rows``) reaches the driver as hashed term numbers,
where the small model is fitted; the fitted arrays, a few hundred KB whatever the input, go to all
tasks for scoring.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vec

BINS = 8
#: byte classes of the structure statistics
CLASSES = np.zeros(256, dtype=np.int64)
CLASSES[97:123] = 1
CLASSES[65:91] = 2
CLASSES[48:58] = 3
CLASSES[[32, 9, 11, 12, 13]] = 4
CLASSES[10] = 5
CLASSES[ord("|")] = 6
CLASSES[ord("!")] = 7
CLASSES[[ord(c) for c in ".,;:?"]] = 8
CLASSES[[ord(c) for c in "#$%&*@~^+=<>{}[]\\_/"]] = 9
CLASSES[128:] = 10
N_CLASSES = 11
N_STATS = N_CLASSES + 6


@dataclass(frozen=True)
class FMConfig:
    """``max_rows`` and ``max_bytes`` (their texts) bound the labelled rows used for fitting; ``n_terms`` the terms
    that get parameters: those in ``min_df`` rows or more with evidence of ``min_z`` alone, or, among the ``pair_terms`` most frequent, ``pair_z`` in a pair (``pair_rows`` rows)."""

    n_hash: int = 1 << 18
    n_terms: int = 2048
    min_df: int = 8
    min_z: float = 4.0
    pair_z: float = 7.0
    pair_terms: int = 4096
    pair_rows: int = 3000
    max_bytes: int = 256 << 20
    factors: int = 8
    epochs: int = 12
    rate: float = 0.05
    start: float = 0.05
    l2: float = 1e-4
    max_rows: int = 12_000
    structure: bool = True
    seed: int = 7


@dataclass
class FMModel:
    slot: np.ndarray  # hashed term -> feature, -1 for none
    edges: np.ndarray  # per statistic the bin edges
    bias: float
    w: np.ndarray
    v: np.ndarray
    config: FMConfig

    def features(self, doc: np.ndarray, term: np.ndarray, stats: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        slot = self.slot[term]
        keep = slot >= 0
        rows, cols = doc[keep], slot[keep].astype(np.int64)
        if self.config.structure:
            n = len(stats)
            base = len(self.w) - N_STATS * BINS
            bins = np.stack([np.searchsorted(self.edges[s], stats[:, s], "right") for s in range(N_STATS)], axis=1)
            rows = np.concatenate([rows, np.repeat(np.arange(n), N_STATS)])
            cols = np.concatenate([cols, (base + np.arange(N_STATS) * BINS + bins).ravel()])
        return rows, cols

    def raw(self, rows: np.ndarray, cols: np.ndarray, n: int) -> np.ndarray:
        total = self.bias + np.bincount(rows, self.w[cols], n)
        for f in range(self.v.shape[1]):
            active = self.v[cols, f]
            total += 0.5 * (np.bincount(rows, active, n) ** 2 - np.bincount(rows, active * active, n))
        return total

    def score(self, doc: np.ndarray, term: np.ndarray, stats: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.raw(*self.features(doc, term, stats), len(stats)), -30, 30)))


def analyse(texts: pa.Array, n_hash: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, hashed term) pairs without repeats, and the statistics matrix, of whole texts."""
    data, offsets = vec.buffers(texts)
    n = len(offsets) - 1
    sums = vec.prefix(vec.LOWER[data])
    starts, ends, first = vec.tokens(data, offsets, vec.NOT_LETTER)
    owner = vec.owners(first)
    term = (vec.ranges(sums, starts, ends) & np.uint64(n_hash - 1)).astype(np.int64)
    pairs = np.unique(owner * n_hash + term)
    doc, term = pairs // n_hash, pairs % n_hash

    size = np.diff(offsets)
    full = np.maximum(size, 1)
    counts = np.bincount(np.repeat(np.arange(n), size) * N_CLASSES + CLASSES[data], minlength=n * N_CLASSES).reshape(n, N_CLASSES)
    line = np.zeros(256, dtype=bool)
    line[10] = True
    l_start, l_end, l_first = vec.tokens(data, offsets, line)
    l_owner = vec.owners(l_first)
    l_pairs = np.unique(np.stack([l_owner.astype(np.uint64), vec.ranges(sums, l_start, l_end)], axis=1), axis=0) if len(l_start) else np.zeros((0, 2), np.uint64)
    n_lines, n_words = np.diff(l_first), np.diff(first)
    stats = np.concatenate(
        [
            counts / full[:, None],
            np.log1p(size)[:, None],
            (n_words / full)[:, None],
            (np.bincount(doc, minlength=n) / np.maximum(n_words, 1))[:, None],
            (np.bincount(l_pairs[:, 0].astype(np.int64), minlength=n) / np.maximum(n_lines, 1))[:, None],
            (n_lines / full)[:, None],
            np.log1p(n_words)[:, None],
        ],
        axis=1,
    )
    return doc, term, stats


def fit(labelled: DataFrame, config: FMConfig = FMConfig(), text: str = "text", label: str = "label") -> FMModel:
    """Fit on at most ``config.max_rows`` rows that the caller has already selected."""
    n_hash = config.n_hash

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            doc, term, stats = analyse(batch.column("text"), n_hash)
            cut = np.searchsorted(doc, np.arange(batch.num_rows + 1))
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("label").cast(pa.int32()),
                    pa.array([term[a:b].astype("<u4").tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)], pa.binary()),
                    pa.array([s.astype("<f8").tobytes() for s in stats], pa.binary()),
                ],
                names=["label", "terms", "stats"],
            )

    got = labelled.select(F.col(text).alias("text"), F.col(label).cast("int").alias("label")).where("label in (0, 1)")
    got = got.mapInArrow(rows, "label int, terms binary, stats binary").toPandas()
    return train(got, config)


def informative(doc: np.ndarray, term: np.ndarray, y: np.ndarray, config: FMConfig) -> np.ndarray:
    """The terms with most evidence on the label, alone or in a pair, in rising order."""
    n = len(y)
    share = y.mean() if n else 0.5
    spread = max(share * (1 - share), 1e-9)
    df = np.bincount(term, minlength=config.n_hash)
    common = np.flatnonzero(df >= config.min_df)
    dense = np.full(config.n_hash, -1, dtype=np.int64)
    dense[common] = np.arange(len(common))
    keep = dense[term] >= 0
    rows, cols = doc[keep], dense[term[keep]]
    held = df[common].astype(float)
    positive = np.bincount(cols, y[rows], len(common))
    evidence = np.abs(positive - held * share) / np.sqrt(np.maximum(held * spread, 1e-9))
    evidence[evidence < config.min_z] = 0
    # pairs: the most frequent terms, by products of 0/1 matrices over a part of the rows
    often = np.sort(np.argsort(-held, kind="stable")[: config.pair_terms])
    place = np.full(len(common), -1, dtype=np.int64)
    place[often] = np.arange(len(often))
    some = np.random.default_rng(config.seed).permutation(n)[: config.pair_rows]
    row_at = np.full(n, -1, dtype=np.int64)
    row_at[some] = np.arange(len(some))
    use = (row_at[rows] >= 0) & (place[cols] >= 0)
    x = np.zeros((len(some), len(often)), dtype=np.float32)
    x[row_at[rows[use]], place[cols[use]]] = 1
    labelled = x[y[some] > 0]
    own = labelled.sum(axis=0) / np.maximum(x.sum(axis=0), 1)
    for a in range(0, len(often), 256):
        b = min(a + 256, len(often))
        both, found = x[:, a:b].T @ x, labelled[:, a:b].T @ labelled
        one, other = own[a:b, None], own[None, :]
        usual = np.clip(found / np.maximum(both, 1), np.minimum(one, other), np.maximum(one, other))
        z = np.abs(found - both * usual) / np.sqrt(np.maximum(both * np.maximum(usual * (1 - usual), spread), 1e-9))
        z[(both < config.min_df) | (z < config.pair_z)] = 0
        z[np.arange(b - a), np.arange(a, b)] = 0
        evidence[often[a:b]] = np.maximum(evidence[often[a:b]], z.max(axis=1, initial=0))
    best = np.argsort(-evidence, kind="stable")[: config.n_terms]
    return np.sort(common[best[evidence[best] > 0]])


def train(got, config: FMConfig) -> FMModel:
    """Fit from hashed rows (label, terms, stats) by AdaGrad on the logistic loss."""
    n = len(got)
    got = got.sort_values(["terms", "stats", "label"], kind="stable")  # the same fit for any order of rows
    y = got["label"].to_numpy(dtype=np.float64)
    terms = [np.frombuffer(x, "<u4").astype(np.int64) for x in got["terms"]]
    stats = np.stack([np.frombuffer(x, "<f8") for x in got["stats"]]) if n else np.zeros((0, N_STATS))
    doc = np.repeat(np.arange(n), [len(t) for t in terms]) if n else np.zeros(0, np.int64)
    term = np.concatenate(terms) if n else np.zeros(0, np.int64)
    chosen = informative(doc, term, y, config)
    slot = np.full(config.n_hash, -1, dtype=np.int32)
    slot[chosen] = np.arange(len(chosen))
    edges = np.quantile(stats, np.arange(1, BINS) / BINS, axis=0).T if n else np.zeros((N_STATS, BINS - 1))
    width = len(chosen) + N_STATS * BINS
    rng = np.random.default_rng(config.seed)
    odds = float(np.log((y.sum() + 1) / (n - y.sum() + 1))) if n else 0.0
    model = FMModel(slot, edges, odds, np.zeros(width), rng.normal(0, config.start if n else 0.0, (width, config.factors)), config)
    rows, cols = model.features(doc, term, stats)
    order = np.argsort(rows, kind="stable")
    rows, cols = rows[order], cols[order]
    start = np.searchsorted(rows, np.arange(n + 1))
    g_w, g_v, g_b = np.full(width, 1e-6), np.full(model.v.shape, 1e-6), 1e-6
    for _ in range(config.epochs):
        shuffled = rng.permutation(n)
        for at in range(0, n, 128):
            pick = shuffled[at : at + 128]
            take = np.concatenate([np.arange(start[i], start[i + 1]) for i in pick])
            r, c = np.repeat(np.arange(len(pick)), start[pick + 1] - start[pick]), cols[take]
            vc = model.v[c]
            summed = np.stack([np.bincount(r, vc[:, f], len(pick)) for f in range(config.factors)], axis=1)
            p = 1 / (1 + np.exp(-np.clip(model.raw(r, c, len(pick)), -30, 30)))
            err = (p - y[pick]) / len(pick)
            used, inverse = np.unique(c, return_inverse=True)
            d_w = np.bincount(inverse, err[r], len(used)) + config.l2 * model.w[used]
            push = err[r][:, None] * (summed[r] - vc)
            d_v = np.stack([np.bincount(inverse, push[:, f], len(used)) for f in range(config.factors)], axis=1)
            d_v += config.l2 * model.v[used]
            g_w[used] += d_w**2
            g_v[used] += d_v**2
            g_b += err.sum() ** 2
            model.w[used] -= config.rate * d_w / np.sqrt(g_w[used])
            model.v[used] -= config.rate * d_v / np.sqrt(g_v[used])
            model.bias -= config.rate * err.sum() / np.sqrt(g_b)
    return model


def score(docs: DataFrame, model: FMModel, keys: list[str], text: str = "text") -> DataFrame:
    """``keys`` of every row and its ``score`` (0 to 1; null and empty texts too)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = [f"k{i}" for i in range(len(keys))]
    source = docs.select(*[F.col(k).alias(a) for k, a in zip(keys, names, strict=True)], F.col(text).alias("text"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fitted = shared.value
        for batch in vec.slices(batches, "text"):
            out = fitted.score(*analyse(batch.column("text"), fitted.config.n_hash))
            yield pa.RecordBatch.from_arrays([*(batch.column(a) for a in names), pa.array(out, pa.float64())], names=[*names, "score"])

    schema = ", ".join([*(f"{a} {source.schema[a].dataType.simpleString()}" for a in names), "score double"])
    scored = source.mapInArrow(rows, schema)
    return scored.select(*[F.col(a).alias(k) for a, k in zip(names, keys, strict=True)], "score")


def rows_within(docs: DataFrame, ids: DataFrame, config: FMConfig) -> int:
    """How many of the sampled rows fit ``max_bytes`` of text at their mean size."""
    size = docs.select("doc_id", F.octet_length("text").alias("b")).join(F.broadcast(ids), "doc_id").agg(F.sum("b").alias("b"), F.count("*").alias("n")).first()
    total, n = size["b"] or 0, size["n"]
    return n if total <= config.max_bytes else max(1, int(n * config.max_bytes / total))


def sample_labels(labels: DataFrame, column: str, allowed, max_rows: int) -> DataFrame:
    """At most ``max_rows`` labelled ids (doc_id, label), by hash order; ``allowed`` tests an id column."""
    picked = labels.where(F.col(column).isin(0, 1) & F.col("doc_id").isNotNull() & allowed(F.col("doc_id")))
    picked = picked.groupBy("doc_id").agg(F.max(column).cast("int").alias("label"))
    return picked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
