"""Language identification by bit-sliced Bloom filters of character n-grams.

All languages share one table: slot i holds as many words as its languages need; bit l of them says that
language l's Bloom filter has bit i set, so the AND of the slots of an n-gram is the set of all languages that (may) contain it.
Per document the popcount of each language is corrected for that filter's false-positive rate.

Defined cases: null text or a text without letters gives ``und`` and score 0; with no labelled row every
text is ``und``; ties go to the first language in name order, and so does a text of which no n-gram is known
(score 0); texts of any length are read whole; repeated rows give repeated results; an empty table gives none;
extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vec
from .common import fold, forget, written

LETTER = regex.compile(r"\p{L}")


@dataclass(frozen=True)
class LangConfig:
    """``rows_per_lang``: expected bound of the rows each language is learnt from (hash sample);
    ``grams``: at most so many of the most frequent n-grams per language (those above the count at which more
    would be in); ``slots``: table size; ``probes``: hashes."""

    n: int = 4
    rows_per_lang: int = 2500
    grams: int = 6000
    slots: int = 1 << 17
    probes: int = 2


@dataclass
class LangModel:
    langs: list[str]
    table: np.ndarray
    false_rate: np.ndarray
    config: LangConfig

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        data, offsets = vec.buffers(texts)
        n_docs = len(offsets) - 1
        if not self.langs:
            return ["und"] * n_docs, np.zeros(n_docs)
        mask = np.zeros((len(data) + 1, self.table.shape[1]), dtype=self.table.dtype)
        keys, at = grams(data, offsets, self.config.n)
        mask[at] = np.bitwise_and(self.table[_slot(keys, 0, self.config.slots)], self.table[_slot(keys, 1, self.config.slots)])
        for probe in range(2, self.config.probes):
            mask[at] &= self.table[_slot(keys, probe, self.config.slots)]
        total = np.diff(np.searchsorted(at, offsets))
        hits = np.zeros((n_docs, len(self.langs)))
        for lang in range(len(self.langs)):
            word, bit = divmod(lang, 8 * self.table.itemsize)
            running = np.concatenate([[0], np.cumsum((mask[:, word] >> self.table.dtype.type(bit)) & self.table.dtype.type(1), dtype=np.int64)])
            hits[:, lang] = running[offsets[1:]] - running[offsets[:-1]]
        share = np.clip((hits / np.maximum(total, 1)[:, None] - self.false_rate) / (1 - self.false_rate), 0, 1)
        best = share.argmax(axis=1)
        top = share[np.arange(n_docs), best]
        score = np.where(top > 0, top / np.maximum(share.sum(axis=1), 1e-12), 0.0)
        lettered = np.diff(np.concatenate([[0], np.cumsum(~vec.NOT_LETTER[data])])[offsets]) > 0
        names = []
        for i, has in enumerate(lettered):
            if has and not LETTER.search(texts[i].as_py() or ""):
                has = False
            names.append(self.langs[best[i]] if has else "und")
            if not has:
                score[i] = 0.0
        return names, score


def grams(data: np.ndarray, offsets: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all n-byte grams (n up to 8) of lower-cased letters and word gaps, and where they start.

    Every byte that is no letter counts as one gap sign; grams of gaps alone are left out."""
    if len(data) < n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    low = np.where(vec.NOT_LETTER[data], np.uint8(32), vec.LOWER[data])
    keys = np.zeros(len(data) - n + 1, dtype=np.uint64)
    for j in range(n):
        keys = (keys << np.uint64(8)) | low[j : len(data) - n + 1 + j]
    good = np.ones(len(keys), dtype=bool)
    for end in offsets[1:]:
        good[max(0, int(end) - n + 1) : int(end)] = False
    good &= ~((low[: len(keys)] == 32) & (low[1 : len(keys) + 1] == 32))
    at = np.flatnonzero(good)
    return keys[at], at


def _slot(keys: np.ndarray, probe: int, slots: int) -> np.ndarray:
    return ((keys + np.uint64(1)) * np.uint64((0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)[probe % 4] + 2 * (probe // 4)) >> np.uint64(64 - int(slots).bit_length() + 1)).astype(np.int64)


def fit(labelled: DataFrame, config: LangConfig = LangConfig()) -> LangModel:
    """Learn from rows (text, lang) by n-gram counts; what reaches the driver is bounded by ``grams`` per language."""
    known = labelled.where("lang is not null and text is not null")
    sizes = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return LangModel([], np.zeros((config.slots, 1), np.uint64), np.zeros(0), config)
    langs = sorted(sizes)
    rate = F.create_map(*[F.lit(x) for lang in langs for x in (lang, min(1.0, config.rows_per_lang / sizes[lang]))])
    unit = F.abs(F.xxhash64("text") % 1_000_003) / F.lit(1_000_003.0)
    picked = known.where(unit < rate[F.col("lang")]).select("lang", "text")
    n = config.n

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            names = batch.column("lang").to_pylist()
            data, offsets = vec.buffers(batch.column("text"))
            keys, at = grams(data, offsets, n)
            codes = np.array([langs.index(x) for x in names])
            lang = codes[np.searchsorted(offsets, at, "right") - 1]
            for code in np.unique(lang):
                gram, count = np.unique(keys[lang == code], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(gram), code, np.int32)), pa.array(gram.view(np.int64)), pa.array(count)], names=["lang", "gram", "n"])

    from pyspark.sql import Window

    counts = written(picked.mapInArrow(counted, "lang int, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).where("n >= 2"), "grams")
    # per language the least count above which at most ``grams`` lie: one row for each count, not for each n-gram
    above = F.sum("c").over(Window.partitionBy("lang").orderBy(F.desc("n")))
    cut = counts.groupBy("lang", "n").agg(F.count("*").alias("c")).withColumn("above", above).where(F.col("above") <= config.grams)
    cut = cut.groupBy("lang").agg(F.min("n").alias("least"))
    top = counts.join(F.broadcast(cut), "lang").where("n >= least").select("lang", "gram").toPandas()
    forget(counts)
    kind = np.uint8 if len(langs) <= 8 else np.uint64
    width = 8 * np.dtype(kind).itemsize
    table = np.zeros((config.slots, -(-len(langs) // width)), dtype=kind)
    for lang, gram in top.groupby("lang")["gram"]:
        word, bit = divmod(int(lang), width)
        keys = gram.to_numpy(dtype=np.int64).view(np.uint64)
        for probe in range(config.probes):
            table[_slot(keys, probe, config.slots), word] |= kind(1 << bit)
    fill = np.array([((table[:, i // width] >> kind(i % width)) & kind(1)).mean() for i in range(len(langs))])
    return LangModel(langs, table, fill**config.probes, config)


def identify(docs: DataFrame, model: LangModel) -> DataFrame:
    """doc_id, lang_pred, score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in vec.slices(batches, "text"):
            names, score = shared.value.predict(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(names, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(rows, f"doc_id {kind}, lang_pred string, score double")


def language(docs: DataFrame, config: LangConfig = LangConfig()) -> DataFrame:
    """Learn from documents outside the held-out fold, predict all."""
    held = fold(F.col("doc_id"), 4) == 2
    model = fit(docs.where(~held).select("text", "lang"), config)
    return identify(docs, model).select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")
