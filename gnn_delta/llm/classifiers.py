"""Quality and toxicity scores by factorisation machine.

Defined cases: a null or empty text is scored by its structure statistics alone; labels other than 0
and 1, null ids and repeated label rows are ignored or merged (the larger label counts); without any
usable label the score is 0.5; extra columns are not read; repeated document rows give repeated rows; a
text of any length is scored whole; a score equal to the threshold counts as reaching it; empty tables give
empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import fm
from .common import fold

QUALITY = fm.FMConfig()
TOXICITY = fm.FMConfig(n_terms=1024, min_z=4.5, epochs=15, max_rows=16_000)
FOLDS = 5


def trainable(doc_id: Column) -> Column:
    return fold(doc_id, FOLDS) != 0


def fit_on(docs: DataFrame, labels: DataFrame, column: str, config: fm.FMConfig, allowed=trainable) -> fm.FMModel:
    """Model for ``labels.column``; the label sample is bounded (config.max_rows), so it is broadcast."""
    ids = fm.sample_labels(labels, column, allowed, config.max_rows)
    docs = docs.select("doc_id", "text")
    fitting = fm.rows_within(docs, ids, config)
    if fitting < config.max_rows:
        ids = fm.sample_labels(labels, column, allowed, fitting)
    return fm.fit(docs.join(F.broadcast(ids), "doc_id"), config)


def judge(docs: DataFrame, labels: DataFrame, column: str, threshold: float, config: fm.FMConfig) -> DataFrame:
    """doc_id, held_out, score, predicted for every document row."""
    model = fit_on(docs, labels, column, config)
    return fm.score(docs, model, ["doc_id"]).select(
        "doc_id",
        (fold(F.col("doc_id"), FOLDS) == 0).alias("held_out"),
        "score",
        F.when(F.col("score") >= threshold, 1).otherwise(0).alias("predicted"),
    )


def quality(docs: DataFrame, labels: DataFrame, config: fm.FMConfig = QUALITY) -> DataFrame:
    """Words, structure statistics and length metadata; a document is kept from a score of 0.3."""
    return judge(docs, labels, "quality", 0.3, config)


def toxicity(docs: DataFrame, labels: DataFrame, config: fm.FMConfig = TOXICITY) -> DataFrame:
    """Hashed terms and their pairwise interactions; toxic from a score of 0.5."""
    return judge(docs, labels, "toxic", 0.5, config)


def keep_quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, config: fm.FMConfig = QUALITY) -> DataFrame:
    """The rows of ``docs`` (all columns) that the quality classifier does not reject, in one scan."""
    model = fit_on(docs, labels, "quality", config)
    return filter_rows(docs, model, threshold)


def filter_rows(docs: DataFrame, model: fm.FMModel, threshold: float) -> DataFrame:
    import numpy as np
    import pyarrow as pa

    from . import vec

    shared = docs.sparkSession.sparkContext.broadcast(model)

    def rows(batches):
        fitted = shared.value
        for batch in vec.slices(batches, "text"):
            score = fitted.score(*fm.analyse(batch.column("text"), fitted.config.n_hash))
            yield batch.filter(pa.array(np.asarray(score >= threshold)))

    return docs.mapInArrow(rows, docs.schema)
