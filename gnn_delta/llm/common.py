"""Shared plumbing of the text operators: storage for intermediate tables, row numbers, safe columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import forget, settled, shared_dir  # noqa: F401


written = settled
#: a list of rows is broadcast up to this size, beyond it is joined by shuffle
BROADCAST_BYTES = 32 << 20
DIGEST_ROW_BYTES = 96


def lower_ascii(text: Column) -> Column:
    """A-Z lower-cased, every other character unchanged."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def fold(doc_id: Column, k: int) -> Column:
    """crc32 of the id as text, modulo k (a null id counts as the empty text)."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % k


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ids_identify(docs: DataFrame, id_col: str) -> bool:
    """Whether no id is null or repeated (only ids are shuffled)."""
    return not docs.groupBy(F.col(id_col).alias("i")).count().where("i is null or count > 1").limit(1).count()


def numbered(docs: DataFrame, id_col: str, text_col: str, nulls: str) -> tuple[DataFrame, str]:
    """All columns and a row number that rises with (id, text); null ids ``first`` or ``last``."""
    name = "row"
    while name in docs.columns:
        name += "_"
    first = F.col(id_col).asc_nulls_first() if nulls == "first" else F.col(id_col).asc_nulls_last()
    order = docs.repartitionByRange(partitions(docs.sparkSession), first, F.col(text_col)).sortWithinPartitions(first, F.col(text_col))
    return written(order.withColumn(name, F.monotonically_increasing_id()), "numbered"), name


def without(docs: DataFrame, dropped: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Rows whose id is not listed; the list (column dropped_id) is broadcast only below a checked size."""
    small = dropped.count() * DIGEST_ROW_BYTES <= BROADCAST_BYTES
    return docs.join(F.broadcast(dropped) if small else dropped, docs[id_col] == dropped["dropped_id"], "left_anti")


def rows_without(docs: DataFrame, id_col: str, text_col: str, find: Callable[[DataFrame], DataFrame], nulls: str = "last") -> DataFrame:
    """``docs`` without the rows that ``find`` names (rows (id, text) in, dropped_id out), row by row.

    Where ids are null or repeat, ``find`` sees row numbers that rise with (id, text) instead of ids, so a row
    never takes others of its id with it."""
    if ids_identify(docs, id_col):
        return without(docs, find(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))), id_col)
    table, row = numbered(docs, id_col, text_col, nulls)
    dropped = find(table.select(F.col(row).alias("id"), F.col(text_col).alias("text")))
    return without(table, dropped, row).drop(row)
