"""Labelled rows for the classifiers: a bounded sample, and the split into learning and held-out rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows that a classifier learns from, at most; they are those of lowest hash.
MAX_LABELLED = 20_000
FOLDS = 5


def held_out(doc_id: Column) -> Column:
    """Whether crc32 of the id as text leaves no remainder by five; null ids are held out."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(FOLDS)) == 0, F.lit(True))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, max_rows: int = MAX_LABELLED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(text, label)`` of at most ``max_rows`` labelled rows that are not held out, chosen by hash of the id.

    Several labels of a document count as their largest, null labels as none; of several texts of one id the first in order is taken. Only the chosen ids are broadcast.
    """
    ids = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    ids = ids.groupBy(F.col("doc_id").alias("lid")).agg(F.max(label).cast("int").alias("label"))
    ids = ids.orderBy(F.xxhash64("lid"), "lid").limit(max_rows)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return rows.join(F.broadcast(ids), F.col("doc_id") == F.col("lid")).groupBy("doc_id").agg(F.min("text").alias("text"), F.max("label").alias("label"))
