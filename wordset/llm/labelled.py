"""The labelled rows that models are fitted on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(doc_id: Column) -> Column:
    """Whether crc32 of the doc_id as text leaves 1 when divided by 3; false without a doc_id."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """``text, y`` of at most ``bound`` labelled rows, the first in the order of a hash of their doc_id.

    Held-out rows and null labels are left out. The chosen ids are a bounded table and broadcast; equal texts count once."""
    y = F.max(F.when(F.col(label) == 1, 1).otherwise(0))
    ids = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").cast("long").alias("_id")).agg(y.alias("y"))
    ids = ids.orderBy(F.xxhash64("_id"), "_id").limit(bound)
    rows = docs.select(F.col("doc_id").cast("long").alias("_doc"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    return rows.join(F.broadcast(ids), F.col("_doc") == F.col("_id")).groupBy(F.xxhash64("text").alias("_h")).agg(F.first("text").alias("text"), F.max("y").alias("y")).select("text", "y")
