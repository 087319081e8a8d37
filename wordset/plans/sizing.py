"""Broadcast behind a check of size, and small frames of literals."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a narrow side is broadcast.
BROADCAST_ROWS = 200_000


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` marked for broadcast if it has no more than ``rows`` rows, else as it is: it will be shuffled.

    The count stops at the bound, whatever the size of the frame."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def literal_frame(spark: SparkSession, rows: list[tuple], schema: pa.Schema) -> DataFrame:
    """A handful of rows as literals of the plan: no job reads them, and the optimizer knows their size."""
    columns = list(zip(*rows, strict=True)) or [[] for _ in schema]
    return spark.createDataFrame(pa.table([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema))
