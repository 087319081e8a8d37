"""Sharding by proportional stratified interleaving.

Rows are shuffled by a seeded hash of their content within their source and ranked; a source of m rows puts its rows at
the fractions (r - u)/m, with a seeded offset u of its own between 0 and 1, so that small sources, of one row even, are spread like large ones. Sorted
by fraction, every stretch of the order holds the sources in proportion, so
cutting it into runs of equal count gives shards that all match the mixture (law ``rows``: counts differ by
one at most). The layout of the input files plays no part.

No rank is taken over a whole source or the whole table by one task. The hash is uniform, so its leading
bits cut any source, however large, into even cells; cells are counted, and a row's rank is its rank within
the cell plus the rows of the cells before it. The fractions are uniform as well and are ranked the same way.

Edge cases: a null source is a source of its own; a null text has size 1; repeated doc_ids and equal rows each
get a slot of their own, equal ones next to each other in the order of their source; very long texts are read once and not moved; with fewer rows than shards some shards stay empty; an empty table gives no rows;
input columns that bear an output name are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordset.functions.store import written

SHARDS = 8
SEED = 20
#: Cells of a source and bins of the fractions, as a power of two.
CELL_BITS = 12


def placed(docs: DataFrame, n_shards: int = SHARDS, seed: int = SEED, stratum: str = "source") -> DataFrame:
    """``doc_id, source, size, text_crc32, position`` and the shard and slot of every row."""
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(
        "doc_id",
        F.col(stratum).alias("stratum"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.xxhash64(F.lit(seed), "doc_id", text).alias("h"),
    )
    rows = written(rows.withColumn("cell", F.shiftrightunsigned("h", 64 - CELL_BITS).cast("int")), "shuffled")

    before = Window.partitionBy("stratum").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = (
        rows.groupBy("stratum", "cell")
        .agg(F.count(F.lit(1)).alias("n"))
        .select(F.col("stratum").alias("c_stratum"), F.col("cell").alias("c_cell"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("skip"), F.sum("n").over(Window.partitionBy("stratum")).alias("m"))
    )
    in_cell = Window.partitionBy("stratum", "cell").orderBy("h", "doc_id", "size", "text_crc32")
    ranked = rows.withColumn("r", F.row_number().over(in_cell)).join(cells, F.col("stratum").eqNullSafe(F.col("c_stratum")) & (F.col("cell") == F.col("c_cell")))
    offset = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit("offset"), "stratum"), 12) + 0.5) / float(1 << 52)
    at = (F.col("r") + F.col("skip") - offset) / F.col("m").cast("double")
    ranked = ranked.select("doc_id", "stratum", "size", "text_crc32", at.alias("at"), "h").withColumn("bin", F.greatest(F.lit(0), F.least(F.floor(F.col("at") * (1 << CELL_BITS)), F.lit((1 << CELL_BITS) - 1))).cast("int"))
    ranked = written(ranked, "ranked")

    # 2^CELL_BITS rows at most, whatever the input
    bins = ranked.groupBy("bin").agg(F.count(F.lit(1)).alias("n"))
    bins = bins.select(F.col("bin").alias("b_bin"), F.coalesce(F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("b_skip"), F.sum("n").over(Window.partitionBy()).alias("total"))
    in_bin = Window.partitionBy("bin").orderBy("at", "stratum", "h", "doc_id")
    out = ranked.withColumn("position", F.row_number().over(in_bin).cast("long")).join(F.broadcast(bins), F.col("bin") == F.col("b_bin"))
    out = out.withColumn("position", F.col("position") + F.col("b_skip") - 1)
    # the first (total mod n) shards are one row longer
    q, extra = F.expr(f"total div {n_shards}"), F.expr(f"total % {n_shards}")
    long = extra * (q + 1)
    shard = F.when(F.col("position") < long, F.expr(f"position div (total div {n_shards} + 1)")).otherwise(extra + F.floor((F.col("position") - long) / F.greatest(q, F.lit(1))))
    out = out.withColumn("shard", shard.cast("int"))
    slot = F.col("position") - F.col("shard") * q - F.least(F.col("shard"), extra)
    return out.select("doc_id", F.col("stratum").alias("source"), "size", "text_crc32", "shard", slot.cast("long").alias("slot"), "position")


def write_shards(docs: DataFrame, path: str, n_shards: int = SHARDS, seed: int = SEED) -> None:
    """Writes the whole rows of ``docs`` as ``shard=k`` folders, each in slot order; doc_id must be unique."""
    where = placed(docs, n_shards, seed).select(F.col("doc_id").alias("_doc"), "shard", "slot")
    rows = docs.drop("shard", "slot").join(where, F.col("doc_id").eqNullSafe(F.col("_doc"))).drop("_doc")
    rows.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
