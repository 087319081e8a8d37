"""Exact deduplication by a heavy-hitter split, in DataFrame operations only.

Frequent digests are found by Spark's one-pass Misra-Gries counter (``freqItems``), whose candidates hold
every digest above the support. A second pass counts the candidates exactly and picks their winners. Those
verified rows number at most 1/support, so they are broadcast, and copies of frequent texts are settled
where they are read. What remains has no group above the support; its winners are found by an ordinary aggregation over digests.

Edge cases: a null text counts as empty; a null doc_id sorts last; rows that agree in everything are still
one group of which exactly one row stays; an empty table gives an empty result; ``decide`` has its own columns only, and
``deduplicated`` the input's, whatever their names; very long texts are hashed whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wordset.functions.store import written
from wordset.plans.sizing import small_side

#: Share of all rows from which a group counts as frequent; at most 1/SUPPORT digests are broadcast.
SUPPORT = 0.001
BLANKS = r"[\x20\x09-\x0D]+"


def digest(text: Column) -> Column:
    """SHA-256 (32 bytes) of the text without its white space."""
    return F.unhex(F.sha2(F.regexp_replace(F.coalesce(text, F.lit("")), BLANKS, "").cast("binary"), 256))


def _n_points(text: Column) -> Column:
    return F.char_length(F.coalesce(text, F.lit(""))).cast("long")


def heavy_winners(rows: DataFrame, support: float = SUPPORT) -> DataFrame:
    """Frequent digests of ``rows (doc_id, n, digest, rid)`` with their verified size and winner."""
    n_rows = rows.agg(F.count(F.lit(1)).alias("_all"))
    # as text: the counter compares its items by equals(), which byte arrays don't have
    candidates = rows.select(F.hex("digest").alias("d")).stat.freqItems(["d"], support).select(F.explode("d_freqItems").alias("d")).select(F.unhex("d").alias("digest"))
    best = F.min(F.struct((-F.col("n")).alias("n"), F.col("doc_id").isNull().alias("u"), "doc_id", "rid")).alias("best")
    found = rows.join(F.broadcast(candidates), "digest").groupBy("digest").agg(F.count(F.lit(1)).alias("size"), best)
    return (
        found.crossJoin(F.broadcast(n_rows))  # one row
        .filter(F.col("size") > support * F.col("_all"))
        .select("digest", F.col("size").alias("h_size"), (-F.col("best.n")).alias("h_n"), F.col("best.doc_id").alias("h_doc"), F.col("best.rid").alias("h_rid"))
    )


def _narrow(docs: DataFrame) -> DataFrame:
    return written(docs.select("doc_id", _n_points(F.col("text")).alias("n"), digest(F.col("text")).alias("digest"), F.monotonically_increasing_id().alias("rid")), "digests")


def _repeated(rest: DataFrame) -> DataFrame:
    """Digests of two rows or more with their size and winner, by aggregates that are combined before the shuffle."""
    best = F.min(F.struct((-F.col("n")).alias("n"), F.col("doc_id").isNull().alias("u"), "doc_id", "rid")).alias("best")
    found = rest.groupBy("digest").agg(F.count(F.lit(1)).alias("size"), best).filter("size > 1")
    return found.select(F.col("digest").alias("r_digest"), "size", (-F.col("best.n")).alias("r_n"), F.col("best.doc_id").alias("r_doc"), F.col("best.rid").alias("r_rid"))


def decide(docs: DataFrame, support: float = SUPPORT) -> DataFrame:
    """One row per document: ``doc_id, keep_id, group_size, kept, text_sha256``."""
    rows = _narrow(docs)
    heavy = written(heavy_winners(rows, support), "heavy")
    marked = rows.join(F.broadcast(heavy), "digest", "left")
    frequent = marked.filter(F.col("h_size").isNotNull()).select("doc_id", F.col("h_doc").alias("keep_id"), F.col("h_size").alias("group_size"), (F.col("rid") == F.col("h_rid")).alias("kept"), "digest")
    rest = marked.filter(F.col("h_size").isNull()).select("doc_id", "n", "digest", "rid")
    found = written(_repeated(rest), "repeated")
    own = F.col("size").isNull()  # one of a kind
    # one row per digest on the right, so that a skewed digest can be split on the left
    rest = rest.join(found, F.col("digest") == F.col("r_digest"), "left").select(
        "doc_id",
        F.when(own, F.col("doc_id")).otherwise(F.col("r_doc")).alias("keep_id"),
        F.coalesce("size", F.lit(1).cast("long")).alias("group_size"),
        (own | (F.col("rid") == F.col("r_rid"))).alias("kept"),
        "digest",
    )
    return frequent.unionByName(rest).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def deduplicated(docs: DataFrame, support: float = SUPPORT) -> DataFrame:
    """The rows of ``docs`` that stay, with their own columns, whatever their names.

    Winners are found on digests. Rows of texts that occur once, and those that lose, are settled where they are read as long as the winners
    fit a broadcast, else in one shuffle. Only rows that agree with a winner in size and doc_id as well, of which one stays, are compared as rows."""
    rows = _narrow(docs)
    heavy = written(heavy_winners(rows, support), "heavy")
    rest = rows.join(F.broadcast(heavy), "digest", "left_anti")
    best = heavy.select(F.col("digest").alias("r_digest"), F.col("h_n").alias("r_n"), F.col("h_doc").alias("r_doc")).unionByName(_repeated(rest).select("r_digest", "r_n", "r_doc"))
    best = written(best, "winners")
    mine = (F.col("digest") == F.col("r_digest")) & (F.col("n") == F.col("r_n")) & F.col("doc_id").eqNullSafe(F.col("r_doc"))
    tied = rows.join(small_side(best), mine).groupBy("digest").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select(F.col("digest").alias("t_digest"))
    tied = written(tied, "tied")
    tagged = docs.select(F.struct("*").alias("row"), digest(F.col("text")).alias("digest"), _n_points(F.col("text")).alias("n"))
    left = tagged.join(small_side(best), F.col("digest") == F.col("r_digest"), "left").filter(F.col("r_digest").isNull() | ((F.col("n") == F.col("r_n")) & F.col("row.doc_id").eqNullSafe(F.col("r_doc"))))
    if not tied.head(1):
        return left.select("row.*")
    left = left.join(small_side(tied), F.col("digest") == F.col("t_digest"), "left")
    # the first row of each partition first, then of all: no task holds a large group
    one = left.filter(F.col("t_digest").isNotNull()).withColumn("at", F.row_number().over(Window.partitionBy("digest").orderBy("n"))).filter("at = 1")
    return left.filter(F.col("t_digest").isNull()).select("row.*").unionByName(one.select("row.*"))
