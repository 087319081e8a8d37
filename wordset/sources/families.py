"""Set frames ``(set_id, elem[, freq])`` made from tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from wordset.sources.tables import load


def from_table(df: DataFrame, set_col: str | Column, elem_col: str | Column, bag: bool = False) -> DataFrame:
    """Distinct pairs of a set's name and an element, without nulls; as a bag with the number of its rows."""
    one = lambda c: F.col(c) if isinstance(c, str) else c
    rows = df.select(one(set_col).cast("string").alias("set_id"), one(elem_col).cast("long").alias("elem")).dropna()
    return rows.groupBy("set_id", "elem").agg(F.count(F.lit(1)).alias("freq")) if bag else rows.distinct()


def dropped_nulls(df: DataFrame, set_col: str, elem_col: str) -> DataFrame:
    """How many rows ``from_table`` leaves out."""
    return df.agg(F.count_if(F.col(set_col).isNull() | F.col(elem_col).isNull()).alias("n_null"), F.count(F.lit(1)).alias("n_rows"))


def explode_sets(df: DataFrame, set_col: str, array_col: str) -> DataFrame:
    return from_table(df.select(F.col(set_col).alias("_s"), F.explode(array_col).alias("_e")), "_s", "_e")


def pack_sets(sets: DataFrame) -> DataFrame:
    """One row per set with its sorted elements; for sets that fit in a row."""
    return sets.groupBy("set_id").agg(F.sort_array(F.collect_set("elem")).alias("elems"))


def tokens(text: str) -> str:
    """SQL: the lower-cased runs of letters and digits of a text."""
    return rf"regexp_extract_all(lower({text}), '[\\p{{L}}\\p{{N}}]+', 0)"


def predicate_set(df: DataFrame, key: str, name: str, condition: str) -> DataFrame:
    """The keys of the rows that meet a condition, as a set of that name."""
    return from_table(df.filter(condition).select(F.lit(name).alias("_s"), F.col(key).alias("_e")), "_s", "_e")


def supp_orders(spark, d):
    return from_table(load(spark, d, "lineitem"), "l_suppkey", "l_orderkey")


def flag_orders(spark, d):
    return from_table(load(spark, d, "lineitem"), F.concat("l_returnflag", "l_linestatus"), "l_orderkey")


def prio_cust(spark, d):
    return from_table(load(spark, d, "orders"), "o_orderpriority", "o_custkey")


def part_orders(spark, d):
    return from_table(load(spark, d, "lineitem"), "l_partkey", "l_orderkey")


def term_docs(spark, d):
    rows = load(spark, d, "documents").select("doc_id", F.explode(F.expr(tokens("text"))).alias("w"))
    return from_table(rows, "w", "doc_id")


def term_passages(spark, d):
    rows = load(spark, d, "documents").select("doc_id", F.posexplode(F.expr(tokens("text"))).alias("i", "w"))
    return from_table(rows, "w", F.expr("doc_id * 16777216 + i div 16"))  # room for 2^28 words a document; wider than 32 bits


def page_terms(spark, d):
    rows = load(spark, d, "pages").select("page_id", F.explode(F.expr(tokens("regexp_replace(html, '<[^>]*>', ' ')"))).alias("w"))
    return from_table(rows, "w", "page_id")


def event_users(spark, d, bag=True):
    return from_table(load(spark, d, "events"), F.concat_ws("|", "event_type", F.expr("date_format(ts, 'yyyy-MM-dd')")), "user_id", bag)


def part_attrs(spark, d):
    rows = load(spark, d, "part").select("p_partkey", F.explode(F.array(F.concat(F.lit("brand="), "p_brand"), F.concat(F.lit("type="), "p_type"), F.concat(F.lit("size="), F.col("p_size").cast("string")))).alias("s"))
    return from_table(rows, "s", "p_partkey")


def doc_attrs(spark, d):
    docs = load(spark, d, "documents").select("doc_id", F.explode(F.array(F.concat(F.lit("lang="), "lang"), F.concat(F.lit("source="), "source"))).alias("s"))
    marks = load(spark, d, "labels").select("doc_id", F.explode(F.array(F.concat(F.lit("quality="), F.col("quality").cast("string")), F.concat(F.lit("toxic="), F.col("toxic").cast("string")))).alias("s"))
    return from_table(docs.unionByName(marks), "s", "doc_id")


def label_vecs(spark, d):
    return from_table(load(spark, d, "embeddings"), "label", "vec_id")


def nation_sets(spark, d):
    c = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    names = F.array(F.concat(F.lit("region="), "r_name"), F.concat(F.lit("nation="), "n_name"), F.concat(F.lit("segment="), "c_mktsegment"))
    return from_table(c.select("c_custkey", F.explode(names).alias("s")), "s", "c_custkey")


def emb_sign(spark, d):
    rows = load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x"))
    return from_table(rows, F.concat(F.col("i").cast("string"), F.when(F.col("x") >= 0, "+").otherwise("-")), "vec_id")


#: A portable order of order keys that is unlike their own.
SCRAMBLE = "((1640531527 * {x} + 12345) & 4294967295)"


def ctl_overlap(spark, d, n1: int, n2: int, r: int) -> DataFrame:
    """Sets A and B of sizes n1 and n2 with exactly r common elements: two runs of the scrambled order keys.

    The frame of wanted keys is bounded by n1 + n2; the order is cut by value ranges, not by a window over the table."""
    keys = load(spark, d, "orders").select("o_orderkey", F.expr(SCRAMBLE.format(x="o_orderkey")).alias("s"))
    top = keys.orderBy("s").limit(n1 + n2 - r)
    from pyspark.sql import Window

    ranked = top.withColumn("i", F.row_number().over(Window.orderBy("s")))
    return ranked.select(F.col("o_orderkey").alias("elem"), F.explode(F.array_compact(F.array(F.when(F.col("i") <= n1, "A"), F.when(F.col("i") > n1 - r, "B")))).alias("set_id")).select("set_id", "elem")


FAMILIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (supp_orders, flag_orders, prio_cust, part_orders, term_docs, term_passages, page_terms, event_users, part_attrs, doc_attrs, label_vecs, nation_sets, emb_sign)
}
