"""Scans and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Columns of the star-schema and event tables; others are read as Parquet declares them.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table under its declared schema, so no file is opened to infer one and only used columns are read."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def load_as(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def load_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int, **options) -> DataFrame:
    """A JDBC table, read in ``parts`` ranges of ``column``."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=column, lowerBound=low, upperBound=high, numPartitions=parts, **options).load()


def write_index(groups: DataFrame, path: str, mode: str = "overwrite") -> None:
    """A group table as Parquet, partitioned by the size class of its sets and sorted, so that a scan for named sets skips
    most files and row groups."""
    classed = groups.withColumn("size_class", F.col("t") % 64)
    classed.repartition("size_class", "set_id").sortWithinPartitions("set_id", "z").write.mode(mode).partitionBy("size_class").parquet(path)


def save_bucketed(groups: DataFrame, name: str, buckets: int, by: str = "zkey") -> DataFrame:
    """A group table bucketed on the join key, so that joins of two indexes need no shuffle."""
    groups.write.mode("overwrite").bucketBy(buckets, by).sortBy("set_id", by).saveAsTable(name)
    return groups.sparkSession.table(name)
