"""The ten operators as queries over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordset.llm import bpe, exact_dedup, html_extract, licenses, near_dedup, packing, quality, rules, sharding, toxicity


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_gray(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(_table(spark, sf_dir, "documents"))


def vocabulary(name: str = "byte_bpe_50k.json") -> str:
    """The place of a public tokenizer's file, on this machine and on every executor."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_pack_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(_table(spark, sf_dir, "documents"), vocabulary())


def op3_bpe_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(_table(spark, sf_dir, "documents"), vocabulary())


def op4_quality_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.scored(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op5_html_tag_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.main_text(_table(spark, sf_dir, "pages"))


def op6_rule_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = rules.ledger(_table(spark, sf_dir, "documents"))
    base = ~rules.passes("base_v1")
    return book.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), rules.passes("strict_v1").alias("kept"))


def op7_exact_heavy_hitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.decide(_table(spark, sf_dir, "documents"))


def op8_toxicity_channel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.scored(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_interleaved_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.placed(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")


def op10_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(_table(spark, sf_dir, "documents"))


OPERATORS = (
    op1_simhash_gray,
    op2_pack_best_fit,
    op3_bpe_automaton,
    op4_quality_neighbours,
    op5_html_tag_paths,
    op6_rule_ledger,
    op7_exact_heavy_hitters,
    op8_toxicity_channel,
    op9_interleaved_shards,
    op10_license_rules,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in OPERATORS}


OP7_SQL = r"""
with d as (select doc_id, length(coalesce(text, '')) as n, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g')) as h from documents)
select doc_id, first_value(doc_id) over o as keep_id, count(*) over (partition by h) as group_size,
 row_number() over o = 1 as kept, h as text_sha256
from d window o as (partition by h order by n desc, doc_id)"""


def oracle_sql() -> dict[str, str]:
    return {"op6_rule_ledger": rules.oracle(), "op7_exact_heavy_hitters": OP7_SQL, "op10_license_rules": licenses.oracle()}
