"""Scans, sinks and stored indexes."""

import pytest
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import codes
from wordset.operators import blocks, prefix
from wordset.sources import families as fam
from wordset.sources import tables


@pytest.mark.parametrize("name", sorted(tables.SCHEMAS))
def test_declared_schemas(spark, sf, name):
    declared, there = tables.load(spark, sf, name), spark.read.parquet(f"{sf}/{name}.parquet")
    assert declared.schema == there.schema and declared.count() == there.count() > 0


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats(spark, sf, tmp_path, fmt):
    nation = tables.load(spark, sf, "nation")
    nation.write.format(fmt).save(f"{tmp_path}/nation")
    assert tables.load_as(spark, f"{tmp_path}/nation", fmt, tables.SCHEMAS["nation"]).exceptAll(nation).count() == 0


def test_text(spark, tmp_path):
    (tmp_path / "t.txt").write_text("a b\nc\n")
    assert [r.value for r in tables.load_as(spark, str(tmp_path / "t.txt"), "text").collect()] == ["a b", "c"]


def test_partitioned_index(spark, sf, tmp_path):
    groups = prefix.build(fam.supp_orders(spark, sf), Cfg()).groups
    tables.write_index(groups, f"{tmp_path}/ix")
    back = spark.read.parquet(f"{tmp_path}/ix")
    assert back.count() == groups.count()
    plan = back.filter("set_id = '1'").select("z", "img_1")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(set_id), EqualTo(set_id,1)]" in plan and "elems" not in plan[plan.index("ReadSchema") :]


def test_bucketed_indexes_join_without_a_shuffle(spark, sf):
    groups = prefix.build(fam.supp_orders(spark, sf), Cfg(), t="5").groups.withColumn("zkey", F.col("z"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        a = tables.save_bucketed(groups.select("set_id", "z", "zkey", "n", "img_1"), "bucketed_a", 4)
        b = tables.save_bucketed(groups.select("set_id", "z", "zkey", "n", "img_1"), "bucketed_b", 4)
        met = a.filter("set_id = '0'").alias("x").join(b.filter("set_id = '1'").alias("y"), "zkey").filter("x.img_1 & y.img_1 <> 0")
        plan = met._jdf.queryExecution().toString()
        assert "Exchange" not in plan[plan.index("== Physical Plan ==") :]
        assert met.count() > 0
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("drop table if exists bucketed_a")
        spark.sql("drop table if exists bucketed_b")


def test_families_explode_and_pack(spark):
    arrays = spark.createDataFrame([("a", [1, 2, 2]), ("b", [2])], "s string, e array<long>")
    sets = fam.explode_sets(arrays, "s", "e")
    assert {r.set_id: r.elems for r in fam.pack_sets(sets).collect()} == {"a": [1, 2], "b": [2]}
    assert fam.predicate_set(arrays.select(F.lit(7).alias("k"), "s"), "k", "p", "s = 'a'").collect()[0].elem == 7


@pytest.mark.parametrize("name", sorted(fam.FAMILIES))
def test_every_family_has_sets(spark, sf, name):
    sets = fam.FAMILIES[name](spark, sf)
    assert sets.columns[:2] == ["set_id", "elem"] and sets.count() == sets.select("set_id", "elem").distinct().count() > 0


def test_unary_sizes():
    w = codes.BitWriter()
    w.unary(2)
    assert "".join(w.parts) == "011"
    head = blocks.encode_sizes([5, 6, 9], [1, 3, 2])
    assert blocks.decode_sizes(head, 5, 3) == ([5, 6, 9], [1, 3, 2])
