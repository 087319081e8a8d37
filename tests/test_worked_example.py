"""The small worked example: w = 16, groups of four, h(x) = (x - 1000) mod 16."""

import pytest
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import words
from wordset.operators import fixed, measures

CFG = Cfg(w=16, m=1, h="sql:({x} - 1000) % 16")
A = [1001, 1002, 1004, 1009, 1016, 1027, 1043]
B = [1001, 1003, 1005, 1009, 1011, 1016, 1022, 1032, 1034, 1049]


@pytest.fixture(scope="module")
def sets(spark):
    return spark.createDataFrame([("A", x) for x in A] + [("B", x) for x in B], "set_id string, elem long")


@pytest.fixture(scope="module")
def ask(spark):
    return spark.createDataFrame([(0, ["A", "B"])], "qid long, set_ids array<string>")


def test_images(sets):
    got = {(r.set_id, r.p): (r.inf, r.sup, r.img_1) for r in fixed.build(sets, CFG).collect()}
    assert got == {("A", 0): (1001, 1009, 534), ("A", 1): (1016, 1043, 2049), ("B", 0): (1001, 1009, 554), ("B", 1): (1011, 1032, 2113), ("B", 2): (1034, 1049, 6)}


@pytest.mark.parametrize("how", ["asof", "bins", "theta"])
def test_pairs_met(sets, ask, how, monkeypatch):
    monkeypatch.setattr(fixed, "BIN", 2)
    g = fixed.query_groups(sets, ask, CFG)
    assert sorted((r.a_p, r.b_p) for r in fixed.overlaps(g, how).collect()) == [(0, 0), (1, 1), (1, 2)]


@pytest.mark.parametrize("how", ["asof", "bins", "theta"])
def test_intersection(sets, ask, how):
    assert sorted(r.elem for r in fixed.intersect(sets, ask, CFG, how=how).collect()) == [1001, 1009, 1016]


def test_unequal_members_with_the_same_hash(sets, ask):
    r = measures.collisions(sets, ask, CFG).first()
    assert (r.pairs, r.r) == (3, 3)
    assert r.unequal == 3  # 1016-1032, 1027-1011, 1043-1011


def test_members_of_a_word(spark):
    df = spark.createDataFrame([(514,), (0,), (-1,), (-(1 << 63),)], "w long").select(words.bits_of(F.col("w")).alias("b"))
    assert [r.b for r in df.collect()] == [[1, 9], [], list(range(64)), [63]]
