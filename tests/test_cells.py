"""Batches over cells: every member is sent once, whatever the number of queries, and results stay exact however cells are cut."""

import pytest
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing
from wordset.operators import blocks, cells, kernels, measures
from wordset.operators import groups as G
from wordset.queries import CFG


@pytest.fixture(scope="module")
def frame(spark):
    """A set of every size from 1 to 3,000, by the multiples of a number."""
    step = {"a": 1, "b": 2, "c": 3, "d": 7, "e": 50, "f": 1000, "g": 2999}
    rows = spark.range(3000).select(F.explode(F.array(*(F.when(F.col("id") % s == 0, F.lit(n)) for n, s in step.items()))).alias("set_id"), F.col("id").alias("elem"))
    return rows.dropna().cache()


ASKED = [["a"], ["a", "b"], ["b", "c"], ["c", "b"], ["b", "c", "d"], ["e", "f"], ["f", "g"], ["a", "b", "c", "d", "e"], ["a", "unknown"], ["d", "d", "b"], ["g", "b"]]


@pytest.fixture(scope="module")
def asked(spark):
    return spark.createDataFrame(list(enumerate(ASKED)), "qid long, set_ids array<string>")


def brute(frame, asked):
    held = {r.set_id: set(r.e) for r in frame.groupBy("set_id").agg(F.collect_set("elem").alias("e")).collect()}
    got = {r.qid: len(set.intersection(*(held.get(s, set()) for s in r.set_ids))) for r in asked.collect()}
    return {q: n for q, n in got.items() if n}


CUTS = [(20, 16, 4), (10, 8, 0), (6, 4, 4)]


@pytest.fixture(params=CUTS, ids=str)
def cut(request, monkeypatch):
    for name, value in zip(("CELL_BITS", "FEWER", "SPREAD"), request.param, strict=True):
        monkeypatch.setattr(cells, name, value)


def test_sizes_by_bit_maps(frame, asked, cut):
    assert {r.qid: r.r for r in cells.sizes(frame, asked).collect()} == brute(frame, asked)


def test_sizes_of_any_elements(spark, asked):
    wide = spark.range(500).select(F.explode(F.array(F.lit("a"), F.lit("b"))).alias("set_id"), (F.col("id") * (1 << 54) - 5).alias("elem")).distinct()
    assert {r.qid: r.r for r in cells.sizes(wide, asked).collect()} == brute(wide, asked)


def test_many_queries_take_several_passes(frame, asked, monkeypatch):
    monkeypatch.setattr(cells, "BATCH", 3)
    assert {r.qid: r.r for r in cells.sizes(frame, asked).collect()} == brute(frame, asked)


def test_thin_sets_are_merged(frame, asked):
    """The way taken where bit maps would be too wide gives the same."""
    _run_on(frame, asked, map_words=0)


def _run_on(frame, asked, map_words):
    import numpy as np
    import pyarrow as pa

    stats = G.set_stats(frame).select("set_id", "n", F.monotonically_increasing_id().alias("no")).localCheckpoint()
    q = G.query_sets(asked, stats).join(stats.select("set_id", "no"), "set_id").groupBy("qid").agg(F.sort_array(F.collect_list(F.struct("rank", "no", "n"))).alias("sets"))
    rows = frame.join(stats, "set_id").select("no", "elem").collect()
    batch = pa.RecordBatch.from_arrays([pa.array([0] * len(rows), pa.int64()), pa.array([r.no for r in rows], pa.int64()), pa.array([r.elem for r in rows], pa.int64())], ["c", "no", "v"])
    before, cells.MAP_WORDS = cells.MAP_WORDS, map_words
    try:
        got = next(cells.count_common([batch], cells._batch(q), 0, Cfg(g="xx64")))
    finally:
        cells.MAP_WORDS = before
    assert dict(zip(*(np.asarray(got[c]).tolist() for c in ("qid", "r")), strict=True)) == brute(frame, asked)


def test_all_kernels_in_all_codings(frame, asked, cut):
    got = {}
    for x in cells.kernel_results(frame, asked, CFG, tuple(kernels.METHODS), blocks.CODECS, 2).filter("r > 0").collect():
        got.setdefault((x.codec, x.method), {})[x.qid] = x.r
    want = brute(frame, asked)
    assert len(got) == len(kernels.METHODS) * len(blocks.CODECS) and all(v == want for v in got.values())


def test_filter_rate_equals_that_of_stored_groups(frame, asked, cut):
    """Groups that are wider than cells are counted once."""
    two = asked.filter(F.size(F.array_distinct("set_ids")) == 2)
    want = sorted(tuple(r) for r in measures.filter_rate(G.build(G.pruned(frame, two), CFG.with_(m=4), keep=True), two, 4).collect())
    assert sorted(tuple(r) for r in cells.filter_rate(frame, two, CFG, 4).collect()) == want


def test_a_member_is_sent_once(frame, spark, monkeypatch):
    """A hundred queries for the same two sets deal out no more rows than one; results of all of them are made of these."""
    import pyarrow as pa

    def rows_of(*_):
        def run(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([pa.array([0], pa.int64()), pa.array([b.num_rows], pa.int64())], ["qid", "r"])

        return run

    monkeypatch.setattr(cells, "on_worker", rows_of)
    two = frame.filter("set_id in ('a', 'b')")
    for n in (1, 100):
        q = spark.createDataFrame([(i, ["a", "b"]) for i in range(n)], "qid long, set_ids array<string>")
        assert [r.r for r in cells.sizes(two, q).collect()] == [two.count()]
        assert [r.r for r in measures.results(two, q).filter("qid = 0").collect()] == [two.count()]


def test_bits_in_numpy_are_those_of_sql(spark):
    import numpy as np

    xs = [0, 1, 2, 12345, (1 << 31) - 1, 1 << 31, (1 << 32) - 1]
    frame = spark.createDataFrame([(x,) for x in xs], "x long")
    for j in (1, 8):
        assert [r[0] for r in frame.select(hashing.h("x", j, CFG)).collect()] == hashing.h_array(np.array(xs), j, CFG).tolist()


def test_other_hashes_are_refused(frame, asked):
    for cfg in (Cfg(g="xx64"), Cfg(h="perm"), Cfg(w=256)):
        with pytest.raises(ValueError):
            cells.filter_rate(frame, asked, cfg, 1)


def test_packed_codes_of_a_cut_set_compare_few_words():
    """Buckets are of the bits in which members of a block differ, so a candidate meets a word or two however finely a set is cut."""
    import numpy as np

    g = np.arange(4000, dtype=np.uint64) * np.uint64(64) + np.uint64(5 << 26)
    one = kernels.Block(6, np.array([5], np.uint64), np.array([len(g)]), np.ones((1, 1), np.uint64), g)
    common, count = kernels.packed_codes([one, one], CFG)
    assert common.tolist() == g.tolist() and count["comparisons"] < 8 * len(g)
