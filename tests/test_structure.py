"""Invariants of the structures, the functions under them, the planner, and what the plans look like."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import codes, hashing
from wordset.functions.store import written
from wordset.operators import fixed, measures, prefix, scan
from wordset.operators import groups as G
from wordset.plans import api, planner, sqlsurface, workloads
from wordset.queries import PAIRS, frames
from wordset.sources import families as fam
from wordset.streaming import sets as st


@pytest.fixture(scope="module")
def f1(spark, sf):
    return fam.supp_orders(spark, sf).cache()


def test_permutation_is_one_to_one_and_inverted(spark):
    xs = spark.range(0, 70_000).select((F.col("id") * 61_357 % (1 << 32)).alias("x")).distinct()
    g = xs.select("x", hashing.g("x", Cfg()).alias("g"))
    assert g.select("g").distinct().count() == xs.count()
    assert g.withColumn("b", hashing.g_inverse("g", Cfg())).filter("b <> x").count() == 0


def test_wide_permutation_on_edge_values(spark):
    xs = spark.createDataFrame([(v,) for v in (0, -1, 1, (1 << 63) - 1, -(1 << 63))], "x long")
    assert xs.select(hashing.g("x", Cfg(g="xx64"))).distinct().count() == 5


@pytest.mark.parametrize("n", [1, 2, 7, 8, 9, 16, 17, 64, 65, 1000, 12345])
def test_exponents(spark, n):
    cfg = Cfg()
    t = hashing.t_scan(n, cfg)
    assert (1 << t) * 8 >= n and (t == 0 or (1 << t - 1) * 8 < n)
    assert spark.sql(f"select {hashing.t_scan_sql(f'{n}L', cfg)}").first()[0] == t
    for other in (1, 50, 3000):
        t = hashing.t_pair(n, other, 64)
        assert 4**t * 64 >= n * other and (t == 0 or 4 ** (t - 1) * 64 < n * other)
        s1, s2 = hashing.fixed_sizes(n, other, 64)
        assert s1 & (s1 - 1) == 0 and s2 & (s2 - 1) == 0
        assert s1 * s2 <= 4 * 64 or 64 * min(n, other) < max(n, other)  # but for sizes that are clamped to 1


def test_groups_partition_the_set(f1):
    cfg = Cfg(m=2)
    ix = G.build(f1, cfg)
    back = ix.groups.select("set_id", "t", "z", F.explode("elems").alias("x")).select("set_id", "t", "z", "x.g", F.col("x.elem").alias("elem"))
    assert back.select("set_id", "elem").exceptAll(f1).count() == 0 and back.count() == f1.count()
    assert back.filter(F.expr(hashing.prefix_sql("g", "t", cfg)) != F.col("z")).count() == 0
    assert ix.groups.filter(F.size("elems") != F.col("n")).count() == 0


def test_levels_are_the_or_of_their_children(f1):
    _, lv = prefix.build_multires(f1, Cfg())
    up = lv.filter("t > 0").groupBy("set_id", (F.col("t") - 1).alias("t"), F.shiftrightunsigned("z", 1).alias("z")).agg(F.bit_or("img").alias("i"), F.min("left").alias("l"), F.max("right").alias("r"))
    joined = lv.join(up, ["set_id", "t", "z"])
    assert joined.filter((F.col("i") != F.col("img")) | (F.col("l") != F.col("left")) | (F.col("r") != F.col("right"))).count() == 0


@pytest.mark.parametrize("t", [0, 2, 5])
def test_inverse_lists_follow_the_pointers(f1, t):
    e, lv = prefix.build_multires(f1, Cfg())
    got = {(r.set_id, r.z, r.y): r.elems for r in prefix.inverse_of(e, lv, t).collect()}
    rows = e.collect()
    at = {(r.set_id, r.pos): r for r in rows}
    for g in lv.filter(F.col("t") == t).collect():
        for y, head in g.first.items():
            walk, pos = [], head
            while pos is not None and pos <= g.right:
                walk.append(at[g.set_id, pos].elem)
                pos = at[g.set_id, pos].next_pos
            assert got[g.set_id, g.z, y] == walk


def test_fixed_levels_merge_neighbours(f1):
    small = f1.filter("set_id in ('0', '1')")
    lv = fixed.build_levels(small, Cfg(), 16)
    for level in (0, 3, 4):
        direct = fixed.build(small, Cfg(), 1 << level).select("set_id", "p", "inf", "sup", "n", "img_1")
        assert lv.filter(F.col("level") == level).select("set_id", "p", "inf", "sup", "n", "img_1").exceptAll(direct).count() == 0


def test_no_false_negatives_and_filtering_rises_with_m(spark, f1):
    ix = G.build(f1, Cfg(m=8))
    pairs = measures.pair_groups(ix, frames(f1, PAIRS[:5]), 8)
    assert pairs.filter("r > 0 and not (" + " and ".join(f"hit_{j}" for j in range(1, 9)) + ")").count() == 0
    rate = {r.m: r.filtered / r.empty_pairs for r in measures.filter_rate(ix, frames(f1, PAIRS[:5]), 8).collect()}
    assert all(rate[m] <= rate[m + 1] for m in range(1, 8))
    b = measures.bounds(64, 1)
    assert rate[1] >= max(b["beta_1"], b["beta_2"])
    assert abs(b["one_image"] - 0.3436) < 1e-4 and abs(b["delta"] - 2.6122) < 1e-4


def test_wasted_merges_fall_with_m(f1):
    q = frames(f1, PAIRS[:5])
    wasted = [measures.merge_cases(G.build(f1, Cfg(m=m)), q, m).agg(F.sum("wasted")).first()[0] for m in (1, 2, 4)]
    assert wasted[0] >= wasted[1] >= wasted[2]


def test_group_sizes_are_near_the_root(f1):
    r = measures.group_tail(G.build(f1, Cfg()), 1.6122).first()
    assert 4 <= r.mean_size <= 8 and r.tail <= 1 / 32


def test_runs_meet_fewer_pairs_than_they_are(f1):
    q = frames(f1, PAIRS[:5])
    g = fixed.query_groups(f1, q, Cfg())
    most = {r.qid: r.c for r in g.groupBy("qid").agg(F.count(F.lit(1)).alias("c")).collect()}
    for r in measures.collisions(f1, q, Cfg()).collect():
        assert r.pairs <= most[r.qid] - 1
        assert r.unequal / r.pairs < 3  # one on average for groups of root(w)


def test_space_overheads(f1):
    got = {(r.structure, r.m): r.overhead for r in measures.space_words(f1, Cfg()).collect()}
    assert got["image_scan", 2] < got["image_scan", 4] < got["image_scan", 8]
    share = {(r.structure, r.codec): r.share for r in measures.space_bits(f1, Cfg(m=1)).collect()}
    assert share["list", "delta"] < 1 and share["list", "gamma"] < 1


def test_codes_round_trip():
    r = random.Random(1)
    values = sorted(r.sample(range(100_000), 300))
    for codec in ("gamma", "delta"):
        assert codes.decode_gaps(codes.encode_gaps(values, codec), len(values), codec) == values
    assert codes.decode_gaps(codes.encode_gaps([], "gamma"), 0, "gamma") == []
    for codec in ("gamma", "delta"):
        x = np.array([1, 2, 3, 4, 7, 8, 255, 256, (1 << 31) - 1, 1 << 31, (1 << 32) - 1] + [r.randrange(1, 1 << r.randint(1, 32)) for _ in range(500)], np.uint64)
        w = codes.BitWriter()
        for v in x.tolist():
            getattr(w, codec)(v)
        assert codes.pack_codes(x, codec) == w.done()[0]
        assert (codes.unpack_codes(codes.pack_codes(x, codec), len(x), codec) == x).all()
    counts = np.array([3, 1, 4, 2])
    v = np.array([0, 4, 9, 7, 1, 2, 3, 8, 0, 5])
    assert (codes.from_gaps(codes.gaps_of(v, counts), counts) == v).all()
    assert codes.unpack_sizes(codes.pack_sizes(np.array([3, 0, 1, 7])))[:4].tolist() == [3, 0, 1, 7]
    low = np.array([r.randrange(1 << 29) for _ in range(100)], np.uint64)
    assert (codes.unpack_low(codes.pack_low(low, 29), 100, 29) == low).all()
    w = codes.BitWriter()
    for n in (0, 2, 5):
        w.unary(n)
    reader = codes.BitReader(w.done()[0])
    assert [reader.unary() for _ in range(3)] == [0, 2, 5]


def test_code_lengths(spark):
    from wordset.functions import words

    for x in (1, 2, 3, 4, 7, 8, 100, 12345):
        g, d = codes.BitWriter(), codes.BitWriter()
        g.gamma(x)
        d.delta(x)
        got = spark.sql(f"select {words.gamma_bits(f'{x}L')}, {words.delta_bits(f'{x}L')}").first()
        assert (got[0], got[1]) == (g.done()[1], d.done()[1])


# ---- settings, planner, front door


@pytest.mark.parametrize("bad", [{"w": 32}, {"w": 60}, {"m": 0}, {"universe_bits": 40}, {"universe_bits": 31}, {"g": "none"}, {"h": "none"}])
def test_bad_settings(bad):
    with pytest.raises(ValueError):
        Cfg(**bad)


def test_index_of_other_settings(f1):
    ix = G.build(f1, Cfg())
    ix.require(Cfg(m=1))
    with pytest.raises(ValueError):
        ix.require(Cfg(seed=1))
    with pytest.raises(ValueError):
        scan.survivors(G.build(f1, Cfg(m=1)), frames(f1, PAIRS[:1]), 2)


def _stats(spark, **sizes):
    return spark.createDataFrame([(s, n, lo, hi) for s, (n, lo, hi) in sizes.items()], "set_id string, n long, inf long, sup long")


def test_planner(spark):
    st_ = _stats(spark, a=(1000, 0, 9999), b=(1200, 0, 9999), c=(40_000, 0, 99_999), d=(900_000, 0, 999_999), e=(10, 20_000, 20_100))
    plan = lambda *n, **k: planner.plan_query(st_, list(n), Cfg(), **k).method
    assert plan("a", "b") == "scan"
    assert plan("a", "c") == "lookup"
    assert plan("a", "d") == "probe"
    assert plan("a", "e") == "empty" and plan("a", "zz") == "empty"
    assert plan("a") == "set" and plan("a", "a") == "set"
    assert plan("a", "b", overlap=0.9) == "merge"
    assert planner.plan_query(st_, ["d", "a", "b"], Cfg()).names == ("a", "b", "d")
    with pytest.raises(ValueError):
        plan()
    assert "probe" in planner.plan_query(st_, ["a", "d"], Cfg()).text()
    q = spark.createDataFrame([(0, ["a", "b"]), (1, ["a", "d"]), (2, ["a", "zz"]), (3, ["a", "e"])], "qid long, set_ids array<string>")
    assert {r.qid: r.method for r in planner.plan_batch(q, st_).collect()} == {0: "scan", 1: "probe", 2: "empty", 3: "empty"}


def test_front_door(spark, f1):
    ix = api.build_index(f1, Cfg(m=2))
    want = {r.elem for r in f1.filter("set_id = '0'").collect()} & {r.elem for r in f1.filter("set_id = '1'").collect()}
    for method in ("auto", "scan", "prefix", "fixed", "probe", "blocks", "merge", "hash", "lookup", "svs"):
        assert {r.elem for r in api.intersect(ix, ["0", "1"], method).collect()} == want, method
    assert api.intersect_count(ix, ["0", "1"]).first().r == len(want)
    assert api.intersect_limit(ix, ["0", "1"], 3).count() == 3
    assert api.intersect(ix, ["0", "nowhere"]).count() == 0
    assert "scan" in api.explain(ix, ["0", "1"])
    assert 0 <= planner.estimate_overlap(ix.index.groups, "0", "1", Cfg(), 0.5) <= 1
    with pytest.raises(ValueError):
        api.intersect(ix, [])
    with pytest.raises(ValueError):
        api.intersect(ix, ["0"], "magic")
    sqlsurface.name_index("f1", ix)
    assert {r.elem for r in sqlsurface.sql("INTERSECT SETS 0, 1 IN f1").collect()} == want
    assert sqlsurface.sql("intersect sets 0, 1 in f1 using merge limit 2").count() == 2
    with pytest.raises(ValueError):
        sqlsurface.sql("INTERSECT SETS 0, 1 IN elsewhere")


def test_table_function_over_arrays(spark):
    sqlsurface.register(spark)
    got = spark.sql("select elem from intersect_sets(array(array(1L, 2L, 3L), array(2L, 3L, 4L)))").collect()
    assert [r.elem for r in got] == [2, 3]


def test_null_elements_are_no_members(spark):
    raw = spark.createDataFrame([("a", 1), ("a", None), (None, 2), ("a", 1)], "s string, e long")
    assert [(r.set_id, r.elem) for r in fam.from_table(raw, "s", "e").collect()] == [("a", 1)]
    assert fam.dropped_nulls(raw, "s", "e").first().n_null == 2


# ---- plans


def test_filter_phase_reads_no_members(f1):
    ix = G.build(f1, Cfg(m=2))
    ix.groups = written(ix.groups, "groups")
    alive, _, _ = scan.survivors(ix, frames(f1, PAIRS[:2]))
    plan = alive._jdf.queryExecution().toString()
    physical = plan[plan.index("== Physical Plan ==") :]
    assert "ReadSchema" in physical and "elems" not in physical
    assert "NestedLoop" not in physical and "CartesianProduct" not in physical


def test_members_are_read_by_survivors(f1):
    """The scan of members meets a broadcast of the surviving groups before any exchange."""
    q = frames(f1, PAIRS[:2])
    ix = G.build(f1, Cfg(m=2), keep=True)
    plan = scan.planned(ix, q)
    alive, legs, _ = scan.survivors(ix, q, plan=plan)
    text = scan._wanted(plan[0], alive, legs, plan[3])._jdf.queryExecution().executedPlan().toString()
    reads = [line for line in text.splitlines() if "FileScan" in line and "elems" in line]
    at = next(i for i, line in enumerate(text.splitlines()) if line in reads)
    join = max(i for i, line in enumerate(text.splitlines()[:at]) if "BroadcastHashJoin" in line)
    assert len(reads) == 1 and "In(set_id" in reads[0]
    assert not any("Exchange" in line for line in text.splitlines()[join:at])


def test_blocks_are_bounded(spark):
    from wordset.operators import blocks

    sets = spark.range(40_000).select(F.lit("a").alias("set_id"), (F.col("id") * 7).alias("elem"))
    sizes = [r.n for r in blocks.build_blocks(sets, Cfg(m=1), 10).select(F.size("g").alias("n")).collect()]
    assert sum(sizes) == 40_000 and len(sizes) == 64 and max(sizes) < 2 << 10


def test_many_predicates(spark):
    df = spark.createDataFrame([(1, 5), (2, 6), (2, 500), (None, 5)], "k int, x int")
    conditions = [f"x < {500 + i}" for i in range(130)]
    assert [r.elem for r in api.intersect_predicates(df, "k", conditions).collect()] == [1, 2]
    assert [r.elem for r in api.intersect_predicates(df, "k", [*conditions, "x = 500"]).collect()] == [2]


# ---- streams


def test_streams(spark, sf):
    events = st.read_events(spark, f"{sf}/events.parquet")
    batch = spark.read.parquet(f"{sf}/events.parquet")
    tumbling = st.run_once(st.window_sets(events), "t_tumbling", "complete").count()
    assert tumbling == batch.select(F.to_date("ts"), "event_type", "user_id").distinct().count()
    assert st.run_once(st.window_sets(events), "t_append", "append").count() <= tumbling  # the last windows stay open
    sliding = st.run_once(st.window_sets(events, "sliding", "2 days", "1 day"), "t_sliding", "complete").count()
    assert sliding > tumbling
    assert st.run_once(st.window_sets(events, "session", gap="6 hours"), "t_session", "complete").count() > 0
    sets = st.run_once(st.stream_sets(events, "40 days"), "t_sets")
    assert sets.count() == batch.select("event_type", "user_id").distinct().count()
    pairs = st.run_once(st.stream_join(events.filter("event_type = 'view'"), events.filter("event_type = 'purchase'"), "6 hours", "30 days"), "t_join").count()
    a, b = batch.filter("event_type = 'view'").alias("a"), batch.filter("event_type = 'purchase'").alias("b")
    assert pairs == a.join(b, F.expr("a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 6 hours")).count()
    stored = spark.createDataFrame([(1,), (2,)], "elem long")
    assert st.run_once(st.stream_probe(events, stored), "t_probe").count() == batch.filter("user_id in (1, 2)").count()
    with pytest.raises(ValueError):
        st.window_sets(events, "weekly")


def test_index_from_a_stream(spark, f1, tmp_path):
    path = f"file://{tmp_path}/index"
    merge = st.merge_index_batch(spark, path, Cfg(m=2))
    small = f1.filter("set_id in ('0', '1', '2')")
    merge(small.filter("elem % 2 = 0"), 0)
    merge(small.filter("elem % 2 = 1 and set_id <> '2'"), 1)
    want = G.build(small.filter("elem % 2 = 0 or set_id <> '2'"), Cfg(m=2)).groups
    got = st.read_index(spark, path)
    assert got.select("set_id", "t", "z", "n", "img_1").exceptAll(want.select("set_id", "t", "z", "n", "img_1")).count() == 0
    assert got.count() == want.count()


def test_members_are_taken_away(spark, f1, tmp_path):
    path = f"file://{tmp_path}/index"
    merge = st.merge_index_batch(spark, path, Cfg(m=2))
    small = f1.filter("set_id in ('0', '1')")
    merge(small, 0)
    merge(small.filter("elem % 3 = 0").withColumn("gone", F.lit(True)), 1)
    want = G.build(small.filter("elem % 3 <> 0"), Cfg(m=2)).groups.select("set_id", "t", "z", "n", "img_1")
    got = st.read_index(spark, path).select("set_id", "t", "z", "n", "img_1")
    assert got.count() == want.count() and got.exceptAll(want).count() == 0


def test_late_events_are_kept_apart(spark, tmp_path):
    path = f"file://{tmp_path}/events"
    split = st.late_policy(path, "1 hour")
    frame = lambda *hours: spark.createDataFrame([(h,) for h in hours], "h int").selectExpr("timestamp '2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, h) as ts", "h")
    split(frame(5, 6, 1), 0)  # nothing is known before the first batch
    split(frame(5, 4, 9), 1)
    split(frame(7, 8, 10), 2)
    split(frame(7, 8, 10), 2)
    read = lambda name: sorted(r.h for r in spark.read.parquet(f"{path}/{name}").collect())
    assert read("late") == [4, 7] and read("on_time") == [1, 5, 5, 6, 8, 9, 10]


def test_stateful_images(spark, sf):
    got = st.run_once(st.image_state(st.read_events(spark, f"{sf}/events.parquet")), "t_state", "update")
    last = got.groupBy("set_id", "z").agg(F.max("n").alias("n"), F.max_by("img", "n").alias("img"))
    counts = {r.set_id: r.n for r in last.groupBy("set_id").agg(F.sum("n").alias("n")).collect()}
    users = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_type").alias("set_id"), F.col("user_id").alias("elem"))
    rows = G.hashed(users, Cfg(m=1)).withColumn("z", F.expr(hashing.prefix_sql("g", 3, Cfg())))
    images = {(r.set_id, r.z): r.img for r in rows.groupBy("set_id", "z").agg(F.expr("bit_or(shiftleft(1L, y_1))").alias("img")).collect()}
    assert {(r.set_id, r.z): r.img for r in last.collect()} == images
    want = {r.event_type: r["count"] for r in spark.read.parquet(f"{sf}/events.parquet").groupBy("event_type").count().collect()}
    assert counts == want


# ---- workloads and timings


def test_controlled_pairs(spark, sf):
    points = [(100, 300, 7), (50, 50, 50), (20, 400, 1)]
    s, q = workloads.controlled(spark, sf, points)
    res = {r.qid: (r.n1, r.nk, r.r) for r in measures.results(s, q).collect()}
    assert res == {0: (100, 300, 7), 1: (50, 50, 50), 2: (20, 400, 1)}


def test_work_falls_as_the_paper_has_it(spark, sf):
    """Kernels' counters: galloping beats merging for uneven sizes; the scan opens few groups where little is common."""
    work = {(r.method, r.qid): r for r in workloads.work_sweep(*workloads.controlled(spark, sf, [(600, 600, 6), (600, 600, 600), (5, 700, 1)]), Cfg(m=4), ("merge", "svs", "scan", "hash")).collect()}
    assert work["svs", 2].comparisons < work["merge", 2].comparisons
    assert work["hash", 2].comparisons < work["merge", 2].comparisons
    assert work["scan", 0].elems_fetched < 0.5 * work["merge", 0].elems_fetched
    assert work["scan", 1].elems_fetched == work["merge", 1].elems_fetched
    assert all(work["scan", i].r == work["merge", i].r for i in range(3))


def test_timing_measures(spark):
    t = measures.timings_frame(spark, [("merge", 0, 2.0), ("scan", 0, 1.0), ("merge", 1, 1.0), ("scan", 1, 4.0)])
    assert {r.method: r.normalised for r in measures.normalise(t).collect()} == {"merge": 1.0, "scan": 2.5 / 1.5}
    assert {r.method: r.share for r in measures.winners(t).collect()} == {"merge": 0.5, "scan": 0.5}
    assert {r.method: r.ratio for r in measures.worst_latency(t, "scan").collect()} == {"merge": 0.5, "scan": 1.0}
    assert {r.method: r.worst_regret for r in measures.regret(t).collect()} == {"merge": 2.0, "scan": 4.0}
    assert {r.method: r.times for r in measures.speedup(t, "scan").collect()} == {"merge": 0.6, "scan": 1.0}
    assert measures.sweep_table(t, "qid").count() == 2
