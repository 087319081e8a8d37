"""All methods and baselines on many small set systems against Python's sets."""

import random

import pytest

from wordset.config import Cfg
from wordset.operators import baselines, blocks, fixed, kernels, prefix, probe, scan
from wordset.operators import groups as G

SYSTEMS = 40


def systems():
    r = random.Random(3)
    sets, queries = {}, []
    for s in range(SYSTEMS):
        universe = r.choice([20, 100, 1000, 1 << 31])
        names = [f"{s}.{i}" for i in range(4)]
        for i, n in enumerate(names):
            size = min(universe, r.choice([0, 1, 2, 7, 8, 9, 40, 130]))
            sets[n] = set(r.sample(range(universe), size)) | ({0, universe - 1} if r.random() < 0.3 else set())
            if i and r.random() < 0.3:  # nested and equal sets
                sets[n] |= sets[names[i - 1]]
        for k in (1, 2, 2, 3, 4):
            queries.append(r.sample(names, k))
        queries += [[names[0], names[0]], [names[0], "nowhere"], [names[1], names[1], names[2]]]
    return sets, queries


SETS, QUERIES = systems()
WANT = sorted((i, x) for i, q in enumerate(QUERIES) if all(s in SETS for s in q) for x in set.intersection(*(SETS[s] for s in q)))
TWO = [(i, q) for i, q in enumerate(QUERIES) if len(set(q)) <= 2]
WANT2 = [w for w in WANT if len(set(QUERIES[w[0]])) <= 2]


@pytest.fixture(scope="module")
def frame(spark):
    return spark.createDataFrame([(n, x) for n, s in SETS.items() for x in s], "set_id string, elem long").cache()


@pytest.fixture(scope="module")
def asked(spark):
    return spark.createDataFrame(list(enumerate(QUERIES)), "qid long, set_ids array<string>").cache()


@pytest.fixture(scope="module")
def asked2(spark):
    return spark.createDataFrame(TWO, "qid long, set_ids array<string>").cache()


def rows(df):
    got = [(r.qid, r.elem) for r in df.collect()]
    assert len(got) == len(set(got))
    return sorted(got)


CONFIGS = [Cfg(m=1), Cfg(m=4), Cfg(w=4, m=2), Cfg(w=16, m=8), Cfg(w=256, m=2), Cfg(g="xx64", h="xx64", m=2), Cfg(h="perm", m=2), Cfg(g="hash", m=1)]


@pytest.mark.parametrize("cfg", CONFIGS, ids=lambda c: f"{c.g}-{c.h}-w{c.w}-m{c.m}")
def test_scan(frame, asked, cfg):
    assert rows(scan.intersect(G.build(frame, cfg), asked)) == WANT


@pytest.mark.parametrize("memo, finest", [(True, True), (True, False), (False, True)])
def test_prefix(frame, asked, memo, finest):
    assert rows(scan.intersect_by_bits(prefix.build(frame, Cfg()), asked, memo, finest)) == WANT


def test_prefix_wide_words(frame, asked):
    assert rows(scan.intersect_by_bits(prefix.build(frame, Cfg(w=256)), asked)) == WANT


@pytest.mark.parametrize("mode", ["same_count", "same_size"])
def test_pairs(frame, asked2, mode):
    assert rows(prefix.intersect_pairs(frame, asked2, Cfg(), mode)) == WANT2


@pytest.mark.parametrize("mode", ["same_count", "same_size"])
def test_multires(frame, asked2, mode):
    e, lv = prefix.build_multires(frame, Cfg())
    assert rows(prefix.intersect_multires(e, lv, frame, asked2, Cfg(), mode)) == WANT2


@pytest.mark.parametrize("sizes", [None, "optimal", (2, 16)])
def test_fixed(frame, asked2, sizes):
    assert rows(fixed.intersect(frame, asked2, Cfg(), sizes)) == WANT2


def test_fixed_refuses_three_sets(frame, asked):
    with pytest.raises(ValueError, match="3 sets|4 sets"):
        fixed.intersect(frame, asked, Cfg())


@pytest.mark.parametrize("how", ["join", "broadcast"])
def test_probe(frame, asked, how):
    assert rows(probe.intersect(frame, asked, Cfg(), how)) == WANT


@pytest.mark.parametrize("method", ["merge", "counting", "hashing_", "smallest_first", "spark_arrays"])
def test_relational_baselines(frame, asked, method):
    assert rows(getattr(baselines, method)(frame, asked)) == WANT


@pytest.mark.parametrize("method", ["lookup", "packed_codes"])
def test_bucketed_baselines(frame, asked, method):
    assert rows(getattr(baselines, method)(frame, asked, Cfg(bucket=4))) == WANT


@pytest.mark.parametrize("method", sorted(kernels.METHODS))
@pytest.mark.parametrize("size", [14, 2])
def test_kernels(frame, asked, method, size):
    assert rows(blocks.intersect(frame, asked, Cfg(bucket=4), method, block_bits=size, m=2)) == WANT


@pytest.mark.parametrize("codec", ["gamma", "delta", "lowbits"])
@pytest.mark.parametrize("method", ["scan", "merge", "lookup"])
def test_coded_blocks(frame, asked, method, codec):
    assert rows(blocks.intersect(frame, asked, Cfg(), method, codec=codec, m=1)) == WANT


@pytest.mark.parametrize("method", ["scan", "fixed"])
def test_bags(spark, method):
    from wordset.plans import api

    a, b = [1, 1, 1, 2, 5, 5], [1, 1, 2, 2, 2, 7]
    raw = spark.createDataFrame([("a", x) for x in a] + [("b", x) for x in b] + [("a", None), (None, 3)], "s string, e long")
    ix = api.build_index(api.from_table(raw, "s", "e", bag=True), Cfg(), bag=True)
    assert sorted((r.elem, r.freq) for r in api.intersect(ix, ["a", "b"], method).collect()) == [(1, 2), (2, 1)]


def test_big_elements_need_a_wide_order(spark):
    xs = [-(1 << 63), -5, -1, 0, 1, (1 << 63) - 1]
    sets = spark.createDataFrame([("a", x) for x in xs] + [("b", x) for x in xs[1:]], "set_id string, elem long")
    q = spark.createDataFrame([(0, ["a", "b"])], "qid long, set_ids array<string>")
    assert rows(scan.intersect(G.build(sets, Cfg(g="xx64", h="xx64")), q)) == [(0, x) for x in xs[1:]]


@pytest.mark.parametrize("how", ["asof", "bins"])
def test_fixed_runs_on_any_universe(spark, how, monkeypatch):
    """Members from end to end of the 64-bit range, sparse and dense beside each other, in bins of a few groups."""
    monkeypatch.setattr(fixed, "BIN", 3)
    r = random.Random(5)
    dense = list(range(10_000, 10_400))
    a = set(r.sample(dense, 200)) | {0, 1 << 62, -(1 << 62), (1 << 63) - 1}
    b = set(r.sample(dense, 150)) | {0, 1 << 61, 1 << 62, -(1 << 63)} | {r.randrange(1 << 60) for _ in range(40)}
    sets = spark.createDataFrame([("a", x) for x in a] + [("b", x) for x in b], "set_id string, elem long")
    q = spark.createDataFrame([(0, ["a", "b"]), (1, ["b", "a"])], "qid long, set_ids array<string>")
    cfg = Cfg(g="xx64", h="xx64")
    assert rows(fixed.intersect(sets, q, cfg, how=how)) == sorted((i, x) for i in (0, 1) for x in a & b)
    groups = fixed.query_groups(sets, q, cfg)
    pairs = lambda how: sorted(map(tuple, fixed.overlaps(groups, how).collect()))
    assert pairs(how) == pairs("theta")
