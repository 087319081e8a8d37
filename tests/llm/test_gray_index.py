"""The Gray-order tree is what searches: it prunes whole groups, and cutting large nodes loses nothing."""

import random

import numpy as np
import pytest

from tests.llm.test_operators import plain_components
from wordset.llm import near_dedup


def gray(fps):
    g = np.array(fps, np.uint64)
    for s in (1, 2, 4, 8, 16, 32):
        g ^= g >> np.uint64(s)
    return np.array(fps, np.uint64)[np.argsort(g)]


def planted(seed, n, families):
    r = random.Random(seed)
    fps = {r.getrandbits(64) for _ in range(n)}
    for f in r.sample(sorted(fps), families):
        fps |= {f ^ sum(1 << b for b in r.sample(range(64), r.randint(1, 4))) for _ in range(4)}
    return sorted(fps)


def frame(spark, fps):
    return spark.createDataFrame([(f - (1 << 64) if f >> 63 else f, i) for i, f in enumerate(fps)], "fp long, doc long")


def test_whole_groups_are_pruned():
    f = gray(planted(5, 6000, 300))
    tree = near_dedup.GrayTree(np.zeros(len(f), np.int64), f)
    label = tree.clusters()
    differ = np.bitwise_count(f[:, None] ^ f[None, :]) <= 3
    a, b = np.nonzero(np.triu(differ, 1))
    assert len(a) > 500
    assert (label[a] == label[b]).all()
    for x in np.unique(label):  # nothing is joined without a chain of links
        members = np.flatnonzero(label == x)
        reached, fresh = {members[0]}, [members[0]]
        while fresh:
            fresh = [y for y in np.flatnonzero(differ[fresh].any(0)) if y not in reached]
            reached.update(fresh)
        assert reached == set(members)
    pairs = len(f) * (len(f) - 1) // 2
    assert tree.pruned > 10_000  # pairs of whole groups, dropped by accumulated differences
    assert tree.compared < pairs / 6


def test_pairs_across_two_nodes():
    f = gray(planted(6, 800, 100))
    side = (np.arange(len(f)) >= len(f) // 2).astype(np.int64)
    tree = near_dedup.GrayTree(side, f)
    label = tree.clusters(np.array([0]), np.array([1]))
    differ = np.bitwise_count(f[:, None] ^ f[None, :]) <= 3
    a, b = np.nonzero(differ & (side[:, None] < side[None, :]))
    assert len(a) and (label[a] == label[b]).all()


@pytest.mark.parametrize("piece", [1 << 19, 40])
def test_large_upper_nodes_are_cut_without_loss(spark, piece):
    r = random.Random(9)
    low = sorted({(0xABCD << 48) ^ r.getrandbits(22) << 20 for _ in range(500)} | {r.getrandbits(64) for _ in range(1500)})
    fps = sorted({f ^ sum(1 << b for b in r.sample(range(64), r.randint(0, 3))) for f in low for _ in range(2)})
    got = {x.node: x.component for x in near_dedup.components(near_dedup.links(frame(spark, fps), piece)).collect()}
    assert [got.get(i, i) for i in range(len(fps))] == plain_components(fps, list(range(len(fps))))


def test_upper_nodes_follow_the_table():
    assert [near_dedup.upper_bits(n) for n in (0, 1, 1024, 1025, 10**6, 10**11)] == [0, 0, 0, 1, 10, 16]
