"""SimHash near-duplicates by a Gray-order hierarchical index.

Every document gets a 64-bit fingerprint of its word shingles. Documents whose fingerprints differ in at most
three bits are linked, and each document learns the smallest doc_id it can reach.

The index is one order and one tree. Each distinct fingerprint is turned by 0, 16, 32 and 48 bits, and every turn is sorted by
Gray rank. In that order fingerprints that share leading bits lie together, and a node of the tree is a run of it, known by the bits
that all its leaves share (mask and pattern). Of four 16-bit blocks a linked pair shares one, so in the turn that puts this block
first the pair lies below one upper node: the one of the first bits. Upper nodes have as many bits as leave them NODE leaves or so, sixteen at most,
so that the tree does the searching at every size of the table; below NODE fingerprints there is one root and one turn. An upper
node of more than PIECE leaves is cut into runs of its Gray order by a range partitioning, each a node of its own, and pairs of these are joined
by the same rule as all others.

The join starts with pairs of upper nodes and descends in pairs of nodes. Bits that both nodes share and their parents did not are
compared once and added to the differences so far; above three the pair of whole groups is dropped. A node whose leaves differ in no more
than three bits is one cluster without any comparison, and pairs of nodes that lie in one cluster already are skipped, so a large group of
near copies costs no all-pairs work. Links leave a task as spanning stars, never as pairs.

Equal texts share a fingerprint and are grouped before anything else, with map-side combining. Clusters are
joined up by alternating star contraction on tables in the shared folder.

Edge cases: null and empty texts have fingerprint zero and are linked like any other; fewer than three words are one
shingle; a row without a doc_id gets the component of its fingerprint, null where no row with it has a doc_id (it then
links nothing); rows with equal doc_id are separate rows of the result; an empty table gives an empty result; very long texts are hashed in pieces of bounded
memory; other columns play no part and pass through ``representatives`` unchanged, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.store import drop_written, free_name, written
from wordset.functions.worker import on_worker
from wordset.plans.sizing import small_side

SHINGLE = 3
DIFFER = 3
HASH_SEED = 42
#: Leaves of an upper node, about, and the most that a task takes as one node.
NODE = 1 << 10
PIECE = 1 << 19
#: Children of a node, and pairs of nodes that a task holds at once.
FANOUT = 4
FRONTIER = 1 << 18

# ---- fingerprints


def fingerprint(text: str | None) -> int:
    words = (text or "").encode().lower().split()  # bytes: only A-Z change, only ASCII white space splits
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) < SHINGLE:
        return xxhash.xxh64_intdigest(joined, HASH_SEED)
    n = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(n + 1) - 1
    starts = (ends - n)[: len(words) - SHINGLE + 1].tolist()
    h = xxhash.xxh64_intdigest
    hashes = np.array([h(joined[a:b], HASH_SEED) for a, b in zip(starts, ends[SHINGLE - 1 :].tolist(), strict=True)], np.uint64)
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 14):  # bounded memory for very long texts
        ones += np.unpackbits(hashes[at : at + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints_of(batches):
    for b in batches:
        texts = b.column("text")
        fp = np.fromiter((fingerprint(t.as_py()) for t in texts), np.uint64, len(texts))
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fp.view(np.int64))], ["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """``doc_id, fp`` (the 64 bits as a signed long) of every row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(on_worker(__name__, "fingerprints_of"), "doc_id long, fp long")


# ---- the index over the fingerprints of many keys


def _spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For counts 2,3: owners 0,0,1,1,1 and places 0,1,0,1,2."""
    owner = np.repeat(np.arange(len(counts)), counts)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)


class GrayTree:
    """Trees over fingerprints that are sorted by group and Gray rank; level 0 are the leaves.

    ``pruned`` counts the pairs of whole groups that accumulated differences dropped, ``compared`` the pairs of leaves that were looked at."""

    def __init__(self, group: np.ndarray, fp: np.ndarray):
        self.fp = fp
        self.pruned = self.compared = 0
        starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        sizes = np.diff(np.r_[starts, len(fp)])
        self.every, self.some = [fp], [fp]
        self.first, self.n_kids = [np.arange(len(fp))], [np.zeros(len(fp), np.int64)]
        self.row = [np.arange(len(fp))]  # the first leaf below a node
        while len(starts) and sizes.max(initial=1) > 1:
            n = -(-sizes // FANOUT)
            owner, place = _spread(n)
            kids = starts[owner] + place * FANOUT
            self.n_kids.append(np.minimum(FANOUT, sizes[owner] - place * FANOUT))
            self.first.append(kids)
            self.every.append(np.bitwise_and.reduceat(self.every[-1], kids))
            self.some.append(np.bitwise_or.reduceat(self.some[-1], kids))
            self.row.append(self.row[-1][kids])
            starts, sizes = np.cumsum(n) - n, n
        self.label = np.arange(len(fp))
        self._lines()

    def _lines(self) -> None:
        """Links what needs no search: nodes of leaves that all lie within DIFFER bits, and Gray neighbours."""
        level = len(self.row)
        for k in range(1, level):
            close = np.bitwise_count(self.every[k] ^ self.some[k]) <= DIFFER
            a = np.flatnonzero(close)
            owner, place = _spread(self.n_kids[k][a])
            self._link(self.row[k][a][owner], self.row[k - 1][self.first[k][a][owner] + place])

    def _find(self, x: np.ndarray) -> np.ndarray:
        while True:
            y = self.label[x]
            if np.array_equal(y, x):
                return x
            x = y

    def _link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self._find(a), self._find(b)
            a, b = np.minimum(a, b), np.maximum(a, b)
            apart = a != b
            a, b = a[apart], b[apart]
            np.minimum.at(self.label, b, a)
        # short paths for later finds
        self.label = self.label[self.label]

    def _uniform(self) -> list[np.ndarray]:
        """By level: the cluster that all leaves of a node lie in, or -1."""
        root = self._find(np.arange(len(self.fp)))
        out = [root]
        for k in range(1, len(self.row)):
            low, high = np.minimum.reduceat(out[-1], self.first[k]), np.maximum.reduceat(out[-1], self.first[k])
            out.append(np.where(low == high, low, -1))
        return out

    def clusters(self, left: np.ndarray | None = None, right: np.ndarray | None = None) -> np.ndarray:
        """For each leaf the first leaf of its cluster, from the links within each group, or between the groups of given numbers ``left`` and ``right``."""
        top = len(self.row) - 1
        if left is None:
            left = right = np.arange(len(self.row[top]))
        if not top:
            self._link(*(x[np.bitwise_count(self.fp[left] ^ self.fp[right]) <= DIFFER] for x in (left, right)))
            return self._find(np.arange(len(self.fp)))
        shared = ~(self.every[top][left] ^ self.some[top][left]) & ~(self.every[top][right] ^ self.some[top][right])
        stack = [(top, left, right, shared, np.bitwise_count((self.every[top][left] ^ self.every[top][right]) & shared).astype(np.int64))]
        same = self._uniform()
        while stack:
            level, a, b, seen, diff = stack.pop()
            if len(a) > FRONTIER:
                for at in range(0, len(a), FRONTIER):
                    part = slice(at, at + FRONTIER)
                    stack.append((level, a[part], b[part], seen[part], diff[part]))
                continue
            one = (same[level][a] >= 0) & (same[level][a] == same[level][b])
            a, b, seen, diff = (x[~one] for x in (a, b, seen, diff))
            if not len(a):
                continue
            if level == 0:
                self._link(a, b)  # diff is exact here: leaves share all bits with themselves
                same = self._uniform()
                continue
            na, nb = self.n_kids[level][a], self.n_kids[level][b]
            # a few pairs at a time: each has up to FANOUT^2 pairs of children
            for part in np.array_split(np.arange(len(a)), max(1, len(a) * FANOUT * FANOUT // (4 * FRONTIER))):
                owner, place = _spread(na[part] * nb[part])
                at = part[owner]
                x = self.first[level][a[at]] + place // nb[at]
                y = self.first[level][b[at]] + place % nb[at]
                keep = x <= y if level > 1 else x < y
                at, x, y = at[keep], x[keep], y[keep]
                k = level - 1
                shared = ~(self.every[k][x] ^ self.some[k][x]) & ~(self.every[k][y] ^ self.some[k][y])
                new = shared & ~seen[at]
                d = diff[at] + np.bitwise_count((self.every[k][x] ^ self.every[k][y]) & new)
                near = d <= DIFFER
                if k:
                    self.pruned += len(near) - int(near.sum())
                else:
                    self.compared += len(near)
                if near.any():
                    stack.append((k, x[near], y[near], shared[near], d[near]))
        return self._find(np.arange(len(self.fp)))


def cut_nodes(batches):
    """Rows ``key, fp, doc`` in Gray order -> the same with ``node``, the run of a key within this partition."""
    from pyspark import TaskContext

    base, made, last, held = (TaskContext.get().partitionId() + 1) << 32, 0, None, 0
    for b in batches:
        if not b.num_rows:
            continue
        key = b.column("key").to_numpy()
        starts = np.flatnonzero(np.r_[last is None or key[0] != last or held >= PIECE, key[1:] != key[:-1]])
        node = np.zeros(len(key), np.int64)
        node[starts] = 1
        node = made + np.cumsum(node)
        made, last = int(node[-1]), key[-1]
        held = len(key) - int(starts[-1]) if len(starts) else held + len(key)
        yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(base + node), b.column("fp"), b.column("doc")], ["key", "node", "fp", "doc"])


def link_nodes(batches):
    """Rows ``x, y, side, fp, doc`` sorted by the pair of nodes x and y, side and Gray rank -> edges ``a, b`` of docs: each cluster as a star.

    A node met with itself has one side; of two different ones only links across are sought."""
    held: list[np.ndarray] = []

    def solved(x, y, side, fp, doc):
        head = np.r_[True, (x[1:] != x[:-1]) | (y[1:] != y[:-1]) | (side[1:] != side[:-1])]
        left = np.flatnonzero(side[head] == 0)
        tree = GrayTree(np.cumsum(head), fp.view(np.uint64))
        label = tree.clusters(left, left + (x != y)[head][left])
        order = np.lexsort((doc, label))
        lab, d = label[order], doc[order]
        head = np.r_[True, lab[1:] != lab[:-1]]
        centre = d[np.flatnonzero(head)[np.cumsum(head) - 1]]
        out = centre != d
        return pa.RecordBatch.from_arrays([pa.array(centre[out]), pa.array(d[out])], ["a", "b"]) if out.any() else None

    for b in batches:
        if not b.num_rows:
            continue
        now = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("x", "y", "side", "fp", "doc")])
        held.append(now)
        if (held[0][:2, 0] == now[:2, -1]).all():
            continue  # one pair so far
        rows = np.concatenate(held, axis=1)
        cut = int(np.flatnonzero((rows[:2] != rows[:2, -1:]).any(0))[-1]) + 1  # the last pair may go on
        held = [rows[:, cut:]]
        if (out := solved(*rows[:, :cut])) is not None:
            yield out
    if held and (out := solved(*np.concatenate(held, axis=1))) is not None:
        yield out


def _gray_rank(fp):
    """The place of fp in Gray order, as a signed long that sorts like the unsigned one."""
    for s in (1, 2, 4, 8, 16, 32):
        fp = fp.bitwiseXOR(F.shiftrightunsigned(fp, s))
    return fp.bitwiseXOR(F.lit(-(1 << 63)))


def upper_bits(n: int) -> int:
    """First bits of an upper node among n fingerprints."""
    return min(16, max(0, (n - 1).bit_length() - (NODE.bit_length() - 1))) if n else 0


def turned(distinct: DataFrame, bits: int) -> DataFrame:
    """``key, fp, doc, gray``: each fingerprint in all turns, the number of its upper node (turn and first bits) and its Gray rank."""
    fp = F.col("fp")
    turns = [fp if not i else F.shiftleft(fp, 16 * i).bitwiseOR(F.shiftrightunsigned(fp, 64 - 16 * i)) for i in range(4 if bits else 1)]
    first = F.shiftrightunsigned("fp", 64 - bits) if bits else F.lit(0)
    rows = distinct.select(F.posexplode(F.array(*turns)).alias("turn", "fp"), "doc")
    return rows.select(F.shiftleft(F.col("turn").cast("long"), 16).bitwiseOR(first).alias("key"), "fp", "doc", _gray_rank(fp).alias("gray"))


def cut_large(rows: DataFrame) -> DataFrame:
    """``x, y, side, fp, doc, gray`` of upper nodes that are too large for a task: their runs in Gray order as nodes, in all pairs whose shared bits
    differ in DIFFER places at most. No task sorts an upper node."""
    dealt = rows.repartitionByRange("key", "gray").sortWithinPartitions("key", "gray").select("key", "fp", "doc")
    rows = written(dealt.mapInArrow(on_worker(__name__, "cut_nodes"), "key long, node long, fp long, doc long"), "gray-runs")
    nodes = written(rows.groupBy("key", "node").agg(F.bit_and("fp").alias("every"), F.bit_or("fp").alias("some")), "nodes")
    a, b = (nodes.select("key", *(F.col(c).alias(f"{s}_{c}") for c in ("node", "every", "some"))) for s in "xy")
    apart = F.bit_count(F.expr("~(x_every ^ x_some) & ~(y_every ^ y_some) & (x_every ^ y_every)"))
    pairs = a.join(b, "key").filter((F.col("x_node") <= F.col("y_node")) & (apart <= DIFFER)).select(F.col("x_node").alias("x"), F.col("y_node").alias("y"))
    ends = pairs.select("x", "y", F.explode(F.array_distinct(F.array("x", "y"))).alias("node"))
    return rows.join(ends, "node").select("x", "y", (F.col("node") != F.col("x")).cast("int").alias("side"), "fp", "doc", _gray_rank(F.col("fp")).alias("gray"))


def links(distinct: DataFrame, piece: int = PIECE) -> DataFrame:
    """Edges ``a, b`` between the ``doc``s of ``distinct (fp, doc)`` that connect just what lies within DIFFER bits."""
    rows = turned(distinct, upper_bits(distinct.count()))
    large = written(rows.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > piece).select("key"), "large-nodes")
    some = bool(large.head(1))
    whole = rows.join(small_side(large), "key", "left_anti") if some else rows
    dealt = whole.select(F.col("key").alias("x"), F.col("key").alias("y"), F.lit(0).alias("side"), "fp", "doc", "gray")
    if some:
        # runs are numbered from 2^32 on, upper nodes below 2^18
        dealt = dealt.unionByName(cut_large(rows.join(small_side(large), "key", "left_semi")))
    dealt = dealt.repartition("x", "y").sortWithinPartitions("x", "y", "side", "gray").select("x", "y", "side", "fp", "doc")
    return dealt.mapInArrow(on_worker(__name__, "link_nodes"), "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """``node, component`` of all nodes of the edges: the smallest node of each component, by star contraction.

    A round points every node at the smallest of its neighbours, first its larger ones and then the rest; stars are
    all that is left in the end. Neighbourhoods are never gathered: only their minimum is."""
    now = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")), "edges")
    mark = None
    while True:
        both = now.select("u", "v").union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        after = written(small.filter("u > v").distinct(), "edges")
        got = after.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        drop_written(now)
        now = after
        if got == mark:
            return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
        mark = got


def near_duplicates(docs: DataFrame) -> DataFrame:
    """One row per document: ``doc_id, fingerprint`` (16 hex digits), ``component_id``."""
    rows = written(fingerprints(docs), "fingerprints")
    distinct = written(rows.groupBy("fp").agg(F.min("doc_id").alias("doc")), "distinct")
    stars = components(links(distinct.filter("doc is not null")))
    label = distinct.join(stars, F.col("doc") == F.col("node"), "left").select(F.col("fp").alias("l_fp"), F.coalesce("component", "doc").alias("component_id"))
    out = rows.join(label, F.col("fp") == F.col("l_fp"), "left")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def representatives(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay: of every component the document with the smallest doc_id.

    Rows are told apart by doc_id: rows that share one stay if any of them is to stay. A null doc_id stays."""
    seen = near_duplicates(docs)
    kept = F.max(F.col("doc_id") == F.col("component_id")).alias("kept")
    gone = written(seen.groupBy("doc_id").agg(kept).filter("doc_id is not null and not kept").select(F.col("doc_id").alias(name := free_name(docs, "gone"))), "gone")
    return docs.join(gone, F.col("doc_id") == F.col(name), "left_anti")
