"""Cells: what all sets of a batch hold below one prefix of the common order, so that a large batch sends every member once.

A plan that deals members by query sends a frequent set once for each query that names it: ten thousand queries over the terms of a
corpus make fifty rows of every member. Here members are dealt by the leading bits of their place, whole cells meet in a worker,
and all queries of the batch run over a cell one after the other, on blocks and tables that are made once for the cell.
"""

from __future__ import annotations

import time
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import codes, hashing
from wordset.functions.store import written
from wordset.functions.worker import on_worker
from wordset.operators import blocks, kernels
from wordset.operators.groups import query_sets, set_stats
from wordset.plans.sizing import small_side

#: Members of a cell, about, as a power of two; smaller ones down to FEWER make up to 2^SPREAD cells of a small collection.
CELL_BITS, FEWER, SPREAD = 20, 16, 4
#: Queries that one pass over the cells answers; a larger batch takes several.
BATCH = 50_000
#: Words of all bit maps of a cell, at most; where sets are many and thin, queries merge members instead.
MAP_WORDS = 1 << 22


def cut_of(members: int, larger: int = 0) -> int:
    """Leading bits of a cell; of one ``larger`` by so many bits."""
    return max(hashing.bit_length(-(-members >> CELL_BITS + larger) if members else 1), min(SPREAD, hashing.bit_length(max(1, members >> FEWER))))


def _images_needed(cfg: Cfg) -> None:
    if cfg.g != "mulshift" or cfg.h != "cw31" or cfg.words > 1:
        raise ValueError("the images of cells are hashed by mulshift and cw31 into one word")


def _run(sets: DataFrame, queries: DataFrame, cfg: Cfg, kernel: str, schema: str, *how, whole: bool = False, larger: int = 0) -> DataFrame:
    """What the worker's ``kernel`` returns for all cells, of all passes; ``sets`` are those that the queries name, stored.

    Members come as their places, or as themselves under an order of 64 bits. ``whole``: a group of a set that is cut by fewer bits than cells
    are goes to all cells below its prefix; these groups have about root(w) members, so a cell gets so many of a set that is smaller than that."""
    spark = sets.sparkSession
    numbers = set_stats(sets).select("set_id", "n", F.monotonically_increasing_id().alias("no"))
    stats = written(numbers.withColumn("t", F.expr(hashing.t_scan_sql("n", cfg)).cast("int")), "set-numbers")
    bits = cut_of(stats.agg(F.sum("n")).first()[0] or 0, larger)
    rows = sets.join(small_side(stats.select("set_id", "no", "t")), "set_id").select("no", "t", "elem", hashing.g("elem", cfg).alias("g"))
    cell = F.expr(hashing.prefix_sql("g", bits, cfg))
    value = F.col("elem" if cfg.universe_bits == 64 else "g").alias("v")
    if whole:
        first = F.expr(f"shiftleft({hashing.prefix_sql('g', 't', cfg)}, greatest(0, {bits} - t))")
        cell = F.explode(F.when(F.col("t") < bits, F.sequence(first, first + F.expr(f"shiftleft(1L, greatest(0, {bits} - t)) - 1"))).otherwise(F.array(cell)))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.select(cell.alias("c"), "no", value).repartitionById(parts, (F.col("c") % parts).cast("int")).sortWithinPartitions("c")
    asked = query_sets(queries, stats.drop("t")).join(small_side(stats.select("set_id", "no")), "set_id")
    asked = written(asked.groupBy("qid").agg(F.sort_array(F.collect_list(F.struct("rank", "no", "n"))).alias("sets")), "asked")
    passes = max(1, -(-asked.count() // BATCH))
    if passes > 1:
        dealt = written(dealt, "cells").repartitionById(parts, (F.col("c") % parts).cast("int")).sortWithinPartitions("c")
    out = None
    for i in range(passes):
        batch = _batch(asked.filter(F.pmod(F.xxhash64("qid"), F.lit(passes)) == i))
        one = dealt.mapInArrow(on_worker(__name__, kernel, batch, bits, cfg, *how), schema)
        out = one if out is None else out.unionByName(one)
    return out


def _batch(asked: DataFrame) -> tuple[np.ndarray, ...]:
    """Queries as arrays: their ids, where each begins in the list of places, places in the list of sets, numbers and sizes of these."""
    t = asked.toArrow()
    lists = t["sets"].combine_chunks()
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
    no, n = (lists.flatten().field(c).to_numpy(zero_copy_only=False) for c in ("no", "n"))
    nos, first, at = np.unique(no, return_index=True, return_inverse=True)
    starts = np.r_[0, np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))].astype(np.int64)
    return t["qid"].to_numpy(), starts, at.astype(np.int64), nos, n[first]


# ---- on the worker


def _by_cell(batches):
    """``c, no, v`` of one cell after the other; rows come in the order of c."""
    now, held = None, []
    for b in batches:
        c, no, v = (b[x].to_numpy() for x in ("c", "no", "v"))
        edges = np.r_[np.flatnonzero(np.r_[True, c[1:] != c[:-1]]), len(c)] if len(c) else []
        for s, e in zip(edges[:-1], edges[1:], strict=True):
            if held and c[s] != now:
                yield now, *map(np.concatenate, zip(*held, strict=True))
                held = []
            now = int(c[s])
            held.append((no[s:e], v[s:e]))
    if held:
        yield now, *map(np.concatenate, zip(*held, strict=True))


class Cell:
    """The sets of a batch below one prefix; members lie set by set in the order of their places."""

    def __init__(self, c: int, no: np.ndarray, v: np.ndarray, batch: tuple, bits: int, cfg: Cfg, m: int = 1, whole: bool = False):
        _, self.starts, self.at, nos, self.n = batch
        self.c, self.bits, self.cfg, self.m, self.whole = c, bits, cfg, m, whole
        at = np.searchsorted(nos, no)
        named = at < len(nos)
        named[named] = nos[at[named]] == no[named]  # a set is not in the batch if all its queries name an unknown one too
        at, v = at[named], v[named]
        if cfg.universe_bits == 64:
            order = np.lexsort((v, at))
            self.owner, self.g = at[order], v[order]
        else:
            key = np.sort(at.astype(np.uint64) << np.uint64(32) | v.astype(np.uint64))
            self.owner, self.g = (key >> np.uint64(32)).astype(np.int64), key & np.uint64((1 << 32) - 1)
        self.ends = np.searchsorted(self.owner, np.arange(len(nos) + 1))
        self._made: dict = {}

    @cached_property
    def queries(self) -> np.ndarray:
        """Places of the queries all of whose sets have members here."""
        here = np.diff(self.ends)[self.at] > 0
        return np.flatnonzero(np.logical_and.reduceat(here, self.starts[:-1])) if len(self.at) else self.at

    def sets_of(self, q: int) -> list[int]:
        return self.at[self.starts[q] : self.starts[q + 1]].tolist()

    @cached_property
    def ranks(self) -> np.ndarray:
        """Every member's place among the different members of the cell."""
        return np.unique(self.g, return_inverse=True)[1]

    @cached_property
    def width(self) -> int:
        return int(self.ranks.max()) + 1 if len(self.ranks) else 0

    @cached_property
    def t(self) -> np.ndarray:
        """Bits that each set is grouped by."""
        t = np.array([hashing.t_scan(n, self.cfg) for n in self.n.tolist()], np.int64)
        return t if self.whole else np.maximum(t, self.bits)

    @cached_property
    def groups(self) -> tuple[np.ndarray, ...]:
        """Of all sets: prefixes, first members, sizes and images of groups, and where each set's groups begin."""
        z = self.g >> (self.cfg.universe_bits - self.t[self.owner]).astype(np.uint64)
        first = np.flatnonzero(np.r_[True, (self.owner[1:] != self.owner[:-1]) | (z[1:] != z[:-1])][: len(z)])
        elem = hashing.g_inverse_array(pa.array(self.g.view(np.int64)), self.cfg).to_numpy()
        imgs = np.empty((len(first), self.m), np.uint64)
        for j in range(self.m):
            imgs[:, j] = np.bitwise_or.reduceat(np.uint64(1) << hashing.h_array(elem, j + 1, self.cfg).astype(np.uint64), first) if len(first) else 0
        return z[first], first, np.diff(np.r_[first, len(z)]), imgs, np.searchsorted(self.owner[first], np.arange(len(self.ends)))

    def block(self, s: int, codec: str = "plain") -> tuple[kernels.Block, int]:
        """A set's block, and the nanoseconds that decoding it took; made once."""
        if (s, codec) in self._made:
            return self._made[s, codec]
        zs, _, ns, imgs, starts = self.groups
        i, j = starts[s], starts[s + 1]
        t, zs, ns, imgs, g, took = int(self.t[s]), zs[i:j], ns[i:j], imgs[i:j], self.g[self.ends[s] : self.ends[s + 1]], 0
        if codec != "plain":
            width = self.cfg.universe_bits - t
            low = g & np.uint64((1 << width) - 1)
            payload = codes.pack_low(low, width) if codec == "lowbits" else codes.pack_codes(codes.gaps_of(low, ns), codec)
            head, z0 = blocks.encode_sizes(zs.astype(np.int64), ns), int(zs[0])
            t0 = time.perf_counter_ns()
            zs, ns = blocks.decode_sizes(head, z0, len(imgs))
            g = blocks.decode_members(payload, t, zs, ns, self.cfg, codec)
            took = time.perf_counter_ns() - t0
        made = kernels.Block(t, np.asarray(zs, np.int64).view(np.uint64), np.asarray(ns, np.int64), imgs, g)
        return self._made.setdefault((s, codec), (made, took))

    @cached_property
    def bitmaps(self) -> np.ndarray:
        """A row of bits for every set, over the different members of the cell."""
        words = -(-self.width // 64)
        out = np.zeros((len(self.n), words), np.uint64)
        np.bitwise_or.at(out.reshape(-1), self.owner * words + (self.ranks >> 6), np.uint64(1) << (self.ranks & 63).astype(np.uint64))
        return out


def count_common(batches, batch: tuple, bits: int, cfg: Cfg):
    """Members that all sets of a query have, by bit maps of the cell."""
    qids, starts, at, _, n = batch
    total = np.zeros(len(qids), np.int64)
    k = np.diff(starts)
    for c, no, v in _by_cell(batches):
        cell = Cell(c, no, v, batch, bits, cfg)
        if len(n) * -(-cell.width // 64) > MAP_WORDS:
            for q in cell.queries.tolist():
                now, *more = sorted((cell.g[cell.ends[s] : cell.ends[s + 1]] for s in cell.sets_of(q)), key=len)
                for x in more:
                    now = np.intersect1d(now, x, assume_unique=True)
                total[q] += len(now)
            continue
        maps = cell.bitmaps
        for size in np.unique(k[cell.queries]).tolist():
            mine = cell.queries[k[cell.queries] == size]
            step = max(1, MAP_WORDS // (maps.shape[1] or 1) // 4)
            for i in range(0, len(mine), step):
                some = mine[i : i + step]
                both = maps[at[starts[some]]]
                for j in range(1, size):
                    both &= maps[at[starts[some] + j]]
                total[some] += np.bitwise_count(both).sum(1, dtype=np.int64)
    got = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(qids[got], pa.int64()), pa.array(total[got], pa.int64())], ["qid", "r"])


def run_methods(batches, batch: tuple, bits: int, cfg: Cfg, methods: tuple[str, ...], m: int, codecs: tuple[str, ...]):
    """The kernels of all methods over the blocks of all codings: results and nanoseconds by query."""
    qids = batch[0]
    r, nanos = (np.zeros((len(codecs), len(methods), len(qids)), np.int64) for _ in range(2))
    for c, no, v in _by_cell(batches):
        cell = Cell(c, no, v, batch, bits, cfg, m)
        for i, codec in enumerate(codecs):
            for q in cell.queries.tolist():
                held, took = zip(*(cell.block(s, codec) for s in cell.sets_of(q)), strict=True)
                for j, method in enumerate(methods):
                    t0 = time.perf_counter_ns()
                    common, _ = kernels.METHODS[method](held, cfg)
                    nanos[i, j, q] += time.perf_counter_ns() - t0 + sum(took)
                    r[i, j, q] += len(common)
            cell._made.clear()  # of one coding at a time
    for i, codec in enumerate(codecs):
        for j, method in enumerate(methods):
            got = np.flatnonzero(nanos[i, j])
            yield pa.RecordBatch.from_arrays([pa.array([codec] * len(got), pa.string()), pa.array([method] * len(got), pa.string()), *(pa.array(x[got], pa.int64()) for x in (qids, r[i, j], nanos[i, j]))], ["codec", "method", "qid", "r", "nanos"])


def filter_pairs(batches, batch: tuple, bits: int, cfg: Cfg, m: int):
    """Pairs of groups that two-set queries align, those without a common member, and of these the ones that the first j images prove so."""
    _, starts, at, _, _ = batch
    empty, filtered = 0, np.zeros(m, np.int64)
    for c, no, v in _by_cell(batches):
        cell = Cell(c, no, v, batch, bits, cfg, m, whole=True)
        zs, first, _, imgs, begin = cell.groups
        ranks, here = cell.ranks, np.zeros(cell.width, bool)
        for q in cell.queries.tolist():
            if starts[q + 1] - starts[q] != 2:
                continue
            a, b = at[starts[q]], at[starts[q] + 1]
            if c & ((1 << max(0, bits - int(cell.t[b]))) - 1):
                continue  # the pair lies in several cells and is counted in the first
            mine = ranks[cell.ends[a] : cell.ends[a + 1]]
            here[mine] = True
            common = np.logical_or.reduceat(here[ranks[cell.ends[b] : cell.ends[b + 1]]], first[begin[b] : begin[b + 1]] - cell.ends[b])
            here[mine] = False
            void = np.flatnonzero(~common) + begin[b]
            za, facing = zs[begin[a] : begin[a + 1]], zs[void] >> np.uint64(cell.t[b] - cell.t[a])
            place = np.searchsorted(za, facing)
            met = place < len(za)
            met[met] = za[place[met]] == facing[met]
            hit = (imgs[begin[a] + place[met]] & imgs[void[met]]) != 0
            empty += len(hit)
            filtered += len(hit) - np.logical_and.accumulate(hit, axis=1).sum(0)
    yield pa.RecordBatch.from_arrays([pa.array(range(1, m + 1), pa.int64()), pa.array([empty] * m, pa.int64()), pa.array(filtered, pa.int64())], ["m", "empty_pairs", "filtered"])


# ---- results


def sizes(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """``qid, r``: the size of every intersection that isn't empty, by bit maps; of any elements."""
    return _run(sets, queries, Cfg(g="xx64"), "count_common", "qid long, r long").groupBy("qid").agg(F.sum("r").alias("r"))


def kernel_results(sets: DataFrame, queries: DataFrame, cfg: Cfg, methods: tuple[str, ...], codecs: tuple[str, ...] = ("plain",), m: int = 2) -> DataFrame:
    """``codec, method, qid, r, seconds``, as ``workloads.kernel_results`` has it, for batches that name their sets often."""
    if not set(methods) <= set(kernels.METHODS) or not set(codecs) <= set(blocks.CODECS):
        raise ValueError(f"methods must be of {sorted(kernels.METHODS)} and codecs of {blocks.CODECS}")
    _images_needed(cfg)
    rows = _run(sets, queries, cfg, "run_methods", "codec string, method string, qid long, r long, nanos long", tuple(methods), m, tuple(codecs), larger=len(methods) * len(codecs) > 1)  # calls cost more than members there
    return rows.groupBy("codec", "method", "qid").agg(F.sum("r").alias("r"), (F.sum("nanos") / 1e9).alias("seconds"))


def filter_rate(sets: DataFrame, queries: DataFrame, cfg: Cfg, m: int) -> DataFrame:
    """``m, empty_pairs, filtered``, as ``measures.filter_rate`` has it, of the two-set queries of a batch."""
    _images_needed(cfg)
    rows = _run(sets, queries, cfg, "filter_pairs", "m long, empty_pairs long, filtered long", m, whole=True)
    return rows.groupBy("m").agg(F.sum("empty_pairs").alias("empty_pairs"), F.sum("filtered").alias("filtered"))
