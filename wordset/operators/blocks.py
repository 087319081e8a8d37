"""Packed blocks: all groups of a set below one coarse prefix in a row, and kernels that intersect blocks.

A row per group of eight members is too fine for a hundred terabytes. Blocks cut every set by the same leading bits of
the common order, which is uniform, so blocks of a set are even, and blocks of different sets with the same prefix hold
all that these sets have in common there. A query meets in one shuffle on (query, prefix), and a kernel works on arrays.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import codes, hashing
from wordset.functions.worker import on_worker
from wordset.operators import kernels
from wordset.operators.groups import group_by_prefix, hashed, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side

#: Codings of a block's members; ``plain`` keeps them as arrays.
CODECS = ("plain", "gamma", "delta", "lowbits")
COUNTERS = ("pairs_met", "pairs_passed", "pairs_hit", "elems_fetched", "comparisons")


#: Members of a block, about, as a power of two.
BLOCK_BITS = 14


def coarse_sql(n: str, block_bits: int = BLOCK_BITS) -> str:
    """Leading bits that cut a set of n into blocks of 2^block_bits members, about."""
    return f"greatest(0, {hashing.bits_of_sql(n)} - {block_bits})"


def block_stats(sets: DataFrame, block_bits: int = BLOCK_BITS) -> DataFrame:
    """The sizes of sets, with the bits ``cb`` that each is cut by."""
    return set_stats(sets).withColumn("cb", F.expr(coarse_sql("n", block_bits)).cast("int"))


def build_blocks(sets: DataFrame, cfg: Cfg, block_bits: int = BLOCK_BITS, m: int | None = None, codec: str = "plain") -> DataFrame:
    """``set_id, cb, c, t, zs, ns, imgs, g, elem`` (arrays in the order of g); coded: ``set_id, cb, c, t, z0, head, imgs, payload``.

    A set is cut by its first ``cb`` bits, as many as its size asks for, so that no row grows with its set. ``head`` holds the sizes of all
    groups from prefix z0 on in unary, so prefixes needn't be stored, and images are those of non-empty groups."""
    if codec not in CODECS:
        raise ValueError(f"codec must be one of {CODECS}")
    m = cfg.m if m is None else m
    if cfg.words > 1:
        raise ValueError("blocks hold images of one word")
    sizes = block_stats(sets, block_bits).withColumn("t", F.expr(f"greatest(cb, {hashing.t_scan_sql('n', cfg)})").cast("int"))
    groups = group_by_prefix(hashed(sets, cfg, m).join(sizes.select("set_id", "cb", "t"), "set_id"), cfg, m, ("set_id", "cb"))
    names = [c for ws in cfg.images(m) for c in ws]
    groups = groups.withColumn("c", F.expr("case when cb = 0 then 0L else shiftrightunsigned(z, t - cb) end"))
    order = F.col("z")  # of fewer than 64 bits: sets have fewer than 2^63 groups
    rows = groups.groupBy("set_id", "cb", "c").agg(F.first("t").alias("t"), F.sort_array(F.collect_list(F.struct(order.alias("o"), "z", "n", F.array(*names).alias("imgs"), "elems"))).alias("b"))
    get = lambda f: F.transform("b", lambda x: x[f])
    flat = F.flatten(get("elems"))
    out = rows.select("set_id", "cb", "c", "t", get("z").alias("zs"), get("n").alias("ns"), F.flatten(get("imgs")).alias("imgs"), F.transform(flat, lambda x: x["g"]).alias("g"), F.transform(flat, lambda x: x["elem"]).alias("elem"))
    if codec == "plain":
        return out
    return out.mapInArrow(on_worker(__name__, "encode_blocks", cfg, codec), "set_id string, cb int, c long, t int, z0 long, head binary, imgs array<long>, payload binary")


def encode_blocks(batches, cfg: Cfg, codec: str):
    for b in batches:
        out, heads, firsts = [], [], []
        for t, zs, ns, g in zip(b["t"].to_pylist(), b["zs"].to_pylist(), b["ns"].to_pylist(), b["g"].to_pylist(), strict=True):
            heads.append(encode_sizes(zs, ns))
            firsts.append(zs[0])
            width = cfg.universe_bits - t
            low = np.array(g, np.int64).view(np.uint64) & np.uint64((1 << width) - 1)
            if codec == "lowbits":
                out.append(codes.pack_low(low, width))
                continue
            out.append(codes.pack_codes(codes.gaps_of(low, np.array(ns)), codec))
        columns = [b["set_id"], b["cb"], b["c"], b["t"], pa.array(firsts, pa.int64()), pa.array(heads, pa.binary()), b["imgs"], pa.array(out, pa.binary())]
        yield pa.RecordBatch.from_arrays(columns, ["set_id", "cb", "c", "t", "z0", "head", "imgs", "payload"])


def encode_sizes(zs: list[int], ns: list[int]) -> bytes:
    """Sizes of the groups from the first prefix to the last, empty ones too, in unary."""
    sizes = np.zeros(zs[-1] - zs[0] + 1, np.int64)
    sizes[np.array(zs) - zs[0]] = ns
    return codes.pack_sizes(sizes)


def decode_sizes(head: bytes, z0: int, groups: int) -> tuple[list[int], list[int]]:
    """Prefixes and sizes of the ``groups`` non-empty groups."""
    sizes = codes.unpack_sizes(head)
    full = np.flatnonzero(sizes)[:groups]
    return (full + z0).tolist(), sizes[full].tolist()


def decode_members(payload: bytes, t: int, zs, ns, cfg: Cfg, codec: str) -> np.ndarray:
    """The members' places in the order, from their coded low bits and their groups' prefixes."""
    width = cfg.universe_bits - t
    if codec == "lowbits":
        low = codes.unpack_low(payload, int(sum(ns)), width)
    else:
        counts = np.array(ns, np.int64)
        low = codes.from_gaps(codes.unpack_codes(payload, int(counts.sum()), codec), counts).astype(np.uint64)
    high = np.repeat(np.array(zs, np.int64).view(np.uint64) << np.uint64(width), ns) if width < 64 else np.zeros(len(low), np.uint64)
    return high | low


def _met(blocks: DataFrame, queries: DataFrame, sets_stats: DataFrame, columns: list[str]) -> DataFrame:
    """Per query and prefix of its most finely cut set, the blocks of all its sets in which it lies: at most k blocks a row. What is sent of a
    smaller set is no more than the largest set, about."""
    q = query_sets(queries, sets_stats).join(sets_stats.select("set_id", "cb"), "set_id")
    q = q.withColumn("fine", F.max("cb").over(Window.partitionBy("qid"))).select("qid", "k", "rank", "set_id", "fine")
    rows = blocks.join(small_side(q.drop("cb")), "set_id")
    rows = rows.withColumn("c", F.explode(F.expr("sequence(shiftleft(c, fine - cb), shiftleft(c + 1, fine - cb) - 1)")))
    met = rows.groupBy("qid", "c").agg(F.max("k").alias("k"), F.sort_array(F.collect_list(F.struct("rank", *columns))).alias("bs"))
    return met.filter(F.size("bs") == F.col("k")).select("qid", "bs")


def run_kernel(sets: DataFrame, queries: DataFrame, cfg: Cfg, method: str, block_bits: int = BLOCK_BITS, m: int | None = None, codec: str = "plain") -> DataFrame:
    """``qid, elems`` and the counters, one row per query and coarse prefix."""
    m = cfg.m if m is None else m
    sets = pruned(sets, queries)
    return run_stored(build_blocks(sets, cfg, block_bits, m, codec), block_stats(sets, block_bits), queries, cfg, method, m, codec)


def run_stored(blocks: DataFrame, stats: DataFrame, queries: DataFrame, cfg: Cfg, method: str | tuple[str, ...], m: int | None = None, codec: str = "plain") -> DataFrame:
    """As ``run_kernel`` over blocks that were built before, with the ``block_stats`` of their sets; with ``nanos``, what the kernel alone took.

    Several methods run on the same blocks, met once; ``method`` says which a row is of."""
    methods = (method,) if isinstance(method, str) else tuple(method)
    if not set(methods) <= set(kernels.METHODS):
        raise ValueError(f"method must be one of {sorted(kernels.METHODS)}")
    m = cfg.m if m is None else m
    members = ["zs", "ns", "g", "elem"] if codec == "plain" else ["z0", "head", "payload"]
    met = _met(blocks, queries, stats, ["t", "imgs", *members])
    schema = "method string, qid long, elems array<long>, " + ", ".join(f"{c} long" for c in (*COUNTERS, "nanos"))
    return met.mapInArrow(on_worker(__name__, "kernel_batches", cfg, methods, m, codec), schema)


class _Column:
    """A field of an array of structs: numbers, or slices of numbers without a copy."""

    def __init__(self, values: pa.Array):
        self.raw = values
        if pa.types.is_list(values.type):
            self.offsets, self.flat = values.offsets.to_numpy(), values.values.to_numpy(zero_copy_only=False)

    def __getitem__(self, i: int):
        return self.flat[self.offsets[i] : self.offsets[i + 1]] if pa.types.is_list(self.raw.type) else self.raw[i].as_py()


def kernel_batches(batches, cfg: Cfg, methods: tuple[str, ...], m: int, codec: str):
    for b in batches:
        rows, held_all = [], []
        bounds, structs = b["bs"].offsets.to_numpy(), b["bs"].values
        col = {f.name: _Column(structs.field(f.name)) for f in structs.type}
        for i, qid in enumerate(b["qid"].to_pylist()):
            held, t0 = [], time.perf_counter_ns()
            for j in range(bounds[i], bounds[i + 1]):
                t, imgs = col["t"][j], col["imgs"][j].view(np.uint64).reshape(-1, m)
                if codec == "plain":
                    zs, ns, g = col["zs"][j], col["ns"][j], col["g"][j].view(np.uint64)
                else:
                    zs, ns = decode_sizes(col["head"][j], col["z0"][j], len(imgs))
                    g = decode_members(col["payload"][j], t, zs, ns, cfg, codec)
                held.append(kernels.Block(t, np.asarray(zs, np.int64).view(np.uint64), np.asarray(ns, np.int64), imgs, g))
            decoding = time.perf_counter_ns() - t0 if codec != "plain" else 0  # coded blocks are decoded for every query
            for method in methods:
                t0 = time.perf_counter_ns()
                common, count = kernels.METHODS[method](held, cfg)
                nanos = time.perf_counter_ns() - t0 + decoding
                if codec == "plain":
                    elems = col["elem"][bounds[i]][np.searchsorted(held[0].g, common)]
                else:  # intersected among places in the order, which are one to one with elements
                    elems = hashing.g_inverse_array(pa.array(common.view(np.int64)), cfg).to_numpy()
                rows.append((method, qid, *(count.get(c, 0) for c in COUNTERS), nanos))
                held_all.append(elems)
        if not rows:
            continue
        cols = list(zip(*rows, strict=True))
        offsets = np.cumsum([0, *map(len, held_all)]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(held_all).astype(np.int64)))
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int64()), lists, *(pa.array(c, pa.int64()) for c in cols[2:])], ["method", "qid", "elems", *COUNTERS, "nanos"])


def intersect(sets: DataFrame, queries: DataFrame, cfg: Cfg, method: str = "scan", **how) -> DataFrame:
    """``qid, elem``."""
    return run_kernel(sets, queries, cfg, method, **how).select("qid", F.explode("elems").alias("elem"))


def counters(sets: DataFrame, queries: DataFrame, cfg: Cfg, method: str = "scan", **how) -> DataFrame:
    """``qid``, the counters and ``r``."""
    return counted(run_kernel(sets, queries, cfg, method, **how))


def counted(rows: DataFrame) -> DataFrame:
    """Kernel rows by method and query: ``method, qid``, the counters and ``r``."""
    return rows.groupBy("method", "qid").agg(*(F.sum(c).alias(c) for c in COUNTERS), F.sum(F.size("elems")).alias("r"))
