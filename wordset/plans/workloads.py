"""The experiments' inputs on the given tables: controlled pairs, term queries, and timed sweeps."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions.store import written
from wordset.operators import baselines, blocks, fixed, measures, prefix, probe, scan
from wordset.operators import groups as G
from wordset.sources import families as fam
from wordset.sources.tables import load

#: The term workload: its ten thousand most frequent queries, so many of each number of terms.
MIX = {2: 6800, 3: 2300, 4: 600, 5: 300}
#: Cells of the scrambled keys, as a power of two.
CELL_BITS = 12

def controlled(spark: SparkSession, d: str, points: list[tuple[int, int, int]]) -> tuple[DataFrame, DataFrame]:
    """Sets ``A0, B0, A1, B1, ...`` with sizes n1, n2 and r common members per point (n1, n2, r), and a query per point."""
    keys = load(spark, d, "orders").select("o_orderkey", F.expr(fam.SCRAMBLE.format(x="o_orderkey")).alias("s"))
    most = max(n1 + n2 - r for n1, n2, r in points)
    # places from counted cells of the scrambled range, so that no task sorts all keys
    keys = keys.withColumn("cell", F.shiftright("s", 32 - CELL_BITS).cast("int"))
    before = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # 2^CELL_BITS rows
    skip = keys.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).select("cell", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("skip"))
    ranked = keys.withColumn("i", F.row_number().over(Window.partitionBy("cell").orderBy("s"))).join(F.broadcast(skip), "cell").withColumn("i", F.col("i") + F.col("skip")).filter(F.col("i") <= most)
    names = []
    for j, (n1, n2, r) in enumerate(points):
        names += [F.when(F.col("i") <= n1, F.lit(f"A{j}")), F.when((F.col("i") > n1 - r) & (F.col("i") <= n1 - r + n2), F.lit(f"B{j}"))]
    sets = ranked.select(F.explode(F.array_compact(F.array(*names))).alias("set_id"), F.col("o_orderkey").alias("elem"))
    queries = spark.createDataFrame([(j, [f"A{j}", f"B{j}"]) for j in range(len(points))], "qid long, set_ids array<string>")
    return sets, queries


def equal_points(n_orders: int) -> list[tuple[int, int, int]]:
    """Equal sets from small to almost half of the keys, one member in a hundred common."""
    return [(n, n, n // 100) for n in (n_orders // 30, n_orders // 15, 2 * n_orders // 15, 4 * n_orders // 15, 7 * n_orders // 15)]


def overlap_points(n_orders: int) -> list[tuple[int, int, int]]:
    """Equal sets of half the keys, from one common member to all."""
    n = n_orders // 2
    return [(n, n, max(1, n * p // 10000)) for p in (0, 100, 1000, 3000, 5000, 7000, 9000, 10000)]


def ratio_points(n_orders: int) -> list[tuple[int, int, int]]:
    """A set of half the keys against ever smaller ones."""
    n = n_orders // 2
    return [(max(1, n // s), n, max(1, n // s // 100)) for s in (1, 2, 4, 8, 16, 32, 64, 100, 200, 625)]


def term_queries(spark: SparkSession, d: str, mix: dict[int, int] = MIX) -> DataFrame:
    """``qid, k, set_ids, freq``: distinct terms of windows of adjacent words of the benchmark and of users' turns, the most frequent
    ones, ``mix[k]`` of each length."""
    text = load(spark, d, "benchmark").select("text").unionAll(load(spark, d, "conversations").filter("role = 'user'").select("text"))
    words = text.select(F.expr(fam.tokens("text")).alias("w"))
    out = None
    for k, top in mix.items():
        windows = words.filter(F.size("w") >= k).select(F.explode(F.expr(f"transform(sequence(1, size(w) - {k - 1}), i -> array_sort(array_distinct(slice(w, i, {k}))))")).alias("set_ids"))
        counts = windows.filter(F.size("set_ids") == k).groupBy("set_ids").agg(F.count(F.lit(1)).alias("freq"))
        best = counts.select(F.lit(k).alias("k"), "set_ids", "freq").orderBy(F.col("freq").desc(), F.array_join("set_ids", " ")).limit(top)
        out = best if out is None else out.unionByName(best)
    order = Window.orderBy("k", F.col("freq").desc(), F.array_join("set_ids", " "))  # the workload's ten thousand
    return out.select((F.row_number().over(order) - 1).cast("long").alias("qid"), "k", "set_ids", "freq")


def makers(sets: DataFrame, queries: DataFrame, cfg: Cfg, index: G.Index) -> dict[str, Callable[[], DataFrame]]:
    """All methods on one workload, each as a plan that isn't run yet."""
    return {
        "scan": lambda: scan.intersect(index, queries),
        "prefix": lambda: scan.intersect_by_bits(index, queries),
        "fixed": lambda: fixed.intersect(sets, queries, cfg),
        "same_count": lambda: prefix.intersect_pairs(sets, queries, cfg),
        "probe": lambda: probe.intersect(sets, queries, cfg),
        "merge": lambda: baselines.merge(sets, queries),
        "hash": lambda: baselines.hashing_(sets, queries),
        "lookup": lambda: baselines.lookup(sets, queries, cfg),
        "svs": lambda: baselines.smallest_first(sets, queries),
        "packed": lambda: baselines.packed_codes(sets, queries, cfg),
    }


def timed_sweep(spark: SparkSession, d: str, points: list[tuple[int, int, int]], cfg: Cfg, methods: list[str] | None = None, runs: int = 3) -> DataFrame:
    """``method, qid, seconds`` of every method at every point, each pair as a query of its own on stored groups."""
    sets, queries = controlled(spark, d, points)
    sets = sets.cache()
    rows = []
    for j in range(len(points)):
        pair = sets.filter(F.col("set_id").isin(f"A{j}", f"B{j}"))
        one = queries.filter(F.col("qid") == j)
        index = G.build(pair, cfg, keep=True)
        plans = {k: v for k, v in makers(pair, one, cfg, index).items() if methods is None or k in methods}
        rows += [(m, j, s) for m, _, s in measures.time_runs({k: (lambda _, f=f: f()) for k, f in plans.items()}, runs)]
    sets.unpersist()
    return measures.timings_frame(spark, rows)


def work_sweep(sets: DataFrame, queries: DataFrame, cfg: Cfg, methods: tuple[str, ...]) -> DataFrame:
    """``method, qid`` and the kernels' counters of every query: what each method does, free of the clock. Blocks are built once."""
    sets = G.pruned(sets, queries)
    return blocks.counted(blocks.run_stored(blocks.build_blocks(sets, cfg), blocks.block_stats(sets), queries, cfg, methods))


def kernel_results(sets: DataFrame, queries: DataFrame, cfg: Cfg, methods: tuple[str, ...], codecs: tuple[str, ...] = ("plain",), m: int = 2) -> DataFrame:
    """``codec, method, qid, r, seconds`` of kernels on one workload, on the same blocks in each coding; ``seconds`` is the kernel's own
    time, with decoding, summed over the blocks of a query."""
    sets = G.pruned(sets, queries)
    out = None
    for codec in codecs:
        rows = blocks.run_stored(blocks.build_blocks(sets, cfg, m=m, codec=codec), blocks.block_stats(sets), queries, cfg, methods, m, codec)
        one = rows.groupBy("method", "qid").agg(F.sum(F.size("elems")).cast("long").alias("r"), (F.sum("nanos") / 1e9).alias("seconds")).select(F.lit(codec).alias("codec"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def random_suppliers(n_suppliers: int, k: int, runs: int = 20, seed: int = 42) -> list[list[str]]:
    """Random combinations of k sets."""
    import random

    r = random.Random(seed)
    return [[str(x) for x in r.sample(range(n_suppliers), k)] for _ in range(runs)]


def random_terms(sets: DataFrame, mix: dict[int, int]) -> DataFrame:
    """``qid, k, set_ids``: queries of distinct terms drawn with the weight of their sets' sizes, ``mix[k]`` of each length: the first postings
    in the order of a digest, k at a time. Draws with a term twice are left out."""
    total = sum(k * n for k, n in mix.items())
    drawn = sets.select("set_id", F.md5(F.concat_ws("|", "set_id", F.col("elem").cast("string"))).alias("d")).orderBy("d", "set_id").limit(total)
    drawn = drawn.withColumn("i", F.row_number().over(Window.orderBy("d", "set_id")) - 1)  # the workload's draws, no more
    out, start, first = None, 0, 0
    for k, n in mix.items():
        part = drawn.filter((F.col("i") >= start) & (F.col("i") < start + k * n))
        qid = (F.floor((F.col("i") - start) / k) + first).cast("long")
        one = part.groupBy(qid.alias("qid")).agg(F.array_sort(F.collect_set("set_id")).alias("set_ids")).filter(F.size("set_ids") == k).select("qid", F.lit(k).alias("k"), "set_ids")
        out = one if out is None else out.unionByName(one)
        start, first = start + k * n, first + n
    return out
