"""Times the headline queries and prints one JSON line.

As in the experiments, pre-processing is kept apart: every method, the baselines too, answers from structures that are stored before the
clock starts; ``preprocessing`` has the seconds of making them. The queries after ``whole`` are timed with all they do.

BENCH_SF_DIR names the tables, BENCH_CPUS the cores. ``--paper`` prints the sweeps of the experiments instead: for each method
seconds relative to merging, and the counters of what each kernel does. ``--kernels`` times the kernels alone on
synthetic sets of up to ten million members.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Queries that have no structure to store, or are about making one.
WHOLE = ("m1_optimal", "m2_same_count", "m3_filter_rate", "space_words", "batch_terms", "auto_plan", "bag_pair")
RUNS = 2


def session():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.driver.memory", "12g")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def timed(make) -> float:
    t = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def headline(spark) -> dict:
    from wordset.queries import QUERIES
    from wordset.served import served

    build, queries = served(spark, SF_DIR)
    have, preprocessing = {}, {}
    for name, make in build.items():
        t = time.perf_counter()
        have[name] = make()
        preprocessing[name] = round(time.perf_counter() - t, 3)
    asked = queries(have)
    for name in ("base_merge", "m3_k3", "m3_blocks"):  # code is compiled and files are cached
        timed(asked[name])
    seconds = {name: round(statistics.median(timed(make) for _ in range(RUNS)), 3) for name, make in asked.items()}
    seconds |= {name: round(statistics.median(timed(lambda: QUERIES[name](spark, SF_DIR)) for _ in range(2)), 3) for name in WHOLE}
    ratio = lambda a, b: round(seconds[a] / seconds[b], 3)
    relative = {
        "m3_pair / merge": ratio("m3_m2", "base_merge_pair"),
        "m3_k3 / merge": ratio("m3_k3", "base_merge"),
        "m3_k4 / merge": ratio("m3_k4", "base_merge_k4"),
        "m3_blocks_pair / merge": ratio("m3_blocks_pair", "base_merge_pair"),
        "m3_blocks_k3 / merge": ratio("m3_blocks", "base_merge"),
        "m3_blocks_k4 / merge": ratio("m3_blocks_k4", "base_merge_k4"),
        "m2_k3 / merge": ratio("m2_k3", "base_merge"),
        "m4_pair / merge": ratio("m4_pair", "base_merge_uneven"),
    }
    return {"metric": "headline_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": Path(SF_DIR).name.removeprefix("sf"), "relative": relative, "preprocessing": preprocessing}


def paper(spark) -> dict:
    """The experiments' workloads by kernels on the same stored blocks: per-query times of their own, so that shares of queries won and worst
    latencies mean something; and pre-processing against sorting. Takes minutes."""
    from wordset.config import Cfg
    from wordset.operators import baselines, blocks, fixed, measures, prefix
    from wordset.operators import groups as G
    from wordset.operators.kernels import METHODS
    from wordset.plans import workloads
    from wordset.sources import families as fam
    from wordset.sources.tables import load

    cfg, n = Cfg(m=2), load(spark, SF_DIR, "orders").count()
    docs = fam.term_docs(spark, SF_DIR)
    loads = {name: workloads.controlled(spark, SF_DIR, points(n)) for name, points in (("equal", workloads.equal_points), ("overlap", workloads.overlap_points), ("ratio", workloads.ratio_points))}
    loads["terms"] = (docs, workloads.term_queries(spark, SF_DIR))
    loads["random_terms"] = (docs, workloads.random_terms(docs, {2: 600, 3: 300, 4: 100}))
    out: dict = {}

    def measured(name, times, queries):
        r = lambda df, c: {x.method: round(x[c], 3) for x in df.collect()}
        out[name] = {"normalised": r(measures.normalise(times), "normalised"), "won": r(measures.winners(times), "share"), "worst": r(measures.worst_latency(times, "scan"), "ratio"), "regret": r(measures.regret(times), "mean_regret"), "speedup": r(measures.speedup(times, "scan"), "times")}
        if "k" in queries.columns:
            by = times.join(queries.select("qid", "k"), "qid")
            out[name]["by_k"] = {k: r(measures.normalise(by.filter(f"k = {k}")), "normalised") for k in (2, 3, 4, 5) if by.filter(f"k = {k}").head(1)}
        else:
            out[name]["sweep"] = [x.asDict() for x in measures.sweep_table(times, "qid").collect()]

    for name, (sets, queries) in loads.items():
        queries = queries.cache()
        got = workloads.kernel_results(sets, queries, cfg, tuple(METHODS)).cache()
        measured(name, got.select("method", "qid", "seconds"), queries)
        if name in ("equal", "terms"):
            coded = workloads.kernel_results(sets, queries, cfg, ("merge", "lookup", "scan"), ("gamma", "delta", "lowbits"), 1)
            coded = coded.selectExpr("concat(method, '_', codec) as method", "qid", "seconds").cache()
            measured(f"{name}_coded", coded.unionByName(got.filter("method = 'merge'").select("method", "qid", "seconds")), queries)
    f1 = fam.supp_orders(spark, SF_DIR).cache()
    builders = {
        "fixed": lambda: fixed.build(f1, cfg),
        "prefix": lambda: prefix.build(f1, cfg).groups,
        "scan_m2": lambda: G.build(f1, cfg).groups,
        "scan_m4": lambda: G.build(f1, cfg.with_(m=4)).groups,
        **{f"blocks_{c}": lambda c=c: blocks.build_blocks(f1, cfg, codec=c) for c in blocks.CODECS},
    }
    out["preprocessing / sorting"] = {name: round(x, 2) for name, x in measures.preprocess_cost(builders, lambda: baselines.sort_only(f1), RUNS)}
    return out


def local_block(values, cfg, t=None):
    """One block of a whole set, built in NumPy: for kernel timings without Spark."""
    import numpy as np

    from wordset.functions import hashing
    from wordset.operators.kernels import Block

    mask = (1 << cfg.universe_bits) - 1
    g = values.astype(np.uint64)
    for a, b in cfg.rounds:
        g = ((g ^ (g >> np.uint64(cfg.universe_bits // 2))) * np.uint64(a) + np.uint64(b)) & np.uint64(mask)
    order = np.argsort(g)
    g, x = g[order], values[order].astype(np.uint64)
    t = hashing.t_scan(len(g), cfg) if t is None else t
    z = g >> np.uint64(cfg.universe_bits - t)
    first = np.flatnonzero(np.r_[True, z[1:] != z[:-1]])
    imgs = []
    for j in range(1, cfg.m + 1):
        a, b = cfg.line(j)
        y = ((x % np.uint64(hashing.PRIME)) * np.uint64(a) + np.uint64(b)) % np.uint64(hashing.PRIME) % np.uint64(cfg.w)
        imgs.append(np.bitwise_or.reduceat(np.uint64(1) << y, first))
    return Block(t, z[first], np.diff(np.r_[first, len(g)]), np.stack(imgs, 1), g)


def kernels_alone(sizes=(1_000_000, 3_000_000, 10_000_000), runs=3) -> dict:
    """Single-threaded kernels on synthetic sets, uniform in [0, 2^32): elements a second, and seconds relative to merging."""
    import numpy as np

    from wordset.config import Cfg
    from wordset.operators import kernels

    rng = np.random.default_rng(42)
    out = {}

    def timed(name, methods, sets, cfg):
        blocks = sorted((local_block(s, cfg) for s in sets), key=lambda b: len(b.g))
        seconds = {}
        want = None
        for m in methods:
            got = []
            for _ in range(runs):
                t = time.perf_counter()
                common, _ = kernels.METHODS[m](blocks, cfg)
                got.append(time.perf_counter() - t)
            want = len(common) if want is None else want
            assert len(common) == want, (m, len(common), want)
            seconds[m] = statistics.median(got)
        total = sum(map(len, sets))
        out[name] = {"r": want} | {m: {"normalised": round(s / seconds["merge"], 3), "elements_per_second": round(total / s)} for m, s in seconds.items()}

    def with_common(sizes, r):
        pool = np.unique(rng.integers(0, 1 << 32, int(1.05 * (sum(sizes) + r)), dtype=np.int64))
        rng.shuffle(pool)
        common, at, sets = pool[:r], r, []
        for n in sizes:
            sets.append(np.r_[common, pool[at : at + n - r]])
            at += n - r
        return sets

    for n in sizes:
        for m in (1, 2, 4):
            timed(f"equal n={n} m={m}", ("merge", "scan"), with_common((n, n), n // 100), Cfg(m=m))
    n = sizes[0]
    for share in (1, 10, 30, 50, 70, 90, 100):
        timed(f"overlap {share}% n={n}", ("merge", "scan"), with_common((n, n), n * share // 100), Cfg(m=4))
    for ratio in (2, 8, 32, 100, 625):
        timed(f"ratio {ratio}", ("merge", "scan", "probe"), with_common((n // ratio, n), max(1, n // ratio // 100)), Cfg(m=4))
    for k in (2, 3, 4):
        sets = [np.unique(rng.integers(0, 20 * n, n, dtype=np.int64)) for _ in range(k)]
        timed(f"k={k} density 5%", ("merge", "scan"), sets, Cfg(m=2))
    return out


if __name__ == "__main__":
    if "--kernels" in sys.argv:
        print(json.dumps(kernels_alone()), flush=True)
        sys.exit()
    spark = session()
    print(json.dumps(paper(spark) if "--paper" in sys.argv else headline(spark)), flush=True)
    from wordset.functions.store import clean

    clean(spark)
    spark.stop()
