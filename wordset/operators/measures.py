"""Cost and accuracy measures over indexes, queries and timings."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.operators import cells, fixed, scan
from wordset.operators.groups import Index, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side

# ---- filtering


def pair_groups(index: Index, queries: DataFrame, m: int) -> DataFrame:
    """Pairs of non-empty groups that two-set queries align: ``qid, z``, whether each image meets (``hit_1`` ...), and
    the common members ``r``."""
    q = scan.legs(index, queries)
    names = [c for ws in index.cfg.images(m) for c in ws]
    a = scan._leg(index, q, 1, ["n", "elems", *names]).select("qid", F.col("z").alias("az"), F.col("elems").alias("ae"), F.col("n").alias("an"), *(F.col(c).alias(f"a_{c}") for c in names))
    b = scan._leg(index, q, 2, ["n", "elems", *names]).select(F.col("qid").alias("bq"), "zkey", "z", F.col("elems").alias("be"), F.col("n").alias("bn"), *(F.col(c).alias(f"b_{c}") for c in names))
    met = a.join(b, (F.col("qid") == F.col("bq")) & (F.col("az") == F.col("zkey")))
    hits = (words.images_meet("a_", "b_", Cfg(w=index.cfg.w, m=1), 1).alias("hit_1"),) if m == 1 else tuple(_meets(index.cfg, j).alias(f"hit_{j}") for j in range(1, m + 1))
    return met.select("qid", "z", "an", "bn", *hits, F.size(F.array_intersect("ae", "be")).alias("r"))


def _meets(cfg: Cfg, j: int):
    names = cfg.images(j)[-1]
    out = F.lit(False)
    for c in names:
        out = out | (F.col(f"a_{c}").bitwiseAND(F.col(f"b_{c}")) != 0)
    return out


def filter_rate(index: Index, queries: DataFrame, m: int) -> DataFrame:
    """By number of images used: pairs of groups without common members, those that some image proves so, over all
    aligned pairs and per query set; ``m, empty_pairs, filtered``."""
    pairs = pair_groups(index, queries, m).filter("r = 0")
    rows = []
    for j in range(1, m + 1):
        passed = F.lit(True)
        for i in range(1, j + 1):
            passed = passed & F.col(f"hit_{i}")
        rows.append(F.struct(F.lit(j).alias("m"), passed.alias("passed")))
    one = pairs.select(F.explode(F.array(*rows)).alias("x")).select("x.*")
    return one.groupBy("m").agg(F.count(F.lit(1)).alias("empty_pairs"), F.count_if(~F.col("passed")).alias("filtered"))


def filter_rate_all_prefixes(index: Index, queries: DataFrame, m: int) -> DataFrame:
    """As above with prefixes at which a group is empty counted as filtered: ``m, empty_pairs, filtered``."""
    base = filter_rate(index, queries, m)
    q = query_sets(queries, index.stats)
    prefixes = q.groupBy("qid").agg(F.max("t").alias("t")).agg(F.sum(F.pow(F.lit(2), F.col("t"))).cast("long").alias("all"))
    met = pair_groups(index, queries, 1).agg(F.count(F.lit(1)).alias("met"))
    one = prefixes.crossJoin(met).select((F.col("all") - F.col("met")).alias("void"))  # one row each
    return base.crossJoin(F.broadcast(one)).select("m", (F.col("empty_pairs") + F.col("void")).alias("empty_pairs"), (F.col("filtered") + F.col("void")).alias("filtered"))


def merge_cases(index: Index, queries: DataFrame, m: int) -> DataFrame:
    """Per query: aligned chains, chains that pass all images, and of these the useful and the wasted merges."""
    alive, q, _ = scan.survivors(index, queries, m)
    got = scan.fetch(index, alive, q).filter(F.size("e") > 0)
    passed = alive.groupBy("qid").agg(F.count(F.lit(1)).alias("passed"))
    useful = got.filter(F.size("e") > 0).groupBy("qid").agg(F.count(F.lit(1)).alias("useful"), F.sum(F.size("e")).alias("r"))
    out = queries.select("qid").join(passed, "qid", "left").join(useful, "qid", "left")
    zero = [F.coalesce(F.col(c), F.lit(0).cast("long")).alias(c) for c in ("passed", "useful", "r")]
    return out.select("qid", *zero).withColumn("wasted", F.col("passed") - F.col("useful"))


def survivors_by_step(index: Index, queries: DataFrame, m: int = 1) -> DataFrame:
    """Per query and number of sets met: chains of groups that are left."""
    q = scan.legs(index, queries)
    k_max = scan.longest(queries)
    out = None
    for rank, s in enumerate(scan.align_images(index, q, k_max, m), 1):
        n = s.groupBy("qid").agg(F.count(F.lit(1)).alias("chains")).select("qid", F.lit(rank).alias("step"), "chains")
        out = n if out is None else out.unionByName(n)
    return out


def collisions(sets: DataFrame, queries: DataFrame, cfg: Cfg, sizes=None) -> DataFrame:
    """Per query over overlapping runs: pairs of groups, and pairs of unequal members with the same hash in them."""
    g = written(fixed.query_groups(sets, queries, cfg, sizes), "runs")
    met = fixed.overlaps(g)
    e = g.select("qid", "side", "p", F.explode("elems.elem").alias("elem")).withColumn("y", hashing.h("elem", 1, cfg))
    a, b = (e.filter(F.col("side") == s).select("qid", F.col("p").alias(f"{x}_p"), "y", F.col("elem").alias(f"{x}_e")) for s, x in ((1, "a"), (2, "b")))
    same = met.join(a, ["qid", "a_p"]).join(b, ["qid", "b_p", "y"]).groupBy("qid").agg(F.count_if(F.col("a_e") != F.col("b_e")).alias("unequal"), F.count_if(F.col("a_e") == F.col("b_e")).alias("r"))
    n = met.groupBy("qid").agg(F.count(F.lit(1)).alias("pairs"))
    return n.join(same, "qid", "left").select("qid", "pairs", F.coalesce("unequal", F.lit(0)).alias("unequal"), F.coalesce("r", F.lit(0)).alias("r"))


def group_sizes(index: Index) -> DataFrame:
    """``n, groups``: how many groups have n members."""
    return index.groups.groupBy(F.col("n").cast("long").alias("n")).agg(F.count(F.lit(1)).alias("groups"))


def false_positives(index: Index, queries: DataFrame, m: int) -> DataFrame:
    """By number of images: pairs of groups without common members that all images let pass; ``m, empty_pairs, passed, rate``."""
    rate = filter_rate(index, queries, m)
    passed = F.col("empty_pairs") - F.col("filtered")
    return rate.select(F.col("m").cast("long").alias("m"), "empty_pairs", passed.alias("passed"), F.round(passed / F.col("empty_pairs"), 6).alias("rate"))


def candidates(sets: DataFrame, queries: DataFrame, cfg: Cfg) -> DataFrame:
    """``qid, i, elems``: the candidates that set i and all larger ones hold but some smaller one doesn't, among members whose hash is in the
    common image of their groups; i counts from 2."""
    index = _one_image(pruned(sets, queries), cfg)
    alive, q, _ = scan.survivors(index, queries, 1)
    mine = q.select(F.col("qid").alias("c_qid"), "rank", F.col("set_id").alias("c_set"))
    last = alive.join(small_side(mine), (F.col("qid") == F.col("c_qid")) & (F.col("rank") == F.col("k"))).select("qid", "k", "z", "c_set", *(c for c in alive.columns if c.startswith("l_")))
    held = last.join(index.groups.select("set_id", F.col("z").alias("g_z"), "elems"), (F.col("c_set") == F.col("set_id")) & (F.col("z") == F.col("g_z")))
    gamma = held.select("qid", "k", F.explode(scan.common_bits(index, 1)(F.col("elems"))).alias("x")).select("qid", "k", F.col("x.elem").alias("elem"))
    where = sets.join(small_side(mine), F.col("set_id") == F.col("c_set")).select("c_qid", "rank", F.col("elem").alias("c_elem"))
    found = gamma.join(where, (F.col("qid") == F.col("c_qid")) & (F.col("elem") == F.col("c_elem"))).groupBy("qid", "k", "elem").agg(F.collect_set("rank").alias("ranks"))
    # from which set on the member is in all larger ones
    start = F.expr("array_max(filter(sequence(1, k), i -> not array_contains(ranks, i)))")
    lost = found.withColumn("gap", start).filter("gap is not null")
    return lost.select("qid", F.explode(F.expr("sequence(gap + 1, k)")).alias("i")).groupBy("qid", F.col("i").cast("long").alias("i")).agg(F.count(F.lit(1)).alias("elems"))


def _one_image(sets: DataFrame, cfg: Cfg) -> Index:
    from wordset.operators.groups import build

    return build(sets, cfg.with_(m=1), keep=True)


def space_multires(levels: DataFrame) -> DataFrame:
    """Per level below the finest, counted from it upward: groups, and the words of their ``first`` entries, each a group-local offset of
    log2 of the group's size in bits."""
    top = levels.groupBy("set_id").agg(F.max("t").alias("top"))
    rows = levels.join(top, "set_id").withColumn("size", F.col("right") - F.col("left") + 1)
    return rows.groupBy((F.col("top") - F.col("t")).cast("long").alias("up")).agg(F.count(F.lit(1)).alias("groups"), F.sum(F.expr(hashing.bits_of_sql("size"))).cast("long").alias("first_words"))


def space_families(sets: DataFrame, cfg: Cfg, ms=(1, 2, 4, 8)) -> DataFrame:
    """``space_words`` of many families ``(family, set_id, elem)`` in one pass; groups are counted, not made."""
    n = sets.groupBy("family", "set_id").agg(F.count(F.lit(1)).alias("n"))
    t = F.expr(hashing.t_scan_sql("n", cfg)).cast("int")
    rows = sets.join(n.select("family", "set_id", t.alias("t")), ["family", "set_id"])
    groups = rows.groupBy("family", "set_id", F.expr(hashing.prefix_sql(hashing.g_sql("elem", cfg), "t", cfg)).alias("z")).agg(F.count(F.lit(1)).alias("n"))
    g = groups.groupBy("family").agg(F.count(F.lit(1)).alias("g"), F.sum("n").alias("n"))
    runs = n.groupBy("family").agg(F.sum(F.expr(f"ceil(n / {cfg.root})")).alias("runs"))
    forms = [("plain", 0, "n"), *(("image_scan", m, f"n + {m + 1} * g") for m in ms), ("prefix_groups", 1, "1.5 * n + 3 * g"), ("fixed_groups", 1, "1.5 * n + 2 * runs"), ("prefix_probe", 0, "n + 2 * g")]
    both = g.join(runs, "family").select("family", "n", F.explode(F.array(*(F.struct(F.lit(s).alias("structure"), F.lit(m).cast("long").alias("m"), F.expr(f).cast("double").alias("words")) for s, m, f in forms))).alias("x"))
    return both.select("family", "x.structure", "x.m", F.floor("x.words").cast("long").alias("words"), F.round(F.col("x.words") / F.col("n") - 1, 6).alias("overhead"))


def group_tail(index: Index, eps: float) -> DataFrame:
    """Mean size of the groups over all prefixes, and the share above (1+eps) root(w)."""
    root = index.cfg.root
    all_ = index.stats.agg(F.sum(F.pow(F.lit(2), F.col("t"))).alias("cells"), F.sum("n").alias("members"))
    big = index.groups.agg(F.count_if(F.col("n") > (1 + eps) * root).alias("big"))
    return all_.crossJoin(big).select((F.col("members") / F.col("cells")).alias("mean_size"), (F.col("big") / F.col("cells")).alias("tail"))


def bounds(w: int, m: int) -> dict[str, float]:
    """Lower bounds on filtering at width w: of one image at groups of root(w); delta, the size factor that groups rarely
    exceed; beta_1 and beta_2, of one image at random sizes; of m images by the better of these; alpha, the factor per image."""
    root = math.isqrt(w)
    delta = 1 + math.sqrt(6 * math.log(4 * root) / root)
    share = max(0.0, 1 - delta / root)
    beta_1 = max(0.0, 1 - (1 + delta * root) / (4 * root)) * share ** (delta * root)
    beta_2 = max(0.0, 1 - math.exp(-root / 12) - 3 / 8) * share ** (1.5 * root)
    beta = max(beta_1, beta_2)
    return {"one_image": (1 - 1 / root) ** root, "delta": delta, "beta_1": beta_1, "beta_2": beta_2, "m_images": 1 - (1 - beta) ** m, "alpha": 1 / (1 - beta)}


def bounds_frame(spark: SparkSession, settings: list[tuple[int, int]]) -> DataFrame:
    """The same for a list of (w, m), computed by Spark."""
    rows = spark.createDataFrame(settings, "w int, m int").withColumn("s", F.sqrt("w"))
    rows = rows.withColumn("delta", 1 + F.sqrt(6 * F.log(4 * F.col("s")) / F.col("s"))).withColumn("q", F.greatest(F.lit(0.0), 1 - F.col("delta") / F.col("s")))
    rows = rows.withColumn("beta_1", F.greatest(F.lit(0.0), 1 - (1 + F.col("delta") * F.col("s")) / (4 * F.col("s"))) * F.pow("q", F.col("delta") * F.col("s")))
    rows = rows.withColumn("beta_2", F.greatest(F.lit(0.0), 1 - F.exp(-F.col("s") / 12) - 0.375) * F.pow("q", 1.5 * F.col("s"))).withColumn("beta", F.greatest("beta_1", "beta_2"))
    r = lambda c: F.round(c, 6)
    return rows.select("w", "m", r(F.pow(1 - 1 / F.col("s"), F.col("s"))).alias("one_image"), r("delta").alias("delta"), r("beta_1").alias("beta_1"), r("beta_2").alias("beta_2"), r(1 - F.pow(1 - F.col("beta"), F.col("m"))).alias("m_images"), r(1 / (1 - F.col("beta"))).alias("alpha"))


def bounds_of(sets: DataFrame, settings: list[tuple[int, int]]) -> DataFrame:
    """The bounds with the ``groups`` of root(w) members that the sets make at each width, and how many of so many pairs of groups without a
    common member one image spares at least (``spared``)."""
    n = set_stats(sets).groupBy("n").agg(F.count(F.lit(1)).alias("alike"))
    roots = F.array(*(F.struct(F.lit(w).alias("w"), F.lit(math.isqrt(w)).alias("s")) for w in sorted({w for w, _ in settings})))
    runs = n.select("n", "alike", F.explode(roots).alias("x")).groupBy("x.w").agg(F.sum(F.expr("alike * ((n + x.s - 1) div x.s)")).alias("groups"))
    rows = bounds_frame(sets.sparkSession, settings).join(runs, "w")
    one = F.pow(1 - 1 / F.sqrt("w"), F.sqrt("w"))
    return rows.select("*", F.round(F.col("groups") * one, 2).alias("spared"))


# ---- space


def space_words(sets: DataFrame, cfg: Cfg, ms=(1, 2, 4, 8)) -> DataFrame:
    """Words per structure: what it stores, counted on the groups, and the overhead over plain lists.

    Lists take a word per element. The scan structure adds m images and a length per group; the prefix structure an image, a
    length and a pointer per element with the first pointers; fixed runs an image, two bounds and a pointer per element."""
    from wordset.operators.groups import build

    index = build(sets, cfg.with_(m=1))
    g = index.groups.agg(F.count(F.lit(1)).alias("groups"), F.sum("n").alias("n"))
    runs = set_stats(sets).agg(F.sum(F.expr(f"ceil(n / {cfg.root})")).alias("runs"))
    both = g.crossJoin(runs)
    rows = [F.struct(F.lit("plain").alias("structure"), F.lit(0).alias("m"), F.col("n").cast("double").alias("words"))]
    rows += [F.struct(F.lit("image_scan").alias("structure"), F.lit(m).alias("m"), (F.col("n") + (m + 1) * F.col("groups")).cast("double").alias("words")) for m in ms]
    rows += [F.struct(F.lit("prefix_groups").alias("structure"), F.lit(1).alias("m"), (1.5 * F.col("n") + 3 * F.col("groups")).cast("double").alias("words"))]
    rows += [F.struct(F.lit("fixed_groups").alias("structure"), F.lit(1).alias("m"), (1.5 * F.col("n") + 2 * F.col("runs")).cast("double").alias("words"))]
    rows += [F.struct(F.lit("prefix_probe").alias("structure"), F.lit(0).alias("m"), (F.col("n") + 2 * F.col("groups")).cast("double").alias("words"))]
    out = both.select("n", F.explode(F.array(*rows)).alias("x")).select("x.*", (F.col("x.words") / F.col("n") - 1).alias("overhead"))
    return out.select("structure", "m", F.col("words").cast("long").alias("words"), F.round("overhead", 6).alias("overhead"))


def space_bits(sets: DataFrame, cfg: Cfg, m: int = 1) -> DataFrame:
    """Bits per coding: of whole lists (gaps of elements) and of the scan structure (gaps or low bits within groups)."""
    from wordset.operators.groups import build

    by = Window.partitionBy("set_id").orderBy("elem")  # gaps of posting lists, as the plain coded lists hold them
    gaps = sets.withColumn("gap", F.col("elem") - F.coalesce(F.lag("elem").over(by), F.lit(-1)))
    lists = gaps.agg(F.sum(F.expr(words.gamma_bits("gap"))).alias("gamma"), F.sum(F.expr(words.delta_bits("gap"))).alias("delta"), (F.count(F.lit(1)) * cfg.universe_bits).alias("plain"))
    index = build(sets, cfg.with_(m=m))
    members = index.groups.select("set_id", "t", "z", "n", F.posexplode("elems.g").alias("i", "g"), F.col("elems.g").alias("gs"))
    low = f"(g & (shiftleft(1L, {cfg.universe_bits} - t) - 1))"
    before = f"coalesce(try_element_at(gs, i) & (shiftleft(1L, {cfg.universe_bits} - t) - 1), -1L)"
    members = members.withColumn("gap", F.expr(f"{low} - if(i = 0, -1L, {before})"))
    coded = members.agg(F.sum(F.expr(words.gamma_bits("gap"))).alias("g_gamma"), F.sum(F.expr(words.delta_bits("gap"))).alias("g_delta"), F.sum(F.lit(cfg.universe_bits) - F.col("t")).alias("g_low"))
    heads = index.groups.agg((F.count(F.lit(1)) * m * cfg.w).alias("images"), F.sum("n").alias("ones"))
    cells = index.stats.agg(F.sum(F.expr("shiftleft(1L, t)")).alias("cells"))
    x = lists.crossJoin(coded).crossJoin(heads).crossJoin(cells)  # one row each
    head = F.col("images") + F.col("ones") + F.col("cells")  # unary sizes: a zero per member and a one per prefix
    rows = [("list", "plain", F.col("plain")), ("list", "gamma", F.col("gamma")), ("list", "delta", F.col("delta")), ("image_scan", "gamma", head + F.col("g_gamma")), ("image_scan", "delta", head + F.col("g_delta")), ("image_scan", "lowbits", head + F.col("g_low"))]
    out = x.select("plain", F.explode(F.array(*(F.struct(F.lit(s).alias("structure"), F.lit(c).alias("codec"), v.cast("long").alias("bits")) for s, c, v in rows))).alias("r"))
    return out.select("r.structure", "r.codec", "r.bits", F.round(F.col("r.bits") / F.col("plain"), 6).alias("share"))


# ---- queries


def results(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """``qid, k, n1, n2, nk, r`` of every query, by one pass over cells, in which every member is sent once."""
    sets = pruned(sets, queries)
    q = query_sets(queries, set_stats(sets))
    sizes = q.groupBy("qid").agg(F.max("k").alias("k"), F.min("n").alias("n1"), F.element_at(F.sort_array(F.collect_list("n")), F.least(F.lit(2), F.max("k"))).alias("n2"), F.max("n").alias("nk"))
    hit = cells.sizes(sets, queries)
    return sizes.join(hit, "qid", "left").select("qid", "k", "n1", "n2", "nk", F.coalesce("r", F.lit(0)).alias("r"))


def query_profile(res: DataFrame) -> DataFrame:
    """By k: number of queries, mean size ratios, mean share of the smallest set in the result, share of empty results."""
    return res.groupBy("k").agg(
        F.count(F.lit(1)).alias("queries"),
        F.round(F.avg(F.col("n1") / F.col("n2")), 6).alias("n1_n2"),
        F.round(F.avg(F.col("n1") / F.col("nk")), 6).alias("n1_nk"),
        F.round(F.avg(F.col("r") / F.col("n1")), 6).alias("r_n1"),
        F.round(F.avg((F.col("r") == 0).cast("double")), 6).alias("empty"),
    )


def selectivity_profile(res: DataFrame) -> DataFrame:
    """By k: share of queries whose result is at least 10 and 100 times smaller than the smallest set."""
    share = lambda f: F.round(F.avg((F.col("r") * f <= F.col("n1")).cast("double")), 6)
    return res.groupBy("k").agg(share(10).alias("tenth"), share(100).alias("hundredth"))


# ---- timings


def time_runs(makers: dict[str, Callable[[int], DataFrame]], runs: int = 20) -> list[tuple[str, int, float]]:
    """``(method, run, seconds)``: each method's plan for each run, written to nowhere."""
    out = []
    for i in range(runs):
        for name, make in makers.items():
            t = time.perf_counter()
            make(i).write.format("noop").mode("overwrite").save()
            out.append((name, i, time.perf_counter() - t))
    return out


def timings_frame(spark: SparkSession, timings: list[tuple[str, int, float]]) -> DataFrame:
    return spark.createDataFrame(timings, "method string, qid long, seconds double")


def normalise(times: DataFrame, base: str = "merge") -> DataFrame:
    """Mean seconds of each method over that of ``base``."""
    mean = times.groupBy("method").agg(F.avg("seconds").alias("seconds"))
    return mean.select("method", "seconds", (F.col("seconds") / F.max(F.when(F.col("method") == base, F.col("seconds"))).over(Window.partitionBy(F.lit(0)))).alias("normalised"))


def winners(times: DataFrame) -> DataFrame:
    """Share of queries in which each method is fastest."""
    first = times.withColumn("at", F.row_number().over(Window.partitionBy("qid").orderBy("seconds", "method"))).filter("at = 1")
    won = first.groupBy("method").agg(F.count(F.lit(1)).alias("won"))
    return times.groupBy("method").agg(F.count_distinct("qid").alias("queries")).join(won, "method", "left").select("method", (F.coalesce("won", F.lit(0)) / F.col("queries")).alias("share"))


def worst_latency(times: DataFrame, ours: str) -> DataFrame:
    """Worst time of each method over that of ``ours``."""
    worst = times.groupBy("method").agg(F.max("seconds").alias("worst"))
    return worst.select("method", "worst", (F.col("worst") / F.max(F.when(F.col("method") == ours, F.col("worst"))).over(Window.partitionBy(F.lit(0)))).alias("ratio"))


def speedup(times: DataFrame, ours: str) -> DataFrame:
    """How many times longer each method takes than ``ours``, on average."""
    mean = times.groupBy("method").agg(F.avg("seconds").alias("seconds"))
    return mean.select("method", (F.col("seconds") / F.max(F.when(F.col("method") == ours, F.col("seconds"))).over(Window.partitionBy(F.lit(0)))).alias("times"))


def regret(times: DataFrame) -> DataFrame:
    """Per method the mean and worst of its time over the best time of the same query."""
    best = F.min("seconds").over(Window.partitionBy("qid"))
    return times.withColumn("x", F.col("seconds") / best).groupBy("method").agg(F.avg("x").alias("mean_regret"), F.max("x").alias("worst_regret"))


def sweep_table(times: DataFrame, parameter: str) -> DataFrame:
    """One row per parameter value, one column per method."""
    return times.groupBy(parameter).pivot("method").agg(F.round(F.avg("seconds"), 6)).orderBy(parameter)


def preprocess_cost(builders: dict[str, Callable[[], DataFrame]], sort: Callable[[], DataFrame], runs: int = 10) -> list[tuple[str, float]]:
    """Mean build seconds of each structure over mean seconds of sorting alone."""

    def mean(make) -> float:
        total = 0.0
        for _ in range(runs):
            t = time.perf_counter()
            make().write.format("noop").mode("overwrite").save()
            total += time.perf_counter() - t
        return total / runs

    base = mean(sort)
    return [("sort", 1.0), *((name, mean(make) / base) for name, make in builders.items())]


