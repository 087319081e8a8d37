"""Groups of equal count of the sorted set, for two sets.

Members are numbered without a window over a whole set: rows are split by ranges of (set, element), numbered within their
range, and offset by the counts of the ranges before. Which groups of two sets overlap is found by an as-of search: at each group's start, the
other set's last group to start before it is the only one that can still be open. The search is cut into bins of equally many groups, so
that neither wide universes nor dense sets make it uneven.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.operators.groups import longest, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side


def numbered(sets: DataFrame) -> DataFrame:
    """The rows with ``i``, their place in their sorted set from 0: one range partitioning, in which a row's number within its partition is
    free, and a small table of where each set begins in each partition."""
    rid = F.monotonically_increasing_id()  # partition and, in 33 bits, row
    dealt = sets.repartitionByRange("set_id", "elem").sortWithinPartitions("set_id", "elem").withColumn("rid", rid)
    dealt = written(dealt.withColumn("part", F.shiftright("rid", 33)), "ranges")
    counts = dealt.groupBy("set_id", "part").agg(F.min("rid").alias("first"), F.count(F.lit(1)).alias("n"))
    skip = F.coalesce(F.sum("n").over(Window.partitionBy("set_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    counts = written(counts.select("set_id", "part", (skip - F.col("first")).alias("shift")), "range-starts")
    return dealt.join(small_side(counts), ["set_id", "part"]).withColumn("i", F.col("rid") + F.col("shift")).drop("rid", "shift", "part")


def _grouped(rows: DataFrame, cfg: Cfg, keys: tuple[str, ...], size: str, bag: bool = False) -> DataFrame:
    rows = rows.withColumn("y_1", hashing.h("elem", 1, cfg)).withColumn("p", F.expr(f"i div {size}"))
    held = F.sort_array(F.collect_list(F.struct("elem", *(["freq"] if bag else []))))
    return rows.groupBy(*keys, "p").agg(F.min("elem").alias("inf"), F.max("elem").alias("sup"), F.count(F.lit(1)).cast("int").alias("n"), *words.image_aggregates(cfg, 1), held.alias("elems"))


def build(sets: DataFrame, cfg: Cfg, size: int | None = None, bag: bool = False) -> DataFrame:
    """``set_id, p, inf, sup, n, img_1, elems``: runs of ``size`` members, root(w) if not given; the last run may be short."""
    return _grouped(numbered(sets), cfg, ("set_id",), str(size or cfg.root), bag)


def build_levels(sets: DataFrame, cfg: Cfg, most: int = 64) -> DataFrame:
    """Groups of 1, 2, 4, ... ``most`` members under ``level`` 0, 1, 2, ...: each level joins neighbours of the one below."""
    now = build(sets, cfg, 1).select(F.lit(0).alias("level"), "set_id", "p", "inf", "sup", "n", "img_1", "elems")
    out = now
    for level in range(1, hashing.bit_length(most) + 1):
        now = now.groupBy("set_id", F.expr("p div 2").alias("p")).agg(F.min("inf").alias("inf"), F.max("sup").alias("sup"), F.sum("n").cast("int").alias("n"), F.bit_or("img_1").alias("img_1"), F.sort_array(F.flatten(F.collect_list("elems"))).alias("elems"))
        now = now.select(F.lit(level).alias("level"), "set_id", "p", "inf", "sup", "n", "img_1", "elems")
        out = out.unionByName(now)
    return out


def query_groups(sets: DataFrame, queries: DataFrame, cfg: Cfg, sizes=None, bag: bool = False) -> DataFrame:
    """The groups of both sets of each query under ``side`` 1 and 2, at sizes: None for root(w), ``optimal``, or a pair of numbers."""
    sets = pruned(sets, queries)
    q = query_sets(queries, set_stats(sets))
    if (k := q.agg(F.max("k")).first()[0] or 0) > 2:
        raise ValueError(f"runs of equal count don't align for {k} sets; fold pairs instead")
    q = q.join(q.groupBy("qid").agg(F.min("n").alias("n1"), F.max("n").alias("n2")), "qid")
    if sizes is None:
        size = F.lit(cfg.root)
    elif sizes == "optimal":
        # s* <= s <= 2 s* for s* = sqrt(w n_own / n_other), as a power of two, in integers
        own, other = "if(rank = 1, n1, n2)", "if(rank = 1, n2, n1)"
        size = F.expr(f"element_at(filter(transform(sequence(0, 31), j -> shiftleft(1L, j)), s -> cast(s as decimal(19,0)) * s * {other} >= cast({cfg.w} as decimal(19,0)) * {own}), 1)")
    else:
        size = F.when(F.col("rank") == 1, sizes[0]).otherwise(sizes[1])
    q = q.select("qid", "k", F.col("rank").alias("side"), "set_id", size.cast("long").alias("size"))
    rows = numbered(sets).join(q, "set_id")
    return _grouped(rows, cfg, ("qid", "k", "side", "size"), "size", bag)


#: Groups of a bin, in the order of their starts.
BIN = 4096


def _binned(spans: DataFrame, extra: list[str]) -> tuple[DataFrame, DataFrame]:
    """The groups of each query in the order of their starts, cut into bins, and for each bin the last group of either side that starts
    before it: the only ones that can reach into it. Bins hold equal numbers of groups, whatever their values."""
    dealt = spans.repartitionByRange("qid", "inf").sortWithinPartitions("qid", "inf").withColumn("rid", F.monotonically_increasing_id())
    # equal starts stay in one bin: the bin is that of the first row of a start
    dealt = written(dealt.withColumn("bin", F.expr(f"rid div {BIN}")), "spans")
    dealt = dealt.withColumn("bin", F.min("bin").over(Window.partitionBy("qid", "inf"))).drop("rid")
    group = F.struct("inf", "p", "sup", *extra)
    ends = dealt.groupBy("qid", "bin").agg(*(F.max(F.when(F.col("side") == s, group)).alias(f"l{s}") for s in (1, 2)))
    before = Window.partitionBy("qid").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    carry = ends.select("qid", "bin", *(F.last(f"l{s}", ignorenulls=True).over(before).alias(f"c{s}") for s in (1, 2)))
    return dealt, carry


def overlaps(groups: DataFrame, how: str = "asof", extra: list[str] | None = None) -> DataFrame:
    """Pairs of groups (``a_*`` of side 1, ``b_*`` of side 2) of each query whose ranges overlap, each once: ``qid, a_p, b_p`` and the
    ``extra`` columns of both.

    ``asof``: at each start, the other side's last group to start before; ``bins``: an equi-join on bins of starts; ``theta``: for tests."""
    extra = extra or []
    names = ["p", "inf", "sup", *extra]
    spans = groups.select("qid", "side", *names)
    sides = lambda rows, *more: [rows.filter(F.col("side") == s).select("qid", *(F.col(c).alias(f"{x}_{c}") for c in [*names, *more])) for s, x in ((1, "a"), (2, "b"))]
    out = ["qid", *(f"{x}_{c}" for x in "ab" for c in ["p", *extra])]
    if how == "theta":  # no key to join on but the query
        a, b = sides(spans)
        return a.join(b.withColumnRenamed("qid", "b_qid"), (F.col("qid") == F.col("b_qid")) & (F.col("a_inf") <= F.col("b_sup")) & (F.col("b_inf") <= F.col("a_sup"))).select(*out)
    if how not in ("asof", "bins"):
        raise ValueError("how must be asof, bins or theta")
    rows, carry = _binned(spans, extra)
    if how == "bins":
        carried = carry.select("qid", "bin", F.explode(F.array(*(F.struct(F.lit(s).alias("side"), F.col(f"c{s}").alias("g")) for s in (1, 2)))).alias("x")).filter("x.g is not null")
        cells = rows.select("qid", "side", *names, "bin", F.lit(True).alias("own")).unionByName(carried.select("qid", "x.side", *(F.col(f"x.g.{c}").alias(c) for c in names), "bin", F.lit(False).alias("own")))
        a, b = sides(cells, "bin", "own")
        met = a.join(b.withColumnRenamed("qid", "b_qid"), (F.col("qid") == F.col("b_qid")) & (F.col("a_bin") == F.col("b_bin")))
        # a pair counts in the bin where the later of the two starts
        return met.filter((F.col("a_own") | F.col("b_own")) & (F.col("a_inf") <= F.col("b_sup")) & (F.col("b_inf") <= F.col("a_sup"))).select(*out)
    # at equal starts side 2 comes first: side 1 then meets it, and not the other way round as well
    order = Window.partitionBy("qid", "bin").orderBy("inf", F.col("side").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = F.struct("inf", "p", "sup", *extra)
    of = lambda s: F.coalesce(F.last(F.when(F.col("side") == s, own), ignorenulls=True).over(order), F.col(f"c{s}"))
    one = F.col("side") == 1
    both = rows.join(small_side(carry.select(F.col("qid").alias("c_qid"), F.col("bin").alias("c_bin"), "c1", "c2")), (F.col("qid") == F.col("c_qid")) & (F.col("bin") == F.col("c_bin")))
    both = both.withColumn("o", F.when(one, of(2)).otherwise(of(1))).filter(F.col("o.sup") >= F.col("inf"))
    return both.select("qid", *(F.when(one if x == "a" else ~one, F.col(c)).otherwise(F.col(f"o.{c}")).alias(f"{x}_{c}") for x in "ab" for c in ["p", *extra]))


def intersect(sets: DataFrame, queries: DataFrame, cfg: Cfg, sizes=None, how: str = "asof", bag: bool = False) -> DataFrame:
    """``qid, elem[, freq]`` of queries of one or two sets."""
    return meet(written(query_groups(sets, queries, cfg, sizes, bag), "fixed-groups"), cfg, how, bag)


def intersect_stored(groups: DataFrame, stats: DataFrame, queries: DataFrame, cfg: Cfg, how: str = "asof") -> DataFrame:
    """The same from groups that ``build`` made and a table keeps, with the sizes of their sets."""
    q = query_sets(queries, stats)
    if longest(queries) > 2:
        raise ValueError("runs of equal count don't align for more than two sets; fold pairs instead")
    return meet(groups.join(small_side(q.select("qid", "k", F.col("rank").alias("side"), "set_id")), "set_id"), cfg, how)


def meet(groups: DataFrame, cfg: Cfg, how: str = "asof", bag: bool = False) -> DataFrame:
    """Common members of groups ``qid, k, side, p, inf, sup, img_1, elems``."""
    names = [c for ws in cfg.images(1) for c in ws]
    # images travel with the ranges, members are read for pairs that pass only
    met = written(overlaps(groups, how, names).filter(words.images_meet("a_", "b_", cfg, 1)).select("qid", "a_p", "b_p"), "met")
    a, b = (groups.filter(F.col("side") == s).select("qid", F.col("p").alias(f"{x}_p"), F.col("elems").alias(f"{x}_elems")) for s, x in ((1, "a"), (2, "b")))
    full = a.join(small_side(met), ["qid", "a_p"]).join(b, ["qid", "b_p"])
    if bag:
        both = full.select("qid", F.explode(_fixed_bag_meet()).alias("x"))
    else:
        both = full.select("qid", F.explode(F.array_intersect("a_elems", "b_elems")).alias("x"))
    alone = groups.filter("k = 1").select("qid", F.explode("elems").alias("x"))
    return both.unionByName(alone).select("qid", F.col("x.elem").alias("elem"), *([F.col("x.freq").alias("freq")] if bag else []))


def _fixed_bag_meet():
    least = lambda x: F.array_min(F.transform(F.filter("b_elems", lambda y: y["elem"] == x["elem"]), lambda y: F.least(x["freq"], y["freq"])))
    return F.filter(F.transform("a_elems", lambda x: F.struct(x["elem"].alias("elem"), least(x).alias("freq"))), lambda x: x["freq"].isNotNull())


def fold(sets: DataFrame, names: list[str], cfg: Cfg) -> DataFrame:
    """More than two sets: smallest first, pair by pair."""
    from wordset.operators.groups import set_stats as stats

    spark = sets.sparkSession
    sized = {r.set_id: r.n for r in stats(sets.filter(F.col("set_id").isin(names))).collect()}  # one row per name
    if not names:
        raise ValueError("a query needs at least one set")
    order = sorted(set(names), key=lambda s: (sized.get(s, 0), s))
    now = sets.filter(F.col("set_id") == order[0]).select(F.lit("now").alias("set_id"), "elem")
    for name in order[1:]:
        more = sets.filter(F.col("set_id") == name).select(F.lit("more").alias("set_id"), "elem")
        got = intersect(now.unionByName(more), spark.createDataFrame([(0, ["now", "more"])], "qid long, set_ids array<string>"), cfg)
        now = written(got.select(F.lit("now").alias("set_id"), "elem"), "fold")
    return now.select("elem")
