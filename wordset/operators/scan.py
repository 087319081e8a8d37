"""k-way intersection over prefix groups: images first, members of the surviving groups after.

The sets of a query are taken smallest first. A group of a larger set, whose prefix is longer, lies below one group of
every smaller set, so groups are aligned by equi-joins on prefixes. Each prefix is cut to its predecessor's length from
columns of its own side, before the join. A row of the chain carries the AND of the images so far, computed once and
shared by all groups below it, and is dropped when an image is zero. Only then are members read, and only those of surviving groups.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.operators.groups import Index, longest, query_sets
from wordset.plans.sizing import BROADCAST_ROWS, literal_frame, small_side


def _names(cfg: Cfg, m: int) -> list[str]:
    return [c for ws in cfg.images(m) for c in ws]


def legs(index: Index, queries: DataFrame) -> DataFrame:
    """``qid, k, rank, set_id, t, t_prev, ts``: each query's sets with the lengths of all its prefixes."""
    from pyspark.sql import Window

    q = query_sets(queries, index.stats)
    by = Window.partitionBy("qid")
    return q.select("qid", "k", "rank", "set_id", "t", F.lag("t").over(by.orderBy("rank")).alias("t_prev"), F.sort_array(F.collect_list(F.struct("rank", "t")).over(by)).alias("ts"))


#: Rows of (query, set) up to which a batch is planned on the driver; larger ones are planned by Spark.
SMALL_BATCH = 1000
_LEGS = pa.schema([("qid", pa.int64()), ("k", pa.int32()), ("rank", pa.int32()), ("set_id", pa.string()), ("t", pa.int32()), ("t_prev", pa.int32()), ("ts", pa.list_(pa.struct([("rank", pa.int32()), ("t", pa.int32())])))])


def planned(index: Index, queries: DataFrame) -> tuple[Index, DataFrame, int, int | None]:
    """The index restricted to the sets that the queries name, their legs, the largest k, and a bound on the groups that may be read.

    A small batch needs one look at the sizes of its sets: names become a filter by which a scan of stored groups skips the files and row
    groups of other sets, and the bound on groups tells whether they can be broadcast. A large batch is a table like any other."""
    pairs = queries.select("qid", F.explode(F.array_distinct("set_ids")).alias("set_id")).limit(SMALL_BATCH + 1).collect()
    if not pairs:
        raise ValueError("a query needs at least one set")
    if len(pairs) > SMALL_BATCH:
        return index, written(legs(index, queries), "legs"), longest(queries), None
    names = sorted({p.set_id for p in pairs})
    near = Index(index.groups.filter(F.col("set_id").isin(names)), index.stats.filter(F.col("set_id").isin(names)), index.cfg, index.method, index.bag, index.meta)
    sizes = {r.set_id: (r.n, r.t) for r in near.stats.select("set_id", "n", "t").collect()}
    by: dict[int, list[str]] = {}
    for p in pairs:
        by.setdefault(p.qid, []).append(p.set_id)
    rows, bound = [], 0
    for qid, asked in by.items():
        if not all(s in sizes for s in asked):
            continue  # the result is empty
        order = sorted(asked, key=lambda s: (sizes[s][0], s))
        ts = [(i, sizes[s][1]) for i, s in enumerate(order, 1)]
        rows += [(qid, len(order), i, s, sizes[s][1], ts[i - 2][1] if i > 1 else None, ts) for i, s in enumerate(order, 1)]
        bound += len(order) << ts[-1][1]
    rows = [(*r[:-1], [{"rank": i, "t": t} for i, t in r[-1]]) for r in rows]
    return near, literal_frame(queries.sparkSession, rows, _LEGS), max(map(len, by.values())), bound


def _leg(index: Index, q: DataFrame, rank: int, columns: list[str]) -> DataFrame:
    """The groups of the sets at one rank of all queries, keyed by their prefix cut to the length before."""
    mine = q.filter(F.col("rank") == rank).select("qid", "k", "set_id", F.col("t").alias("qt"), "t_prev")
    rows = index.groups.select("set_id", "t", "z", *columns).join(mine, "set_id")
    return rows.withColumn("zkey", F.expr("shiftrightunsigned(z, t - coalesce(t_prev, t))"))


def align_images(index: Index, q: DataFrame, k_max: int, m: int, memo: bool = True) -> list[DataFrame]:
    """Per rank, the rows ``qid, k, z, n, img_*`` of group chains whose images still meet after that many sets.

    ``memo=False`` keeps the images of all sets apart and tests them at the end, for comparison."""
    cfg, names = index.cfg, _names(index.cfg, m)
    now = _leg(index, q, 1, ["n", *names]).select("qid", "k", "z", "n", *(F.col(c).alias(f"l_{c}") for c in names))
    out = [now]
    for rank in range(2, k_max + 1):
        more = _leg(index, q, rank, ["n", *names]).select(F.col("qid").alias("r_qid"), "zkey", F.col("z").alias("r_z"), F.col("n").alias("r_n"), *(F.col(c).alias(f"r_{c}") for c in names))
        left = now.filter(F.col("k") >= rank)
        pairs = left.join(more, (F.col("qid") == F.col("r_qid")) & (F.col("z") == F.col("zkey")))
        met = pairs.select("qid", "k", F.col("r_z").alias("z"), F.col("r_n").alias("n"), *(F.col(f"l_{c}").bitwiseAND(F.col(f"r_{c}")).alias(f"l_{c}") for c in names))
        now = met.filter(~words.any_zero("l_", cfg, m)) if memo or rank == k_max else met
        out.append(now)
    return out


def survivors(index: Index, queries: DataFrame, m: int | None = None, memo: bool = True, plan: tuple | None = None) -> tuple[DataFrame, DataFrame, int]:
    """Chains of groups that pass all images: ``qid, k, z, t_k, ts``; the legs; the largest k."""
    cfg = index.cfg
    m = cfg.m if m is None else m
    if m > cfg.m:
        raise ValueError("the index has fewer images")
    _, q, k_max, _ = plan = plan or planned(index, queries)
    index = plan[0]
    steps = align_images(index, q, k_max, m, memo)
    done = [s.filter(F.col("k") == r).select("qid", "k", "z", *(f"l_{c}" for c in _names(cfg, m))) for r, s in enumerate(steps, 1)]
    full = done[0]
    for d in done[1:]:
        full = full.unionByName(d)
    last = q.filter(F.col("rank") == F.col("k")).select(F.col("qid").alias("q_qid"), F.col("t").alias("t_k"), "ts")
    return full.join(last, F.col("qid") == F.col("q_qid")).drop("q_qid"), q, k_max


def _wanted(index: Index, alive: DataFrame, q: DataFrame, bound: int | None) -> DataFrame:
    """The groups that surviving chains name, with their members.

    They are a table of (set, prefix), and members are read by one join with it: broadcast while it is small, so that
    the members of groups that images proved empty never leave the scan. ``bound`` is a proven bound on its rows; without one they are counted."""
    legs_ = q.select(F.col("qid").alias("w_qid"), "rank", F.col("set_id").alias("w_set"))
    at = F.expr("shiftrightunsigned(z, t_k - get(ts, rank - 1).t)").alias("w_z")
    wanted = alive.join(legs_, F.col("qid") == F.col("w_qid")).select("qid", F.col("z").alias("chain"), "t_k", "k", "rank", "w_set", at, *(c for c in alive.columns if c.startswith("l_")))
    wanted = F.broadcast(wanted) if bound is not None and bound <= BROADCAST_ROWS else small_side(written(wanted, "wanted"))
    return index.groups.select("set_id", "z", "elems").join(wanted, (F.col("set_id") == F.col("w_set")) & (F.col("z") == F.col("w_z")))


def gather(index: Index, alive: DataFrame, q: DataFrame, bound: int | None = None) -> DataFrame:
    """``qid, elem[, freq]``: members of surviving chains that all k sets have. A member counts in the one chain that has its own
    prefix, so a group that stands above several chains sends each member once."""
    rows = _wanted(index, alive, q, bound)
    if index.bag:
        rows = rows.select("qid", "k", "chain", "t_k", F.explode("elems").alias("x")).select("qid", "k", "chain", "t_k", "x.elem", "x.freq")
    else:  # places are computed again rather than read
        rows = rows.select("qid", "k", "chain", "t_k", F.explode("elems.elem").alias("elem"))
    rows = rows.filter(F.expr(hashing.prefix_sql(hashing.g_sql("elem", index.cfg), "t_k", index.cfg)) == F.col("chain"))
    if index.bag:
        return rows.groupBy("qid", "elem", "k").agg(F.count(F.lit(1)).alias("c"), F.min("freq").alias("freq")).filter("c = k").select("qid", "elem", "freq")
    return rows.groupBy("qid", "elem", "k").agg(F.count(F.lit(1)).alias("c")).filter("c = k").select("qid", "elem")


def fetch(index: Index, alive: DataFrame, q: DataFrame, elems=None, finest: bool = False, bound: int | None = None) -> DataFrame:
    """Members common to all groups of each surviving chain: ``qid, z, e``, by meeting a chain's k short lists one after the other.

    From the largest set down (``finest``) or from the smallest up. ``elems`` turns the group's member array into the one to
    intersect (a filter by image bits)."""
    rows = _wanted(index, alive, q, bound)
    order = F.col("rank") if not finest else -F.col("rank")
    lists = rows.select("qid", "chain", "k", F.struct(order.alias("o"), (elems(F.col("elems")) if elems else F.col("elems")).alias("e")).alias("x")).filter(F.size("x.e") > 0)
    met = lists.groupBy("qid", "chain").agg(F.first("k").alias("k"), F.sort_array(F.collect_list("x")).alias("xs")).filter(F.size("xs") == F.col("k"))
    meet = _bag_meet if index.bag else F.array_intersect
    e = F.aggregate(F.slice("xs", F.lit(2), F.size("xs")), F.element_at("xs", 1)["e"], lambda acc, x: meet(acc, x["e"]))
    return met.select("qid", F.col("chain").alias("z"), e.alias("e"))


def _bag_meet(a, b):
    """Common members of two arrays with the smaller frequency."""
    return F.filter(
        F.transform(a, lambda x: F.struct(x["g"].alias("g"), x["elem"].alias("elem"), F.array_min(F.transform(F.filter(b, lambda y: y["elem"] == x["elem"]), lambda y: F.least(x["freq"], y["freq"]))).alias("freq"))),
        lambda x: x["freq"].isNotNull(),
    )


def _emit(got: DataFrame, bag: bool) -> DataFrame:
    one = got.select("qid", F.explode_outer("e").alias("x")).filter("x is not null")  # an inner one would be guarded by the same fold again
    return one.select("qid", F.col("x.elem").alias("elem"), *([F.col("x.freq").alias("freq")] if bag else []))


def intersect(index: Index, queries: DataFrame, m: int | None = None, memo: bool = True) -> DataFrame:
    """``qid, elem[, freq]`` of queries ``(qid, set_ids)``; a query with an unknown or empty set has no rows."""
    plan = planned(index, queries)
    alive, q, _ = survivors(index, queries, m, memo, plan)
    return gather(plan[0], alive, q, plan[3])


def common_bits(index: Index, m: int) -> object:
    """Keeps the members whose hash is a bit of the chain's common image: those another member may equal."""
    cfg = index.cfg
    tests = []
    for j, names in enumerate(cfg.images(m), 1):
        bit = hashing.h_sql("x.elem", j, cfg)
        if cfg.words == 1:
            tests.append(f"(shiftrightunsigned(l_{names[0]}, cast({bit} as int)) & 1) = 1")
        else:
            word = f"element_at(array({', '.join('l_' + c for c in names)}), cast({bit} div 64 as int) + 1)"
            tests.append(f"(shiftrightunsigned({word}, cast({bit} % 64 as int)) & 1) = 1")
    return lambda elems: F.expr(f"filter(elems, x -> {' and '.join(tests)})")


def intersect_by_bits(index: Index, queries: DataFrame, memo: bool = True, finest: bool = True) -> DataFrame:
    """As ``intersect`` with one image, but only members that hash to a common bit are compared at all."""
    plan = planned(index, queries)
    alive, q, _ = survivors(index, queries, 1, memo, plan)
    return _emit(fetch(plan[0], alive, q, common_bits(index, 1), finest, plan[3]), index.bag)
