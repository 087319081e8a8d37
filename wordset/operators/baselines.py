"""What the methods are measured against, as relational plans; the cursor programs are in ``kernels``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions.store import written
from wordset.operators.groups import dealt_by_element, longest, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side


def _legs(sets: DataFrame, queries: DataFrame):
    """The named sets, the legs of all queries, the largest k, and the members of the sets at a rank. Sets that ``stored`` wrote are read as they lie."""
    sets, sizes = (sets, sets.wordset_sizes) if hasattr(sets, "wordset_sizes") else (named := pruned(sets, queries), set_stats(named))
    q = written(query_sets(queries, sizes), "legs")
    legs = small_side(q.select("qid", "k", "rank", "set_id"))
    k_max = longest(queries)
    return sets, q, k_max, lambda rank: sets.join(legs.filter(F.col("rank") == rank).drop("rank"), "set_id").drop("set_id")


def stored(sets: DataFrame) -> DataFrame:
    """The sets as a table clustered by set, with their sizes beside: what the baselines have as their own pre-processing."""
    out = written(sets.repartitionByRange("set_id", "elem").sortWithinPartitions("set_id", "elem"), "stored-sets")
    out.wordset_sizes = written(set_stats(out), "sizes")
    return out


def merge(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """Sorted lists met in step: a sort-merge join per further set."""
    _, _, k_max, leg = _legs(sets, queries)
    now = leg(1)
    for rank in range(2, k_max + 1):
        more = leg(rank).select("qid", "elem").hint("merge")
        now = now.filter(F.col("k") >= rank).join(more, ["qid", "elem"], "left_semi").unionByName(now.filter(F.col("k") < rank))
    return now.select("qid", "elem")


def counting(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """One pass over all lists: an element in as many lists as the query has."""
    sets, q, _, _ = _legs(sets, queries)
    rows = dealt_by_element(sets).join(small_side(q.select("qid", "k", "set_id")), "set_id")
    return rows.groupBy("qid", "elem").agg(F.count(F.lit(1)).alias("c"), F.max("k").alias("k")).filter("c = k").select("qid", "elem")


def hashing_(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """The smallest list against a hash table of each other one, dropping what misses."""
    _, _, k_max, leg = _legs(sets, queries)
    now = leg(1)
    for rank in range(2, k_max + 1):
        more = leg(rank).select("qid", "elem").hint("shuffle_hash")
        now = now.filter(F.col("k") >= rank).join(more, ["qid", "elem"], "left_semi").unionByName(now.filter(F.col("k") < rank))
    return now.select("qid", "elem")


def smallest_first(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """Candidates of the smallest list, narrowed list by list; the planner picks each join by the candidates' size."""
    _, _, k_max, leg = _legs(sets, queries)
    now = leg(1)
    for rank in range(2, k_max + 1):
        now = now.filter(F.col("k") >= rank).join(leg(rank).select("qid", "elem"), ["qid", "elem"], "left_semi").unionByName(now.filter(F.col("k") < rank))
    return now.select("qid", "elem")


def lookup(sets: DataFrame, queries: DataFrame, cfg: Cfg) -> DataFrame:
    """A directory from id ranges to buckets of about ``cfg.bucket`` members; each candidate scans one bucket."""
    sets = pruned(sets, queries)
    sizes = set_stats(sets).withColumn("width", F.expr(f"greatest(1, ((sup - inf + 1) * {cfg.bucket}) div n)"))
    q = query_sets(queries, sizes).join(sizes.select("set_id", "inf", "width"), "set_id")
    k_max = longest(queries)
    rows = sets.join(sizes.select("set_id", "inf", "width"), "set_id").withColumn("bucket", F.expr("(elem - inf) div width"))
    buckets = rows.groupBy("set_id", "bucket").agg(F.collect_list("elem").alias("elems"))
    one = lambda r: q.filter(F.col("rank") == r)
    now = sets.join(small_side(one(1).select("qid", "k", "set_id")), "set_id").select("qid", "k", "elem")
    for rank in range(2, k_max + 1):
        to = one(rank).select(F.col("qid").alias("t_qid"), F.col("set_id").alias("t_set"), "inf", "width")
        going = now.filter(F.col("k") >= rank).join(small_side(to), F.col("qid") == F.col("t_qid")).withColumn("t_bucket", F.expr("floor((elem - inf) / width)"))
        hit = going.join(buckets, (F.col("t_set") == F.col("set_id")) & (F.col("t_bucket") == F.col("bucket"))).filter(F.array_contains("elems", F.col("elem")))
        now = hit.select("qid", "k", "elem").unionByName(now.filter(F.col("k") < rank))
    return now.select("qid", "elem")


def packed_codes(sets: DataFrame, queries: DataFrame, cfg: Cfg, bits: int = 8) -> DataFrame:
    """Buckets by leading hash bits; short codes in a bucket are compared first and members behind equal codes verified."""
    from wordset.functions import hashing

    sets = pruned(sets, queries)
    sizes = set_stats(sets)
    q = query_sets(queries, sizes)
    q = q.join(q.groupBy("qid").agg(F.max("n").alias("n_max")), "qid").withColumn("t", F.expr(hashing.bits_of_sql("n_max div 8")).cast("int"))
    k_max = longest(queries)
    g = hashing.g_sql("elem", cfg)

    def leg(rank: int) -> DataFrame:
        rows = sets.join(small_side(q.filter(F.col("rank") == rank).select("qid", "k", "t", "set_id")), "set_id")
        code = F.expr(f"shiftrightunsigned({g}, greatest(0, {cfg.universe_bits} - t - {bits})) & {(1 << bits) - 1}")
        return rows.select("qid", "k", F.expr(hashing.prefix_sql(g, "t", cfg)).alias("z"), code.alias("code"), "elem")

    now = leg(1)
    for rank in range(2, k_max + 1):
        more = leg(rank).select("qid", "z", "code", F.col("elem").alias("other"))
        met = now.filter(F.col("k") >= rank).join(more, ["qid", "z", "code"]).filter("elem = other").select(*now.columns)
        now = met.unionByName(now.filter(F.col("k") < rank))
    return now.select("qid", "elem")


def spark_arrays(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """Spark's own ``array_intersect`` over whole lists, for lists that fit in a row."""
    sets = pruned(sets, queries)
    q = query_sets(queries, set_stats(sets))
    lists = sets.groupBy("set_id").agg(F.collect_list("elem").alias("elems")).join(small_side(q.select("qid", "k", "set_id")), "set_id")
    all_ = lists.groupBy("qid").agg(F.collect_list("elems").alias("ls"))
    return all_.select("qid", F.explode(F.aggregate(F.slice("ls", F.lit(2), F.size("ls")), F.element_at("ls", 1), F.array_intersect)).alias("elem"))


def spark_intersect(sets: DataFrame, a: str, b: str) -> DataFrame:
    """``INTERSECT`` of two named sets."""
    of = lambda s: sets.filter(F.col("set_id") == s).select("elem")
    return of(a).intersect(of(b))


def sort_only(sets: DataFrame) -> DataFrame:
    """Sorting, the yardstick of pre-processing."""
    return sets.repartitionByRange("set_id", "elem").sortWithinPartitions("set_id", "elem")
