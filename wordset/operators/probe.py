"""Sets of very unequal sizes: the few members of the small set are looked up in the large one, by groups.

Both sides are cut by the first ceil(log2 n1) bits of the common order, so that a group of the small set has about
one member, and a member is searched by its place in the order among the members of the facing group only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing
from wordset.functions.store import written
from wordset.operators.groups import longest, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side


def intersect(sets: DataFrame, queries: DataFrame, cfg: Cfg, how: str = "join") -> DataFrame:
    """``qid, elem``. ``join``: members meet on (prefix, place), both sides dealt alike; ``broadcast``: the small side goes to
    every task behind a check of its size, so that the large sets are never shuffled."""
    sets, sizes = (sets, sets.wordset_sizes) if hasattr(sets, "wordset_sizes") else (near := pruned(sets, queries), set_stats(near))
    q = query_sets(queries, sizes)
    q = written(q.withColumn("t", F.expr(f"max(if(rank = 1, {hashing.bits_of_sql('n')}, null)) over (partition by qid)").cast("int")), "legs")
    legs = small_side(q.select("qid", "k", "rank", "t", "set_id"))
    rows = sets.select("set_id", "elem", hashing.g("elem", cfg).alias("g"))
    k_max = longest(queries)

    def leg(rank: int) -> DataFrame:
        return rows.join(legs.filter(F.col("rank") == rank), "set_id").select("qid", "k", F.expr(hashing.prefix_sql("g", "t", cfg)).alias("z"), "g", "elem")

    now = leg(1)
    for rank in range(2, k_max + 1):  # set i is searched for what sets 1 to i-1 have in common
        big = leg(rank).select("qid", "z", "g")
        going, done = now.filter(F.col("k") >= rank), now.filter(F.col("k") < rank)
        if how == "broadcast":
            found = big.join(small_side(going), ["qid", "z", "g"]).select("qid", "k", "z", "g", "elem")
        else:
            found = going.join(big, ["qid", "z", "g"], "left_semi")
        now = found.unionByName(done)
    return now.select("qid", "elem")


def bounds(sets: DataFrame, cfg: Cfg, t: str) -> DataFrame:
    """``set_id, z, left, right``: the run of places of each group, the only structure that the search needs."""
    from pyspark.sql import Window

    rows = sets.join(set_stats(sets).withColumn("t", F.expr(t).cast("int")).select("set_id", "t"), "set_id").withColumn("z", F.expr(hashing.prefix_sql(hashing.g_sql("elem", cfg), "t", cfg)))
    n = rows.groupBy("set_id", "z").agg(F.count(F.lit(1)).alias("n"))
    right = F.sum("n").over(Window.partitionBy("set_id").orderBy("z").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return n.select("set_id", "z", (right - F.col("n")).alias("left"), (right - 1).alias("right"))
