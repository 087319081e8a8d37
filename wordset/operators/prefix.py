"""Prefix groups with one image and inverse lists: two sets at a granularity of their own, k sets, all granularities."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.functions.worker import on_worker
from wordset.operators import scan
from wordset.operators.groups import Index, group_by_prefix, hashed, ordered, pruned, query_sets, set_stats
from wordset.plans.sizing import small_side


def build(sets: DataFrame, cfg: Cfg, t: str | None = None, bag: bool = False, keep: bool = False) -> Index:
    """One resolution: groups of about root(w) members with an image; the inverse list of a bit is read off the members."""
    from wordset.operators import groups

    out = groups.build(sets, cfg, 1, t, bag, keep)
    out.method = "prefix"
    return out


def inverse_lists(index: Index) -> DataFrame:
    """``set_id, t, z, y, elems``: the members of each group by image bit, in the order of g."""
    e = index.groups.select("set_id", "t", "z", F.posexplode("elems").alias("i", "x"))
    e = e.select("set_id", "t", "z", "i", F.col("x.elem").alias("elem")).withColumn("y", hashing.h("elem", 1, index.cfg))
    return e.groupBy("set_id", "t", "z", "y").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "elem"))), lambda x: x["elem"]).alias("elems"))


def intersect_pairs(sets: DataFrame, queries: DataFrame, cfg: Cfg, mode: str = "same_count") -> DataFrame:
    """Two sets per query. ``same_count``: as many groups in both, so that few pairs meet even for unequal sizes;
    ``same_size``: groups of equal size, one of the smaller set facing several of the larger.

    Members are grouped for the query from the hashed rows; the pair's own exponent comes from its sizes."""
    sets = pruned(sets, queries)
    if mode == "same_size":
        return scan.intersect_by_bits(build(sets, cfg, keep=True), queries)
    if mode != "same_count":
        raise ValueError("mode must be same_count or same_size")
    q = query_sets(queries, set_stats(sets))
    pair = q.groupBy("qid").agg(F.max("k").alias("k"), F.min("n").alias("n1"), F.max("n").alias("n2"))
    product = "cast(n1 as decimal(19,0)) * cast(n2 as decimal(19,0))"
    t = F.expr(f"element_at(filter(sequence(0, 40), t -> cast(pow(4, t) as decimal(38,0)) * {cfg.w} >= {product}), 1)")
    mine = q.join(pair.filter("k <= 2").select("qid", t.cast("int").alias("t")), "qid").select("qid", "k", "rank", "set_id", "t")
    rows = hashed(sets, cfg, 1).join(mine, "set_id")
    g = group_by_prefix(rows, cfg, 1, ("qid", "k", "rank"))
    one, two = (g.filter(F.col("rank") == r).select("qid", "k", "z", *(F.col(c).alias(f"{s}_{c}") for c in [x for ws in cfg.images(1) for x in ws]), F.col("elems").alias(f"{s}_e")) for r, s in ((1, "a"), (2, "b")))
    met = one.join(two.drop("k"), ["qid", "z"]).filter(words.images_meet("a_", "b_", cfg, 1))
    both = met.select("qid", F.explode(F.array_intersect("a_e", "b_e")).alias("x"))
    alone = one.filter("k = 1").select("qid", F.explode("a_e").alias("x"))
    return both.unionByName(alone).select("qid", F.col("x.elem").alias("elem"))


# ---- all granularities of one order


#: Levels that are made in one pass over the level below them.
STRIDE = 5


def build_multires(sets: DataFrame, cfg: Cfg, coarse: int = 4) -> tuple[DataFrame, DataFrame]:
    """The element table ``set_id, pos, g, elem, y, next_pos`` and the level table ``set_id, t, z, left, right, img, first``.

    Positions number a set's members by g. No window spans a whole set: members are numbered within their coarse
    prefix, and the counts of the prefixes before give the offset. A group of level t is the union of its two halves at level
    t+1, so levels are made upward from the finest, several in one pass."""
    rows = hashed(sets, cfg, 1).withColumn("c", F.expr(hashing.prefix_sql("g", coarse, cfg)))
    in_block = Window.partitionBy("set_id", "c").orderBy(ordered("g", cfg))
    counts = rows.groupBy("set_id", "c").agg(F.count(F.lit(1)).alias("n"))
    skip = F.coalesce(F.sum("n").over(Window.partitionBy("set_id").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    counts = counts.select("set_id", "c", skip.alias("skip"))
    placed = rows.withColumn("i", F.row_number().over(in_block)).join(counts, ["set_id", "c"]).withColumn("pos", F.col("i") + F.col("skip") - 1)
    # the next member with the same bit: within the block, else the first of a later block
    same = Window.partitionBy("set_id", "c", "y_1").orderBy("pos")
    heads = placed.groupBy("set_id", "y_1", "c").agg(F.min("pos").alias("head"))
    later = heads.select("set_id", "y_1", "c", F.lead("head").over(Window.partitionBy("set_id", "y_1").orderBy("c")).alias("after"))
    elements = placed.withColumn("within", F.lead("pos").over(same)).join(later, ["set_id", "y_1", "c"])
    elements = written(elements.select("set_id", "pos", "g", "elem", F.col("y_1").alias("y"), F.coalesce("within", "after").alias("next_pos")), "multires-elements")

    sizes = set_stats(sets).withColumn("t", F.expr(hashing.bits_of_sql("n")).cast("int"))  # levels 0 to ceil(log2 n)
    leaf = elements.join(sizes.select("set_id", "t"), "set_id").withColumn("z", F.expr(hashing.prefix_sql("g", "t", cfg)))
    level = written(leaf.groupBy("set_id", "t", "z", "y").agg(F.min("pos").alias("at"), F.max("pos").alias("last")), "level")
    rows = level
    while (top := level.agg(F.max("t")).first()[0]) and top > 0:
        # the next STRIDE levels of each set in one shuffle, from the top level so far
        up = level.withColumn("by", F.explode(F.expr(f"sequence(1, least({STRIDE}, t))"))).filter("t > 0")
        up = up.select("set_id", (F.col("t") - F.col("by")).alias("t"), F.expr("shiftrightunsigned(z, by)").alias("z"), "y", "at", "last", "by")
        up = written(up.groupBy("set_id", "t", "z", "y").agg(F.min("at").alias("at"), F.max("last").alias("last"), F.max("by").alias("by"), F.lit(0).alias("_")), "level")
        rows = rows.unionByName(up.drop("by", "_"))
        level = up.filter((F.col("by") == STRIDE) & (F.col("t") > 0)).drop("by", "_")
    out = rows.groupBy("set_id", "t", "z").agg(F.min("at").alias("left"), F.max("last").alias("right"), words.word_of(F.col("y")).alias("img"), F.map_from_entries(F.sort_array(F.collect_list(F.struct("y", "at")))).alias("first"))
    return elements, written(out, "multires-levels")


def inverse_of(elements: DataFrame, levels: DataFrame, t: int, cfg: Cfg = Cfg()) -> DataFrame:
    """``set_id, z, y, elems`` at level t: for each bit of a group, the list that starts at ``first`` and follows ``next_pos``
    up to the right bound. Members come to their group by an equi-join on the prefix; a task walks one group after the other."""
    at = levels.filter(F.col("t") == t).select("set_id", "z", "left", "right", F.map_entries("first").alias("heads"))
    e = elements.select(F.col("set_id").alias("e_set"), F.expr(hashing.prefix_sql("g", t, cfg)).alias("e_z"), "pos", "elem", "next_pos")
    # the heads come with the group's first member only
    rows = e.join(at, (F.col("set_id") == F.col("e_set")) & (F.col("z") == F.col("e_z"))).select("set_id", "z", "pos", "elem", "next_pos", "right", F.when(F.col("pos") == F.col("left"), F.col("heads")).alias("heads"))
    rows = rows.repartition("set_id", "z").sortWithinPartitions("set_id", "z", "pos")
    return rows.mapInArrow(on_worker(__name__, "walk_lists"), "set_id string, z long, y int, elems array<long>")


def walk_lists(batches):
    """Rows of groups in order of place -> the inverse lists, by following pointers from each list's head."""
    held: list[tuple] = []
    key = None

    def walked():
        at = {r[2]: (r[3], r[4]) for r in held}
        right = held[0][5]
        for head in held[0][6]:
            elems, pos = [], head["value"]
            while pos is not None and pos <= right:
                elem, pos = at[pos]
                elems.append(elem)
            yield held[0][0], held[0][1], head["key"], elems

    def batch(rows):
        cols = list(zip(*rows, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int32()), pa.array(cols[3], pa.list_(pa.int64()))], ["set_id", "z", "y", "elems"])

    for b in batches:
        out = []
        for r in zip(*(c.to_pylist(maps_as_pydicts=None) for c in b.columns), strict=True):
            if key != r[:2] and held:
                out += walked()
                held = []
            key = r[:2]
            held.append(r)
        if out:
            yield batch(out)
    if held:
        yield batch(list(walked()))


def intersect_multires(elements: DataFrame, levels: DataFrame, sets: DataFrame, queries: DataFrame, cfg: Cfg, mode: str = "same_size") -> DataFrame:
    """k sets at the exponents their sizes ask for, or two at the pair's own, from one stored structure."""
    sizes = set_stats(sets)
    t = hashing.t_scan_sql("n", cfg)
    groups = levels.select("set_id", "t", "z", "left", "right", F.col("img").alias("img_1"))
    if mode == "same_count":
        q = query_sets(queries, sizes)
        p = "cast(min(n) over (partition by qid) as decimal(19,0)) * cast(max(n) over (partition by qid) as decimal(19,0))"
        q = q.withColumn("p", F.expr(p)).select("qid", "k", "rank", "set_id", F.expr(f"element_at(filter(sequence(0, 40), t -> cast(pow(4, t) as decimal(38,0)) * {cfg.w} >= p), 1)").cast("int").alias("t"))
        top = levels.groupBy("set_id").agg(F.max("t").alias("top"))
        q = q.join(top, "set_id")
        q = q.withColumn("t", F.least("t", F.min("top").over(Window.partitionBy("qid"))))
    else:
        q = query_sets(queries, sizes.withColumn("t", F.expr(t).cast("int"))).select("qid", "k", "rank", "set_id", "t")
    q = q.withColumn("t_prev", F.coalesce(F.lag("t").over(Window.partitionBy("qid").orderBy("rank")), F.col("t")))
    k_max = scan.longest(queries)
    now = None
    for rank in range(1, k_max + 1):
        mine = q.filter(F.col("rank") == rank)
        leg = groups.join(mine, ["set_id", "t"]).select("qid", "k", F.expr("shiftrightunsigned(z, t - t_prev)").alias("zkey"), "z", "img_1", F.struct("set_id", "left", "right").alias("span"))
        if now is None:
            now = leg.select("qid", "k", "z", "img_1", F.array("span").alias("spans"))
            continue
        r = leg.select(F.col("qid").alias("r_qid"), "zkey", F.col("z").alias("r_z"), F.col("img_1").alias("r_img"), "span")
        ended = now.filter(F.col("k") < rank)
        step = now.filter(F.col("k") >= rank).join(r, (F.col("qid") == F.col("r_qid")) & (F.col("z") == F.col("zkey")))
        step = step.select("qid", "k", F.col("r_z").alias("z"), F.col("img_1").bitwiseAND(F.col("r_img")).alias("img_1"), F.array_append("spans", F.col("span")).alias("spans")).filter("img_1 <> 0")
        now = step.unionByName(ended)
    last = q.groupBy("qid").agg(F.max_by("t", "rank").alias("t_last"))
    spans = now.select("qid", "k", "z", "img_1", F.explode("spans").alias("s")).select("qid", "k", "z", "img_1", F.col("s.set_id").alias("set_id")).join(last, "qid")
    # members meet their groups by an equi-join on the prefix that the query asks for; the bounds need no comparison then
    at = small_side(q.select(F.col("qid").alias("e_qid"), F.col("set_id").alias("e_set"), F.col("t").alias("e_t")))
    e = elements.join(at, F.col("set_id") == F.col("e_set")).select("e_qid", "e_set", F.expr(hashing.prefix_sql("g", "e_t", cfg)).alias("e_z"), "elem", "y")
    spans = spans.join(at, (F.col("qid") == F.col("e_qid")) & (F.col("set_id") == F.col("e_set"))).drop("e_qid", "e_set").withColumn("sz", F.expr("shiftrightunsigned(z, t_last - e_t)"))
    found = spans.join(e, (F.col("qid") == F.col("e_qid")) & (F.col("set_id") == F.col("e_set")) & (F.col("sz") == F.col("e_z"))).filter(F.expr("shiftrightunsigned(img_1, y) & 1") == 1)
    return found.groupBy("qid", "k", "z", "elem").agg(F.count_distinct("set_id").alias("c")).filter("c = k").select("qid", "elem").distinct()
