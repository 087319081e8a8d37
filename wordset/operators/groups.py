"""Small groups of sets by prefixes of a common random order, with word images."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.plans.sizing import small_side


@dataclass
class Index:
    """Groups ``(set_id, t, z, n, img_*, elems)`` of a collection, its set sizes, and the settings of both.

    ``elems`` holds the members as structs ``(g, elem[, freq])`` in the order of g."""

    groups: DataFrame
    stats: DataFrame
    cfg: Cfg
    method: str = "scan"
    bag: bool = False
    meta: dict = field(default_factory=dict)

    def require(self, other: Cfg) -> None:
        mine, theirs = (tuple(getattr(c, k) for k in ("w", "universe_bits", "g", "h", "seed")) for c in (self.cfg, other))
        if mine != theirs:
            raise ValueError(f"the index was built with {mine}, not {theirs}")


def set_stats(sets: DataFrame) -> DataFrame:
    """``set_id, n, inf, sup``."""
    return sets.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"), F.min("elem").alias("inf"), F.max("elem").alias("sup"))


def hashed(sets: DataFrame, cfg: Cfg, m: int | None = None) -> DataFrame:
    """The rows with their place g and their image bits y_1 ... y_m."""
    m = cfg.m if m is None else m
    return sets.select("*", hashing.g("elem", cfg).alias("g"), *(hashing.h("elem", j, cfg).alias(f"y_{j}") for j in range(1, m + 1)))


def ordered(g: str, cfg: Cfg):
    """A column that sorts signed longs as the unsigned numbers they stand for."""
    return F.col(g).bitwiseXOR(F.lit(-(1 << 63))) if cfg.universe_bits == 64 else F.col(g)


def members(bag: bool) -> F.Column:
    fields = ["g", "elem", *(["freq"] if bag else [])]
    return F.struct(*fields)


def group_by_prefix(rows: DataFrame, cfg: Cfg, m: int, keys: tuple[str, ...] = ("set_id",), bag: bool = False) -> DataFrame:
    """Groups of hashed rows that carry their set's ``t``: images and ordered members in one aggregation.

    With g uniform no group is much larger than root(w), so no task collects more than a group at a time."""
    z = F.expr(hashing.prefix_sql("g", "t", cfg)).alias("z")
    order = F.struct(ordered("g", cfg).alias("o"), *(c for c in ("g", "elem", *(["freq"] if bag else []))))
    held = F.sort_array(F.collect_list(order))
    out = rows.withColumn("z", z).groupBy(*keys, "t", "z").agg(F.count(F.lit(1)).cast("int").alias("n"), *words.image_aggregates(cfg, m), held.alias("_e"))
    names = ("g", "elem", *(["freq"] if bag else []))
    return out.select(*keys, "t", "z", "n", *(c for ws in cfg.images(m) for c in ws), F.transform("_e", lambda x: F.struct(*(x[c].alias(c) for c in names))).alias("elems"))


def build(sets: DataFrame, cfg: Cfg, m: int | None = None, t: str | None = None, bag: bool = False, keep: bool = False) -> Index:
    """Index of a set frame: every set with as many groups as its own size asks for, or as the SQL text ``t`` over ``n`` says.

    The join with the sizes is on set_id and left to the planner: sizes are few for few large sets and then broadcast by
    their measured size, and both sides are shuffled alike for many small sets."""
    m = cfg.m if m is None else m
    sizes = set_stats(sets).withColumn("t", F.expr(t or hashing.t_scan_sql("n", cfg)).cast("int"))
    rows = hashed(sets, cfg, m).join(sizes.select("set_id", "t"), "set_id")
    groups = group_by_prefix(rows, cfg, m, bag=bag)
    if keep:  # clustered by set: files are even, and a scan for named sets skips the files and row groups of others
        groups = written(groups.repartitionByRange("set_id", "z").sortWithinPartitions("set_id", "z"), "groups")
        sizes = written(sizes, "sizes")
    return Index(groups, sizes, cfg, bag=bag)


def pruned(sets: DataFrame, queries: DataFrame) -> DataFrame:
    """The sets that the queries name, as a table of their own.

    Without a stored index the source is read once, however many sets and joins a query has, and what nothing names is
    dropped where it is read."""
    names = queries.select(F.explode("set_ids").alias("set_id")).distinct()
    return written(sets.join(small_side(names), "set_id", "left_semi"), "named-sets")


def dealt_by_element(sets: DataFrame) -> DataFrame:
    """The rows dealt by element over all shuffle partitions: what queries make of them grows far beyond the rows themselves,
    and counts by (query, element) need no further shuffle."""
    return sets.repartition(int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions")), "elem")


def query_sets(queries: DataFrame, stats: DataFrame) -> DataFrame:
    """``qid, k, rank, set_id, n, t``: the sets of each query, smallest first, each once.

    A query with an unknown set is left out: its result is empty."""
    from pyspark.sql import Window

    named = queries.select("qid", F.explode(F.array_distinct("set_ids")).alias("set_id"))
    by = Window.partitionBy("qid")
    found = named.join(stats, "set_id", "left").withColumn("missing", F.max(F.col("n").isNull()).over(by)).filter(~F.col("missing")).drop("missing")
    return found.select("qid", F.count(F.lit(1)).over(by).cast("int").alias("k"), F.row_number().over(by.orderBy("n", "set_id")).alias("rank"), "set_id", "n", *(c for c in ("t",) if c in stats.columns))


def longest(queries: DataFrame) -> int:
    """Most sets in a query: how many joins a batch needs; one number to the driver."""
    return queries.agg(F.max(F.size(F.array_distinct("set_ids")))).first()[0] or 0
