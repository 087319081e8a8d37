"""Which method a query gets, from the sizes of its sets."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing


@dataclass(frozen=True)
class Rules:
    """Thresholds: size ratios from which lookups, then probes win, and the share of the result from which merging wins."""

    lookup_from: int = 32
    probe_from: int = 100
    merge_from: float = 0.7
    many_sets: int = 4


@dataclass(frozen=True)
class Plan:
    names: tuple[str, ...]  # smallest set first
    sizes: tuple[int, ...]
    ts: tuple[int, ...]
    method: str
    why: str

    def text(self) -> str:
        sets = ", ".join(f"{s}[n={n}, t={t}]" for s, n, t in zip(self.names, self.sizes, self.ts, strict=True))
        return f"{self.method}: {sets} ({self.why}; joins: {max(0, len(self.names) - 1)} on (query, prefix))"


def order_sets(stats: DataFrame, names: list[str]) -> list[tuple[str, int, int, int]]:
    """Name, size and range of the named sets, smallest first; a row per name comes to the driver."""
    if not names:
        raise ValueError("a query needs at least one set")
    known = {r.set_id: r for r in stats.filter(F.col("set_id").isin(list(dict.fromkeys(names)))).collect()}
    rows = [(s, known[s].n, known[s].inf, known[s].sup) if s in known else (s, 0, None, None) for s in dict.fromkeys(names)]
    return sorted(rows, key=lambda r: (r[1], r[0]))


def plan_query(stats: DataFrame, names: list[str], cfg: Cfg, overlap: float | None = None, rules: Rules = Rules()) -> Plan:
    """The method for one query. ``overlap`` is an estimate of the result's share of the smallest set, where there is one."""
    rows = order_sets(stats, names)
    ordered = tuple(r[0] for r in rows)
    sizes = tuple(r[1] for r in rows)
    ts = tuple(hashing.t_scan(max(1, n), cfg) for n in sizes)
    make = lambda method, why: Plan(ordered, sizes, ts, method, why)
    if sizes[0] == 0:
        return make("empty", "a set is unknown or empty")
    if len(rows) == 1:
        return make("set", "one set")
    if max(r[2] for r in rows) > min(r[3] for r in rows):
        return make("empty", "the sets' ranges don't meet")
    ratio = sizes[-1] / sizes[0]
    if overlap is not None and overlap >= rules.merge_from and ratio < 2:
        return make("merge", f"about {overlap:.0%} of the smallest set is common")
    if ratio >= rules.probe_from:
        return make("probe", f"sizes differ {ratio:.0f} times")
    if ratio >= rules.lookup_from:
        return make("lookup", f"sizes differ {ratio:.0f} times")
    if len(rows) >= rules.many_sets and ratio >= rules.lookup_from / 2:
        return make("prefix", "many sets of uneven sizes")
    return make("scan", f"sizes differ {ratio:.1f} times")


def plan_batch(queries: DataFrame, stats: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """``qid, k, n1, nk, method`` of a batch, in SQL: no query comes to the driver."""
    named = queries.select("qid", F.explode(F.array_distinct("set_ids")).alias("set_id")).join(stats, "set_id", "left")
    q = named.groupBy("qid").agg(F.count(F.lit(1)).alias("k"), F.min(F.coalesce("n", F.lit(0))).alias("n1"), F.max(F.coalesce("n", F.lit(0))).alias("nk"), F.max("inf").alias("low"), F.min("sup").alias("high"))
    ratio = F.col("nk") / F.col("n1")
    method = (
        F.when(F.col("n1") == 0, "empty")
        .when(F.col("k") == 1, "set")
        .when(F.col("low") > F.col("high"), "empty")
        .when(ratio >= rules.probe_from, "probe")
        .when(ratio >= rules.lookup_from, "lookup")
        .when((F.col("k") >= rules.many_sets) & (ratio >= rules.lookup_from / 2), "prefix")
        .otherwise("scan")
    )
    return q.select("qid", "k", "n1", "nk", method.alias("method"))


def estimate_overlap(groups: DataFrame, a: str, b: str, cfg: Cfg, share: float = 0.1) -> float:
    """The result's share of the smaller of two sets, from a sample of its groups: of each prefix that is kept, all members meet."""
    keep = lambda s: groups.filter((F.col("set_id") == s) & (F.pmod(F.xxhash64("z"), F.lit(1000)) < int(share * 1000)))
    one = keep(a).select("z", F.explode("elems.elem").alias("elem"))
    two = groups.filter(F.col("set_id") == b).select(F.explode("elems.elem").alias("elem"))
    n = one.count()
    return one.join(two, "elem", "left_semi").count() / n if n else 0.0
