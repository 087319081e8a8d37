"""The library's front door: build an index once, then ask."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.operators import baselines, blocks, fixed, prefix, probe, scan
from wordset.operators import groups as G
from wordset.plans import planner
from wordset.sources import families

METHODS = ("auto", "scan", "prefix", "fixed", "probe", "blocks", "merge", "hash", "lookup", "svs")


@dataclass
class SetIndex:
    """A set frame with its groups and sizes."""

    sets: DataFrame
    index: G.Index
    cfg: Cfg
    bag: bool = False

    @property
    def stats(self) -> DataFrame:
        return self.index.stats


def build_index(sets: DataFrame, cfg: Cfg = Cfg(), bag: bool = False, keep: bool = False) -> SetIndex:
    """``keep`` writes the groups to the shared folder, so that later queries read them."""
    return SetIndex(sets, G.build(sets, cfg, bag=bag, keep=keep), cfg, bag)


def _one(ix: SetIndex, names: list[str]) -> DataFrame:
    return ix.sets.sparkSession.createDataFrame([(0, names)], "qid long, set_ids array<string>")


def intersect_batch(ix: SetIndex, queries: DataFrame, method: str = "scan") -> DataFrame:
    """``qid, elem[, freq]`` of ``(qid, set_ids)`` by one method."""
    if method not in METHODS:
        raise ValueError(f"method must be one of {METHODS}")
    if ix.bag and method not in ("scan", "fixed", "auto"):
        raise ValueError("frequencies are kept by scan and fixed")
    sets, cfg = ix.sets, ix.cfg
    if method in ("auto", "scan"):
        if method == "auto" and not ix.bag:
            return _auto(ix, queries)
        return scan.intersect(ix.index, queries)
    if method == "prefix":
        return scan.intersect_by_bits(ix.index, queries)
    if method == "fixed":
        return fixed.intersect(sets, queries, cfg, bag=ix.bag)
    if method == "probe":
        return probe.intersect(sets, queries, cfg)
    if method == "blocks":
        return blocks.intersect(sets, queries, cfg)
    if method == "lookup":
        return baselines.lookup(sets, queries, cfg)
    return {"merge": baselines.merge, "hash": baselines.hashing_, "svs": baselines.smallest_first}[method](sets, queries)


def _auto(ix: SetIndex, queries: DataFrame) -> DataFrame:
    """Each query by the method its sizes ask for: at most one plan per method, united."""
    chosen = planner.plan_batch(queries, ix.stats)
    tagged = queries.join(chosen.select("qid", "method"), "qid")
    used = sorted(r.method for r in chosen.select("method").distinct().collect())  # a handful of method names
    out = None
    for m in used:
        if m == "empty":
            continue
        part = intersect_batch(ix, tagged.filter(F.col("method") == m).select("qid", "set_ids"), "svs" if m == "set" else m)
        out = part if out is None else out.unionByName(part)
    return queries.sparkSession.createDataFrame([], "qid long, elem long") if out is None else out


def intersect(ix: SetIndex, names: list[str], method: str = "auto") -> DataFrame:
    """``elem[, freq]`` of the named sets' intersection."""
    if not names:
        raise ValueError("a query needs at least one set")
    if method == "auto" and not ix.bag:
        method = planner.plan_query(ix.stats, names, ix.cfg).method
        if method == "empty":
            return ix.sets.select("elem").limit(0)
        method = "svs" if method == "set" else method
    return intersect_batch(ix, _one(ix, names), method).drop("qid")


def intersect_count(ix: SetIndex, names: list[str], method: str = "auto") -> DataFrame:
    return intersect(ix, names, method).agg(F.count(F.lit(1)).alias("r"))


def intersect_limit(ix: SetIndex, names: list[str], n: int, method: str = "auto") -> DataFrame:
    """Any n common elements: the plan stops once it has them."""
    return intersect(ix, names, method).limit(n)


def is_disjoint(ix: SetIndex, queries: DataFrame) -> DataFrame:
    """``qid, disjoint``: proven by images alone where no chain of groups passes, else by members."""
    alive, q, _ = scan.survivors(ix.index, queries)
    hit = scan.gather(ix.index, alive, q).select("qid").distinct().withColumn("hit", F.lit(True))
    return queries.select("qid").join(hit, "qid", "left").select("qid", F.col("hit").isNull().alias("disjoint"))


def explain(ix: SetIndex, names: list[str]) -> str:
    return planner.plan_query(ix.stats, names, ix.cfg).text()


def counters(ix: SetIndex, queries: DataFrame, method: str = "scan", **how) -> DataFrame:
    return blocks.counters(ix.sets, queries, ix.cfg, method, **how)


def intersect_predicates(df: DataFrame, key: str, conditions: list[str]) -> DataFrame:
    """Keys with rows that meet each of the conditions, maybe different rows: the intersection of the conditions' sets."""
    if not conditions:
        raise ValueError("a query needs at least one condition")
    parts = [conditions[i : i + 62] for i in range(0, len(conditions), 62)]  # a word of bits for each
    words = [reduce(Column.bitwiseOR, (F.when(F.expr(c), F.lit(1 << i)).otherwise(0).cast("long") for i, c in enumerate(part))) for part in parts]
    rows = df.filter(F.col(key).isNotNull()).groupBy(F.col(key).cast("long").alias("elem")).agg(*(F.bit_or(w).alias(f"w{j}") for j, w in enumerate(words)))
    return rows.filter(reduce(Column.__and__, (F.col(f"w{j}") == (1 << len(part)) - 1 for j, part in enumerate(parts)))).select("elem")


def search(ix: SetIndex, terms: list[str]) -> DataFrame:
    """Documents that hold all terms; terms are lower-cased like the index."""
    return intersect(ix, [t.lower() for t in terms])


def evaluate(sets: DataFrame, expression) -> DataFrame:
    """``elem`` of a nested expression: a name, or ("and" | "or" | "not", parts...); not is "in the first, in no other"."""
    if isinstance(expression, str):
        return sets.filter(F.col("set_id") == expression).select("elem")
    op, *parts = expression
    done = [evaluate(sets, p) for p in parts]
    out = done[0]
    for more in done[1:]:
        out = out.join(more, "elem", "left_semi") if op == "and" else out.unionByName(more).distinct() if op == "or" else out.join(more, "elem", "left_anti")
    return out


from_table = families.from_table
