"""Every method, baseline, measure and workload as a query over the given tables, with its SQL."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing
from wordset.functions.store import written
from wordset.operators import baselines, blocks, cells, fixed, kernels, measures, prefix, probe, scan
from wordset.operators import groups as G
from wordset.plans import api, planner, workloads
from wordset.plans.sizing import literal_frame
from wordset.sources import families as fam
from wordset.sources.tables import load

CFG = Cfg(m=4)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# ---- set frames and queries

F_SQL = {
    "F1": "select distinct l_suppkey::varchar as set_id, l_orderkey as elem from lineitem",
    "F2": "select distinct l_returnflag || l_linestatus as set_id, l_orderkey as elem from lineitem",
    "F3": "select distinct o_orderpriority as set_id, o_custkey as elem from orders",
    "F4": "select distinct l_partkey::varchar as set_id, l_orderkey as elem from lineitem",
    "F5": r"select distinct w as set_id, doc_id as elem from (select doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) as w from documents)",
    "F7": r"select distinct w as set_id, page_id as elem from (select page_id, unnest(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[\p{L}\p{N}]+')) as w from pages)",
    "F8": "select event_type || '|' || strftime(ts, '%Y-%m-%d') as set_id, user_id as elem, count(*) as freq from events group by all",
    "F9": "select distinct unnest(['brand=' || p_brand, 'type=' || p_type, 'size=' || p_size]) as set_id, p_partkey as elem from part",
    "F10": "select distinct * from (select unnest(['lang=' || lang, 'source=' || source]) as set_id, doc_id as elem from documents union all select unnest(['quality=' || quality, 'toxic=' || toxic]), doc_id from labels) where set_id is not null",
    "F11": "select distinct label::varchar as set_id, vec_id as elem from embeddings",
    "F14": "select distinct (i - 1)::varchar || case when x >= 0 then '+' else '-' end as set_id, vec_id as elem from (select vec_id, unnest(embedding) as x, generate_subscripts(embedding, 1) as i from embeddings)",
}


def named_queries(spark: SparkSession, names: list[list[str]]) -> DataFrame:
    """Queries from lists of set names; a handful of literals, not data."""
    return literal_frame(spark, list(enumerate(names)), pa.schema([("qid", pa.int64()), ("set_ids", pa.list_(pa.string()))]))


def suppliers(k: int, n: int = 20) -> list[list[str]]:
    """Pairs (0,1), (2,3), ... or runs of k consecutive suppliers."""
    return [[str(2 * i), str(2 * i + 1)] if k == 2 else [str(i + j) for j in range(k)] for i in range(n)]


def q_sql(names: list[list[str]]) -> str:
    return "(values " + ", ".join(f"({i}::bigint, '{s}')" for i, q in enumerate(names) for s in dict.fromkeys(q)) + ") q(qid, set_id)"


def inter_sql(family: str, names: list[list[str]]) -> str:
    """All intersections by counting: an element in as many sets as its query names."""
    return f"with sets as ({F_SQL[family]}), q as (select * from {q_sql(names)}) select qid, elem from q join sets using (set_id) group by qid, elem having count(*) = (select count(*) from q p where p.qid = q.qid)"


PAIRS, TRIPLES, QUADS = suppliers(2), suppliers(3), suppliers(4)
FLAGS = [["AF", "NF"], ["AO", "RO"], ["NO", "RF"]]
TERMS3 = [["in", "the", "of"], ["in", "the", "of", "and"], ["the", "en"]]


def frames(d: DataFrame, names) -> DataFrame:
    return named_queries(d.sparkSession, names)


# ---- fixed runs

_two = inter_sql("F1", PAIRS)


@query("m1_pair", _two)
def m1_pair(spark, d):
    s = fam.supp_orders(spark, d)
    return fixed.intersect(s, frames(s, PAIRS), CFG)


@query("m1_optimal", inter_sql("F2", FLAGS))
def m1_optimal(spark, d):
    s = fam.flag_orders(spark, d)
    return fixed.intersect(s, frames(s, FLAGS), CFG, "optimal")


@query("m1_bins", _two)
def m1_bins(spark, d):
    s = fam.supp_orders(spark, d)
    return fixed.intersect(s, frames(s, PAIRS), CFG, how="bins")


@query("m1_fold", "select elem from (" + inter_sql("F1", [["0", "1", "2"]]) + ")")
def m1_fold(spark, d):
    return fixed.fold(fam.supp_orders(spark, d), ["0", "1", "2"], CFG)


_runs = f"select *, (row_number() over (partition by set_id order by elem) - 1) // {CFG.root} as p from ({F_SQL['F1']})"
_bit63 = "case when {y} = 63 then (-9223372036854775807 - 1) else 1::bigint << {y} end"


def _img_sql(j: int, cfg: Cfg = CFG) -> str:
    y = f"({hashing.h_sql('elem', j, cfg, True)})"
    return f"bit_or({_bit63.format(y=y)})"


@query("m1_groups", f"select set_id, p, min(elem) as inf, max(elem) as sup, count(*) as n, {_img_sql(1)} as img_1 from ({_runs}) group by set_id, p")
def m1_groups(spark, d):
    return fixed.build(fam.supp_orders(spark, d), CFG).select("set_id", "p", "inf", "sup", F.col("n").cast("long").alias("n"), "img_1")


@query(
    "m1_pairs_examined",
    f"""with g as (select set_id, p, min(elem) as inf, max(elem) as sup from ({_runs}) group by set_id, p), q as (select * from {q_sql(PAIRS)}),
s as (select set_id, count(*) as n from ({F_SQL["F1"]}) group by set_id),
r as (select qid, set_id, row_number() over (partition by qid order by n, set_id) as side from q join s using (set_id))
select x.qid, count(*) as pairs from r x join r y on x.qid = y.qid and x.side = 1 and y.side = 2 join g a on a.set_id = x.set_id join g b on b.set_id = y.set_id
where a.inf <= b.sup and b.inf <= a.sup group by x.qid""",
)
def m1_pairs_examined(spark, d):
    s = fam.supp_orders(spark, d)
    g = fixed.query_groups(s, frames(s, PAIRS), CFG)
    return fixed.overlaps(g).groupBy("qid").agg(F.count(F.lit(1)).alias("pairs"))


# ---- prefix groups


@query("m2_same_count", _two)
def m2_same_count(spark, d):
    s = fam.supp_orders(spark, d)
    return prefix.intersect_pairs(s, frames(s, PAIRS), CFG, "same_count")


@query("m2_same_size", _two)
def m2_same_size(spark, d):
    s = fam.supp_orders(spark, d)
    return prefix.intersect_pairs(s, frames(s, PAIRS), CFG, "same_size")


def _m2(names, **how):
    def run(spark, d):
        s = fam.supp_orders(spark, d)
        return scan.intersect_by_bits(prefix.build(G.pruned(s, q := frames(s, names)), CFG, keep=True), q, **how)

    return run


query("m2_k3", inter_sql("F1", TRIPLES))(_m2(TRIPLES))
query("m2_k4", inter_sql("F1", QUADS))(_m2(QUADS))
query("m2_nomemo", inter_sql("F1", TRIPLES))(_m2(TRIPLES, memo=False))
query("m2_forward", inter_sql("F1", TRIPLES))(_m2(TRIPLES, finest=False))


@query("m2_terms", inter_sql("F5", TERMS3))
def m2_terms(spark, d):
    q = named_queries(spark, TERMS3)
    return scan.intersect_by_bits(prefix.build(G.pruned(fam.term_docs(spark, d), q), CFG, keep=True), q)


@query("m2_multires", _two)
def m2_multires(spark, d):
    s = fam.supp_orders(spark, d)
    e, lv = prefix.build_multires(s, CFG)
    return prefix.intersect_multires(e, lv, s, frames(s, PAIRS), CFG)


@query("m2_multires_same_count", _two)
def m2_multires_same_count(spark, d):
    s = fam.supp_orders(spark, d)
    e, lv = prefix.build_multires(s, CFG)
    return prefix.intersect_multires(e, lv, s, frames(s, PAIRS), CFG, "same_count")


# ---- image scan


def _m3(names, m, family=fam.supp_orders, cfg=CFG):
    def run(spark, d):
        s = family(spark, d)
        return scan.intersect(G.build(G.pruned(s, q := frames(s, names)), cfg.with_(m=m), keep=True), q)

    return run


for _m in (1, 2, 4, 8):
    query(f"m3_m{_m}", _two)(_m3(PAIRS, _m))
query("m3_k3", inter_sql("F1", TRIPLES))(_m3(TRIPLES, 2))
query("m3_k4", inter_sql("F1", QUADS))(_m3(QUADS, 2))
query("m3_xx64", inter_sql("F1", TRIPLES))(_m3(TRIPLES, 2, cfg=Cfg(g="xx64", h="xx64")))
query("m3_hperm", inter_sql("F1", TRIPLES))(_m3(TRIPLES, 2, cfg=Cfg(h="perm")))
query("m3_w16", inter_sql("F1", TRIPLES))(_m3(TRIPLES, 2, cfg=Cfg(w=16)))
query("m3_w256", inter_sql("F1", TRIPLES))(_m3(TRIPLES, 2, cfg=Cfg(w=256)))


# ---- probing


def _m4(names, how="join", family=None):
    def run(spark, d):
        s = fam.part_orders(spark, d).unionByName(fam.flag_orders(spark, d))
        return probe.intersect(s, frames(s, names), CFG, how)

    return run


F_SQL["F42"] = f"{F_SQL['F4']} union all {F_SQL['F2']}"
_small_big = [[str(i), f] for i, f in zip(range(12), ["AF", "NF", "RO", "AO", "NO", "RF"] * 2, strict=True)]
_small_3 = [[str(i), "AF", "NO"] for i in range(8)]
query("m4_pair", inter_sql("F42", _small_big))(_m4(_small_big))
query("m4_k3", inter_sql("F42", _small_3))(_m4(_small_3))
query("m4_broadcast", inter_sql("F42", _small_big))(_m4(_small_big, "broadcast"))


# ---- baselines


def _base(method, names, *args):
    def run(spark, d):
        s = fam.supp_orders(spark, d)
        return method(s, frames(s, names), *args)

    return run


_three = inter_sql("F1", TRIPLES)
query("base_merge", _three)(_base(baselines.merge, TRIPLES))
query("base_counting", _three)(_base(baselines.counting, TRIPLES))
query("base_hash", _three)(_base(baselines.hashing_, TRIPLES))
query("base_svs", _three)(_base(baselines.smallest_first, TRIPLES))
query("base_lookup", _three)(_base(baselines.lookup, TRIPLES, CFG))
query("base_packed", _three)(_base(baselines.packed_codes, TRIPLES, CFG))
query("base_arrays", _three)(_base(baselines.spark_arrays, TRIPLES))


@query("base_intersect", f"select elem from ({F_SQL['F1']}) where set_id = '0' intersect select elem from ({F_SQL['F1']}) where set_id = '1'")
def base_intersect(spark, d):
    return baselines.spark_intersect(fam.supp_orders(spark, d), "0", "1")


# ---- kernels over packed blocks


def _kernel(method, names, codec="plain", m=1):
    def run(spark, d):
        s = fam.supp_orders(spark, d)
        return blocks.intersect(s, frames(s, names), CFG, method, codec=codec, m=m)

    return run


for _name in ("merge", "hash", "skip", "packed", "lookup", "svs", "adaptive", "median", "hybrid", "probe"):
    query(f"kernel_{_name}", _three)(_kernel(_name, TRIPLES))
query("m3_blocks", _three)(_kernel("scan", TRIPLES, m=2))
for _codec in ("gamma", "delta", "lowbits"):
    query(f"m3_{_codec}", _two)(_kernel("scan", PAIRS, _codec))
    if _codec != "lowbits":
        query(f"base_merge_{_codec}", _two)(_kernel("merge", PAIRS, _codec))
        query(f"base_lookup_{_codec}", _two)(_kernel("lookup", PAIRS, _codec))


# ---- structures and measures, recomputed by SQL from the same portable hash functions


def e_sql(family: str = "F1", m: int = 4) -> str:
    """CTEs ``sets, st, e``: members with size, exponent, place, prefix and image bits."""
    g = hashing.g_sql("elem", CFG, True)
    ys = ", ".join(f"{hashing.h_sql('elem', j, CFG, True)} as y_{j}" for j in range(1, m + 1))
    return f"""sets as ({F_SQL[family]}), st as (select set_id, count(*) as n, min(elem) as inf, max(elem) as sup, {hashing.t_scan_sql('count(*)', CFG, True)} as t from sets group by set_id),
e0 as (select set_id, elem, n, t, {g} as g, {ys} from sets join st using (set_id)), e as (select *, {hashing.prefix_sql('g', 't', CFG, True)} as z from e0)"""


def grp_sql(m: int = 4) -> str:
    return f"grp as (select set_id, t, z, count(*) as n, {', '.join(f'bit_or({_bit63.format(y=f'y_{j}')}) as img_{j}' for j in range(1, m + 1))} from e group by set_id, t, z)"


def legs_sql(names) -> str:
    return f"q as (select * from {q_sql(names)}), legs as (select qid, set_id, t, count(*) over (partition by qid) as k, row_number() over (partition by qid order by n, set_id) as rank from q join st using (set_id) where qid not in (select qid from q where set_id not in (select set_id from st)))"


def _f1_index(spark, d, m=4):
    s = fam.supp_orders(spark, d)
    return s, G.build(s, CFG.with_(m=m), keep=True)


@query("m2_groups", f"with {e_sql(m=1)}, {grp_sql(1)} select set_id, t, z, n, img_1 from grp")
def m2_groups(spark, d):
    g = prefix.build(fam.supp_orders(spark, d), CFG).groups
    return g.select("set_id", F.col("t").cast("long").alias("t"), "z", F.col("n").cast("long").alias("n"), "img_1")


@query("m2_inverse", f"with {e_sql(m=1)} select set_id, z, y_1 as y, count(*) as n, sum(elem)::bigint as total, arg_min(elem, g) as first from e group by set_id, z, y_1")
def m2_inverse(spark, d):
    lists = prefix.inverse_lists(prefix.build(fam.supp_orders(spark, d), CFG))
    return lists.select("set_id", "z", F.col("y").cast("long").alias("y"), F.size("elems").cast("long").alias("n"), F.expr("aggregate(elems, 0L, (a, x) -> a + x)").alias("total"), F.element_at("elems", 1).alias("first"))


_levels = f"""with {e_sql(m=1)}, p as (select set_id, n, g, y_1 as y, row_number() over (partition by set_id order by g) - 1 as pos, case when n <= 1 then 0 else length(bin(n - 1)) end as top from e),
l as (select set_id, unnest(range(0, top + 1)) as t, g, y, pos from p), z as (select set_id, t, {hashing.prefix_sql('g', 't', CFG, True)} as z, y, pos from l)
select set_id, t, z, min(pos) as "left", max(pos) as "right", bit_or({_bit63.format(y='y')}) as img, count(distinct y) as n_first from z group by set_id, t, z"""


@query("m2_levels", _levels)
def m2_levels(spark, d):
    _, lv = prefix.build_multires(fam.supp_orders(spark, d), CFG)
    return lv.select("set_id", F.col("t").cast("long").alias("t"), "z", F.col("left").cast("long").alias("left"), F.col("right").cast("long").alias("right"), "img", F.size("first").cast("long").alias("n_first"))


@query("m2_next", f"with {e_sql(m=1)}, p as (select set_id, elem, g, y_1 as y, row_number() over (partition by set_id order by g) - 1 as pos from e) select set_id, pos, elem, y, coalesce(lead(pos) over (partition by set_id, y order by pos), -1) as next_pos from p")
def m2_next(spark, d):
    e, _ = prefix.build_multires(fam.supp_orders(spark, d), CFG)
    return e.select("set_id", F.col("pos").cast("long").alias("pos"), "elem", F.col("y").cast("long").alias("y"), F.coalesce(F.col("next_pos"), F.lit(-1)).cast("long").alias("next_pos"))


@query("m3_group_sizes", f"with {e_sql(m=1)}, {grp_sql(1)} select n, count(*) as groups from grp group by n")
def m3_group_sizes(spark, d):
    return measures.group_sizes(_f1_index(spark, d, 1)[1])


_pairs_cte = f"""{e_sql()}, {grp_sql()}, {legs_sql(PAIRS)},
pr as (select a.qid, a.set_id as sa, b.set_id as sb, x.z as za, y.z as zb, {', '.join(f'(x.img_{j} & y.img_{j}) <> 0 as hit_{j}' for j in range(1, 5))}
 from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2 join grp x on x.set_id = a.set_id join grp y on y.set_id = b.set_id and (y.z >> (y.t - x.t)) = x.z),
cm as (select l.qid, eb.z as zb, count(*) as r from legs l join legs k on l.qid = k.qid and l.rank = 1 and k.rank = 2 join e ea on ea.set_id = l.set_id join e eb on eb.set_id = k.set_id and eb.elem = ea.elem group by l.qid, eb.z),
pt as (select pr.*, coalesce(cm.r, 0) as r from pr left join cm using (qid, zb))"""
_rate = " union all ".join(f"select {j} as m, count(*) as empty_pairs, count(*) filter (not ({' and '.join(f'hit_{i}' for i in range(1, j + 1))})) as filtered from pt where r = 0" for j in range(1, 5))


@query("m3_filter_rate", f"with {_pairs_cte} {_rate}")
def m3_filter_rate(spark, d):
    s, ix = _f1_index(spark, d)
    return measures.filter_rate(ix, frames(s, PAIRS), 4)


_void = "(select sum(power(2, t))::bigint from (select qid, max(t) as t from legs group by qid)) - (select count(*) from pt)"


@query("m3_filter_all", f"with {_pairs_cte}, b as ({_rate}) select m, empty_pairs + {_void} as empty_pairs, filtered + {_void} as filtered from b")
def m3_filter_all(spark, d):
    s, ix = _f1_index(spark, d)
    return measures.filter_rate_all_prefixes(ix, frames(s, PAIRS), 4)


@query("m3_merge_cases", f"with {_pairs_cte}, a as (select qid, count(*) filter (hit_1 and hit_2) as passed, count(*) filter (r > 0) as useful, sum(r)::bigint as r, count(*) filter (hit_1 and hit_2 and r = 0) as wasted from pt group by qid) select i.qid, coalesce(passed, 0) as passed, coalesce(useful, 0) as useful, coalesce(r, 0) as r, coalesce(wasted, 0) as wasted from (select unnest(range({len(PAIRS)})) as qid) i left join a using (qid)")
def m3_merge_cases(spark, d):
    s, ix = _f1_index(spark, d, 2)
    return measures.merge_cases(ix, frames(s, PAIRS), 2)


_coll = f"""with {e_sql(m=1)}, run as (select set_id, elem, y_1 as y, (row_number() over (partition by set_id order by elem) - 1) // {CFG.root} as p from e), rg as (select set_id, p, min(elem) as inf, max(elem) as sup from run group by set_id, p), {legs_sql(PAIRS)},
mt as (select a.qid, a.set_id as sa, b.set_id as sb, x.p as pa, y.p as pb from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2 join rg x on x.set_id = a.set_id join rg y on y.set_id = b.set_id where x.inf <= y.sup and y.inf <= x.sup),
sm as (select qid, count(*) filter (u.elem <> v.elem) as unequal, count(*) filter (u.elem = v.elem) as r from mt join run u on u.set_id = sa and u.p = pa join run v on v.set_id = sb and v.p = pb and v.y = u.y group by qid),
np as (select qid, count(*) as pairs from mt group by qid) select qid, pairs, coalesce(unequal, 0) as unequal, coalesce(r, 0) as r from np left join sm using (qid)"""


@query("m1_collisions", _coll)
def m1_collisions(spark, d):
    s = fam.supp_orders(spark, d)
    return measures.collisions(s, frames(s, PAIRS), CFG)


@query("m2_survivors", f"with {e_sql(m=1)}, {grp_sql(1)}, {legs_sql(TRIPLES)}, s1 as (select qid, l.t, z, img_1 as h from legs l join grp using (set_id) where rank = 1), "
       "s2 as (select s1.qid, y.t, y.z, s1.h & y.img_1 as h from s1 join legs l on l.qid = s1.qid and l.rank = 2 join grp y on y.set_id = l.set_id and (y.z >> (y.t - s1.t)) = s1.z where (s1.h & y.img_1) <> 0), "
       "s3 as (select s2.qid, y.t, y.z, s2.h & y.img_1 as h from s2 join legs l on l.qid = s2.qid and l.rank = 3 join grp y on y.set_id = l.set_id and (y.z >> (y.t - s2.t)) = s2.z where (s2.h & y.img_1) <> 0) "
       "select qid, 1 as step, count(*) as chains from s1 group by qid union all select qid, 2, count(*) from s2 group by qid union all select qid, 3, count(*) from s3 group by qid")  # fmt: skip
def m2_survivors(spark, d):
    s, ix = _f1_index(spark, d, 1)
    return measures.survivors_by_step(ix, frames(s, TRIPLES))


_space = f"""with {e_sql(m=1)}, {grp_sql(1)}, a as (select (select count(*) from grp) as g, (select count(*) from e) as n, (select sum(ceil(n / {CFG.root}.0)) from st) as runs)
select structure, m, floor(words)::bigint as words, round(words / n - 1, 6) as overhead from (select n, unnest(['plain', 'image_scan', 'image_scan', 'image_scan', 'image_scan', 'prefix_groups', 'fixed_groups', 'prefix_probe']) as structure,
 unnest([0, 1, 2, 4, 8, 1, 1, 0]) as m, unnest([n::double, n + 2.0 * g, n + 3.0 * g, n + 5.0 * g, n + 9.0 * g, 1.5 * n + 3 * g, 1.5 * n + 2 * runs, n + 2.0 * g]) as words from a)"""


@query("space_words", _space)
def space_words(spark, d):
    return measures.space_words(fam.supp_orders(spark, d), CFG)


_lb = "(length(bin({x})) - 1)"
_gm = "(2 * " + _lb + " + 1)"
_dl = "(" + _lb + " + 2 * (length(bin(length(bin({x})))) - 1) + 1)"
_bits = f"""with {e_sql(m=1)}, {grp_sql(1)}, li as (select elem - coalesce(lag(elem) over (partition by set_id order by elem), -1) as x from e),
lw as (select *, g & ((1::bigint << ({CFG.universe_bits} - t)) - 1) as low from e), gp as (select t, low - coalesce(lag(low) over (partition by set_id, z order by g), -1) as x from lw),
v as (select (select count(*) * {CFG.universe_bits} from e) as plain, (select sum({_gm.format(x='x')}) from li) as lg, (select sum({_dl.format(x='x')}) from li) as ld, (select sum({_gm.format(x='x')}) from gp) as gg, (select sum({_dl.format(x='x')}) from gp) as gd, (select sum({CFG.universe_bits} - t) from e) as lo,
 (select count(*) * {CFG.w} + sum(n) from grp) + (select sum(1::bigint << t) from st) as head)
select structure, codec, bits::bigint as bits, round(bits / plain, 6) as share from (select plain, unnest(['list', 'list', 'list', 'image_scan', 'image_scan', 'image_scan']) as structure, unnest(['plain', 'gamma', 'delta', 'gamma', 'delta', 'lowbits']) as codec, unnest([plain, lg, ld, head + gg, head + gd, head + lo]) as bits from v)"""


@query("space_bits", _bits)
def space_bits(spark, d):
    return measures.space_bits(fam.supp_orders(spark, d), CFG)


@query("bounds", f"""with runs as (select w, sum((n + s - 1) // s)::bigint as groups from (select set_id, count(*) as n from ({F_SQL['F1']}) group by set_id) cross join (values (16, 4), (64, 8), (256, 16), (1024, 32), (4096, 64)) v(w, s) group by w)
select w, m, round(power(1 - 1 / s, s), 6) as one_image, round(delta, 6) as delta, round(b1, 6) as beta_1, round(b2, 6) as beta_2, round(1 - power(1 - greatest(b1, b2), m), 6) as m_images, round(1 / (1 - greatest(b1, b2)), 6) as alpha, groups, round(groups * power(1 - 1 / s, s), 2) as spared
from (select *, greatest(0, 1 - (1 + delta * s) / (4 * s)) * power(q, delta * s) as b1, greatest(0, 1 - exp(-s / 12) - 0.375) * power(q, 1.5 * s) as b2 from (select *, greatest(0, 1 - delta / s) as q from
(select w, m, sqrt(w) as s, 1 + sqrt(6 * ln(4 * sqrt(w)) / sqrt(w)) as delta from (values (16), (64), (256), (1024), (4096)) a(w), (values (1), (2), (4), (8)) b(m)))) join runs using (w)""")
def bounds(spark, d):
    """The bounds at every width for the groups that the suppliers' orders make there."""
    return measures.bounds_of(fam.supp_orders(spark, d), [(w, m) for w in (16, 64, 256, 1024, 4096) for m in (1, 2, 4, 8)])


# ---- workloads


def ctl_cte(points: list[tuple[str, str, str]]) -> str:
    """CTEs ``k, c, p, u``: the points (n1, n2 and r as expressions of the number of orders, n) and their sets' members by counting."""
    scramble = fam.SCRAMBLE.format(x="o_orderkey")
    pts = " union all ".join(f"select {j}::bigint as qid, {n1} as n1, {n2} as n2, {r} as r from c" for j, (n1, n2, r) in enumerate(points))
    return f"""k as (select o_orderkey, row_number() over (order by {scramble}) as i from orders), c as (select count(*) as n from orders), p as ({pts}),
u as (select qid, 'A' as s, o_orderkey from p join k on i <= n1 union all select qid, 'B', o_orderkey from p join k on i > n1 - r and i <= n1 - r + n2)"""


def ctl_sql(points: list[tuple[str, str, str]]) -> str:
    """Per point the size of the result."""
    return f"with {ctl_cte(points)} select qid, count(*) as r from (select qid, o_orderkey from u group by all having count(*) = 2) group by qid"


def _points(spark, d, points_of):
    return workloads.controlled(spark, d, points_of(load(spark, d, "orders").count()))


def _sweep(points_of, method="scan"):
    """A sweep over all orders; its points come from the table's own count."""

    def run(spark, d):
        got = blocks.run_kernel(*_points(spark, d, points_of), CFG, method, m=2)
        return got.groupBy("qid").agg(F.sum(F.size("elems")).alias("r")).filter("r > 0")

    return run


_sizes = [f"({a} * n // {b})" for a, b in ((1, 30), (1, 15), (2, 15), (4, 15), (7, 15))]
EQUAL = [(x, x, f"{x} // 100") for x in _sizes]
OVERLAP = [("n // 2", "n // 2", f"greatest(1, n // 2 * {p} // 10000)") for p in (0, 100, 1000, 3000, 5000, 7000, 9000, 10000)]
RATIO = [(f"greatest(1, n // 2 // {s})", "n // 2", f"greatest(1, n // 2 // {s} // 100)") for s in (1, 2, 4, 8, 16, 32, 64, 100, 200, 625)]
query("w1_equal", ctl_sql(EQUAL))(_sweep(workloads.equal_points))
query("w2_overlap", ctl_sql(OVERLAP))(_sweep(workloads.overlap_points))
query("w3_ratio", ctl_sql(RATIO))(_sweep(workloads.ratio_points, method="probe"))


@query("w4_keywords", " union all ".join(f"select {k}::bigint as k, count(*) as r from ({inter_sql('F1', suppliers(k))})" for k in (2, 3, 4)))
def w4_keywords(spark, d):
    s = fam.supp_orders(spark, d)
    ix = G.build(G.pruned(s, frames(s, suppliers(2) + suppliers(4))), CFG.with_(m=2), keep=True)
    out = [scan.intersect(ix, frames(s, suppliers(k))).agg(F.count(F.lit(1)).alias("r")).select(F.lit(k).cast("long").alias("k"), "r") for k in (2, 3, 4)]
    return out[0].unionByName(out[1]).unionByName(out[2])


_words = r"select regexp_extract_all(lower(text), '[\p{L}\p{N}]+') as w from (select text from benchmark union all select text from conversations where role = 'user')"
_qterms = " union all ".join(
    f"select * from (select {k} as k, ids, count(*) as freq from (select list_sort(list_distinct(w[i:i + {k - 1}])) as ids from (select w, unnest(range(1, len(w) - {k - 2})) as i from ({_words}) where len(w) >= {k})) where len(ids) = {k} group by ids order by freq desc, array_to_string(ids, ' ') limit {top})"
    for k, top in workloads.MIX.items()
)
_results = f"""with tq as (select row_number() over (order by k, freq desc, array_to_string(ids, ' ')) - 1 as qid, k, ids from ({_qterms})), sets as ({F_SQL["F5"]}), st as (select set_id, count(*) as n from sets group by set_id),
q as (select qid, k, unnest(ids) as set_id from tq), qs as (select qid, k, set_id, n, count(n) over (partition by qid) as known from q left join st using (set_id)),
sz as (select qid, k, min(n) as n1, list_sort(list(n))[2] as n2, max(n) as nk from qs where known = k group by qid, k),
hit as (select qid, count(*) as r from (select qid, elem from qs join sets using (set_id) where known = k group by qid, elem having count(*) = any_value(k)) group by qid),
res as (select qid, k, n1, n2, nk, coalesce(r, 0) as r from sz left join hit using (qid))"""


def _results_frame(spark, d):
    return measures.results(fam.term_docs(spark, d), written(workloads.term_queries(spark, d), "term-queries"))


@query("batch_terms", _results + " select qid, k::bigint as k, n1, nk, r from res")
def batch_terms(spark, d):
    return _results_frame(spark, d).select("qid", F.col("k").cast("long").alias("k"), "n1", "nk", "r")


@query("batch_terms_scan", _results + " select qid, r from res where r > 0")
def batch_terms_scan(spark, d):
    """The term workload as one batch through the image scan."""
    q = written(workloads.term_queries(spark, d), "term-queries")
    return cells.kernel_results(G.pruned(fam.term_docs(spark, d), q), q, CFG, ("scan",), m=2).filter("r > 0").select("qid", "r")


@query("query_profile", _results + " select k::bigint as k, count(*) as queries, round(avg(n1 / n2), 6) as n1_n2, round(avg(n1 / nk), 6) as n1_nk, round(avg(r / n1), 6) as r_n1, round(avg((r = 0)::int), 6) as empty from res group by k")
def query_profile(spark, d):
    return measures.query_profile(_results_frame(spark, d)).withColumn("k", F.col("k").cast("long"))


@query("selectivity_profile", _results + " select k::bigint as k, round(avg((r * 10 <= n1)::int), 6) as tenth, round(avg((r * 100 <= n1)::int), 6) as hundredth from res group by k")
def selectivity_profile(spark, d):
    return measures.selectivity_profile(_results_frame(spark, d)).withColumn("k", F.col("k").cast("long"))


@query("auto_plan", inter_sql("F42", _small_big + [["AF", "NF"]]))
def auto_plan(spark, d):
    s = fam.part_orders(spark, d).unionByName(fam.flag_orders(spark, d))
    q = frames(s, _small_big + [["AF", "NF"]])
    return api.intersect_batch(api.build_index(G.pruned(s, q), CFG.with_(m=2), keep=True), q, "auto")


@query("plan_methods", f"""with sets as ({F_SQL['F42']}), st as (select set_id, count(*) as n, min(elem) as inf, max(elem) as sup from sets group by set_id), q as (select * from {q_sql(_small_big + [['AF', 'NF']])}),
a as (select qid, count(*) as k, min(n) as n1, max(n) as nk, max(inf) > min(sup) as apart from q join st using (set_id) group by qid)
select qid, k, n1, nk, case when apart then 'empty' when nk / n1 >= 100 then 'probe' when nk / n1 >= 32 then 'lookup' else 'scan' end as method from a""")
def plan_methods(spark, d):
    s = fam.part_orders(spark, d).unionByName(fam.flag_orders(spark, d))
    return planner.plan_batch(frames(s, _small_big + [["AF", "NF"]]), G.set_stats(s))


# ---- bags, predicates and other families

_DAY = "2024-01-0{}"
BAGS = [[f"view|{_DAY.format(i)}", f"click|{_DAY.format(i)}"] for i in range(1, 8)]
BAGS3 = [[f"{e}|{_DAY.format(i)}" for e in ("view", "click", "purchase")] for i in range(1, 8)]


def bag_sql(names) -> str:
    return f"with sets as ({F_SQL['F8']}), q as (select * from {q_sql(names)}) select qid, elem, min(freq) as freq from q join sets using (set_id) group by qid, elem having count(*) = (select count(*) from q p where p.qid = q.qid) and qid not in (select q.qid from q left join (select distinct set_id as s from sets) on s = q.set_id where s is null)"


def _bag(names, method):
    def run(spark, d):
        s = fam.event_users(spark, d)
        q = frames(s, names)
        return api.intersect_batch(api.build_index(G.pruned(s, q), CFG.with_(m=2), bag=True, keep=True), q, method)

    return run


query("bag_pair", bag_sql(BAGS))(_bag(BAGS, "scan"))
query("bag_k3", bag_sql(BAGS3))(_bag(BAGS3, "scan"))
query("bag_fixed", bag_sql(BAGS))(_bag(BAGS, "fixed"))


@query("conj_predicates", "select distinct p_partkey as elem from part where p_brand = 'Brand#1' and p_type like 'ECONOMY%' and p_size between 1 and 10")
def conj_predicates(spark, d):
    return api.intersect_predicates(load(spark, d, "part"), "p_partkey", ["p_brand = 'Brand#1'", "p_type like 'ECONOMY%'", "p_size between 1 and 10"])


DIMS = [["quality=1", "lang=en"], ["quality=0", "lang=de"], ["quality=1", "lang=en", "source=src0"]]
query("dim_intersect", inter_sql("F10", DIMS))(_m3(DIMS, 2, fam.doc_attrs))
SIGNS = [[f"{i}+" for i in range(k)] for k in (2, 3, 4, 5, 6, 8)]
query("sign_conjunction", inter_sql("F14", SIGNS))(_m3(SIGNS, 4, fam.emb_sign))
VECS = [["0", "1"], ["2", "3"]]


@query("disjoint_labels", f"select qid, true as disjoint from (values (0::bigint), (1::bigint)) q(qid) where not exists (select 1 from ({inter_sql('F11', VECS)}) x where x.qid = q.qid)")
def disjoint_labels(spark, d):
    s = fam.label_vecs(spark, d)
    return api.is_disjoint(api.build_index(s, CFG.with_(m=1), keep=True), frames(s, VECS))


PAGES = [["the", "of"], ["the", "and", "of"]]


@query("page_search", inter_sql("F7", PAGES))
def page_search(spark, d):
    q = named_queries(spark, PAGES)
    return scan.intersect(G.build(G.pruned(fam.page_terms(spark, d), q), CFG.with_(m=2), keep=True), q)


@query("pair_support", f"with s as ({F_SQL['F1']}) select a.set_id as a, b.set_id as b, count(*) as support from s a join s b on a.elem = b.elem and a.set_id < b.set_id group by a.set_id, b.set_id")
def pair_support(spark, d):
    s = fam.supp_orders(spark, d)
    a, b = s.select("elem", F.col("set_id").alias("a")), s.select("elem", F.col("set_id").alias("b"))
    return a.join(b, "elem").filter("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("support"))


@query("boolean_sets", f"with s as ({F_SQL['F10']}) (select elem from s where set_id = 'lang=en' intersect (select elem from s where set_id = 'source=src0' union select elem from s where set_id = 'source=src1')) except select elem from s where set_id = 'toxic=1'")
def boolean_sets(spark, d):
    s = fam.doc_attrs(spark, d)
    return api.evaluate(s, ("not", ("and", "lang=en", ("or", "source=src0", "source=src1")), "toxic=1"))


# ---- trade-offs and levels of fixed runs, bounds for probing

GRID = [(4, 16), (8, 8), (16, 4), (16, 16)]
_grid = " union all ".join(
    f"""select {s1}::bigint as s1, {s2}::bigint as s2, count(*) as pairs from (select a.qid, x.p, y.p from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2
 join (select set_id, (i // {s1}) as p, min(elem) as inf, max(elem) as sup from run group by all) x on x.set_id = a.set_id join (select set_id, (i // {s2}) as p, min(elem) as inf, max(elem) as sup from run group by all) y on y.set_id = b.set_id where x.inf <= y.sup and y.inf <= x.sup)"""
    for s1, s2 in GRID
)


@query("m1_sizes_grid", f"with {e_sql(m=1)}, run as (select set_id, elem, row_number() over (partition by set_id order by elem) - 1 as i from e), {legs_sql(PAIRS)} {_grid}")
def m1_sizes_grid(spark, d):
    """Pairs of runs met for several pairs of sizes."""
    s = fam.supp_orders(spark, d)
    s = G.pruned(s, q := frames(s, PAIRS))
    out = None
    for s1, s2 in GRID:
        one = fixed.overlaps(fixed.query_groups(s, q, CFG, (s1, s2))).agg(F.count(F.lit(1)).alias("pairs")).select(F.lit(s1).cast("long").alias("s1"), F.lit(s2).cast("long").alias("s2"), "pairs")
        out = one if out is None else out.unionByName(one)
    return out


@query("m1_levels", " union all ".join(f"select {lv}::bigint as level, set_id, (i // {1 << lv}) as p, min(elem) as inf, max(elem) as sup, count(*) as n, bit_or({_bit63.format(y='y_1')}) as img_1 from (select set_id, elem, y_1, row_number() over (partition by set_id order by elem) - 1 as i from (with {e_sql('F4', 1)} select * from e)) group by set_id, i // {1 << lv}" for lv in range(5)))
def m1_levels(spark, d):
    g = fixed.build_levels(fam.part_orders(spark, d), CFG, 16)
    return g.select(F.col("level").cast("long").alias("level"), "set_id", "p", "inf", "sup", F.col("n").cast("long").alias("n"), "img_1")


@query("m4_bounds", f"with {e_sql(m=1)}, b as (select set_id, z, count(*) as n from e group by set_id, z) select set_id, z, (sum(n) over w - n)::bigint as \"left\", (sum(n) over w - 1)::bigint as \"right\" from b window w as (partition by set_id order by z)")
def m4_bounds(spark, d):
    return probe.bounds(fam.supp_orders(spark, d), CFG, hashing.t_scan_sql("n", CFG))


@query("work_counters")
def work_counters(spark, d):
    """What each kernel does at each point of the sweep of equal sets."""
    return workloads.work_sweep(*_points(spark, d, workloads.equal_points), CFG, tuple(kernels.METHODS))
