"""The experiments as queries: what each method answers, opens and stores on the workloads, free of the clock (``bench.py`` has the times)."""

from __future__ import annotations

from pyspark.sql import functions as F

from wordset.functions import hashing
from wordset.functions.store import written
from wordset.operators import baselines, blocks, cells, kernels, measures, prefix
from wordset.operators import groups as G
from wordset.plans import workloads
from wordset.queries import CFG, EQUAL, F_SQL, PAIRS, TRIPLES, _bit63, _levels, _pairs_cte, _points, _rate, _results, ctl_cte, ctl_sql, e_sql, frames, grp_sql, legs_sql, q_sql, query
from wordset.sources import families as fam
from wordset.sources.tables import load

METHODS = tuple(kernels.METHODS)
CODED = ("merge", "lookup", "scan")
CODECS = blocks.CODECS


def _values(names, column: str) -> str:
    return "(values " + ", ".join(f"('{n}')" for n in names) + f") v_{column}({column})"


# ---- all methods on the workloads

_ctl_results = ctl_sql(EQUAL)


@query("w1_all_methods", f"select method, qid, r from ({_ctl_results}) cross join {_values(METHODS, 'method')}")
def w1_all_methods(spark, d):
    """Equal sets, one member in a hundred common, by every kernel on the same blocks."""
    return workloads.kernel_results(*_points(spark, d, workloads.equal_points), CFG, METHODS).filter("r > 0").select("method", "qid", "r")


def _terms(spark, d):
    q = written(workloads.term_queries(spark, d), "term-queries")
    return G.pruned(fam.term_docs(spark, d), q), q


def _by_k(got, queries, *keys):
    return got.filter("r > 0").join(queries.select("qid", "k"), "qid").groupBy(*keys, F.col("k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("hits"), F.sum("r").alias("r"))


@query("w6_all_methods", _results + f" select method, k::bigint as k, count(*) as hits, sum(r)::bigint as r from res cross join {_values(METHODS, 'method')} where r > 0 group by method, k")
def w6_all_methods(spark, d):
    """The ten thousand most frequent queries, by every kernel, by number of terms."""
    s, q = _terms(spark, d)
    return _by_k(cells.kernel_results(s, q, CFG, METHODS), q, "method")


@query("w8_coded_equal", f"select codec, method, qid, r from ({_ctl_results}) cross join {_values(CODECS, 'codec')} cross join {_values(CODED, 'method')}")
def w8_coded_equal(spark, d):
    """Equal sets in each coding."""
    return workloads.kernel_results(*_points(spark, d, workloads.equal_points), CFG, CODED, CODECS, 1).filter("r > 0").select("codec", "method", "qid", "r")


@query("w9_coded_terms", _results + f" select codec, method, k::bigint as k, count(*) as hits, sum(r)::bigint as r from res cross join {_values(CODECS, 'codec')} cross join {_values(CODED, 'method')} where r > 0 group by codec, method, k")
def w9_coded_terms(spark, d):
    """The most frequent queries in each coding."""
    s, q = _terms(spark, d)
    return _by_k(cells.kernel_results(s, q, CFG, CODED, CODECS, 1), q, "codec", "method")


# ---- random term sets

RANDOM = {2: 600, 3: 300, 4: 100}


def _draws() -> str:
    out, start, first = [], 0, 0
    for k, n in RANDOM.items():
        out.append(f"select (i - {start}) // {k} + {first} as qid, {k} as k, list_sort(list_distinct(list(set_id))) as ids from dr where i >= {start} and i < {start + k * n} group by all having len(ids) = {k}")
        start, first = start + k * n, first + n
    total = sum(k * n for k, n in RANDOM.items())
    return f"dr as (select set_id, row_number() over (order by d, set_id) - 1 as i from (select set_id, md5(set_id || '|' || elem) as d from sets order by d, set_id limit {total})), tq as ({' union all '.join(out)})"


_random = f"""with sets as ({F_SQL["F5"]}), st as (select set_id, count(*) as n from sets group by set_id), {_draws()}, q as (select qid, k, unnest(ids) as set_id from tq),
sz as (select qid, k, min(n) as n1, list_sort(list(n))[2] as n2, max(n) as nk from q join st using (set_id) group by qid, k),
hit as (select qid, count(*) as r from (select qid, elem from q join sets using (set_id) group by qid, elem having count(*) = any_value(k)) group by qid),
res as (select qid, k, n1, n2, nk, coalesce(r, 0) as r from sz left join hit using (qid))"""


def _random_results(spark, d):
    s = written(fam.term_docs(spark, d), "terms")
    return measures.results(s, written(workloads.random_terms(s, RANDOM), "random-queries"))


@query("w6b_random_terms", _random + " select qid, k::bigint as k, n1, nk, r from res")
def w6b_random_terms(spark, d):
    """Terms drawn with the weight of their postings: less in common than neighbouring words have."""
    return _random_results(spark, d).select("qid", F.col("k").cast("long").alias("k"), "n1", "nk", "r")


@query("w6b_profile", _random + " select k::bigint as k, count(*) as queries, round(avg(n1 / n2), 6) as n1_n2, round(avg(n1 / nk), 6) as n1_nk, round(avg(r / n1), 6) as r_n1, round(avg((r = 0)::int), 6) as empty from res group by k")
def w6b_profile(spark, d):
    return measures.query_profile(_random_results(spark, d)).withColumn("k", F.col("k").cast("long"))


# ---- filtering

F_SQL["F13"] = f"select s || qid as set_id, o_orderkey as elem from (with {ctl_cte(EQUAL)} select * from u)"
EQUAL_NAMES = [[f"A{j}", f"B{j}"] for j in range(len(EQUAL))]


def pairs_sql(family: str, legs: str, m: int) -> str:
    """CTE ``pt``: aligned pairs of groups of two-set queries, whether each image meets, and their common members."""
    return f"""{e_sql(family, m)}, {grp_sql(m)}, {legs},
    pr as (select a.qid, a.set_id as sa, b.set_id as sb, x.z as za, y.z as zb, {', '.join(f'(x.img_{j} & y.img_{j}) <> 0 as hit_{j}' for j in range(1, m + 1))}
     from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2 join grp x on x.set_id = a.set_id join grp y on y.set_id = b.set_id and (y.z >> (y.t - x.t)) = x.z),
    cm as (select l.qid, eb.z as zb, count(*) as r from legs l join legs k on l.qid = k.qid and l.rank = 1 and k.rank = 2 join e ea on ea.set_id = l.set_id join e eb on eb.set_id = k.set_id and eb.elem = ea.elem group by l.qid, eb.z),
    pt as (select pr.*, coalesce(cm.r, 0) as r from pr left join cm using (qid, zb))"""


def rate_sql(m: int) -> str:
    return " union all ".join(f"select {j}::bigint as m, count(*) as empty_pairs, count(*) filter (not ({' and '.join(f'hit_{i}' for i in range(1, j + 1))})) as filtered from pt where r = 0" for j in range(1, m + 1))


_legs_of = "legs as (select qid, set_id, t, count(*) over (partition by qid) as k, row_number() over (partition by qid order by n, set_id) as rank from q join st using (set_id) where qid not in (select qid from q where set_id not in (select set_id from st)))"


@query("w11_filter_equal", f"with {pairs_sql('F13', legs_sql(EQUAL_NAMES), 8)} {rate_sql(8)}")
def w11_filter_equal(spark, d):
    """Share of empty pairs that one to eight images filter, on the sweep of equal sets."""
    s, q = _points(spark, d, workloads.equal_points)
    return measures.filter_rate(G.build(s, CFG.with_(m=8), keep=True), q, 8).withColumn("m", F.col("m").cast("long"))


_two_terms = _results.replace("with tq", "tq").split(", sets as")[0]


@query("term_filter_rate", f"with {_two_terms}, {pairs_sql('F5', 'q as (select qid, unnest(ids) as set_id from tq where k = 2), ' + _legs_of, 8)} {rate_sql(8)}")
def term_filter_rate(spark, d):
    """The same on the two-term queries of the term workload."""
    q = written(workloads.term_queries(spark, d).filter("k = 2"), "term-queries").select("qid", "set_ids")
    return cells.filter_rate(G.pruned(fam.term_docs(spark, d), q), q, CFG, 8)


@query("m3_false_positives", f"with {_pairs_cte}, b as ({_rate}) select m::bigint as m, empty_pairs, empty_pairs - filtered as passed, round((empty_pairs - filtered) / empty_pairs, 6) as rate from b")
def m3_false_positives(spark, d):
    s = fam.supp_orders(spark, d)
    return measures.false_positives(G.build(s, CFG, keep=True), frames(s, PAIRS), 4)


@query("scan_counters", f"with {pairs_sql('F13', legs_sql(EQUAL_NAMES), 4)} select qid, count(*) as pairs_met, count(*) filter (hit_1 and hit_2 and hit_3 and hit_4) as pairs_passed, count(*) filter (r > 0) as pairs_hit, sum(r)::bigint as r from pt group by qid")
def scan_counters(spark, d):
    """What the scan kernel opens at each point of the sweep of equal sets."""
    return workloads.work_sweep(*_points(spark, d, workloads.equal_points), CFG, ("scan",)).select("qid", "pairs_met", "pairs_passed", "pairs_hit", "r")


_steps = f"""with {e_sql(m=1)}, {grp_sql(1)}, {legs_sql(TRIPLES)}, s1 as (select qid, l.t, z, img_1 as h from legs l join grp using (set_id) where rank = 1),
s2 as (select s1.qid, y.t, y.z, s1.h & y.img_1 as h from s1 join legs l on l.qid = s1.qid and l.rank = 2 join grp y on y.set_id = l.set_id and (y.z >> (y.t - s1.t)) = s1.z where (s1.h & y.img_1) <> 0),
s3 as (select s2.qid, l.set_id, y.t, y.z, s2.h & y.img_1 as h from s2 join legs l on l.qid = s2.qid and l.rank = 3 join grp y on y.set_id = l.set_id and (y.z >> (y.t - s2.t)) = s2.z where (s2.h & y.img_1) <> 0),
gm as (select s3.qid, e.elem from s3 join e on e.set_id = s3.set_id and e.z = s3.z where (s3.h & ({_bit63.format(y='e.y_1')})) <> 0),
ms as (select gm.qid, gm.elem, max(case when m.elem is null then l.rank end) as gap from gm join legs l using (qid) left join e m on m.set_id = l.set_id and m.elem = gm.elem group by gm.qid, gm.elem)
select qid, i, count(*) as elems from (select qid, unnest(range(gap + 1, 4)) as i from ms where gap is not null) group by qid, i"""


@query("m2_candidates", _steps)
def m2_candidates(spark, d):
    """Candidates by the first set from which on they are in all."""
    s = fam.supp_orders(spark, d)
    return measures.candidates(s, frames(s, TRIPLES), CFG)


@query("group_tail", f"with {e_sql(m=1)}, {grp_sql(1)} select round((select sum(n) from st) / (select sum(power(2, t)) from st), 6) as mean_size, round((select count(*) from grp where n > 2.6122 * {CFG.root}) / (select sum(power(2, t)) from st), 6) as tail")
def group_tail(spark, d):
    got = measures.group_tail(G.build(fam.supp_orders(spark, d), CFG.with_(m=1)), 1.6122)
    return got.select(F.round("mean_size", 6).alias("mean_size"), F.round("tail", 6).alias("tail"))


# ---- space and pre-processing

FAMILIES = {"F1": fam.supp_orders, "F2": fam.flag_orders, "F3": fam.prio_cust, "F4": fam.part_orders, "F5": fam.term_docs, "F7": fam.page_terms, "F9": fam.part_attrs, "F10": fam.doc_attrs, "F11": fam.label_vecs, "F12": fam.nation_sets, "F14": fam.emb_sign}
F_SQL["F12"] = "select distinct unnest(['region=' || r_name, 'nation=' || n_name, 'segment=' || c_mktsegment]) as set_id, c_custkey as elem from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"
F_SQL["all"] = " union all ".join(f"select '{f}' as family, set_id, elem from ({F_SQL[f]})" for f in FAMILIES)
_fam_space = f"""with sets as ({F_SQL['all']}), st as (select family, set_id, count(*) as n, {hashing.t_scan_sql('count(*)', CFG, True)} as t from sets group by all),
e as (select family, set_id, t, {hashing.g_sql('elem', CFG, True)} as g from sets join st using (family, set_id)), gr as (select family, set_id, {hashing.prefix_sql('g', 't', CFG, True)} as z from e group by all),
a as (select family, (select count(*) from gr where gr.family = x.family) as g, sum(n) as n, sum(ceil(n / {CFG.root}.0)) as runs from st x group by family)
select family, structure, m::bigint as m, floor(words)::bigint as words, round(words / n - 1, 6) as overhead from (select family, n, unnest(['plain', 'image_scan', 'image_scan', 'image_scan', 'image_scan', 'prefix_groups', 'fixed_groups', 'prefix_probe']) as structure,
 unnest([0, 1, 2, 4, 8, 1, 1, 0]) as m, unnest([n::double, n + 2.0 * g, n + 3.0 * g, n + 5.0 * g, n + 9.0 * g, 1.5 * n + 3 * g, 1.5 * n + 2 * runs, n + 2.0 * g]) as words from a)"""


@query("w5_space_families", _fam_space)
def w5_space_families(spark, d):
    """Words of every structure over all families of sets."""
    out = None
    for name, make in FAMILIES.items():
        one = make(spark, d).select(F.lit(name).alias("family"), "set_id", "elem")
        out = one if out is None else out.unionByName(one)
    return measures.space_families(out, CFG)


@query("space_multires", f"with l as ({_levels}), top as (select set_id, max(t) as top from l group by set_id) select (top - t)::bigint as up, count(*) as groups, sum({hashing.bits_of_sql('(\"right\" - \"left\" + 1)')})::bigint as first_words from l join top using (set_id) group by all")
def space_multires(spark, d):
    """Words of the ``first`` entries of the structure of all granularities, by level."""
    return measures.space_multires(prefix.build_multires(fam.supp_orders(spark, d), CFG)[1])


@query("sort_only", F_SQL["F1"])
def sort_only(spark, d):
    """The yardstick of pre-processing: the sets, sorted."""
    return baselines.sort_only(fam.supp_orders(spark, d))


@query("term_passages", r"with w as (select doc_id, unnest(ws) as w, generate_subscripts(ws, 1) - 1 as i from (select doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') as ws from documents)), s as (select distinct w, doc_id * 16777216 + i // 16 as elem from w) select elem from s where w in ('the', 'of', 'and') group by elem having count(*) = 3")
def term_passages(spark, d):
    """Passages of sixteen words that hold three terms: ids wider than 32 bits."""
    s = fam.term_passages(spark, d)
    q = frames(s, [["the", "of", "and"]])
    from wordset.operators import scan

    return scan.intersect(G.build(G.pruned(s, q), CFG.with_(m=2, g="xx64", h="xx64"), keep=True), q).select("elem")


@query("ctl_overlap", f"with k as (select o_orderkey, row_number() over (order by {fam.SCRAMBLE.format(x='o_orderkey')}) as i from orders) select o_orderkey as elem from k where i > 380 and i <= 400")
def ctl_overlap(spark, d):
    s = fam.ctl_overlap(spark, d, 400, 300, 20)
    return baselines.spark_intersect(s, "A", "B")


@query("random_pairs", f"select qid, count(*) as r from (select qid, elem from {q_sql(workloads.random_suppliers(100, 2))} join ({F_SQL['F1']}) using (set_id) group by qid, elem having count(*) = 2) group by qid")
def random_pairs(spark, d):
    """Twenty random combinations of two suppliers, as each point of an experiment has."""
    s = fam.supp_orders(spark, d)
    from wordset.operators import scan

    q = frames(s, workloads.random_suppliers(100, 2))
    return scan.intersect(G.build(G.pruned(s, q), CFG.with_(m=2), keep=True), q).groupBy("qid").agg(F.count(F.lit(1)).alias("r"))


@query("join_right", "select n_name, count(s_suppkey) as suppliers from supplier right join nation on s_nationkey = n_nationkey group by n_name")
def join_right(spark, d):
    s = load(spark, d, "supplier").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("suppliers"))
    return s.join(load(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"), "right").select("n_name", F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("image_udaf", f"with {e_sql(m=1)}, {grp_sql(1)} select set_id, z, img_1 from grp where set_id in ('0', '1', '2')")
def image_udaf(spark, d):
    """The image as a grouped Pandas aggregate, the twin of the built-in ``bit_or``."""
    from wordset.functions.words import image_pandas

    s = fam.supp_orders(spark, d).filter("set_id in ('0', '1', '2')")
    sizes = G.set_stats(s).select("set_id", F.expr(hashing.t_scan_sql("n", CFG)).cast("int").alias("t"))
    rows = G.hashed(s, CFG, 1).join(sizes, "set_id").withColumn("z", F.expr(hashing.prefix_sql("g", "t", CFG)))
    return rows.groupBy("set_id", "z").agg(image_pandas()(F.col("y_1")).alias("img_1"))


LEVEL = 4


@query("m2_inverse_walk", f"with {e_sql(m=1)}, p as (select set_id, elem, g, y_1, case when n <= 1 then 0 else length(bin(n - 1)) end as top, {hashing.prefix_sql('g', LEVEL, CFG, True)} as z4 from e) select set_id, z4 as z, y_1 as y, count(*) as n, sum(elem)::bigint as total, arg_min(elem, g) as first from p where top >= {LEVEL} group by set_id, z4, y_1")
def m2_inverse_walk(spark, d):
    """The inverse lists of one level of the structure of all granularities, by first and next."""
    e, lv = prefix.build_multires(fam.supp_orders(spark, d), CFG)
    lists = prefix.inverse_of(e, lv, LEVEL, CFG)
    return lists.select("set_id", "z", F.col("y").cast("long").alias("y"), F.size("elems").cast("long").alias("n"), F.expr("aggregate(elems, 0L, (a, x) -> a + x)").alias("total"), F.element_at("elems", 1).alias("first"))
