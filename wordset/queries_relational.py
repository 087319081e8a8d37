"""The relational surface around the methods: joins, aggregates, windows, sorts, set operators, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing, words
from wordset.functions.store import written
from wordset.operators import baselines, fixed, prefix, scan
from wordset.operators import groups as G
from wordset.plans import api, sqlsurface
from wordset.plans.sizing import small_side
from wordset.queries import CFG, F_SQL, PAIRS, TRIPLES, _bit63, e_sql, frames, grp_sql, inter_sql, legs_sql, query
from wordset.sources import families as fam
from wordset.sources.tables import load
from wordset.streaming import sets as st

# ---- joins

_OC = "select o_orderkey, c_name from orders join customer on o_custkey = c_custkey where o_totalprice > 200000"


def _oc(spark, d):
    return load(spark, d, "orders").filter("o_totalprice > 200000"), load(spark, d, "customer")


@query("join_broadcast", _OC)
def join_broadcast(spark, d):
    o, c = _oc(spark, d)
    return o.join(small_side(c.select("c_custkey", "c_name")), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@query("join_shuffle_hash", _OC)
def join_shuffle_hash(spark, d):
    o, c = _oc(spark, d)
    return o.join(c.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@query("join_merge", _OC)
def join_merge(spark, d):
    o, c = _oc(spark, d)
    return o.join(c.hint("merge"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@query("join_inner", _OC)
def join_inner(spark, d):
    o, c = _oc(spark, d)
    return o.join(c, F.col("o_custkey") == F.col("c_custkey"), "inner").select("o_orderkey", "c_name")


@query("join_left", "select c_custkey, count(o_orderkey) as orders from customer left join orders on o_custkey = c_custkey group by c_custkey")
def join_left(spark, d):
    o = load(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("orders"))  # aggregated before the join
    return load(spark, d, "customer").join(o, F.col("o_custkey") == F.col("c_custkey"), "left").select("c_custkey", F.coalesce("orders", F.lit(0)).alias("orders"))


@query("join_full", f"with s as ({F_SQL['F1']}) select coalesce(a.elem, b.elem) as elem, a.elem is not null as in_a, b.elem is not null as in_b from (select elem from s where set_id = '0') a full join (select elem from s where set_id = '1') b on a.elem = b.elem")
def join_full(spark, d):
    s = fam.supp_orders(spark, d)
    a, b = (s.filter(F.col("set_id") == x).select(F.col("elem").alias(f"e{x}")) for x in ("0", "1"))
    return a.join(b, F.col("e0") == F.col("e1"), "full").select(F.coalesce("e0", "e1").alias("elem"), F.col("e0").isNotNull().alias("in_a"), F.col("e1").isNotNull().alias("in_b"))


@query("join_cross", "select r_name, n_name from region cross join nation where n_nationkey < 3")
def join_cross(spark, d):
    """Five regions by three nations: both sides are fixed dimension tables."""
    return load(spark, d, "region").crossJoin(F.broadcast(load(spark, d, "nation").filter("n_nationkey < 3"))).select("r_name", "n_name")


def _overlap(how):
    def run(spark, d):
        s = fam.supp_orders(spark, d)
        return fixed.overlaps(fixed.query_groups(s, frames(s, PAIRS), CFG), how).select("qid", F.col("a_p").cast("long").alias("a_p"), F.col("b_p").cast("long").alias("b_p"))

    return run


_over = f"""with {e_sql(m=1)}, run as (select set_id, elem, (row_number() over (partition by set_id order by elem) - 1) // {CFG.root} as p from e), rg as (select set_id, p, min(elem) as inf, max(elem) as sup from run group by set_id, p), {legs_sql(PAIRS)}
select a.qid, x.p as a_p, y.p as b_p from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2 join rg x on x.set_id = a.set_id join rg y on y.set_id = b.set_id where x.inf <= y.sup and y.inf <= x.sup"""
query("join_asof", _over)(_overlap("asof"))
query("join_range_bins", _over)(_overlap("bins"))
query("join_theta_overlap", _over)(_overlap("theta"))


@query("join_interval_events", "select a.event_id as purchase, count(*) as views from events a join events b on a.user_id = b.user_id and a.event_type = 'purchase' and b.event_type = 'view' and b.ts between a.ts - interval 6 hour and a.ts group by a.event_id")
def join_interval_events(spark, d):
    """Views of a user in the six hours before a purchase: an equi-join on user and hour bin, then the exact interval."""
    e = load(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    width = 6 * 3600 * 1_000_000
    a = e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("us").alias("a_us"), F.explode(F.array(F.expr(f"us div {width}"), F.expr(f"us div {width} - 1"))).alias("bin"))
    b = e.filter("event_type = 'view'").select(F.col("user_id").alias("b_user"), F.col("us").alias("b_us"), F.expr(f"us div {width}").alias("b_bin"))
    met = a.join(b, (F.col("user_id") == F.col("b_user")) & (F.col("bin") == F.col("b_bin"))).filter((F.col("b_us") <= F.col("a_us")) & (F.col("b_us") >= F.col("a_us") - width))
    return met.groupBy("purchase").agg(F.count(F.lit(1)).alias("views"))


@query("join_semi_chain", "select elem from (" + inter_sql("F1", [["0", "1", "2"]]) + ")")
def join_semi_chain(spark, d):
    s = fam.supp_orders(spark, d)
    one = lambda x: s.filter(F.col("set_id") == x).select("elem")
    return one("0").join(one("1"), "elem", "left_semi").join(one("2"), "elem", "left_semi")


@query("join_anti", f"with s as ({F_SQL['F1']}) select elem from s where set_id = '0' and elem not in (select elem from s where set_id = '1')")
def join_anti(spark, d):
    s = fam.supp_orders(spark, d)
    one = lambda x: s.filter(F.col("set_id") == x).select("elem")
    return one("0").join(one("1"), "elem", "left_anti")


@query("join_prefix", f"with {e_sql(m=1)}, {grp_sql(1)}, {legs_sql(PAIRS)} select a.qid, y.z, count(*) as ancestors from legs a join legs b on a.qid = b.qid and a.rank = 1 and b.rank = 2 join grp x on x.set_id = a.set_id join grp y on y.set_id = b.set_id and (y.z >> (y.t - x.t)) = x.z group by a.qid, y.z")
def join_prefix(spark, d):
    s = fam.supp_orders(spark, d)
    ix = G.build(s, CFG.with_(m=1))
    q = scan.legs(ix, frames(s, PAIRS))
    a = scan._leg(ix, q, 1, []).select("qid", F.col("z").alias("az"))
    b = scan._leg(ix, q, 2, []).select(F.col("qid").alias("bq"), "zkey", "z")
    return a.join(b, (F.col("qid") == F.col("bq")) & (F.col("az") == F.col("zkey"))).groupBy("qid", "z").agg(F.count(F.lit(1)).alias("ancestors"))


# ---- aggregates


@query("agg_stats", f"with s as ({F_SQL['F1']}) select set_id, count(*) as n, min(elem) as inf, max(elem) as sup from s group by set_id")
def agg_stats(spark, d):
    return G.set_stats(fam.supp_orders(spark, d))


@query("agg_image", f"with {e_sql(m=1)} select set_id, bit_or({_bit63.format(y='y_1')}) as some, bit_count(bit_or({_bit63.format(y='y_1')}))::bigint as bits from e where z = 0 group by set_id")
def agg_image(spark, d):
    g = prefix.build(fam.supp_orders(spark, d), CFG).groups.filter("z = 0")
    return g.groupBy("set_id").agg(F.bit_or("img_1").alias("some")).withColumn("bits", F.bit_count("some").cast("long"))


@query("agg_collect", f"with s as ({F_SQL['F4']}) select set_id, array_to_string(list_sort(list(elem)), ',') as elems from s group by set_id")
def agg_collect(spark, d):
    return fam.pack_sets(fam.part_orders(spark, d)).select("set_id", F.array_join(F.col("elems").cast("array<string>"), ",").alias("elems"))


@query("agg_distinct", "select l_returnflag, count(distinct l_orderkey) as orders, count(distinct l_suppkey) as suppliers from lineitem group by l_returnflag")
def agg_distinct(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("agg_approx")
def agg_approx(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"))


@query("agg_having_k", inter_sql("F1", TRIPLES))
def agg_having_k(spark, d):
    s = fam.supp_orders(spark, d)
    return baselines.counting(s, frames(s, TRIPLES))


def _lines(spark, d):
    return load(spark, d, "lineitem").select("l_returnflag", "l_linestatus", "l_orderkey")


_gs = "select coalesce(l_returnflag, '*') as flag, coalesce(l_linestatus, '*') as status, count(*) as n from lineitem group by {} "


def _named(df: DataFrame) -> DataFrame:
    return df.select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), "n")


@query("agg_rollup", _gs.format("rollup(l_returnflag, l_linestatus)"))
def agg_rollup(spark, d):
    return _named(_lines(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))


@query("agg_cube", _gs.format("cube(l_returnflag, l_linestatus)"))
def agg_cube(spark, d):
    return _named(_lines(spark, d).cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))


@query("agg_grouping_sets", _gs.format("grouping sets ((l_returnflag), (l_linestatus), ())"))
def agg_grouping_sets(spark, d):
    rows = _lines(spark, d)
    return _named(rows.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))


@query("agg_pivot", "select event_type, count(*) filter (user_id % 3 = 0) as r0, count(*) filter (user_id % 3 = 1) as r1, count(*) filter (user_id % 3 = 2) as r2 from events group by event_type")
def agg_pivot(spark, d):
    e = load(spark, d, "events").select("event_type", (F.col("user_id") % 3).cast("string").alias("r"))
    return e.groupBy("event_type").pivot("r", ["0", "1", "2"]).count().select("event_type", *(F.coalesce(F.col(str(i)), F.lit(0)).alias(f"r{i}") for i in range(3)))


@query("unpivot_sets", "select 'lang=' || lang as set_id, doc_id as elem from documents union all select 'source=' || source, doc_id from documents")
def unpivot_sets(spark, d):
    wide = load(spark, d, "documents").select("doc_id", "lang", "source")
    return wide.unpivot(["doc_id"], ["lang", "source"], "attr", "value").select(F.concat("attr", F.lit("="), "value").alias("set_id"), F.col("doc_id").alias("elem"))


@query("agg_percentile", f"with s as (select set_id, count(*) as n from ({F_SQL['F1']}) group by set_id) select round(quantile_cont(n, 0.5), 6) as p50, round(quantile_cont(n, 0.95), 6) as p95, round(avg(n), 6) as mean, round(stddev_samp(n), 6) as sd from s")
def agg_percentile(spark, d):
    s = G.set_stats(fam.supp_orders(spark, d))
    return s.agg(F.round(F.percentile("n", 0.5), 6).alias("p50"), F.round(F.percentile("n", 0.95), 6).alias("p95"), F.round(F.avg("n"), 6).alias("mean"), F.round(F.stddev("n"), 6).alias("sd"))


# ---- windows and sorts


@query("win_rank", "select o_custkey, o_orderkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, ntile(4) over w as q from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey), v as (partition by o_custkey order by o_orderpriority)")
def win_rank(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    cols = {"rn": F.row_number().over(w), "rk": F.rank().over(v), "dr": F.dense_rank().over(v), "q": F.ntile(4).over(w)}
    return load(spark, d, "orders").select("o_custkey", "o_orderkey", *(c.cast("long").alias(n) for n, c in cols.items()))


@query("win_gaps", f"with s as ({F_SQL['F4']}) select set_id, elem, elem - coalesce(lag(elem) over (partition by set_id order by elem), -1) as gap from s")
def win_gaps(spark, d):
    by = Window.partitionBy("set_id").orderBy("elem")
    return fam.part_orders(spark, d).select("set_id", "elem", (F.col("elem") - F.coalesce(F.lag("elem").over(by), F.lit(-1))).alias("gap"))


@query("win_next", f"with s as ({F_SQL['F4']}) select set_id, elem, coalesce(lead(elem) over w, -1) as next, first_value(elem) over w as head from s window w as (partition by set_id order by elem)")
def win_next(spark, d):
    by = Window.partitionBy("set_id").orderBy("elem")
    return fam.part_orders(spark, d).select("set_id", "elem", F.coalesce(F.lead("elem").over(by), F.lit(-1)).alias("next"), F.first("elem").over(by).alias("head"))


@query("win_prefix_sum", f"with {e_sql(m=1)}, {grp_sql(1)} select set_id, z, coalesce(sum(n) over (partition by set_id order by z rows between unbounded preceding and 1 preceding), 0)::bigint as \"left\" from grp")
def win_prefix_sum(spark, d):
    by = Window.partitionBy("set_id").orderBy("z").rowsBetween(Window.unboundedPreceding, -1)
    return prefix.build(fam.supp_orders(spark, d), CFG).groups.select("set_id", "z", F.coalesce(F.sum("n").over(by), F.lit(0)).alias("left"))


@query("win_range", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as last_day from events")
def win_range(spark, d):
    by = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    e = load(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    return e.select("event_id", F.count(F.lit(1)).over(by).alias("last_day"))


@query("topk_terms", f"with s as ({F_SQL['F5']}) select set_id, count(*) as n from s group by set_id order by n desc, set_id limit 50")
def topk_terms(spark, d):
    return fam.term_docs(spark, d).groupBy("set_id").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "set_id").limit(50)


@query("topk_per_lang", r"with t as (select lang, w, count(*) as n from (select lang, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) as w from documents) group by lang, w) select lang, w, n from t qualify row_number() over (partition by lang order by n desc, w) <= 5")
def topk_per_lang(spark, d):
    t = load(spark, d, "documents").select("lang", F.explode(F.expr(fam.tokens("text"))).alias("w")).groupBy("lang", "w").agg(F.count(F.lit(1)).alias("n"))
    return t.withColumn("at", F.row_number().over(Window.partitionBy("lang").orderBy(F.col("n").desc(), "w"))).filter("at <= 5").select("lang", "w", "n")


@query("global_sort", "select s_suppkey, row_number() over (order by s_acctbal desc, s_suppkey) as at from supplier")
def global_sort(spark, d):
    """Ranks from sorted ranges: the place within the range after the counted rows of the ranges before it."""
    order = F.col("s_acctbal").desc(), F.col("s_suppkey")
    s = load(spark, d, "supplier").select("s_suppkey", "s_acctbal").repartitionByRange(*order)
    s = written(s.withColumn("part", F.spark_partition_id()), "ranges")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row per range
    skip = s.groupBy("part").agg(F.count(F.lit(1)).alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("skip"))
    ranked = s.withColumn("i", F.row_number().over(Window.partitionBy("part").orderBy(*order)))
    return ranked.join(F.broadcast(skip), "part").select("s_suppkey", (F.col("i") + F.col("skip")).cast("long").alias("at"))


@query("sorted_index", f"with {e_sql(m=1)}, {grp_sql(1)} select set_id, z, n from grp")
def sorted_index(spark, d):
    return prefix.build(fam.supp_orders(spark, d), CFG).groups.repartition("set_id").sortWithinPartitions("set_id", "z").select("set_id", "z", F.col("n").cast("long").alias("n"))


@query("intersect_count", "select count(*) as r from (" + inter_sql("F2", [["AF", "NF"]]) + ")")
def intersect_count(spark, d):
    return api.intersect_count(api.build_index(fam.flag_orders(spark, d), CFG.with_(m=2)), ["AF", "NF"], "scan")


@query("intersect_limit")
def intersect_limit(spark, d):
    return api.intersect_limit(api.build_index(fam.flag_orders(spark, d), CFG.with_(m=2)), ["AF", "NF"], 10, "scan")


@query("is_disjoint", "select q.qid, not exists (select 1 from (" + inter_sql("F1", TRIPLES) + ") x where x.qid = q.qid) as disjoint from (select unnest(range(20)) as qid) q")
def is_disjoint(spark, d):
    s = fam.supp_orders(spark, d)
    return api.is_disjoint(api.build_index(s, CFG.with_(m=2)), frames(s, TRIPLES))


# ---- set operators

_a, _b = (f"select elem from ({F_SQL['F1']}) where set_id = '{i}'" for i in (0, 1))
_oa, _ob = "select o_orderpriority as p from orders where o_orderkey % 2 = 0", "select o_orderpriority as p from orders where o_orderkey % 3 = 0"


def _ab(spark, d):
    s = fam.supp_orders(spark, d)
    return tuple(s.filter(F.col("set_id") == x).select("elem") for x in ("0", "1"))


def _pab(spark, d):
    o = load(spark, d, "orders")
    return tuple(o.filter(f"o_orderkey % {m} = 0").select(F.col("o_orderpriority").alias("p")) for m in (2, 3))


query("set_intersect", f"{_a} intersect {_b}")(lambda s, d: (lambda ab: ab[0].intersect(ab[1]))(_ab(s, d)))
query("set_union", f"{_a} union {_b}")(lambda s, d: (lambda ab: ab[0].union(ab[1]).distinct())(_ab(s, d)))
query("set_except", f"{_a} except {_b}")(lambda s, d: (lambda ab: ab[0].subtract(ab[1]))(_ab(s, d)))
query("set_intersect_all", f"{_oa} intersect all {_ob}")(lambda s, d: (lambda ab: ab[0].intersectAll(ab[1]))(_pab(s, d)))
query("set_except_all", f"{_oa} except all {_ob}")(lambda s, d: (lambda ab: ab[0].exceptAll(ab[1]))(_pab(s, d)))
query("set_union_by_name", f"{_oa} union all {_ob}")(lambda s, d: (lambda ab: ab[0].unionByName(ab[1]))(_pab(s, d)))

# ---- scans, predicates, functions


@query("filter_surface", "select p_partkey, case when p_size < 10 then 'small' when p_size < 30 then 'middle' else 'large' end as class from part where p_size between 3 and 45 and p_brand in ('Brand#1', 'Brand#2') and p_type not like '%STEEL%' and regexp_matches(p_type, '^[A-Z]+') and p_name is not null")
def filter_surface(spark, d):
    p = load(spark, d, "part").filter(F.col("p_size").between(3, 45) & F.col("p_brand").isin("Brand#1", "Brand#2") & ~F.col("p_type").like("%STEEL%") & F.col("p_type").rlike("^[A-Z]+") & F.col("p_name").isNotNull())
    return p.select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large").alias("class"))


@query("json_sets", "select (props->>'k')::bigint % 10 as k, count(distinct event_id) as n from events where props->>'k' is not null group by 1")
def json_sets(spark, d):
    e = load(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")).filter("k is not null")
    return e.groupBy((F.col("k") % 10).alias("k")).agg(F.count_distinct("event_id").alias("n"))


@query("date_sets", "select year(o_orderdate)::bigint as y, month(o_orderdate)::bigint as m, count(distinct o_custkey) as n from orders group by 1, 2")
def date_sets(spark, d):
    o = load(spark, d, "orders").select("o_custkey", F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).alias("m"))
    return o.groupBy("m").agg(F.count_distinct("o_custkey").alias("n")).select(F.year("m").cast("long").alias("y"), F.month("m").cast("long").alias("m"), "n")


@query("bit_functions", f"with {e_sql(m=1)}, {grp_sql(1)} select set_id, z, bit_count(img_1)::bigint as ones, (img_1 & 255)::bigint as low, xor(img_1, -1) as inverse from grp")
def bit_functions(spark, d):
    g = prefix.build(fam.supp_orders(spark, d), CFG).groups
    return g.select("set_id", "z", F.bit_count("img_1").cast("long").alias("ones"), F.col("img_1").bitwiseAND(F.lit(255)).alias("low"), F.bitwise_not("img_1").alias("inverse"))


@query("bits_of_images", f"with {e_sql(m=1)} select distinct set_id, z, y_1::bigint as y from e where set_id in ('0', '1')")
def bits_of_images(spark, d):
    g = prefix.build(fam.supp_orders(spark, d).filter(F.col("set_id").isin("0", "1")), CFG).groups
    return g.select("set_id", "z", F.explode(words.bits_of(F.col("img_1"))).alias("y")).withColumn("y", F.col("y").cast("long"))


@query("permutation_inverse", f"select o_orderkey, {hashing.g_sql('o_orderkey', CFG, True)} as g, o_orderkey as back from orders")
def permutation_inverse(spark, d):
    g = load(spark, d, "orders").select("o_orderkey", hashing.g("o_orderkey", CFG).alias("g"))
    return g.withColumn("back", hashing.g_inverse("g", CFG))


@query("sql_functions", "select o_orderkey, o_orderkey & 4095 as a, case when ((o_orderkey + 1) + 7) // 8 <= 1 then 0 else length(bin(((o_orderkey + 1) + 7) // 8 - 1)) end::int as t, (2 * (length(bin(o_orderkey + 1)) - 1) + 1)::int as gb from orders")
def sql_functions(spark, d):
    sqlsurface.register(spark, CFG)
    return load(spark, d, "orders").select("o_orderkey", F.expr("image_and(o_orderkey, 4095)").alias("a"), F.expr("t_scan(o_orderkey + 1)").alias("t"), F.expr("gamma_bits(o_orderkey + 1)").alias("gb"))


@query("table_functions", f"with {e_sql(m=1)} select distinct y_1::bigint as y from e where set_id = '0' and z = 0")
def table_functions(spark, d):
    sqlsurface.register(spark, CFG)
    g = prefix.build(fam.supp_orders(spark, d).filter("set_id = '0'"), CFG).groups.filter("z = 0").select("img_1")
    g.createOrReplaceTempView("one_group")
    return spark.sql("select cast(b.y as bigint) as y from one_group, lateral bits_of(img_1) b")


@query("sql_statement", "select elem from (" + inter_sql("F2", [["AF", "NO"]]) + ")")
def sql_statement(spark, d):
    sqlsurface.name_index("flags", api.build_index(fam.flag_orders(spark, d), CFG.with_(m=2)))
    return sqlsurface.sql("INTERSECT SETS AF, 'NO' IN flags USING scan")


@query("g_hash_order", inter_sql("F1", TRIPLES))
def g_hash_order(spark, d):
    """The order by a hash instead of a permutation: ties are broken by the element, which the members carry."""
    s = fam.supp_orders(spark, d)
    return scan.intersect(G.build(s, Cfg(g="hash", m=2)), frames(s, TRIPLES))


# ---- streams, run to the end of what is there


@query("stream_windows", "select count(*) as n, sum(freq)::bigint as freq from (select event_type, date_trunc('day', ts) as day, user_id, count(*) as freq from events group by all)")
def stream_windows(spark, d):
    sets = st.run_once(st.window_sets(st.read_events(spark, f"{d}/events.parquet")), "w_sets", "complete")
    return sets.agg(F.count(F.lit(1)).alias("n"), F.sum("freq").alias("freq"))


@query("stream_intersect", "select day as start_day, user_id as elem from (select strftime(ts, '%Y-%m-%d') as day, user_id, event_type from events where event_type in ('view', 'click', 'purchase')) group by day, user_id having count(distinct event_type) = 3")
def stream_intersect(spark, d):
    out = st.run_once(st.stream_intersect(st.read_events(spark, f"{d}/events.parquet"), ["view", "click", "purchase"]), "w_all", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("start_day"), "elem")
