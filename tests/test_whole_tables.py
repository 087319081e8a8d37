"""Queries that must take all rows, however large the table."""

from pyspark.sql import functions as F

from wordset import queries, queries_experiments, queries_relational  # noqa: F401
from wordset.operators import kernels
from wordset.plans import workloads


def test_global_sort_ranks_more_than_a_million_suppliers(spark, tmp_path):
    n = 1_000_500
    s = spark.range(n).select(F.col("id").alias("s_suppkey"), F.lit("s").alias("s_name"), F.lit(0).alias("s_nationkey"), (F.col("id") % 1000).cast("double").alias("s_acctbal"))
    s.write.parquet(f"{tmp_path}/supplier.parquet")
    got = queries.QUERIES["global_sort"](spark, str(tmp_path)).agg(F.count(F.lit(1)), F.countDistinct("at"), F.min("at"), F.max("at")).first()
    assert tuple(got) == (n, n, 1, n)
    first, last = (queries.QUERIES["global_sort"](spark, str(tmp_path)).filter(F.col("at") == at).first().s_suppkey for at in (1, n))
    assert (first, last) == (999, 1_000_000)


def test_sweeps_take_their_points_from_the_table(spark, sf):
    n = spark.read.parquet(f"{sf}/orders.parquet").count()
    got = {r.qid: r.r for r in queries.QUERIES["w2_overlap"](spark, sf).collect()}
    assert got == {j: r for j, (_, _, r) in enumerate(workloads.overlap_points(n))}


def test_counters_of_every_kernel(spark, sf):
    n = spark.read.parquet(f"{sf}/orders.parquet").count()
    want = {(m, j, r) for m in kernels.METHODS for j, (_, _, r) in enumerate(workloads.equal_points(n)) if r}
    got = {(x.method, x.qid, x.r) for x in queries.QUERIES["work_counters"](spark, sf).collect()}
    assert len(kernels.METHODS) == 11 and want <= got


def test_bounds_are_of_groups_of_the_table(spark, sf, tmp_path):
    """Twice the suppliers with the same orders make twice the groups; bounds stay what they are."""
    one = spark.read.parquet(f"{sf}/lineitem.parquet")
    one.unionByName(one.withColumn("l_suppkey", F.col("l_suppkey") + 1_000_000)).write.parquet(f"{tmp_path}/lineitem.parquet")
    a, b = ({(r.w, r.m): (r.one_image, r.m_images, r.groups) for r in queries.QUERIES["bounds"](spark, d).collect()} for d in (sf, str(tmp_path)))
    assert len(a) == 20 and b == {k: (x, y, 2 * n) for k, (x, y, n) in a.items()}
