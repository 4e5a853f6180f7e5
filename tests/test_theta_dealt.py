"""A theta join compares its pairs in many tasks, though its rows come from one partition."""

from pyspark.sql import functions as F

from rangebound.functions import expr as E
from rangebound.operators import algebra
from rangebound.sources import ingest


def test_theta_join_uses_all_cores(spark):
    df = spark.range(200).coalesce(1).select(F.col("id").alias("k"), ((F.col("id") * 7919) % 97).alias("v"))
    a = ingest.inject(df, "k", {"v": F.col("v")}, 20, 9)
    got = algebra.theta_join(a, a, lambda c: E.rlt(c("v"), c("r_v"))).df
    assert got.select("v__lb", F.spark_partition_id().alias("p")).where("p is not null").select("p").distinct().count() > 4
    rows = a.df.collect()
    want = sorted((x["v__lb"], y["v__ub"], int(x["v__ub"] < y["v__lb"])) for x in rows for y in rows if x["v__lb"] < y["v__ub"])
    assert sorted(tuple(r) for r in got.select("v__lb", "r_v__ub", "_m_lb").collect()) == want
