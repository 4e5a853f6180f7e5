"""The attribute-wise comparison of one range key by running sums, against all pairs."""

import pytest
from pyspark.sql import functions as F

from rangebound.operators import order
from rangebound.sources import ingest


@pytest.mark.parametrize("desc,partition", [((), ()), (("k",), ()), ((), ("g",))])
def test_as_all_pairs(spark, desc, partition):
    df = spark.range(90).select("id", (F.col("id") * 7 % 15).alias("k"), (F.col("id") % 3).alias("g"))
    rf = ingest.inject(df, "id", {"k": F.col("k")}, 40, 4, 20, 20, keep=("g",))
    columns = ("_rid", "_dup", "pos__lb", "pos__sg", "pos__ub")
    fast, slow = (order.rank(rf, ["k"], desc, partition, method=m, compare="attributewise").df.select(*columns) for m in ("auto", "naive"))
    assert sorted(map(tuple, fast.collect())) == sorted(map(tuple, slow.collect()))
    plan = fast._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_two_ranges_compare_all_pairs(spark):
    df = spark.range(30).select("id", (F.col("id") % 4).alias("k"), (F.col("id") % 5).alias("j"))
    rf = ingest.inject(df, "id", {"k": F.col("k"), "j": F.col("j")}, 50, 3)
    got, want = (sorted(map(tuple, order.rank(rf, ["k", "j"], method=m, compare="attributewise").df.select("_rid", "pos__lb", "pos__ub").collect())) for m in ("auto", "naive"))
    assert got == want
