"""Windows on values: equal key ranges meet once, whatever the number of their rows."""

import pytest
from pyspark.sql import functions as F

from rangebound.operators import window
from rangebound.sources import ingest


@pytest.mark.parametrize("agg", ["sum", "count", "min", "max"])
def test_as_all_pairs(spark, agg):
    df = spark.range(70).select("id", (F.col("id") * 7 % 12).alias("k"), (F.col("id") * 31 % 41 - 20).alias("v"))
    rf = ingest.inject(df, "id", {"k": F.col("k"), "v": F.col("v")}, 30, 4, 20, 20)
    for lo, hi in ((-1, 1), (0, 0), (-3, 0)):
        got, want = (sorted(tuple(r) for r in window.group_window(rf, agg, None if agg == "count" else "v", "k", lo, hi, method=m).df.select("_rid", "_dup", "x__lb", "x__sg", "x__ub").collect()) for m in ("bucket", "naive"))
        assert got == want


def test_one_value_of_many_rows(spark):
    n = 100_000  # as pairs, 10^10
    rf = ingest.inject(spark.range(n).withColumn("k", F.lit(5).cast("long")), "id", {"k": F.col("k")}, 0, 1, keep=("id",))
    got = window.group_window(rf, "sum", "id", "k", -1, 1).df.agg(F.count(F.lit(1)), F.min("x__lb"), F.max("x__ub")).first()
    assert tuple(got) == (n, n * (n - 1) // 2, n * (n - 1) // 2)
