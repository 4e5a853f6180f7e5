"""Windows join what has a row for each row of the table by sorting; such sides look small, but don't fit the driver."""

import pytest
from pyspark.sql import functions as F

from rangebound.operators import window
from rangebound.sources import ingest


@pytest.mark.parametrize("method", ["pairs", "bucket"])
def test_rows_of_the_table_are_not_broadcast(spark, method):
    df = spark.range(300).select(F.col("id").alias("k"), ((F.col("id") * 7919) % 997).alias("v"))
    rf = ingest.inject(df, "k", {"v": F.col("v")}, 30, 200, 10, 10)
    got = window.window(rf, "count", None, ["v"], -2, 0, method=method).df.select("_rid", "_dup", "x__lb", "x__ub")
    got.collect()
    plan = got._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    joins = [x for x in plan.split("\n") if "BroadcastHashJoin" in x and "_rid" in x.split("]")[0]]
    assert not joins
