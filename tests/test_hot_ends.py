"""Many ranges that begin at one position: wide windows have no row for each pair of them."""

from pyspark.sql import functions as F

from rangebound.operators import window
from rangebound.sources import ingest


def joined(plan):
    """Most rows that a join of the finished plan put out."""
    if plan.nodeName().startswith("AdaptiveSparkPlan"):
        plan = plan.executedPlan()
    while "QueryStage" in plan.nodeName():
        plan = plan.plan()
    rows = plan.metrics().get("numOutputRows")
    own = rows.get().value() if "Join" in plan.nodeName() and rows.isDefined() else 0
    return max([own, *[joined(plan.children().apply(i)) for i in range(plan.children().size())]])


def test_equal_ranges_are_not_paired(spark):
    n = 1500
    df = spark.range(n).select(F.col("id").alias("k"), ((F.col("id") * 7919) % 997 - 500).cast("long").alias("v"))
    rf = ingest.from_intervals(df, "k", {"at": (F.lit(0).cast("long"), F.lit(1).cast("long"), F.lit(9).cast("long"))}, keep=("v",))
    got = window.window(rf, "sum", "v", ["at"], -2, 0, method="bucket", ties=False).df.select("_rid", "v", "x__lb", "x__ub")
    rows = got.collect()
    assert joined(got._jdf.queryExecution().executedPlan()) < 20 * n
    values = sorted((r["v"], r["_rid"]) for r in rows)
    for r in rows[::50]:
        rest = [v for v, i in values if i != r["_rid"]]
        assert r["x__lb"] == r["v"] + sum(min(v, 0) for v in rest[:2]) and r["x__ub"] == r["v"] + sum(max(v, 0) for v in rest[-2:])
