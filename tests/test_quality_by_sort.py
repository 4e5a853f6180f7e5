"""Quality measures join rows and pairs of members by sorting: broadcast sides would stand in the driver."""

from rangebound.functions import metrics


def test_no_side_is_broadcast(spark):
    rows = spark.range(20).selectExpr("id AS _rid", "id AS x__lb", "id + 2 AS x__ub")
    pairs = spark.range(20).selectExpr("id AS _rid", "id div 2 AS member")
    for got in (metrics.quality(rows, rows, ["_rid"], "x__lb", "x__ub"), metrics.membership_quality(pairs, pairs, ["_rid", "member"])):
        assert got.first() is not None
        assert "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()
    assert metrics.quality(rows, rows, ["_rid"], "x__lb", "x__ub").first()["n_rows"] == 20
