"""Windows that compare all pairs do so block by block: no row for each pair, and the same bounds."""

from pyspark.sql import functions as F

from rangebound.operators import order, window
from rangebound.plans import compare
from rangebound.sources import ingest


def frame(spark, n=150):
    df = spark.range(n).select(F.col("id").alias("k"), ((F.col("id") * 7919) % 997 - 400).alias("v"), (F.col("id") % 3).alias("g"))
    return ingest.inject(df, "k", {"v": F.col("v")}, 30, 200, 10, 10, keep=("g",))


def rows(rf):
    return sorted(tuple(r) for r in rf.df.select("_rid", "_dup", "x__lb", "x__sg", "x__ub", "x_certain", "x_possible").collect())


def lists_pairs(rf):
    plan = rf.df._jdf.queryExecution().executedPlan().toString()
    return "CartesianProduct" in plan or "NestedLoopJoin" in plan


def test_naive_by_blocks(spark, monkeypatch):
    monkeypatch.setattr(compare, "BLOCK", 64)
    rf = frame(spark)
    for lo, hi, part in ((-2, 0, ()), (1, 2, ("g",))):
        by = lambda m: window.window(rf, "sum", "v", ["v"], lo, hi, part, method=m, detail=True)  # noqa: B023, E731
        got = by("naive")
        assert not lists_pairs(got)
        assert rows(got) == rows(by("pairs"))


def test_rewrite_by_blocks(spark, monkeypatch):
    monkeypatch.setattr(compare, "BLOCK", 64)
    rf = frame(spark)
    for agg in ("sum", "count", "min", "max"):
        by = lambda m: window.window(rf, agg, None if agg == "count" else "v", ["v"], -2, 0, method=m, detail=True)  # noqa: B023, E731
        got = by("rewrite")
        assert not lists_pairs(got)
        assert rows(got) == rows(by("pairs"))


def test_index_has_each_member_once(spark):
    rf = frame(spark)
    spec = window.WindowSpec("sum", "v", ("v",), -2, 0)
    members = window._members(order.rank(rf, ["v"]), spec)
    index = window.band_index(members, 2).cache()
    assert index.count() == members.count()
    by = lambda **kw: window.window(rf, "sum", "v", ["v"], -2, 0, detail=True, **kw)
    assert rows(by(method="rewrite", index=index, width=2)) == rows(by(method="pairs"))


def test_registered_without_pairs(spark, monkeypatch):
    monkeypatch.setattr(compare, "LISTED", 16)
    window.register_aggregate("members", lambda sure, maybe, slots: F.size(sure).cast("long"), lambda sure, maybe, slots: (F.size(sure) + F.size(maybe)).cast("long"))
    rf = frame(spark)
    got = window.window(rf, "members", "v", ["v"], -2, 0, detail=True)
    assert "collect_list" not in got.df._jdf.queryExecution().executedPlan().toString()
    assert all(r[2] == r[5] and r[4] == r[5] + r[6] for r in rows(got))
    assert [r[5:] for r in rows(got)] == [r[5:] for r in rows(window.window(rf, "count", None, ["v"], -2, 0, method="pairs", detail=True))]
