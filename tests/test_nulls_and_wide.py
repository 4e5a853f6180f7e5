"""Null keys, partitions and groups in every method; hashed ids; summaries of wide windows against all pairs."""

import random

import pytest
from pyspark.sql import functions as F
from test_order import frame, positions

from rangebound.functions import expr as E
from rangebound.operators import algebra, order, window
from rangebound.plans import prefix, worlds
from rangebound.schema import Attr, RangeFrame
from rangebound.sources import ingest

ONE = (1, 1, 1)
METHODS = ["naive", "rewrite", "onepass", "dist", "cdf"]


def grouped(spark):
    df = spark.createDataFrame([(1, 5, "a"), (2, 3, "a"), (3, 9, None), (4, 4, None)], "k long, v long, g string")
    return ingest.from_intervals(df, "k", {"v": (F.col("v"), F.col("v"), F.col("v") + 2)}, None, ("g",))


@pytest.mark.parametrize("method", METHODS)
def test_a_null_partition_is_a_partition(spark, method):
    got = order.rank(grouped(spark), ["v"], partition=["g"], method=method)
    assert [r[:5] for r in positions(got)] == [(1, 0, 0, 1, 1), (2, 0, 0, 0, 1), (3, 0, 1, 1, 1), (4, 0, 0, 0, 0)]


@pytest.mark.parametrize("method", ["naive", "rewrite", "bucket", "pairs", "onepass"])
def test_windows_keep_a_null_partition(spark, method):
    got = window.window(grouped(spark), "count", None, ["v"], -1, 0, partition=["g"], method=method).df
    assert sorted((r["_rid"], r["x__lb"], r["x__ub"]) for r in got.collect()) == [(1, 1, 2), (2, 1, 2), (3, 2, 2), (4, 1, 1)]
    whole = window.window(grouped(spark), "sum", "v", ["v"], None, 0, partition=["g"]).df
    assert whole.count() == 4


@pytest.mark.parametrize("method", METHODS)
def test_null_keys_come_first(spark, method):
    df = spark.createDataFrame([(1, 5, 6), (2, None, None), (3, 1, 9), (4, None, None)], "k long, a long, b long")
    rf = ingest.from_intervals(df, "k", {"v": (F.col("a"), F.col("a"), F.col("b"))})
    for desc in ([], ["v"]):
        got = {r["_rid"]: (r["pos__lb"], r["pos__ub"]) for r in order.rank(rf, ["v"], desc=desc, method=method).df.collect()}
        assert got == {2: (0, 0), 4: (1, 1), 1: (2, 3), 3: (2, 3)}


@pytest.mark.parametrize("method", ["select", "prune", "onepass"])
def test_topk_with_null_keys(spark, method):
    df = spark.createDataFrame([(1, 5), (2, None), (3, 1), (4, 7)], "k long, a long")
    rf = ingest.from_intervals(df, "k", {"v": (F.col("a"), F.col("a"), F.col("a"))})
    assert {r["_rid"] for r in order.topk(rf, ["v"], 2, method=method).df.collect()} == {2, 3}
    assert {r["_rid"] for r in order.topk(rf, ["v"], 2, desc=["v"], method=method).df.collect()} == {2, 4}


def test_a_cut_beyond_the_driver(spark, monkeypatch):
    rf = frame(spark, [(i, (i, i, i + i % 3), ONE) for i in range(50)], ["v"])
    spec = order.RankSpec(("v",))
    want = [order.cut(rf, spec, k) for k in (1, 7, 50, 51)]
    monkeypatch.setattr(order, "CUT_ROWS", 0)
    assert [order.cut(rf, spec, k) for k in (1, 7, 50, 51)] == want and want[-1] is None


def test_rows_without_a_group_stay(spark):
    df = spark.createDataFrame([(1, 5, "a"), (2, None, None), (3, 8, None)], "k long, v long, g string")
    got = {r["_rid"]: (r["v__lb"], r["v__ub"]) for r in ingest.from_imputation(df, "k", "v", "g").df.collect()}
    assert got == {1: (5, 5), 2: (8, 8), 3: (8, 8)}


def test_union_and_worlds_of_hashed_ids(spark):
    rf = frame(spark, [(i, (i % 3, i % 3, i % 3 + 1), ONE) for i in range(9)], ["v"])
    rf = algebra.project(rf, k=E.rlit(F.col("_rid") % 4), v="v")
    rf = RangeFrame(rf.df.withColumn("k", F.col("k__lb")).select("_rid", "k", "v__lb", "v__sg", "v__ub", "_m_lb", "_m_sg", "_m_ub"), (Attr("k"), Attr("v", False)))
    one = algebra.aggregate(rf, ["k"], {"n": ("sum", "v")})
    both = algebra.union(one, one)
    assert both.df.count() == both.df.select("_rid").distinct().count() == 8
    assert worlds.sample_worlds(both, 3).count() == 24


def test_many_splitters_search_as_few_do(spark):
    df = spark.range(5000).selectExpr("id", "named_struct('k0', if(id % 50 = 0, null, id div 7), 'k1', id) as p")
    cuts = sorted([(None if i % 11 == 0 else i, 3 * i) for i in range(300)], key=prefix.ordered)
    got = prefix.with_bucket(df, "p", cuts, ["bigint", "bigint"]).withColumn("want", prefix.bucket_of(F.col("p"), cuts, ["bigint", "bigint"]))
    assert got.where("_b <> want").count() == 0 and got.agg(F.max("_b")).first()[0] > 200


@pytest.mark.parametrize("agg,lo,hi", [("sum", -2, 0), ("sum", 1, 3), ("count", -1, 1), ("min", -2, 0), ("max", 1, 3), ("avg", -1, 1)])
def test_summaries_agree_with_all_pairs(spark, agg, lo, hi):
    rng = random.Random(f"{agg}{lo}")
    rows = []
    for i in range(260):
        a = rng.randint(0, 400)
        wide = rng.choice([0, 0, 0, 2, 30, 390]) if rng.random() < 0.5 else 0
        v = rng.randint(-50, 50)
        m = rng.choice([(1, 1, 1), (0, 1, 1), (1, 1, 2), (0, 0, 1)])
        rows.append((i, (a, a + wide // 2, a + wide), (v, v + 1, v + rng.randint(1, 5)), m))
    rf = frame(spark, rows, ["k", "v"])
    out = lambda method: sorted(tuple(r) for r in window.window(rf, agg, "v", ["k"], lo, hi, method=method, detail=method != "x").df.select("_rid", "_dup", "x__lb", "x__sg", "x__ub", "x_certain", "x_possible").collect())
    assert out("bucket") == out("naive")


@pytest.mark.parametrize("agg", ["sum", "count", "min", "max"])
def test_rewrite_with_and_without_an_index(spark, agg):
    rng = random.Random(agg)
    rf = frame(spark, [(i, (a := rng.randint(0, 60), a, a + rng.choice([0, 0, 9])), (v := rng.randint(-9, 9), v, v + 1), ONE) for i in range(60)], ["k", "v"])
    spec = window.WindowSpec(agg, "v", ("k",), -2, 0)
    index = window.band_index(window._members(order.rank(rf, ["k"]), spec), 16).cache()
    out = lambda **kw: sorted(tuple(r) for r in window.window(rf, agg, "v", ["k"], -2, 0, **kw).df.select("_rid", "x__lb", "x__sg", "x__ub").collect())
    assert out(method="rewrite") == out(method="naive") == out(method="rewrite", index=index, width=16)


def test_joins_on_two_uncertain_keys(spark):
    rng = random.Random(5)
    make = lambda n, at: frame(spark, [(at + i, (a := rng.randint(0, 9), a, a + rng.randint(0, 2)), (b := rng.randint(0, 3), b, b + rng.randint(0, 1)), (rng.randint(0, 1), 1, 1)) for i in range(n)], ["a", "b"])
    x, y = make(25, 0), make(25, 100)
    got = algebra.join(x, y, [("a", "a"), ("b", "b")]).df.collect()
    rows = lambda rf: [r.asDict() for r in rf.df.collect()]
    meets = lambda p, q, c: p[f"{c}__lb"] <= q[f"{c}__ub"] and q[f"{c}__lb"] <= p[f"{c}__ub"]
    assert len(got) == sum(meets(p, q, "a") and meets(p, q, "b") for p in rows(x) for q in rows(y)) > 20
    semi = {r["_rid"]: (r["_m_lb"], r["_m_ub"]) for r in algebra.semi_join(x, y, [("a", "a"), ("b", "b")]).df.collect()}
    assert set(semi) == {p["_rid"] for p in rows(x) if any(meets(p, q, "a") and meets(p, q, "b") for q in rows(y))}
    point = lambda r: r["a__lb"] == r["a__ub"] and r["b__lb"] == r["b__ub"]
    sure = {p["_rid"] for p in rows(x) if p["_m_lb"] and point(p) and any(q["_m_lb"] and point(q) and (p["a__lb"], p["b__lb"]) == (q["a__lb"], q["b__lb"]) for q in rows(y))}
    assert {k for k, v in semi.items() if v[0]} == sure


def test_unknown_aggregates_raise(spark):
    rf = frame(spark, [(1, (1, 1, 2), ONE)], ["k"])
    with pytest.raises(ValueError):
        window.sweep_windows([], "median", -1, 0)
    with pytest.raises(ValueError):
        window.window(rf, "median", "k", ["k"], -1, 0, method="onepass")
