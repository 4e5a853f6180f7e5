"""Worked examples, world enumeration, agreement of methods, top-k, plans."""

import random

import pytest
from pyspark.sql import functions as F

from rangebound.functions import expr as E
from rangebound.operators import algebra, order, window
from rangebound.plans import det
from rangebound.plans.worlds import worlds_of
from rangebound.schema import Attr, RangeFrame
from rangebound.sources import ingest

MULT = "_m_lb long, _m_sg long, _m_ub long"


def frame(spark, rows, attrs):
    """rows: (rid, (lb, sg, ub) per attribute..., (m_lb, m_sg, m_ub))."""
    flat = [(r[0], *[x for t in r[1:] for x in t]) for r in rows]
    cols = ", ".join(["_rid long", *[f"{a}__{e} long" for a in attrs for e in ("lb", "sg", "ub")], MULT])
    return RangeFrame(spark.createDataFrame(flat, cols), tuple(Attr(a, False) for a in attrs))


def positions(rf):
    return sorted(tuple(r) for r in rf.df.select("_rid", "_dup", "pos__lb", "pos__sg", "pos__ub", "_m_lb", "_m_sg", "_m_ub").collect())


SORT = [(1, (1, 1, 1), (1, 1, 3), (7, 7, 7), (1, 1, 2)), (2, (2, 3, 3), (15, 15, 15), (4, 4, 4), (0, 1, 1)), (3, (1, 1, 2), (2, 2, 2), (2, 4, 5), (1, 1, 1))]


@pytest.mark.parametrize("method", ["naive", "rewrite", "onepass", "dist", "cdf"])
def test_worked_sort(spark, method):
    rf = frame(spark, SORT, ["A", "B", "C"]).project("A", "B")
    assert positions(order.rank(rf, ["A", "B"], method=method)) == [(1, 0, 0, 0, 1, 1, 1, 1), (1, 1, 1, 1, 2, 0, 0, 1), (2, 0, 2, 2, 3, 0, 1, 1), (3, 0, 0, 1, 2, 1, 1, 1)]


def test_worked_sort_attributewise(spark):
    rf = frame(spark, SORT, ["A", "B", "C"]).project("A", "B")
    got = {r[:2]: r[2:5] for r in positions(order.rank(rf, ["A", "B"], compare="attributewise"))}
    assert got[2, 0] == (1, 2, 3)


def test_worked_window(spark):
    rf = frame(spark, SORT, ["A", "B", "C"])
    got = window.window(rf, "sum", "C", ["B"], -1, 0, partition=["A"], ties=False)
    assert sorted(tuple(r) for r in got.df.select("_rid", "_dup", "x__lb", "x__ub").collect()) == [(1, 0, 7, 14), (1, 1, 7, 14), (2, 0, 4, 9), (3, 0, 2, 12)]


def test_deterministic_examples(spark):
    bag = spark.createDataFrame([(3, 15, 1), (1, 1, 2)], "A int, B int, m int")
    assert sorted(tuple(r) for r in det.det_rank(bag, ["A"], "m").collect()) == [(1, 1, 0), (1, 1, 1), (3, 15, 2)]
    rows = spark.createDataFrame([("a", 5, 3, 3), ("b", 3, 1, 1), ("b", 3, 4, 1)], "A string, B int, C int, m int")
    assert sorted(r["x"] for r in det.det_window(rows, "sum", "B", ["A"], -2, 0, mult="m").collect()) == [5, 10, 11, 13, 15]
    assert det.det_topk(bag.drop("m"), ["A"], 1).collect()[0]["A"] == 1


def test_membership_illustration(spark):
    spec = window.WindowSpec("count", None, ("k",), -1, 4)
    rows = spark.createDataFrame([(0, 2), (5, 7), (9, 12), (5, 8), (3, 10)], "lb int, ub int")
    t = E.Triple(F.lit(4), F.lit(5), F.lit(6))
    c, p, _ = window.membership(spec, t, E.Triple(F.col("lb"), F.col("lb"), F.col("ub")), F.lit(1), F.lit(False), F.lit(True))
    assert [tuple(r) for r in rows.select(c, p).collect()] == [(False, False), (True, False), (False, True), (True, False), (False, True)]


@pytest.mark.parametrize("method", ["select", "prune", "onepass"])
def test_topk_regressions(spark, method):
    one = (1, 1, 1)
    a = frame(spark, [(0, (0, 0, 0), one), (1, (0, 5, 10), one), (2, (1, 1, 1), one), (3, (2, 2, 2), one), (4, (3, 3, 3), one)], ["k"])
    assert [(r["_rid"], r["_m_lb"]) for r in order.topk(a, ["k"], 1, method=method).df.collect()] == [(0, 1)]
    b = frame(spark, [(0, (0, 5, 10), one), (1, (0, 0, 0), one), (2, (1, 1, 1), one), (3, (2, 2, 2), one), (4, (3, 3, 3), one)], ["k"])
    assert sorted((r["_rid"], r["_m_lb"]) for r in order.topk(b, ["k"], 1, method=method).df.collect()) == [(0, 0), (1, 0)]


def test_nested_ranges_stay_possible():
    rows = [(0, 0, 1, 1, 1, True, 0), (1, 2, 1, 1, 1, True, 1), (1, 4, 1, 1, 1, True, 2), (2, 3, 1, 1, 1, True, 3), (3, 4, 1, 1, 1, True, 4)]
    got, _ = window.sweep_windows(rows, "count", -1, 0)
    assert {r: (lo, hi) for r, lo, hi, _ in got}[2] == (1, 2)


def random_rows(rng, n=3):
    out = []
    for i in range(n):
        t = []
        for lo, hi in ((0, 1), (0, 4), (-3, 3)):
            a = rng.randint(lo, hi)
            b = min(hi, a + rng.randint(0, 2))
            t.append((a, rng.randint(a, b), b))
        m = sorted(rng.randint(0, 2) for _ in range(3))
        out.append((i, *t, (min(m[0], 1), max(m[1], min(m[0], 1)), max(m[2], 1))))
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_all_worlds_lie_inside(spark, seed):
    """Positions are tight; window bounds hold in every world, with and without an uncertain partition."""
    rng = random.Random(seed)
    rows = random_rows(rng)
    rf = frame(spark, rows, ["A", "B", "C"])
    enc = [r.asDict() for r in rf.df.collect()]
    try:
        worlds = list(worlds_of(enc, [("A", False), ("B", False), ("C", False)], 30_000))
    except ValueError:
        pytest.skip("too many worlds")
    seen: dict = {}
    for w in worlds:
        ws = sorted(w, key=lambda r: (r[3], r[0], r[1]))
        dup: dict = {}
        for i, r in enumerate(ws):
            k = (r[0], dup.setdefault(r[0], 0))
            dup[r[0]] += 1
            lo, hi = seen.get(k, (i, i))
            seen[k] = (min(lo, i), max(hi, i))
    ranked = order.rank(rf, ["B"], ties=False)
    got = {(r["_rid"], r["_dup"]): (r["pos__lb"], r["pos__ub"]) for r in ranked.df.collect()}
    for k, (lo, hi) in seen.items():
        assert got[k][0] <= lo and hi <= got[k][1], (k, got[k], lo, hi)
    for agg in ("sum", "min", "avg") if seed == 1 else ("count", "max"):
        for part in ((), ("A",)):
            x = window.window(rf, agg, "C", ["B"], -1, 0, partition=part, ties=False).df.collect()
            bound = {(r["_rid"], r["_dup"]): (r["x__lb"], r["x__ub"]) for r in x}
            for w in worlds:
                groups: dict = {}
                for r in w:
                    groups.setdefault(r[2] if part else 0, []).append(r)
                count: dict = {}
                done = {}
                for g in groups.values():
                    g = sorted(g, key=lambda r: (r[3], r[0], r[1]))
                    for i, r in enumerate(g):
                        vals = [y[4] for y in g[max(0, i - 1) : i + 1]]
                        v = {"sum": sum(vals), "count": len(vals), "min": min(vals), "max": max(vals), "avg": sum(vals) / len(vals)}[agg]
                        done.setdefault(r[0], []).append((g is None, v))
                        count[r[0]] = count.get(r[0], 0) + 1
                for rid, vs in done.items():
                    # Copies of a row may be matched with its boxes in any order: each value needs some box that holds it.
                    for _, v in vs:
                        assert any(bound[k][0] - 1e-9 <= v <= bound[k][1] + 1e-9 for k in bound if k[0] == rid), (agg, part, rid, v)


def test_methods_agree(spark):
    o = spark.read.parquet("/root/testdata/sf0.001/customer.parquet")
    rf = ingest.inject(o, "c_custkey", {"bal": ingest.cents("c_acctbal")}, 30, 100_000, e=10, d=10, keep=("c_nationkey",))
    base = positions(order.rank(rf, ["bal"], method="naive"))
    for m in ("rewrite", "onepass", "dist"):
        assert positions(order.rank(rf, ["bal"], method=m)) == base
    part = positions(order.rank(rf, ["bal"], partition=["c_nationkey"], method="naive"))
    assert positions(order.rank(rf, ["bal"], partition=["c_nationkey"], method="onepass")) == part
    for lo, hi in ((-2, 0), (1, 2)):
        res = []
        for m in ("naive", "bucket", "onepass", "rewrite"):
            x = window.window(rf, "sum", "bal", ["bal"], lo, hi, partition=["c_nationkey"], method=m, chunk=16)
            res.append(sorted(tuple(r) for r in x.df.select("_rid", "_dup", "x__lb", "x__ub").collect()))
        assert all(r == res[0] for r in res)


def test_certain_rows_are_plain_sql(spark):
    c = spark.read.parquet("/root/testdata/sf0.001/supplier.parquet").select("s_suppkey", ingest.cents("s_acctbal").alias("v"))
    rf = ingest.from_certain(c, "s_suppkey")
    got = order.rank(rf, ["v"]).df.select("s_suppkey", "pos__lb", "pos__ub").collect()
    want = {r["s_suppkey"]: i for i, r in enumerate(c.orderBy("v", "s_suppkey").collect())}
    assert all(r["pos__lb"] == r["pos__ub"] == want[r["s_suppkey"]] for r in got)


def test_edges(spark):
    rf = frame(spark, [(1, (0, 1, 2), (1, 1, 1))], ["k"])
    assert order.topk(rf, ["k"], 0).df.count() == 0
    assert order.topk(rf, ["k"], 5).df.count() == 1
    none = rf.with_df(rf.df.where("false"))
    assert order.rank(none, ["k"]).df.count() == 0
    assert window.window(none, "sum", "k", ["k"], -1, 0).df.count() == 0
    bad = frame(spark, [(1, (3, 1, 2), (1, 1, 1)), (2, (0, 1, 2), (1, 0, 1))], ["k"])
    assert sorted(r["reason"] for r in bad.validate().collect()) == ["k out of order", "multiplicity out of order"]


def test_dates_and_strings_as_keys(spark):
    df = spark.sql("SELECT * FROM VALUES (1L, date'2020-01-02', 'b'), (2L, date'2020-01-01', 'c'), (3L, date'2020-01-02', 'a') t(id, day, s)")
    rf = ingest.from_certain(df, "id")
    got = {r["id"]: r["pos__lb"] for r in order.rank(rf, ["day", "s"], desc=["day"]).df.collect()}
    assert got == {3: 0, 1: 1, 2: 2}


def test_closure_and_parquet(spark, tmp_path):
    rf = frame(spark, [(i, (i, i + 1, i + 2), (1, 1, 1)) for i in range(6)], ["k"])
    top = order.topk(rf, ["k"], 2)
    sel = algebra.select(top, E.rlt(top.c("k"), E.rlit(3)))
    agg = algebra.aggregate(sel, [], {"n": ("count", None)}).df.collect()[0]
    assert agg["n__lb"] <= 2 <= agg["n__ub"]
    ingest.write(top, str(tmp_path / "x"))
    assert positions(ingest.read(spark, str(tmp_path / "x"))) == positions(top)


def test_plans(spark):
    o = spark.read.parquet("/root/testdata/sf0.001/orders.parquet")
    rf = ingest.inject(o, "o_orderkey", {"price": ingest.cents("o_totalprice")}, 5, 100_000)
    plan = order.rank(rf, ["price"]).df._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
    # The only single task sums the buckets' totals: each such exchange comes after an aggregate by bucket.
    for i, line in enumerate(lines := plan.splitlines()):
        if "SinglePartition" in line:
            assert any("Aggregate" in x for x in lines[i + 1 : i + 4]), lines[i : i + 4]
    band = window.window(rf, "sum", "price", ["price"], -2, 0).df._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in band
