"""Expressions, algebra by enumeration, heaps, measures, baselines, streaming, entry."""

import random

import pytest
from pyspark.sql import functions as F

from rangebound.functions import expr as E
from rangebound.functions import metrics
from rangebound.functions.heaps import ConnectedHeap, UnconnectedHeaps
from rangebound.operators import algebra as A
from rangebound.plans import baselines as B
from rangebound.plans.joins import as_of
from rangebound.plans.worlds import bag_of_worlds, enumerate_worlds, worlds_of
from rangebound.sources import ingest
from rangebound.streaming import bounds
from tests.test_order import frame


def one(spark, *triples):
    t = spark.range(1)
    return tuple(t.select(*[getattr(x, e) for x in triples for e in ("lb", "sg", "ub")]).collect()[0])


def lit(a, b, c):
    return E.Triple(F.lit(a), F.lit(b), F.lit(c))


def test_expressions(spark):
    assert one(spark, E.rlt(lit(1, 1, 3), E.rlit(2))) == (False, True, True)
    assert one(spark, E.weigh(lit(10, 20, 30), lit(1, 2, 3))) == (10, 40, 90)
    assert one(spark, lit(-1, 0, 2) * lit(-3, 1, 4)) == (-6, 0, 8)
    assert one(spark, lit(-4, -2, 3).abs(), -lit(1, 2, 3)) == (0, 2, 4, -3, -2, -1)
    assert one(spark, E.rcase(E.rlt(lit(1, 1, 3), E.rlit(2)), E.rlit(5), E.rlit(9))) == (5, 5, 9)
    assert one(spark, E.rnot(E.req(lit(1, 1, 2), E.rlit(1)))) == (False, False, True)
    assert one(spark, lit(4, 6, 8).divide(lit(-1, 1, 2), F.lit(-99.0), F.lit(99.0)))[::2] == (-99.0, 99.0)


@pytest.mark.parametrize("seed", range(3))
def test_algebra_bounds_worlds(spark, seed):
    """select, aggregate, distinct, difference: every world's result is inside the bounds."""
    rng = random.Random(seed)
    rows = []
    for i in range(3):
        a = rng.randint(0, 3)
        b = a + rng.randint(0, 2)
        lo = rng.randint(0, 1)
        rows.append((i, (a, rng.randint(a, b), b), (lo, 1, rng.randint(1, 2))))
    rf, other = frame(spark, rows, ["k"]), frame(spark, rows[:1], ["k"])
    enc = [r.asDict() for r in rf.df.collect()]
    worlds = [[r[2] for r in w] for w in worlds_of(enc, [("k", False)], 30_000)]
    less = A.aggregate(A.select(rf, E.rlt(rf.c("k"), E.rlit(2))), [], {"n": ("count", None), "s": ("sum", "k")}).df.collect()[0]
    for w in worlds:
        v = [x for x in w if x < 2]
        if less["n__ub"] is None:
            assert not v
        else:
            assert less["n__lb"] <= len(v) <= less["n__ub"] and less["s__lb"] <= sum(v) <= less["s__ub"]
    d = A.distinct(rf).df.agg(F.sum("_m_lb"), F.sum("_m_ub")).collect()[0]
    assert all(d[0] <= len(set(w)) <= d[1] for w in worlds)
    left = A.difference(rf, other).df.agg(F.coalesce(F.sum("_m_lb"), F.lit(0)), F.coalesce(F.sum("_m_ub"), F.lit(0))).collect()[0]
    taken = [[r[2] for r in w] for w in worlds_of(enc[:1], [("k", False)])]
    for w in worlds:
        for t in taken:
            rest = list(w)
            for x in t:
                if x in rest:
                    rest.remove(x)
            assert left[0] <= len(rest) <= left[1]


def test_uncertain_group_keys_cover(spark):
    rows = [(0, (0, 0, 1), (1, 1, 1)), (1, (1, 1, 1), (1, 1, 1)), (2, (1, 2, 2), (0, 1, 1))]
    rf = frame(spark, rows, ["k"])
    got = A.aggregate(rf, ["k"], {"n": ("count", None)}).df.collect()
    for w in worlds_of([r.asDict() for r in rf.df.collect()], [("k", False)]):
        keys = [r[2] for r in w]
        for k in set(keys):
            assert any(g["k__lb"] <= k <= g["k__ub"] and g["n__lb"] <= keys.count(k) <= g["n__ub"] for g in got)


def test_heaps():
    orders = [lambda r: r[0], lambda r: r[1]]
    h = ConnectedHeap(orders)
    for r in ((1, 3), (2, 6), (3, 2), (4, 1)):
        h.insert(r)
    assert h.pop(0) == (1, 3)
    assert [r[1] for r in h.ascending(1)] == [1, 2, 6]
    rng = random.Random(5)
    a, b = ConnectedHeap(orders), UnconnectedHeaps(orders)
    for _ in range(600):
        if len(a) and rng.random() < 0.45:
            k = rng.randint(0, 1)
            assert a.pop(k) == b.pop(k)
        else:
            r = (rng.randint(0, 99), rng.randint(0, 99))
            a.insert(r), b.insert(r)
        for k in (0, 1):
            heap = a.heaps[k]
            assert all((heap[(i - 1) // 2][0], heap[(i - 1) // 2][1]) <= (e[0], e[1]) for i, e in enumerate(heap) if i)
            assert all(e[3][k] == i for i, e in enumerate(heap))


def test_measures(spark):
    b = spark.createDataFrame([(1, 0, 10), (2, 3, 3), (3, 0, 4)], "id int, lb int, ub int")
    t = spark.createDataFrame([(1, 0, 5), (2, 3, 3), (3, 2, 2)], "id int, lb int, ub int")
    got = metrics.quality(b, t, ["id"], "lb", "ub").collect()[0]
    assert (got["n_rows"], got["recall_ppm"], got["accuracy_ppm"], got["size_ratio_ppm"]) == (3, 1_000_000, 500_000, 1_500_000)
    m = metrics.membership_quality(spark.createDataFrame([(1, 1), (1, 2)], "a int, b int"), spark.createDataFrame([(1, 1)], "a int, b int"), ["a", "b"]).collect()[0]
    assert tuple(m) == (0.5, 1.0)


def test_baselines(spark):
    s = spark.read.parquet("/root/testdata/sf0.001/supplier.parquet")
    rf = ingest.inject(s, "s_suppkey", {"v": ingest.cents("s_acctbal")}, 60, 500_000)
    probs = B.threshold_topk(rf, ["v"], 3, 0.01).collect()
    assert all(0 < r["p"] <= 1 for r in probs)
    assert abs(sum(r["p"] for r in probs) - 3) < 0.3
    sure = {r["_rid"] for r in B.threshold_topk(rf, ["v"], 3, 1.0).collect()}
    some = {r["_rid"] for r in B.threshold_topk(rf, ["v"], 3, 0.0).collect()}
    assert sure <= {r["_rid"] for r in probs} <= some
    assert B.most_likely_per_position(rf, ["v"], 3).count() == 3
    assert B.most_likely_topk(rf, ["v"], 2).count() == 2
    tiny = frame(spark, [(0, (0, 0, 2), (1, 1, 1)), (1, (1, 1, 1), (1, 1, 1))], ["k"])
    assert B.exact_topk_lists(tiny, "k", 1)[0][0] == (0,)
    assert bag_of_worlds(enumerate_worlds(tiny), ["k"]).count() == 3


def test_constructors(spark):
    df = spark.createDataFrame([(1, 5, 0.6), (1, 7, 0.3), (2, 4, 1.0)], "k long, v long, w double")
    got = {r["k"]: (r["v__lb"], r["v__sg"], r["v__ub"], r["_m_lb"]) for r in ingest.from_alternatives(df, "k", ("v",), "w").df.collect()}
    assert got == {1: (5, 5, 7, 0), 2: (4, 4, 4, 1)}
    a = spark.createDataFrame([(1, "x", 5), (2, "x", 9)], "id long, g string, t int")
    b = spark.createDataFrame([("x", 3, 30), ("x", 7, 70)], "g string, p int, v int")
    assert {r["id"]: r["v_as_of"] for r in as_of(a, b, "t", "p", ["g"], "v").collect()} == {1: 30, 2: 70}


def test_stream_equals_batch(spark, tmp_path):
    e = spark.read.parquet("/root/testdata/sf0.001/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e = e.select("event_type", F.col("ts").alias("a"), (F.col("ts") + F.expr("interval 90 seconds")).alias("b"))
    e.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    one_ = lambda df: sorted(map(tuple, bounds.group_bounds(df, "a", "b", 3600, keys=("event_type",)).collect()))
    got = bounds.run_available(bounds.group_bounds(stream, "a", "b", 3600, keys=("event_type",)), str(tmp_path / "out"))
    assert sorted(map(tuple, got.collect())) == one_(e)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
