"""The heap trace replays the whole table, in traces of bounded size."""

from pyspark.sql import functions as F

from rangebound import queries as q
from rangebound import workloads as X


def test_heap_trace_replays_all_line_items(spark):
    sf = "/root/testdata/sf0.01"
    got = q.QUERIES["heap_trace"](spark, sf).toPandas()
    li = spark.read.parquet(f"{sf}/lineitem.parquet")
    want = {r["p"]: r["n"] for r in li.groupBy(F.expr(f"l_orderkey div {X.ORDERS_PER_TRACE}").alias("p")).agg(F.count("*").alias("n")).collect()}
    for kind in ("connected", "unconnected"):
        mine = got[got.kind == kind]
        assert dict(zip(mine.part, mine.n, strict=True)) == want and mine.n.sum() == li.count()
    assert (got.groupby("part").digest.nunique() == 1).all()


def test_heap_traces_stay_small(spark):
    n = lambda sf: q.QUERIES["heap_trace"](spark, f"/root/testdata/{sf}").toPandas()
    small, large = n("sf0.001"), n("sf0.01")
    assert large.n.max() < 2 * small.n.max() and len(large) > 5 * len(small)
