"""Whole lists of members: handed on a few at a time, from blocks that wide ranges reach few of."""

import pyarrow as pa
from pyspark.sql import functions as F

from rangebound.operators import window
from rangebound.plans import compare
from rangebound.sources import ingest


def test_lists_come_in_parts(monkeypatch):
    n = 300
    monkeypatch.setattr(compare, "VALUES", 1000)
    both = [(i, 0, 1, 1, 1, 0, i, n, i, i, i, mine) for mine in (True, False) for i in range(n)]
    names = [*compare.COLUMNS, "_own"]
    t = pa.table([pa.array(x) for x in zip(*both, strict=True)], names=names)
    parts = list(compare._compare("", -2, 0, True)(t))
    assert len(parts) > 100 and sum(p.num_rows for p in parts) == n
    assert max(len(p.column("_pl").combine_chunks().flatten()) for p in parts) < 1000 + n
    assert all(len(x) == n - 1 for p in parts for x in p.column("_pl").to_pylist())


def test_wide_ranges_are_dealt_few_times(spark):
    df = spark.range(3000).select(F.col("id").alias("k"), F.col("id").alias("v"))
    rf = ingest.inject(df, "k", {"v": F.col("v")}, 30, 3000)
    members = window._members(window.rank(rf, ["v"]), window.WindowSpec("sum", "v", ("v",), -2, 0)).cache()
    dealt = compare.deal_near(members, window.band_index(members, 16), -2, 0, [], 16, True)
    assert dealt.count() < 3 * members.count()
