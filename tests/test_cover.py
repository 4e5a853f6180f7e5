"""Nodes that cover a range of cells: each cell once, by an expression that stays small with the levels."""

from pyspark.sql import functions as F

from rangebound.plans import overlap


def test_each_cell_once(spark):
    ranges = [(a, b) for a in (0, 1, 5, 16, 63, 250) for b in (0, 1, 4, 15, 17, 64, 255, 1000) if a <= b]
    nodes = overlap._cover(F.col("a"), F.col("b"), 4)
    for r in spark.createDataFrame(ranges, "a long, b long").select("a", "b", nodes.alias("x")).collect():
        cells = [c for level, node in r["x"] for c in range(node * overlap.FAN**level, (node + 1) * overlap.FAN**level)]
        assert sorted(cells) == list(range(r["a"], r["b"] + 1))
    one, two = (len(str(overlap._cover(F.col("a"), F.col("b"), n))) for n in (4, 8))
    assert two < 3 * one
