"""How good bounds are. A range's size is its length; a range of length 0 has ratio 1 where it is met."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.joins import by_sort


def _overlap(b: tuple[Column, Column], t: tuple[Column, Column]) -> Column:
    return F.least(b[1], t[1]) - F.greatest(b[0], t[0])


def recall(b: tuple[Column, Column], t: tuple[Column, Column]) -> Column:
    """Share of the tight range that the bound covers; for a point 1 if it lies in the bound."""
    o = _overlap(b, t)
    return F.when(t[0] == t[1], (o >= 0).cast("double")).otherwise(F.greatest(o, F.lit(0)) / F.nullif(t[1] - t[0], F.lit(0)))


def accuracy(b: tuple[Column, Column], t: tuple[Column, Column]) -> Column:
    """Share of the bound that is tight; for a point bound 1 if it lies in the tight range."""
    o = _overlap(b, t)
    return F.when(b[0] == b[1], (o >= 0).cast("double")).otherwise(F.greatest(o, F.lit(0)) / F.nullif(b[1] - b[0], F.lit(0)))


def accuracy_formula(b: tuple[Column, Column], t: tuple[Column, Column]) -> Column:
    """Hull over overlap: 1 for equal ranges, more for looser bounds; null where they don't overlap."""
    hull = F.greatest(b[1], t[1]) - F.least(b[0], t[0])
    return F.when(hull == 0, 1.0).otherwise(hull / F.nullif(F.greatest(_overlap(b, t), F.lit(0)), F.lit(0)))


def size_ratio(b: tuple[Column, Column], t: tuple[Column, Column]) -> Column:
    """Size of the bound over that of the tight range; 1 where both are points, null where only the tight one is."""
    return F.when((t[0] == t[1]) & (b[0] == b[1]), 1.0).otherwise((b[1] - b[0]) / F.nullif(t[1] - t[0], F.lit(0)))


def quality(bound: DataFrame, tight: DataFrame, ids: Sequence[str], lb: str, ub: str) -> DataFrame:
    """One row of means, in millionths: recall, accuracy, accuracy_formula, size_ratio, and how many rows."""
    b, t = (F.col(f"b.{lb}"), F.col(f"b.{ub}")), (F.col(f"t.{lb}"), F.col(f"t.{ub}"))
    both = bound.alias("b").join(by_sort(tight.select(*ids, lb, ub)).alias("t"), list(ids))
    ppm = lambda c: F.floor(F.avg(c) * 1_000_000 + 0.5).cast("long")
    return both.agg(F.count(F.lit(1)).alias("n_rows"), ppm(recall(b, t)).alias("recall_ppm"), ppm(accuracy(b, t)).alias("accuracy_ppm"), ppm(accuracy_formula(b, t)).alias("formula_ppm"), ppm(size_ratio(b, t)).alias("size_ratio_ppm"))


def membership_quality(bound: DataFrame, tight: DataFrame, pair: Sequence[str]) -> DataFrame:
    """Of possible window members (pairs): share that is right, share that is found."""
    a, b = bound.select(*pair).distinct().withColumn("_b", F.lit(1)), tight.select(*pair).distinct().withColumn("_t", F.lit(1))
    both = a.join(by_sort(b), list(pair), "full")
    hit = F.sum(F.when(F.col("_b").isNotNull() & F.col("_t").isNotNull(), 1).otherwise(0))
    return both.agg((hit / F.count("_b")).alias("membership_accuracy"), (hit / F.count("_t")).alias("membership_recall"))


def soundness(bound: DataFrame, worlds: DataFrame, ids: Sequence[str], value: str) -> DataFrame:
    """Share of values in worlds that lie inside their row's bounds: must be 1."""
    both = worlds.select(*ids, value).join(bound.select(*ids, f"{value}__lb", f"{value}__ub"), list(ids), "left")
    ok = (F.col(value) >= F.col(f"{value}__lb")) & (F.col(value) <= F.col(f"{value}__ub"))
    return both.agg(F.count(F.lit(1)).alias("n"), F.avg(F.coalesce(ok, F.lit(False)).cast("double")).alias("inside"))
