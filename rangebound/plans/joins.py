"""Joins of ranges by buckets: equal buckets, then the exact predicate, each pair once."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def by_sort(df: DataFrame) -> DataFrame:
    """A side that has about a row for each row of the table: it meets the other by sorting. Files and shuffles of narrow rows look
    small, and a broadcast of them would stand in the driver's memory."""
    return df.hint("merge")


def buckets(low: Column, high: Column, width: int) -> Column:
    """Numbers of the buckets of a whole-number range."""
    return F.sequence(F.floor(low / width), F.floor(high / width))


def bucket_index(df: DataFrame, low: str, high: str, width: int) -> DataFrame:
    """The range index: a row for each bucket that a row's range meets."""
    return df.withColumn("_k", F.explode(buckets(F.col(low), F.col(high), width)))


def band_pairs(left: DataFrame, right: DataFrame, left_range: tuple[str, str], right_range: tuple[str, str], width: int, on: Sequence[str] = (), indexed: bool = False) -> DataFrame:
    """Pairs whose ranges meet. Columns of `right` have the prefix s_; `on` are equal (null-safe) keys.
    A pair is kept in the first bucket that both ranges have. indexed: right is a bucket_index already."""
    a = bucket_index(left, *left_range, width)
    b = right if indexed else bucket_index(right, *right_range, width)
    b = b.select(*[F.col(c).alias(f"s_{c}") for c in b.columns])
    cond = F.col("_k") == F.col("s__k")
    for c in on:
        cond = cond & F.col(c).eqNullSafe(F.col(f"s_{c}"))
    l0, l1, r0, r1 = F.col(left_range[0]), F.col(left_range[1]), F.col(f"s_{right_range[0]}"), F.col(f"s_{right_range[1]}")
    cond = cond & (l0 <= r1) & (r0 <= l1) & (F.col("_k") == F.greatest(F.floor(l0 / width), F.floor(r0 / width)))
    return a.join(b, cond).drop("_k", "s__k")


def overlap_pairs(left: DataFrame, right: DataFrame, left_range: tuple[str, str], right_range: tuple[str, str], width: int | None = None) -> DataFrame:
    """Pairs of whole-number ranges that meet: rows with a point on both sides join by equality, and
    only uncertain rows are replicated over buckets."""
    lc, rc = F.col(left_range[0]) == F.col(left_range[1]), F.col(right_range[0]) == F.col(right_range[1])
    s = right.select(*[F.col(c).alias(f"s_{c}") for c in right.columns])
    src = F.col(f"s_{right_range[0]}") == F.col(f"s_{right_range[1]}")
    points = left.where(lc).join(s.where(src), F.col(left_range[0]) == F.col(f"s_{right_range[0]}"))
    w = width or 16
    one = band_pairs(left.where(~lc), right, left_range, right_range, w)
    two = band_pairs(left.where(lc), right.where(~rc), left_range, right_range, w)
    return points.unionByName(one).unionByName(two)


def as_of(left: DataFrame, right: DataFrame, at: str, point: str, on: Sequence[str], value: str) -> DataFrame:
    """Each left row with the value of the last right row at or before it, per key: one union, one sort."""
    kinds = dict(right.dtypes)
    a = left.withColumns({"_at": F.col(at), "_v": F.lit(None).cast(kinds[value]), "_side": F.lit(1)})
    b = right.select(*on, F.col(point).alias("_at"), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    from pyspark.sql import Window as W

    w = W.partitionBy(*on).orderBy("_at", "_side").rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b, allowMissingColumns=True).withColumn(f"{value}_as_of", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_at", "_v", "_side")
