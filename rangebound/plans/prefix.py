"""Distributed running sums: no task ever holds the whole order.

Rows are dealt to buckets that follow the order. A bucket's sums start from the totals of the buckets
before it, and those are one row per bucket. The bucket is a pure function of the row (literal
splitters taken from a sample, or the order key itself where it has few values), so a task that
runs again deals alike. Nulls come first in every order, and are a partition like any other.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SAMPLE_PER_BUCKET = 50
#: Most splitters; their table is one literal, searched by halving.
MOST_BUCKETS = 1 << 13
#: Types whose values the literal table holds unchanged.
_PLAIN = ("tinyint", "smallint", "int", "bigint", "float", "double", "string", "boolean", "date")


def ordered(values: Sequence) -> tuple:
    """A row's values as a key that sorts as Spark's structs do, nulls first."""
    return tuple((v is not None, v if v is not None else 0) for v in values)


def join_null_safe(left: DataFrame, right: DataFrame, keys: Sequence[str], how: str = "inner") -> DataFrame:
    """Join on equal keys, nulls being equal; the keys stay once."""
    r = right.withColumnsRenamed({k: f"_same_{k}" for k in keys})
    cond = reduce(lambda x, y: x & y, [F.col(k).eqNullSafe(F.col(f"_same_{k}")) for k in keys])
    return left.join(r, cond, how).drop(*[f"_same_{k}" for k in keys])


def splitters(df: DataFrame, point: str, rid: str, buckets: int) -> list[tuple]:
    """At most buckets - 1 values of the struct column `point` that cut its order about evenly.
    The sample is of bounded size and chosen by a hash of the row id."""
    if buckets < 2:
        return []
    want = SAMPLE_PER_BUCKET * buckets
    total = df.count()
    u = F.pmod(F.xxhash64(rid), F.lit(1 << 30))
    rows = df.where(u < int((1 << 30) * (2 * want / total))) if total > 4 * want else df
    got = rows.select(point, u.alias("_u")).orderBy("_u").limit(want).select(point).collect()
    values = sorted((tuple(r[0]) for r in got), key=ordered)
    step = len(values) / buckets
    return sorted({values[int(i * step)] for i in range(1, buckets) if int(i * step) < len(values)}, key=ordered)


def bucket_of(point: Column, cuts: Sequence[tuple], kinds: Sequence[str]) -> Column:
    """Number of cuts at or below the point, by a balanced tree of comparisons."""

    def lit(cut: tuple) -> Column:
        return F.struct(*[F.lit(v).cast(k).alias(f"k{i}") for i, (v, k) in enumerate(zip(cut, kinds, strict=True))])

    def tree(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(point >= lit(cuts[mid]), tree(mid + 1, hi)).otherwise(tree(lo, mid))

    return tree(0, len(cuts)).cast("int")


def with_bucket(df: DataFrame, point: str | Column, cuts: Sequence[tuple], kinds: Sequence[str], into: str = "_b") -> DataFrame:
    """Adds the number of cuts at or below the point. Few cuts are a tree of comparisons; many are a literal array
    that is searched by halving, in one expression of fixed size."""
    point = F.col(point) if isinstance(point, str) else point
    if len(cuts) <= 64 or not all(k in _PLAIN or k.startswith("decimal") for k in kinds):
        return df.withColumn(into, bucket_of(point, cuts, kinds))
    rows = [{f"k{i}": v if isinstance(v, (bool, int, float, str)) or v is None else str(v) for i, v in enumerate(c)} for c in cuts]
    shape = ", ".join(f"k{i}: {k}" for i, k in enumerate(kinds))
    table = F.from_json(F.lit(json.dumps(rows)), f"array<struct<{shape}>>")
    steps = F.array(*[F.lit(1 << k) for k in reversed(range(len(cuts).bit_length()))])
    found = F.aggregate(steps, F.lit(0), lambda at, step: F.when((at + step <= len(cuts)) & (point >= F.get(table, at + step - 1)), at + step).otherwise(at))
    return df.withColumn(into, found)


def bucket_count(df: DataFrame, buckets: int | None = None) -> int:
    """As many as shuffle partitions, unless given."""
    return min(buckets or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), MOST_BUCKETS)


def running_sums(df: DataFrame, bucket: Sequence[str], order: Sequence[str], weights: dict[str, str], partition: Sequence[str] = (), many: bool = False) -> DataFrame:
    """Adds, for each of `weights` (new column -> column), the sum over all rows that come before.
    `bucket` columns follow the order; `order` sorts within a bucket and must not tie. many: there may be about as many
    buckets as rows, so the totals of those before are running sums themselves, over buckets of buckets."""
    partition, bucket = list(partition), list(bucket)
    totals = df.groupBy(*partition, *bucket).agg(*[F.sum(w).alias(f"_t_{n}") for n, w in weights.items()])
    if many:
        coarse = totals.withColumn("_at", F.struct(*[F.col(c).alias(f"k{i}") for i, c in enumerate(bucket)]))
        kinds = [f.dataType.simpleString() for f in coarse.schema["_at"].dataType.fields]
        cuts = splitters(coarse.withColumn("_id", F.xxhash64(*bucket)), "_at", "_id", bucket_count(df))
        coarse = with_bucket(coarse, "_at", cuts, kinds, "_c")
        offsets = running_sums(coarse, ["_c"], ["_at"], {f"_o_{n}": f"_t_{n}" for n in weights}, partition).select(*partition, *bucket, *[f"_o_{n}" for n in weights])
    else:
        before = W.partitionBy(*partition).orderBy(*bucket).rowsBetween(W.unboundedPreceding, -1)
        offsets = totals.select(*partition, *bucket, *[F.coalesce(F.sum(f"_t_{n}").over(before), F.lit(0)).alias(f"_o_{n}") for n in weights])
    local = W.partitionBy(*partition, *bucket).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    out = df.withColumns({n: F.coalesce(F.sum(w).over(local), F.lit(0)) for n, w in weights.items()})
    # One row per bucket (and partition): Spark broadcasts it while it is small.
    out = join_null_safe(out, offsets, [*partition, *bucket])
    return out.withColumns({n: (F.col(n) + F.col(f"_o_{n}")).cast("long") for n in weights}).drop(*[f"_o_{n}" for n in weights])
