"""Deterministic operators on bags: total order, positions, top-k, row and group windows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .prefix import bucket_count, join_null_safe, running_sums, splitters, with_bucket

AGG = {"sum": F.sum, "count": F.count, "min": F.min, "max": F.max, "avg": F.avg}


def total_order(df: DataFrame, keys: Sequence[str], desc: Sequence[str] = ()) -> list:
    """The keys, then all other columns by name, as sort columns."""
    rest = sorted(c for c in df.columns if c not in keys)
    return [F.col(k).desc() if k in desc else F.col(k).asc() for k in keys] + [F.col(c) for c in rest]


def copies(df: DataFrame, mult: str | None) -> DataFrame:
    """A row for each copy, numbered by _dup."""
    if mult is None:
        return df.withColumn("_dup", F.lit(0))
    return df.where(F.col(mult) > 0).withColumn("_dup", F.explode(F.sequence(F.lit(0), F.col(mult).cast("int") - 1))).drop(mult)


def det_rank(df: DataFrame, keys: Sequence[str], mult: str | None = None, into: str = "pos", desc: Sequence[str] = ()) -> DataFrame:
    """0-based positions, a row for each copy, by distributed running sums. Descending keys are numbers."""
    rest = sorted(c for c in df.columns if c not in keys and c != mult)
    point = F.struct(*[(-F.col(k) if k in desc else F.col(k)).alias(f"k{i}") for i, k in enumerate([*keys, *rest])])
    one = df.withColumns({"_point": point, "_w": F.col(mult).cast("long") if mult else F.lit(1).cast("long")})
    kinds = [f.dataType.simpleString() for f in one.schema["_point"].dataType.fields]
    cuts = splitters(one.withColumn("_id", F.xxhash64("_point")), "_point", "_id", bucket_count(df))
    placed = with_bucket(one, "_point", cuts, kinds)
    placed = placed.groupBy(*[c for c in df.columns if c != mult], "_point", "_b").agg(F.sum("_w").alias("_w"))
    got = running_sums(placed, ["_b"], ["_point"], {into: "_w"})
    got = got.withColumn("_dup", F.explode(F.sequence(F.lit(0), F.col("_w").cast("int") - 1)))
    return got.withColumn(into, F.col(into) + F.col("_dup")).drop("_point", "_b", "_w", "_dup")


def det_topk(df: DataFrame, keys: Sequence[str], k: int, desc: Sequence[str] = ()) -> DataFrame:
    return df.orderBy(*total_order(df, keys, desc)).limit(k)


def det_window(df: DataFrame, agg: str, arg: str, keys: Sequence[str], lo: int | None, hi: int, partition: Sequence[str] = (), mult: str | None = None, into: str = "x", desc: Sequence[str] = ()) -> DataFrame:
    """Row window over copies; each copy has a window of its own."""
    one = copies(df, mult)
    order = total_order(one.drop(*partition), keys, desc)
    w = W.partitionBy(*partition).orderBy(*order).rowsBetween(W.unboundedPreceding if lo is None else lo, hi)
    return one.withColumn(into, AGG[agg](arg).over(w)).drop("_dup")


def det_group_window(df: DataFrame, agg: str, arg: str, keys: Sequence[str], lo: int, hi: int, partition: Sequence[str] = (), into: str = "x") -> DataFrame:
    """Window over groups of equal keys: those whose dense rank differs by lo to hi. Groups are aggregated first: dense
    ranks are running sums over the distinct keys, and a window's value folds hi - lo + 1 groups."""
    part, keys = list(partition), list(keys)
    v = F.col(arg)
    some = df.groupBy(*part, *keys).agg(F.sum(v).alias("_s"), F.count(v).alias("_n"), F.min(v).alias("_lo"), F.max(v).alias("_hi"), F.lit(1).cast("long").alias("_one"))
    some = some.withColumn("_at", F.struct(*[F.col(k).alias(f"k{i}") for i, k in enumerate(keys)]))
    cuts = splitters(some.withColumn("_id", F.xxhash64("_at")), "_at", "_id", bucket_count(df))
    some = with_bucket(some, "_at", cuts, [f.dataType.simpleString() for f in some.schema["_at"].dataType.fields])
    some = running_sums(some, ["_b"], ["_at"], {"_dr": "_one"}, part)
    reach = some.select(*part, "_s", "_n", "_lo", "_hi", F.explode(F.sequence(F.col("_dr") - hi, F.col("_dr") - lo)).alias("_dr"))
    fold = {"sum": F.sum("_s"), "count": F.sum("_n"), "min": F.min("_lo"), "max": F.max("_hi"), "avg": F.sum("_s") / F.sum("_n")}[agg]
    met = join_null_safe(some.select(*part, *keys, "_dr"), reach.groupBy(*part, "_dr").agg(fold.alias(into)), [*part, "_dr"], "left").drop("_dr")
    return join_null_safe(df, met, [*part, *keys])
