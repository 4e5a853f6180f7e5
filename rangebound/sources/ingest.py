"""Constructors of range frames, and Parquet files of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.prefix import join_null_safe
from ..schema import MULT, RID, Attr, RangeFrame, schema_from_json


def _ones() -> list[Column]:
    return [F.lit(1).cast("long").alias(c) for c in MULT]


def from_certain(df: DataFrame, rid: str | Column) -> RangeFrame:
    """A table without uncertainty; rid is a unique column."""
    key = F.col(rid) if isinstance(rid, str) else rid
    attrs = tuple(Attr(c) for c in df.columns)
    return RangeFrame(df.select(key.cast("long").alias(RID), *df.columns, *_ones()), attrs)


def from_intervals(df: DataFrame, rid: str | Column, ranges: dict[str, tuple], mult: tuple | None = None, keep: tuple[str, ...] = ()) -> RangeFrame:
    """ranges: attribute -> (low, guess, high) Columns; keep: certain columns; mult: multiplicity Columns."""
    key = F.col(rid) if isinstance(rid, str) else rid
    triples = [c.alias(f"{a}__{e}") for a, t in ranges.items() for c, e in zip(t, ("lb", "sg", "ub"), strict=True)]
    ms = [m.cast("long").alias(c) for m, c in zip(mult, MULT, strict=True)] if mult else _ones()
    return RangeFrame(df.select(key.cast("long").alias(RID), *keep, *triples, *ms), (*(Attr(k) for k in keep), *(Attr(a, False) for a in ranges)))


def draw(key: Column, salt: int) -> Column:
    """The hash of the injection, in whole-number arithmetic any engine repeats. Ids of 2^40 and more (hashed ones)
    count by their remainder, so that nothing overflows."""
    return (F.pmod(key, F.lit(1 << 40)) * 7919 + salt * 104729) % 10007


def box(key: Column, value: Column, u: int, r: int, per: int = 100, salt: int = 0) -> tuple[Column, Column, Column]:
    """(low, guess, high): a share u / per of rows gets a range of width 1 to r around its value."""
    unsure = draw(key, salt + 1) % per < u
    width = 1 + (draw(key, salt + 2) * 997) % r
    low = value - (draw(key, salt + 3) * 997) % (width + 1)
    return F.when(unsure, low).otherwise(value), value, F.when(unsure, low + width).otherwise(value)


def doubt(key: Column, e: int = 0, d: int = 0) -> tuple[Column, Column, Column]:
    """Multiplicities: e percent of rows may be absent, d percent may be two."""
    low = F.when(draw(key, 4) % 100 < e, 0).otherwise(1) if e else F.lit(1)
    high = F.when(draw(key, 5) % 100 < d, 2).otherwise(1) if d else F.lit(1)
    return low, F.lit(1), high


def inject(df: DataFrame, key: str, cols: dict[str, Column], u: int, r: int, e: int = 0, d: int = 0, keep: tuple[str, ...] = (), per: int = 100) -> RangeFrame:
    """Deterministic uncertainty: cols maps attribute names to whole-number Columns; `per` is 100 for u in percent."""
    k = F.col(key)
    return from_intervals(df, key, {a: box(k, c, u, r, per, 10 * i) for i, (a, c) in enumerate(cols.items())}, doubt(k, e, d), keep)


def cents(col: str) -> Column:
    return F.round(F.col(col) * 100).cast("long")


def from_alternatives(df: DataFrame, key: str, values: tuple[str, ...], weight: str | None = None) -> RangeFrame:
    """Rows of one key are alternatives: one box row with the hull of the values; the guess is the
    alternative of greatest weight, then of the smallest values. With weights that sum to under 1, none may hold."""
    order = F.struct(*([-F.col(weight)] if weight else []), *values)
    best = F.min_by(F.struct(*values), order)
    aggs = [f(c).alias(f"{c}__{e}") for c in values for f, e in ((F.min, "lb"), (F.max, "ub"))]
    total = F.round(F.sum(weight), 9) if weight else F.lit(1.0)
    got = df.groupBy(key).agg(*aggs, best.alias("_best"), total.alias("_total"))
    return from_intervals(got, key, {c: (F.col(f"{c}__lb"), F.col(f"_best.{c}"), F.col(f"{c}__ub")) for c in values}, (F.when(F.col("_total") < 1, 0).otherwise(1), F.lit(1), F.lit(1)), (key,))


def from_repairs(df: DataFrame, keys: tuple[str, ...], values: tuple[str, ...], rid: Column) -> RangeFrame:
    """Key repair: rows that violate a key become one box row with the hull of their values."""
    aggs = [f(c).alias(f"{c}__{e}") for c in values for f, e in ((F.min, "lb"), (F.min, "sg"), (F.max, "ub"))]
    got = df.groupBy(*keys).agg(*aggs)
    return from_intervals(got, rid, {c: tuple(F.col(f"{c}__{e}") for e in ("lb", "sg", "ub")) for c in values}, None, keys)


def from_imputation(df: DataFrame, key: str, col: str, group: str, keep: tuple[str, ...] = ()) -> RangeFrame:
    """Missing values get the range of their group, guessed at its low end (the whole table's where the group has no
    value). Rows without a group are a group."""
    seen = df.groupBy(group).agg(F.min(col).alias("_lo"), F.max(col).alias("_hi"))
    every = df.agg(F.min(col).alias("_all_lo"), F.max(col).alias("_all_hi"))
    got = join_null_safe(df, seen, [group], "left").crossJoin(F.broadcast(every))  # one row
    lo, hi = F.coalesce("_lo", "_all_lo"), F.coalesce("_hi", "_all_hi")
    return from_intervals(got, key, {col: (F.coalesce(F.col(col), lo), F.coalesce(F.col(col), lo), F.coalesce(F.col(col), hi))}, None, (group, *keep))


def load(spark: SparkSession, source: str, kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """A certain table from files (parquet, orc, json, csv) or, kind "table", from the catalog; then from_intervals and
    the like say what is uncertain. Text formats need a schema, so that no file is read twice."""
    if kind == "table":
        return spark.table(source)
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(source)


def from_columns(df: DataFrame, rid: str, uncertain: tuple[str, ...], keep: tuple[str, ...] = ()) -> RangeFrame:
    """A table that already has a__lb, a__sg and a__ub for each uncertain attribute, and multiplicities if not all are 1."""
    mult = tuple(F.col(c) for c in MULT) if set(MULT) <= set(df.columns) else None
    return from_intervals(df, rid, {a: tuple(F.col(f"{a}__{e}") for e in ("lb", "sg", "ub")) for a in uncertain}, mult, keep)


def write(rf: RangeFrame, path: str, mode: str = "overwrite", partition: tuple[str, ...] = ()) -> None:
    """Parquet, clustered as the rows are; the range schema goes in a column's metadata. partition: certain attributes
    that become folders, so that a filter on them skips files."""
    df = rf.df.select(*rf.columns)
    df = df.withMetadata(RID, {"range_schema": rf.schema_json()})
    out = df.write.mode(mode)
    (out.partitionBy(*partition) if partition else out).parquet(path)


def write_bucketed(rf: RangeFrame, table: str, keys: tuple[str, ...], buckets: int, mode: str = "overwrite") -> None:
    """A catalog table dealt and sorted by certain attributes, so that joins and groups on them need no exchange."""
    df = rf.df.select(*rf.columns).withMetadata(RID, {"range_schema": rf.schema_json()})
    df.write.mode(mode).bucketBy(buckets, *keys).sortBy(*keys).format("parquet").saveAsTable(table)


def read_table(spark: SparkSession, table: str) -> RangeFrame:
    df = spark.table(table)
    attrs, unit = schema_from_json(df.schema[RID].metadata["range_schema"])
    out = RangeFrame(df, attrs, unit)
    return out.with_df(df.select(*out.columns))


def read(spark: SparkSession, path: str) -> RangeFrame:
    df = spark.read.parquet(path)
    attrs, unit = schema_from_json(df.schema[RID].metadata["range_schema"])
    out = RangeFrame(df, attrs, unit)
    return out.with_df(df.select(*out.columns))
