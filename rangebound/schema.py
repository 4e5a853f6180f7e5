"""Range frames: DataFrames of box rows, flat in primitive columns.

A certain attribute is one column; an uncertain one is three, `a__lb <= a__sg <= a__ub`. A row
stands for between `_m_lb` and `_m_ub` rows, `_m_sg` in the guess world. `_rid` is unique and certain; after a split,
`_rid` and `_dup` are.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.expr import Triple

RID, DUP = "_rid", "_dup"
MULT = ("_m_lb", "_m_sg", "_m_ub")
ENDS = ("lb", "sg", "ub")


@dataclass(frozen=True)
class Attr:
    name: str
    certain: bool = True

    @property
    def columns(self) -> tuple[str, ...]:
        return (self.name,) if self.certain else tuple(f"{self.name}__{e}" for e in ENDS)


@dataclass(frozen=True)
class RangeFrame:
    """df: the flat encoding; attrs: its attributes in order; unit: whether it has been split."""

    df: DataFrame
    attrs: tuple[Attr, ...]
    unit: bool = False

    def attr(self, name: str) -> Attr:
        for a in self.attrs:
            if a.name == name:
                return a
        raise KeyError(f"no attribute {name}; there are {[a.name for a in self.attrs]}")

    def c(self, name: str) -> Triple:
        """The triple of Columns of an attribute."""
        a = self.attr(name)
        return Triple(*(F.col(x) for x in (a.columns * 3 if a.certain else a.columns)))

    @property
    def m(self) -> Triple:
        return Triple(*(F.col(x) for x in MULT))

    @property
    def ids(self) -> tuple[str, ...]:
        return (RID, DUP) if self.unit else (RID,)

    @property
    def columns(self) -> list[str]:
        return [*self.ids, *(c for a in self.attrs for c in a.columns), *MULT]

    def with_df(self, df: DataFrame) -> RangeFrame:
        return replace(self, df=df)

    def project(self, *names: str) -> RangeFrame:
        """The named attributes only; rows and their ids stay."""
        kept = tuple(self.attr(n) for n in names)
        out = RangeFrame(self.df, kept, self.unit)
        return out.with_df(self.df.select(*out.columns))

    def certain(self) -> DataFrame:
        """Rows in every world, with all values certain."""
        same = [F.col(f"{a.name}__lb") == F.col(f"{a.name}__ub") for a in self.attrs if not a.certain]
        return self.df.where(reduce(lambda x, y: x & y, same, F.col("_m_lb") > 0))

    def possible(self) -> DataFrame:
        return self.df.where("_m_ub > 0")

    def guess(self) -> DataFrame:
        """The guess world: values and multiplicities of the guess, a row for each copy."""
        cols = [F.col(a.name if a.certain else f"{a.name}__sg").alias(a.name) for a in self.attrs]
        one = self.df.where("_m_sg > 0")
        if self.unit:
            return one.select(*self.ids, *cols)
        return one.select(RID, *cols, F.explode(F.sequence(F.lit(0), F.col("_m_sg").cast("int") - 1)).alias(DUP))

    def validate(self) -> DataFrame:
        """Rows that break an invariant, with the reason."""
        rules = {"multiplicity out of order": (F.col("_m_lb") < 0) | (F.col("_m_lb") > F.col("_m_sg")) | (F.col("_m_sg") > F.col("_m_ub")) | (F.col("_m_ub") <= 0), "no row id": F.col(RID).isNull()}
        kinds = dict(self.df.dtypes)
        for a in self.attrs:
            t = self.c(a.name)
            rules[f"null in {a.name}"] = t.lb.isNull() | t.sg.isNull() | t.ub.isNull()
            if kinds[a.columns[0]] in ("double", "float"):
                rules[f"NaN in {a.name}"] = F.isnan(t.lb) | F.isnan(t.sg) | F.isnan(t.ub)
            if not a.certain:
                rules[f"{a.name} out of order"] = (t.lb > t.sg) | (t.sg > t.ub)
        reason = F.coalesce(*[F.when(bad, F.lit(name)) for name, bad in rules.items()])
        return self.df.withColumn("reason", reason).where(F.col("reason").isNotNull())

    def canonicalize(self) -> RangeFrame:
        """Equal box rows become one, with added multiplicities; the smallest row id stays."""
        cols = [c for a in self.attrs for c in a.columns]
        df = self.df.groupBy(*cols).agg(F.min(RID).alias(RID), *[F.sum(c).alias(c) for c in MULT])
        return RangeFrame(df, self.attrs).with_df(df.select(RID, *cols, *MULT))

    def split(self, limit: int | None = None) -> RangeFrame:
        """One row for each possible copy, each in 0 or 1 rows of a world; at most `limit` copies."""
        if self.unit:
            return self
        last = F.col("_m_ub").cast("int") - 1
        rows = self.df.where("_m_ub > 0").withColumn(DUP, F.explode(F.sequence(F.lit(0), last if limit is None else F.least(last, F.lit(limit - 1)))))
        rows = rows.withColumns({c: (F.col(DUP) < F.col(c)).cast("long") for c in MULT})
        out = RangeFrame(rows, self.attrs, True)
        return out.with_df(rows.select(*out.columns, *[c for c in self.df.columns if c not in out.columns]))

    def width_stats(self) -> DataFrame:
        """A row for each numeric uncertain attribute: rows that are uncertain, mean and largest width."""
        out = []
        for a in self.attrs:
            if not a.certain:
                w = (F.col(f"{a.name}__ub") - F.col(f"{a.name}__lb")).cast("double")
                out.append(self.df.agg(F.lit(a.name).alias("attr"), F.sum((w > 0).cast("long")).alias("uncertain"), F.avg(w).alias("mean_width"), F.max(w).alias("max_width")))
        return reduce(DataFrame.union, out) if out else self.df.sparkSession.createDataFrame([], "attr string, uncertain long, mean_width double, max_width double")

    def explain(self, mode: str = "formatted") -> None:
        self.df.explain(mode)

    def schema_json(self) -> str:
        return json.dumps({"attrs": [[a.name, a.certain] for a in self.attrs], "unit": self.unit})


def schema_from_json(text: str) -> tuple[tuple[Attr, ...], bool]:
    d = json.loads(text)
    return tuple(Attr(n, c) for n, c in d["attrs"]), d["unit"]
