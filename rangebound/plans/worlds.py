"""Possible worlds: all of them for tiny frames, samples at any size."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import combinations_with_replacement, product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import DUP, MULT, RID, RangeFrame
from ..sources.ingest import draw


def worlds_of(rows: Sequence[dict], attrs: Sequence[tuple[str, bool]], limit: int = 20_000) -> Iterator[list[tuple]]:
    """Each world as a list of (rid, copy, values...). rows: encoded rows of whole numbers. A row's
    copies are alike, so their values are listed in one order only."""
    options = []
    total = 1
    for r in rows:
        values = list(product(*[[r[a]] if certain else range(r[f"{a}__lb"], r[f"{a}__ub"] + 1) for a, certain in attrs]))
        mine = [c for m in range(r["_m_lb"], r["_m_ub"] + 1) for c in combinations_with_replacement(values, m)]
        total *= len(mine)
        if total > limit:
            raise ValueError(f"more than {limit} worlds")
        options.append([(r[RID], c) for c in mine])
    for chosen in product(*options):
        yield [(rid, i, *v) for rid, copies in chosen for i, v in enumerate(copies)]


def few_rows(rf: RangeFrame, most: int = 64) -> list[dict]:
    """All rows of a frame that is to be enumerated; an error if there are more than `most`."""
    rows = [r.asDict() for r in rf.df.limit(most + 1).collect()]
    if len(rows) > most:
        raise ValueError(f"more than {most} rows")
    return rows


def enumerate_worlds(rf: RangeFrame, limit: int = 20_000) -> DataFrame:
    """(world_id, _rid, _dup, attributes): for frames of a few rows."""
    attrs = [(a.name, a.certain) for a in rf.attrs]
    rows = few_rows(rf)
    out = [(w, *row) for w, world in enumerate(worlds_of(rows, attrs, limit)) for row in world]
    return rf.df.sparkSession.createDataFrame(out, ", ".join(["world_id long", f"{RID} long", f"{DUP} int", *[f"{a} long" for a, _ in attrs]]))


def sample_worlds(rf: RangeFrame, samples: int, seed: int = 0) -> DataFrame:
    """(world_id, _rid, _dup, attributes) of `samples` worlds in one plan. Draws are whole-number hashes of row, copy,
    sample and attribute, uniform over each range."""
    df = rf.df.withColumn("world_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(samples - 1).cast("long"))))
    base = F.pmod(F.col(RID), F.lit(1 << 40)) + F.col("world_id") * 613 + seed * 31
    m = F.col("_m_lb") + draw(base, 50) % (F.col("_m_ub") - F.col("_m_lb") + 1)
    if rf.unit:
        df = df.where(m > 0)
    else:
        df = df.withColumn("_n", m.cast("int")).where("_n > 0").withColumn(DUP, F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    cols = []
    for i, a in enumerate(rf.attrs):
        t = rf.c(a.name)
        cols.append(t.lb.alias(a.name) if a.certain else (t.lb + (draw(base + F.col(DUP) * 7, 60 + i) * 997) % (t.ub - t.lb + 1)).alias(a.name))
    return df.select("world_id", RID, DUP, *cols)


def bag_of_worlds(worlds: DataFrame, columns: Sequence[str]) -> DataFrame:
    """By tuple: least (certain) and greatest (possible) multiplicity over all worlds."""
    n = worlds.select("world_id").distinct().count()
    each = worlds.groupBy("world_id", *columns).agg(F.count(F.lit(1)).alias("_k"))
    return each.groupBy(*columns).agg(F.when(F.count(F.lit(1)) == n, F.min("_k")).otherwise(0).alias(MULT[0]), F.max("_k").alias(MULT[2]))
