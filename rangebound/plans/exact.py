"""Tight window bounds, by trying every order that the rows near a window may have.

Whatever a world is, a row's window holds only rows that may be in it, and of these the nearest. So the worlds of an
owner and its possible members are all that matter, and of a range's values only those beside an end of another's:
between them nothing changes places, and sums are extreme at ends. Owners with more combinations than `limit`
get nulls. This is the exact baseline of the quality measures; no solver is at hand.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from itertools import product
from math import prod

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import metrics
from ..operators import order, window
from ..schema import RID, RangeFrame
from . import baselines as B
from .joins import by_sort
from .scratch import materialise

#: Positions of a stretch, whose owners are tried by four tasks.
OWNERS = 1024

SCHEMA = f"{RID} long, x__lb long, x__ub long, worlds long, member array<long>"


def _choices(rows: list[tuple]) -> list[list[int]]:
    """For each (rid, low, high, ...) the keys at which the order of the rows can change."""
    ends = sorted({e + d for r in rows for e in r[1:3] for d in (-1, 0, 1)})
    return [[r[1]] if r[1] == r[2] else [e for e in ends if r[1] <= e <= r[2]] for r in rows]


def _worlds(rows: list[tuple], limit: int) -> int:
    """How many worlds the choices make, counted until there are more than the limit."""
    ends = sorted({e + d for r in rows for e in r[1:3] for d in (-1, 0, 1)})
    n = 1
    for r in rows:
        if r[1] != r[2]:
            n *= bisect_right(ends, r[2]) - bisect_left(ends, r[1])
            if n > limit:
                break
    return n


def tight_window(rows: list[tuple], owner: int, agg: str, lo: int, hi: int, keyed: bool, limit: int) -> tuple | None:
    """(low, high, worlds, members) over rows (rid, key low, key high, value low, value high); keyed: the value is the key."""
    if _worlds(rows, limit) > limit:
        return None
    options = _choices(rows)
    n = prod(len(o) for o in options)
    fold = {"sum": sum, "min": min, "max": max, "count": len}[agg]
    low = high = None
    member: set[int] = set()
    for keys in product(*options):
        world = sorted((k, r[0], i) for i, (k, r) in enumerate(zip(keys, rows, strict=True)))
        at = next(i for i, w in enumerate(world) if w[1] == owner)
        inside = [w for i, w in enumerate(world) if at + lo <= i <= at + hi]
        if not inside:
            continue
        member |= {w[1] for w in inside}
        a = fold([w[0] if keyed else rows[w[2]][3] for w in inside])
        b = fold([w[0] if keyed else rows[w[2]][4] for w in inside])
        low, high = a if low is None else min(low, a), b if high is None else max(high, b)
    return low, high, n, sorted(member)


def tight_windows(rf: RangeFrame, agg: str, arg: str | None, key: str, lo: int, hi: int, limit: int = 4096) -> DataFrame:
    """(RID, x__lb, x__ub, worlds, member) of each row; rows must be certain and keys whole numbers."""
    unit = order.rank(rf, [key], ties=False)
    spec = window.WindowSpec(agg, arg, (key,), lo, hi, ties=False)
    k = unit.c(key)
    members = window._members(unit, spec).join(by_sort(unit.df.select(RID, k.lb.cast("long").alias("k0"), k.ub.cast("long").alias("k1"))), RID)
    near = window._band(members, spec, None, None)

    def try_all(pdf: pd.DataFrame) -> pd.DataFrame:
        # Many owners at a time: a frame for each would cost more than most owners' worlds.
        out = []
        columns = [pdf[c].tolist() for c in (RID, "k0", "k1", "v__lb", "v__ub", f"s_{RID}", "s_k0", "s_k1", "s_v__lb", "s_v__ub")]
        groups: dict[int, dict[int, tuple]] = {}
        for me, a, b, c, d, *s in zip(*columns, strict=True):
            groups.setdefault(me, {me: (me, a, b, c, d)})[s[0]] = tuple(s)
        for me, rows in groups.items():
            got = tight_window(list(rows.values()), me, agg, lo, hi, arg == key, limit)
            out.append((me, *(got or (None,) * 4)))
        frame = pd.DataFrame(out, columns=[RID, "x__lb", "x__ub", "worlds", "member"])
        return frame.astype({c: "Int64" for c in ("x__lb", "x__ub", "worlds")})

    # Stretches of positions hold about as many owners each, however many rows there are.
    return near.groupBy(F.floor(F.col("p__lb") / OWNERS).alias("_b"), F.pmod(F.xxhash64(RID), F.lit(4)).alias("_o")).applyInPandas(try_all, SCHEMA)


def window_quality(rf: RangeFrame, agg: str, arg: str | None, key: str, lo: int, hi: int, samples: int = 20, limit: int = 4096) -> DataFrame:
    """A row for the bounds and one for sampled worlds: how good their aggregates and their possible members are
    against tight ones, in millionths, over the rows that could be enumerated."""
    tight = materialise(tight_windows(rf, agg, arg, key, lo, hi, limit))
    known = tight.where("x__lb is not null")
    spec = window.WindowSpec(agg, arg, (key,), lo, hi, ties=False)
    pairs = window._flag_ids(window._band(window._members(order.rank(rf, [key], ties=False), spec), spec, None, None), spec)
    worlds = B.positions([key])(B.sample_worlds(rf, samples))
    seen = worlds.select("world_id", RID, F.explode(F.sequence(F.col("pos") + lo, F.col("pos") + hi)).alias("at")).join(by_sort(worlds.select("world_id", F.col(RID).alias("member"), F.col("pos").alias("at"))), ["world_id", "at"]).select(RID, "member").distinct()
    right = known.select(RID, F.explode("member").alias("member"))
    bound = window.window(rf, agg, arg, [key], lo, hi, ties=False).df.select(RID, "x__lb", "x__ub")
    value = arg or key
    sampled = B.baseline_sampled(rf, B.windowed(agg, value, [key], lo, hi), samples, "x").select(RID, F.col("x__lb").cast("long").alias("x__lb"), F.col("x__ub").cast("long").alias("x__ub"))
    out = None
    for name, b, m in (("bounds", bound, pairs), (f"sample{samples}", sampled, seen)):
        one = metrics.quality(b, known, [RID], "x__lb", "x__ub")
        ids = metrics.membership_quality(m.join(by_sort(known.select(RID)), RID, "left_semi"), right, [RID, "member"])
        ppm = lambda c: F.floor(F.col(c) * 1_000_000 + 0.5).cast("long").alias(f"{c}_ppm")
        one = one.crossJoin(ids.select(ppm("membership_accuracy"), ppm("membership_recall"))).withColumn("method", F.lit(name))  # one row each
        out = one if out is None else out.unionByName(one)
    return out.crossJoin(tight.agg(F.sum(F.col("x__lb").isNull().cast("long")).alias("n_skipped")))  # one row
