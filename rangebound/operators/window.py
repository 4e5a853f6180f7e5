"""Row-based windowed aggregates: low, guess and high value of each row's window.

Rows are split into copies and get positions in their partition. A copy is certainly in a row's
window if its whole position range lies within the least window, possibly if it meets the greatest; the row
itself is certainly in its own window wherever the frame holds it. What certain members leave of
the frame are slots; bounds fill them with the possible members that push them furthest.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left, insort
from collections.abc import Callable, Sequence
from dataclasses import dataclass, replace
from itertools import count as counter

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.expr import Triple, req, rlit
from ..functions.heaps import ConnectedHeap, UnconnectedHeaps
from ..plans import compare
from ..plans.joins import band_pairs, by_sort, overlap_pairs
from ..plans.overlap import summaries
from ..plans.prefix import join_null_safe, running_sums
from ..plans.scratch import materialise
from ..schema import DUP, MULT, RID, Attr, RangeFrame
from .order import RankSpec, _dist, _events, _paired, order_keys, rank

AGGREGATES = ("sum", "count", "min", "max", "avg")
#: Pairs a row, besides those of its frame, up to which the band join is the cheaper plan: 150,000 orders took 5.1 s and
#: 8.6 s (pairs, summaries) at some 25 pairs a row, 10.1 s and 12.9 s at some 300.
PAIRS_A_ROW = 512


@dataclass(frozen=True)
class WindowSpec:
    agg: str
    arg: str | None
    keys: tuple[str, ...]
    lo: int
    hi: int
    desc: tuple[str, ...] = ()
    partition: tuple[str, ...] = ()
    ties: bool = True

    @property
    def has_self(self) -> bool:
        return self.lo <= 0 <= self.hi

    @property
    def size(self) -> int:
        return self.hi - self.lo + 1


#: aggregate -> (low, high) over the Columns of collected members; see register_aggregate.
_CUSTOM: dict[str, tuple[Callable, Callable]] = {}


def register_aggregate(name: str, low: Callable[[Column, Column, Column], Column], high: Callable[[Column, Column, Column], Column]) -> None:
    """A further aggregate: low and high take (values of certain members, values of possible members,
    slots), the first two as array Columns (low ends for low, high ends for high), and return a Column."""
    _CUSTOM[name] = (low, high)


def _fold(values: Column, slots: Column, sign: int) -> Column:
    """Sum of at most `slots` values that push the bound, worst first."""
    return F.aggregate(F.slice(F.sort_array(values, asc=sign < 0), F.lit(1), F.greatest(slots, F.lit(0)).cast("int")), F.lit(0).cast("long"), lambda s, x: s + x.cast("long"))


def _mean(certain_sum: Column, certain_n: Column, values: Column, slots: Column, sign: int) -> Column:
    """struct(s, n): the mean pushed by possible values, worst first, while they push it."""
    start = F.struct(F.coalesce(certain_sum, F.lit(0)).cast("long").alias("s"), certain_n.cast("long").alias("n"))

    def step(acc: Column, x: Column) -> Column:
        x = x.cast("long")
        push = (acc["n"] == 0) | ((x * acc["n"] < acc["s"]) if sign < 0 else (x * acc["n"] > acc["s"]))
        return F.when(push, F.struct((acc["s"] + x).alias("s"), (acc["n"] + 1).alias("n"))).otherwise(acc)

    return F.aggregate(F.slice(F.sort_array(values, asc=sign < 0), F.lit(1), F.greatest(slots, F.lit(0)).cast("int")), start, step)


def _bounds(pairs: DataFrame, owner: Sequence[str], spec: WindowSpec) -> DataFrame:
    """pairs: the owner's ids, is_certain, is_possible (exclusive), is_guess, v__lb/sg/ub, c__own.
    One hash aggregate by owner; lists hold only possible values that can push a bound."""
    c, p, g = F.col("is_certain"), F.col("is_possible"), F.col("is_guess")
    lb, sg, ub = F.col("v__lb"), F.col("v__sg"), F.col("v__ub")
    n_cert = F.sum(c.cast("long"))
    base = {"_nc": n_cert, "_np": F.sum(p.cast("long")), "_ng": F.sum(g.cast("long"))}
    agg = spec.agg
    if agg == "sum":
        base |= {"_cl": F.sum(F.when(c, lb)), "_ch": F.sum(F.when(c, ub)), "_g": F.sum(F.when(g, sg)), "_pl": F.collect_list(F.when(p & (lb < 0), lb)), "_ph": F.collect_list(F.when(p & (ub > 0), ub))}
    elif agg in ("min", "max"):
        f = F.min if agg == "min" else F.max
        base |= {"_cl": f(F.when(c, lb)), "_ch": f(F.when(c, ub)), "_g": f(F.when(g, sg)), "_pl": f(F.when(p, lb)), "_ph": f(F.when(p, ub)), "_least": F.min(F.when(p, lb)), "_most": F.max(F.when(p, ub))}
    elif agg == "avg":
        base |= {"_cl": F.sum(F.when(c, lb)), "_ch": F.sum(F.when(c, ub)), "_g": F.sum(F.when(g, sg)), "_pl": F.collect_list(F.when(p, lb)), "_ph": F.collect_list(F.when(p, ub))}
    elif agg in _CUSTOM:
        base |= {"_cl": F.collect_list(F.when(c, lb)), "_ch": F.collect_list(F.when(c, ub)), "_pl": F.collect_list(F.when(p, lb)), "_ph": F.collect_list(F.when(p, ub)), "_g": F.collect_list(F.when(g, sg))}
    elif agg != "count":
        raise ValueError(f"{agg} is none of {AGGREGATES} and has not been registered")
    return _from_members(pairs.groupBy(*owner).agg(*[x.alias(k) for k, x in base.items()]), owner, spec)


def _from_members(got: DataFrame, owner: Sequence[str], spec: WindowSpec) -> DataFrame:
    """Bounds from what _bounds has gathered of each owner."""
    agg, zero = spec.agg, F.lit(0).cast("long")
    slots = F.greatest(F.lit(spec.size) - F.col("_nc"), F.lit(0))
    if agg == "count":
        low, guess, high = F.col("_nc"), F.col("_ng"), F.least(F.lit(spec.size).cast("long"), F.col("_nc") + F.col("_np"))
    elif agg == "sum":
        low = F.coalesce("_cl", zero) + _fold(F.col("_pl"), slots, -1)
        guess, high = F.coalesce("_g", zero), F.coalesce("_ch", zero) + _fold(F.col("_ph"), slots, 1)
    elif agg == "min":
        some = slots > 0
        low = F.when(some, F.least("_cl", "_pl")).otherwise(F.col("_cl"))
        high = F.coalesce("_ch", F.when(some, F.col("_most")))
        guess = F.col("_g")
    elif agg == "max":
        some = slots > 0
        low = F.coalesce("_cl", F.when(some, F.col("_least")))
        high = F.when(some, F.greatest("_ch", "_ph")).otherwise(F.col("_ch"))
        guess = F.col("_g")
    elif agg == "avg":
        a, b = _mean(F.col("_cl"), F.col("_nc"), F.col("_pl"), slots, -1), _mean(F.col("_ch"), F.col("_nc"), F.col("_ph"), slots, 1)
        got = got.withColumns({"_a": a, "_b": b})
        low, high = F.col("_a.s") / F.nullif(F.col("_a.n"), zero), F.col("_b.s") / F.nullif(F.col("_b.n"), zero)
        guess = F.col("_g") / F.nullif(F.col("_ng"), zero)
        got = got.withColumns({"x_low_sum": F.col("_a.s"), "x_low_n": F.col("_a.n"), "x_high_sum": F.col("_b.s"), "x_high_n": F.col("_b.n")})
    else:
        # Named first: lists are long, and both bounds are read again by the guess.
        got = got.withColumns({"_a": _CUSTOM[agg][0](F.col("_cl"), F.col("_pl"), slots), "_b": _CUSTOM[agg][1](F.col("_ch"), F.col("_ph"), slots)})
        low, high = F.col("_a"), F.col("_b")
        guess = _CUSTOM[agg][0](F.col("_g"), F.array().cast("array<bigint>"), zero)
    extra = ["x_low_sum", "x_low_n", "x_high_sum", "x_high_n"] if agg == "avg" else []
    # The guess of a row that isn't in the guess world is kept inside its bounds.
    guess = F.least(F.greatest(F.coalesce(guess, low), low), high)
    return got.select(*owner, low.alias("x__lb"), guess.alias("x__sg"), high.alias("x__ub"), F.col("_nc").alias("x_certain"), F.col("_np").alias("x_possible"), (F.col("_nc") == 0).cast("int").alias("x_maybe_empty"), *extra)


def membership(spec: WindowSpec, t: Triple, s: Triple, s_m_lb: Column, same: Column, both_guess: Column) -> tuple[Column, Column, Column]:
    """(certain, possible but not certain, guess) of member s in owner t's window, given positions in one partition."""
    sure = (s_m_lb >= 1) & (s.lb >= t.ub + spec.lo) & (s.ub <= t.lb + spec.hi)
    maybe = (s.ub >= t.lb + spec.lo) & (s.lb <= t.ub + spec.hi)
    if spec.has_self:
        sure = sure | same
        maybe = maybe | same
    else:
        sure, maybe = sure & ~same, maybe & ~same
    guess = both_guess & (s.sg >= t.sg + spec.lo) & (s.sg <= t.sg + spec.hi)
    return sure, maybe & ~sure, guess


def _members(rf: RangeFrame, spec: WindowSpec) -> DataFrame:
    """Slim rows: ids, certain partition, multiplicities, positions (p__*), value (v__*)."""
    v = rf.c(spec.arg) if spec.arg else rlit(F.lit(0).cast("long"))
    return rf.df.select(RID, DUP, *spec.partition, *MULT, F.col("pos__lb").alias("p__lb"), F.col("pos__sg").alias("p__sg"), F.col("pos__ub").alias("p__ub"), *[x.alias(f"v__{e}") for x, e in zip((v.lb, v.sg, v.ub), ("lb", "sg", "ub"), strict=True)])


def _flag(pairs: DataFrame, spec: WindowSpec) -> DataFrame:
    t, s = (Triple(*(F.col(f"{x}p__{e}") for e in ("lb", "sg", "ub"))) for x in ("", "s_"))
    same = (F.col(RID) == F.col(f"s_{RID}")) & (F.col(DUP) == F.col(f"s_{DUP}"))
    c, p, g = membership(spec, t, s, F.col("s__m_lb"), same, (F.col("_m_sg") > 0) & (F.col("s__m_sg") > 0))
    return pairs.select(RID, DUP, c.alias("is_certain"), p.alias("is_possible"), g.alias("is_guess"), *[F.col(f"s_v__{e}").alias(f"v__{e}") for e in ("lb", "sg", "ub")])


def _flag_ids(pairs: DataFrame, spec: WindowSpec) -> DataFrame:
    """(RID, member): pairs of which one is certainly or possibly in the other's window."""
    t, s = (Triple(*(F.col(f"{x}p__{e}") for e in ("lb", "sg", "ub"))) for x in ("", "s_"))
    same = (F.col(RID) == F.col(f"s_{RID}")) & (F.col(DUP) == F.col(f"s_{DUP}"))
    c, p, _ = membership(spec, t, s, F.col("s__m_lb"), same, F.lit(False))
    return pairs.where(c | p).select(RID, F.col(f"s_{RID}").alias("member")).distinct()


def _prefixed(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(c).alias(f"s_{c}") for c in df.columns])


def band_index(members: DataFrame, width: int) -> DataFrame:
    """The range index of the indexed rewrite, to be written or cached: each member once, by the length of its range of
    positions and the bucket in which that begins."""
    return compare.level_index(members, "p__lb", "p__ub", width)


def _band(members: DataFrame, spec: WindowSpec, width: int | None, index: DataFrame | None) -> DataFrame:
    """Owners meet the members whose positions overlap the greatest window, by position bucket."""
    w = width or max(16, 2 * spec.size)
    if index is not None:
        index = index.drop("_level", "_k")
    owners = members.withColumns({"o_lo": F.col("p__lb") + spec.lo, "o_hi": F.col("p__ub") + spec.hi})
    return band_pairs(owners, by_sort(members if index is None else index), ("o_lo", "o_hi"), ("p__lb", "p__ub"), w, spec.partition)


def _guess_windows(members: DataFrame, spec: WindowSpec) -> DataFrame:
    """(RID, DUP, _ng, _g): the windows of the guess world, whose positions are dense. Rows are dealt by stretches of
    positions, and a stretch also gets the rows of its neighbours that its windows reach."""
    p = list(spec.partition)
    step = max(4096, 4 * spec.size)
    g = members.where("_m_sg > 0").select(RID, DUP, *p, F.col("p__sg").alias("_q"), "v__sg")
    g = g.withColumn("_s", F.explode(F.sequence(F.floor((F.col("_q") - max(0, spec.hi)) / step), F.floor((F.col("_q") - min(0, spec.lo)) / step))))
    w = W.partitionBy(*p, "_s").orderBy("_q").rangeBetween(spec.lo, spec.hi)
    value = {"sum": F.sum("v__sg"), "count": F.sum(F.lit(1).cast("long")), "min": F.min("v__sg"), "max": F.max("v__sg"), "avg": F.sum("v__sg")}[spec.agg]
    got = g.withColumns({"_ng": F.count(F.lit(1)).over(w), "_g": value.over(w)})
    return got.where(F.floor(F.col("_q") / step) == F.col("_s")).select(RID, DUP, "_ng", "_g")


def _summarised(members: DataFrame, spec: WindowSpec, width: int | None, most: int) -> DataFrame:
    """The default plan: certain members by pairs of short ranges, all that overlaps by summaries of the `size` + 1 values that push
    a bound furthest. Certain members and the owner are taken out of these; as many slots less are to be filled, so that
    enough are left. most: rows that there may be."""
    # Partition columns may have any name; ours must not meet them.
    members = members.withColumnsRenamed({c: f"_p{i}" for i, c in enumerate(spec.partition)})
    spec = replace(spec, partition=tuple(f"_p{i}" for i in range(len(spec.partition))))
    p, k = list(spec.partition), spec.size + 1
    lb, ub = F.col("v__lb"), F.col("v__ub")
    entry = lambda v: F.struct(v.alias("v"), F.col(RID), F.col(DUP))
    # Values that can't push a bound of a sum are left out of its lists; a count has no values.
    kind = dict(members.dtypes)["v__lb"]
    none = F.array().cast(f"array<struct<v:{kind},{RID}:bigint,{DUP}:int>>")
    give = lambda v, ok: F.when(ok, F.array(entry(v))).otherwise(none)
    yes = (lambda v: F.lit(False)) if spec.agg == "count" else lambda v: v.isNotNull()
    one = F.lit(1).cast("long")
    rows = members.select(*p, F.col("p__lb").alias("_c0"), F.col("p__ub").alias("_c1"), one.alias("n"), give(lb, lb < 0 if spec.agg == "sum" else yes(lb)).alias("low"), give(ub, ub > 0 if spec.agg == "sum" else yes(ub)).alias("high"))
    owners = members.select(RID, DUP, *p, (F.col("p__lb") + spec.lo).alias("_c0"), (F.col("p__ub") + spec.hi).alias("_c1"))
    # A certain member lies between the owner's last start and first end of the frame: few do, as each takes a place.
    asks = members.select(RID, DUP, *p, (F.col("p__ub") + spec.lo).alias("_c0"), (F.col("p__lb") + spec.hi).alias("_c1")).where("_c0 <= _c1")
    short = members.where((F.col("_m_lb") >= 1) & (F.col("p__ub") - F.col("p__lb") < spec.size)).select(RID, DUP, *p, "p__lb", "p__ub", "v__lb", "v__ub")
    sure = band_pairs(asks, by_sort(short.withColumn("p__at", F.col("p__lb"))), ("_c0", "_c1"), ("p__lb", "p__at"), width or max(16, 2 * spec.size), p)
    sure = sure.where((F.col("s_p__ub") <= F.col("_c1")) & ((F.col(RID) != F.col(f"s_{RID}")) | (F.col(DUP) != F.col(f"s_{DUP}"))))
    fold = {"min": F.min, "max": F.max}.get(spec.agg, F.sum)
    ids = F.struct(F.col(f"s_{RID}").alias(RID), F.col(f"s_{DUP}").alias(DUP))
    near = sure.groupBy(RID, DUP).agg(F.count(F.lit(1)).alias("_nc"), fold("s_v__lb").alias("_cl"), fold("s_v__ub").alias("_ch"), *([] if spec.agg == "count" else [F.collect_list(ids).alias("_ids")]))
    far = summaries(owners, rows, (RID, DUP), p, k, most)
    own = members.select(RID, DUP, lb.alias("own_l"), ub.alias("own_h"), (F.col("p__ub") - F.col("p__lb") >= max(spec.lo, -spec.hi)).alias("self_far"))
    got = own.join(by_sort(near), [RID, DUP], "left").join(by_sort(far), [RID, DUP], "left").join(by_sort(_guess_windows(members, spec)), [RID, DUP], "left")
    other = lambda x: (x[RID] != F.col(RID)) | (x[DUP] != F.col(DUP))
    free = lambda x: other(x) & ~F.coalesce(F.array_contains("_ids", F.struct(x[RID].alias(RID), x[DUP].alias(DUP))), F.lit(False))
    both = lambda a: F.transform(F.filter(F.coalesce(a, none), other if spec.agg == "count" else free), lambda x: x["v"])
    zero = F.lit(0).cast("long")
    # The row itself is a certain member of its window, if the frame holds it.
    mine = F.lit(spec.has_self)
    cl, ch = F.col("_cl"), F.col("_ch")
    if spec.agg in ("min", "max"):
        pick = F.least if spec.agg == "min" else F.greatest
        cl, ch = F.when(mine, pick("_cl", "own_l")).otherwise(cl), F.when(mine, pick("_ch", "own_h")).otherwise(ch)
    elif spec.agg in ("sum", "avg"):
        cl, ch = F.when(mine, F.coalesce("_cl", zero) + F.coalesce("own_l", zero)).otherwise(cl), F.when(mine, F.coalesce("_ch", zero) + F.coalesce("own_h", zero)).otherwise(ch)
    nc = F.coalesce("_nc", zero)
    got = got.select(RID, DUP, (nc + mine.cast("long")).alias("_nc"), (F.coalesce("n", zero) - nc - F.col("self_far").cast("long")).alias("_np"), F.coalesce("_ng", zero).alias("_ng"), "_g", cl.alias("_cl"), ch.alias("_ch"), both("low").alias("_pl"), both("high").alias("_ph"))
    if spec.agg in ("min", "max"):
        got = got.withColumns({"_least": F.array_min("_pl"), "_most": F.array_max("_ph"), "_pl": F.array_min("_pl"), "_ph": F.array_max("_ph")})
    got = got.where("_nc > 0 or _np > 0")
    return _from_members(got, (RID, DUP), spec)


def _all_pairs(members: DataFrame, spec: WindowSpec) -> DataFrame:
    cond = F.lit(True)
    for p in spec.partition:
        cond = cond & F.col(p).eqNullSafe(F.col(f"s_{p}"))
    return members.join(_prefixed(members), cond)


def _compared(members: DataFrame, spec: WindowSpec, width: int | None = None, index: DataFrame | None = None) -> DataFrame | None:
    """Bounds from pairs that are compared block by block: all of them, or those within reach by the index. Registered
    aggregates get whole lists, by an index made here if none is given. None for values that aren't whole numbers."""
    kinds = dict(members.dtypes)
    if any(kinds[f"v__{e}"] not in compare.WHOLE for e in ("lb", "sg", "ub")):
        return None
    # Partition columns may have any name; ours must not meet them.
    on = [f"_p{i}" for i in range(len(spec.partition))]
    names = dict(zip(spec.partition, on, strict=True))
    members = materialise(members.withColumnsRenamed(names))
    w, listed = width or max(16, 2 * spec.size), spec.agg not in AGGREGATES
    if index is not None or listed:
        by = band_index(members, w) if index is None else index.withColumnsRenamed(names)
        dealt = compare.deal_near(members, by, spec.lo, spec.hi, on, w, listed)
    else:
        dealt = compare.deal_all(members, on)
    got = compare.listed(dealt, on, spec.lo, spec.hi) if listed else compare.gathered(dealt, on, spec.agg, spec.lo, spec.hi)
    got = _from_members(got, (RID, DUP), spec)
    if spec.agg in ("min", "max"):
        got = got.withColumns({f"x__{e}": F.col(f"x__{e}").cast(kinds["v__lb"]) for e in ("lb", "sg", "ub")})
    return got


def _rewrite_fill(flags: DataFrame, spec: WindowSpec) -> DataFrame:
    """Bounds by two orders per owner: possible values ranked from both ends, kept while there are slots. All aggregates but
    avg, whose fill stops by itself."""
    owner = W.partitionBy(RID, DUP)
    f = flags.where("is_certain or is_possible or is_guess").withColumn("nc", F.sum(F.col("is_certain").cast("long")).over(owner))
    low = F.row_number().over(owner.orderBy(F.col("is_certain").desc(), F.col("is_possible").desc(), "v__lb")) - F.col("nc")
    high = F.row_number().over(owner.orderBy(F.col("is_certain").desc(), F.col("is_possible").desc(), F.desc("v__ub"))) - F.col("nc")
    f = f.withColumns({"rl": low, "rh": high})
    room = F.lit(spec.size) - F.col("nc")
    zero = F.lit(0).cast("long")
    c, p, g = F.col("is_certain"), F.col("is_possible"), F.col("is_guess")
    fill_low, fill_high = p & (F.col("rl") <= room), p & (F.col("rh") <= room)
    n_pos = F.sum(p.cast("long"))
    if spec.agg == "sum":
        lo = F.sum(F.when(c, F.col("v__lb")).when(fill_low & (F.col("v__lb") < 0), F.col("v__lb")).otherwise(zero))
        hi = F.sum(F.when(c, F.col("v__ub")).when(fill_high & (F.col("v__ub") > 0), F.col("v__ub")).otherwise(zero))
        guess = F.sum(F.when(g, F.col("v__sg")).otherwise(zero))
    elif spec.agg == "count":
        lo, guess, hi = F.max("nc"), F.sum(g.cast("long")), F.sum((c | fill_low).cast("long"))
    elif spec.agg == "min":
        lo, guess = F.min(F.when(c | fill_low, F.col("v__lb"))), F.min(F.when(g, F.col("v__sg")))
        hi = F.coalesce(F.min(F.when(c, F.col("v__ub"))), F.max(F.when(fill_high, F.col("v__ub"))))
    else:
        hi, guess = F.max(F.when(c | fill_high, F.col("v__ub"))), F.max(F.when(g, F.col("v__sg")))
        lo = F.coalesce(F.max(F.when(c, F.col("v__lb"))), F.min(F.when(fill_low, F.col("v__lb"))))
    got = f.groupBy(RID, DUP).agg(lo.alias("x__lb"), guess.alias("_g"), hi.alias("x__ub"), F.max("nc").alias("x_certain"), n_pos.alias("x_possible"))
    return got.select(RID, DUP, "x__lb", F.least(F.greatest(F.coalesce("_g", "x__lb"), "x__lb"), "x__ub").alias("x__sg"), "x__ub", "x_certain", "x_possible", (F.col("x_certain") == 0).cast("int").alias("x_maybe_empty"))


def sweep_windows(rows: list[tuple], spec_agg: str, lo: int, hi: int, connected: bool = True) -> tuple[list[tuple], dict]:
    """One pass over (p_lb, p_ub, m_lb, v_lb, v_ub, owned, id) by low position. Owned rows open a
    window; it closes once no later row can be in it. Certain rows wait in a list by low position,
    possible ones in a heap with three orders: high position, low value, high value. Rows are evicted
    below every window that is still open. Returns (id, low, high, certain, possible) and the counters."""
    if spec_agg not in AGGREGATES:
        raise ValueError(f"the sweep has {AGGREGATES}, not {spec_agg}")
    rows = sorted(rows, key=lambda r: (r[0], r[1], r[6]))
    size = hi - lo + 1
    own_in = lo <= 0 <= hi
    heap = (ConnectedHeap if connected else UnconnectedHeaps)([lambda r: r[1], lambda r: r[3], lambda r: -r[4]])
    sure: list[tuple] = []  # (p_lb, n, row)
    open_: list[tuple] = []  # (p_ub + hi, n, row), least first
    lows: list[tuple] = []  # (p_lb, n) of open windows
    tick = counter()
    out: list[tuple] = []
    widest = 0

    def close(row: tuple) -> None:
        p_lb, p_ub, _, v_lb, v_ub, _, rid = row
        cert: list[tuple] = []
        ids = set()
        for _, _, s in sure[bisect_left(sure, (p_ub + lo, -1)) :]:
            if s[0] > p_lb + hi:
                break
            if s[1] <= p_lb + hi and (s[6] != rid):
                cert.append((s[3], s[4]))
                ids.add(s[6])
        if own_in:
            cert.append((v_lb, v_ub))
        ids.add(rid)
        slots = max(0, size - len(cert))
        meets = lambda s: s[6] not in ids and s[1] >= p_lb + lo and s[0] <= p_ub + hi
        n_pos = sum(1 for s in heap.ascending(0) if meets(s)) if spec_agg == "count" or not own_in else -1
        low = high = None
        if spec_agg == "count":
            low, high = len(cert), min(size, len(cert) + n_pos)
        elif spec_agg == "sum":
            low, high = sum(c[0] for c in cert), sum(c[1] for c in cert)
            left = slots
            for s in heap.ascending(1) if left else ():
                if s[3] >= 0 or not left:
                    break
                if meets(s):
                    low += s[3]
                    left -= 1
            left = slots
            for s in heap.ascending(2) if left else ():
                if s[4] <= 0 or not left:
                    break
                if meets(s):
                    high += s[4]
                    left -= 1
        elif spec_agg in ("min", "max"):
            pos = [s for s in heap.ascending(1) if meets(s)] if slots else []
            f = min if spec_agg == "min" else max
            cl, ch = [c[0] for c in cert], [c[1] for c in cert]
            if spec_agg == "min":
                low = f(cl + [s[3] for s in pos]) if cl or pos else None
                high = f(ch) if ch else (max(s[4] for s in pos) if pos else None)
            else:
                low = f(cl) if cl else (min(s[3] for s in pos) if pos else None)
                high = f(ch + [s[4] for s in pos]) if ch or pos else None
        else:
            for sign, k in ((1, 3), (-1, 4)):
                s_, n_, left = sum(c[k - 3] for c in cert), len(cert), slots
                for s in heap.ascending(1 if sign > 0 else 2) if left else ():
                    if not left:
                        break
                    if meets(s):
                        if n_ and sign * s[k] * n_ >= sign * s_:
                            break
                        s_, n_, left = s_ + s[k], n_ + 1, left - 1
                mean = s_ / n_ if n_ else None
                low, high = (mean, high) if sign > 0 else (low, mean)
        out.append((rid, low, high, len(cert)))

    def evict(below: int) -> None:
        while len(heap) and heap.peek(0)[1] < below:
            heap.pop(0)
        k = bisect_left(sure, (below, -1))
        del sure[:k]

    closed: set[int] = set()
    for row in rows:
        now = row[0]
        while open_ and open_[0][0] < now:
            _, n, done = heapq.heappop(open_)
            close(done)
            closed.add(n)
            while lows and lows[0][1] in closed:
                closed.discard(heapq.heappop(lows)[1])
        evict(min(lows[0][0] if lows else now, now) + lo)
        n = next(tick)
        if row[5]:
            heapq.heappush(open_, (row[1] + hi, n, row))
            heapq.heappush(lows, (row[0], n))
        if row[2] >= 1:
            insort(sure, (row[0], n, row))
        heap.insert(row)
        widest = max(widest, len(heap))
    while open_:
        close(heapq.heappop(open_)[2])
    return out, {"ops": heap.ops, "widest": widest}


def _onepass(members: DataFrame, spec: WindowSpec, chunk: int) -> DataFrame:
    """The sweep over chunks of positions. A chunk owns the rows whose low position lies in it, and also gets
    the rows that may be in their windows."""
    if spec.agg not in AGGREGATES:
        raise ValueError(f"the sweep has {AGGREGATES}, not {spec.agg}")
    p = list(spec.partition)
    own = members.withColumn("_k", F.floor(F.col("p__lb") / chunk))
    reach = own.groupBy(*p, "_k").agg(F.min(F.col("p__lb") + min(0, spec.lo)).alias("from"), F.max(F.col("p__ub") + max(0, spec.hi)).alias("to"))
    w = max(chunk, spec.size)
    spread = reach.withColumn("_w", F.explode(F.sequence(F.floor(F.col("from") / w), F.floor(F.col("to") / w))))
    placed = members.withColumn("_w", F.explode(F.sequence(F.floor(F.col("p__lb") / w), F.floor(F.col("p__ub") / w))))
    a, b = spread.alias("a"), placed.alias("b")
    cond = (F.col("a._w") == F.col("b._w")) & (F.col("b.p__ub") >= F.col("a.from")) & (F.col("b.p__lb") <= F.col("a.to"))
    cond = cond & (F.col("a._w") == F.greatest(F.floor(F.col("a.from") / w), F.floor(F.col("b.p__lb") / w)))
    for c in p:
        cond = cond & F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}"))
    rows = a.join(b, cond).select(*[F.col(f"a.{c}").alias(c) for c in p], F.col("a._k").alias("_k"), *[F.col(f"b.{c}").alias(c) for c in (RID, DUP, "_m_lb", "p__lb", "p__ub", "v__lb", "v__ub")], (F.floor(F.col("b.p__lb") / chunk) == F.col("a._k")).alias("own"))
    real = spec.agg == "avg"

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        items = list(zip(pdf["p__lb"].tolist(), pdf["p__ub"].tolist(), pdf["_m_lb"].tolist(), pdf["v__lb"].tolist(), pdf["v__ub"].tolist(), pdf["own"].tolist(), zip(pdf[RID].tolist(), pdf[DUP].tolist(), strict=True), strict=True))
        got, _ = sweep_windows(items, spec.agg, spec.lo, spec.hi)
        frame = pd.DataFrame([(r[0], r[1], a, b, c) for r, a, b, c in got], columns=[RID, DUP, "x__lb", "x__ub", "x_certain"])
        return frame.astype({"x__lb": "float64" if real else "Int64", "x__ub": "float64" if real else "Int64"})

    kind = "double" if real else "long"
    found = rows.groupBy(*p, "_k").applyInPandas(sweep, f"{RID} long, {DUP} int, x__lb {kind}, x__ub {kind}, x_certain long")
    # The guess is the deterministic window of the guess world.
    g = members.where("_m_sg > 0")
    ow = W.partitionBy(*p)
    f = {"sum": F.sum, "count": F.count, "min": F.min, "max": F.max, "avg": F.avg}[spec.agg]
    guess = g.withColumn("_guess", f("v__sg").over(ow.orderBy("p__sg").rowsBetween(spec.lo, spec.hi))).select(RID, DUP, "_guess")
    out = found.join(guess, [RID, DUP], "left")
    empty = F.lit(0) if spec.agg in ("sum", "count") else F.col("x__lb")
    sg = F.least(F.greatest(F.coalesce("_guess", empty), "x__lb"), "x__ub")
    return out.select(RID, DUP, "x__lb", sg.alias("x__sg"), "x__ub", "x_certain", F.lit(-1).cast("long").alias("x_possible"), (F.col("x_certain") == 0).cast("int").alias("x_maybe_empty"))


def _uncertain_partition(rf: RangeFrame, spec: WindowSpec) -> DataFrame:
    """Partitions of which one key is a range of whole numbers.

    A row stands in each partition that it may be in, there without certainty unless its key is certain. All owners of
    certain keys see the same partition, so their windows are those of a certain partition over these rows. An owner
    whose own partition is unknown has no certain member but itself, and any row that may share a partition with it
    may be next to it: its bounds take the values that push furthest among those of all its partitions."""
    soft = [p for p in spec.partition if not rf.attr(p).certain]
    if len(soft) > 1:
        raise ValueError("one partition key may be a range; further ones must be certain")
    extra = [p for p in spec.partition if p not in soft]
    full = RankSpec(spec.keys, spec.desc, (), "corner", spec.ties)
    part, v = rf.c(soft[0]), rf.c(spec.arg) if spec.arg else rlit(F.lit(0).cast("long"))
    keys = order_keys(rf, full)
    end = lambda e: F.struct(*[getattr(k, e).alias(f"k{i}") for i, k in enumerate(keys)])
    base = rf.df.select(RID, *extra, *MULT, end("lb").alias("_lo"), end("sg").alias("_sg"), end("ub").alias("_hi"), part.lb.cast("long").alias("g0"), part.sg.cast("long").alias("gs"), part.ub.cast("long").alias("g1"), *[x.alias(f"v__{e}") for x, e in zip((v.lb, v.sg, v.ub), ("lb", "sg", "ub"), strict=True)])
    sizes = base.agg(F.max(F.col("g1") - F.col("g0")).alias("w"), F.sum(F.col("_m_ub") * (1 + F.coalesce(F.col("g1") - F.col("g0"), F.lit(0)))).alias("n")).first()
    stride, most = (sizes["w"] or 0) + 1, sizes["n"] or 0
    sure, zero = F.coalesce(F.col("g0") == F.col("g1"), F.lit(True)), F.lit(0).cast("long")  # a null key is a partition
    m = [*extra, "_at"]
    grown = base.withColumn("_at", F.explode_outer(F.sequence("g0", "g1"))).withColumn("_o", F.coalesce(F.col("_at") - F.col("g0"), zero).cast("int"))
    grown = grown.withColumns({"_m_lb": F.when(sure, F.col("_m_lb")).otherwise(zero), "_m_sg": F.when(F.coalesce(F.col("gs") == F.col("_at"), F.lit(True)), F.col("_m_sg")).otherwise(zero)})
    pos = _dist(grown.select(RID, "_o", *m, *MULT, "_lo", "_sg", "_hi"), (RID, "_o"), m, None)
    unit = grown.join(pos, [RID, "_o"]).withColumn("_d", F.explode(F.sequence(F.lit(0), F.col("_m_ub").cast("int") - 1)))
    d = F.col("_d").cast("long")
    members = materialise(unit.select(RID, (F.col("_d") * stride + F.col("_o")).cast("int").alias(DUP), "_d", *m, "g0", "gs", "g1", *[(d < F.col(c)).cast("long").alias(c) for c in MULT], *[(F.col(f"_p_{e}") + d).alias(f"p__{e}") for e in ("lb", "sg", "ub")], *[f"v__{e}" for e in ("lb", "sg", "ub")]))
    inside = replace(spec, partition=tuple(m))
    slim = members.drop("_d", "g0", "gs", "g1")
    known = _summarised(slim, inside, None, most) if spec.agg in AGGREGATES else _bounds(_flag(_band(slim, inside, None, None), inside), (RID, DUP), inside)
    known = known.join(members.where(sure).select(RID, DUP, "_d"), [RID, DUP]).withColumn(DUP, F.col("_d")).drop("_d")
    if spec.has_self and spec.agg in AGGREGATES:
        rest = _unknown_partition(members, spec, extra, slim, inside)
    else:
        rest = _partition_pairs(rf, base, spec, extra)
    return known.unionByName(rest.select(*known.columns))


def _unknown_partition(members: DataFrame, spec: WindowSpec, extra: Sequence[str], slim: DataFrame, inside: WindowSpec) -> DataFrame:
    """Bounds of the owners that may be in several partitions, for frames that hold the owner."""
    k, zero = spec.size + 1, F.lit(0).cast("long")
    m = [*extra, "_at"]
    kind = dict(members.dtypes)["v__lb"]
    open_ = F.col("g0") < F.col("g1")
    # By partition: rows in it, rows whose range begins with it, and the values at both ends (salted, so that a hot
    # partition is cut where it is read).
    salt = F.pmod(F.xxhash64(RID), F.lit(32))
    lists = None
    for name, c, way in (("low", "v__lb", F.asc), ("high", "v__ub", F.desc)):
        push = (F.col(c) < 0 if name == "low" else F.col(c) > 0) if spec.agg == "sum" else F.lit(True)
        some = members.where(push).select(*m, RID, "_d", F.col(c).alias("v"), salt.alias("_salt"))
        for by in ([*m, "_salt"], m):
            some = some.withColumn("_n", F.row_number().over(W.partitionBy(*by).orderBy(way("v"), RID, "_d"))).where(F.col("_n") <= k)
        some = some.groupBy(*m).agg(F.collect_list(F.struct("v", RID, F.col("_d").alias(DUP))).alias(name))  # k at most
        lists = some if lists is None else lists.unionByName(some, allowMissingColumns=True)
    counts = members.groupBy(*m).agg(F.count(F.lit(1)).alias("all"), F.sum((F.coalesce(F.col("_at") == F.col("g0"), F.lit(True))).cast("long")).alias("begun"))
    facts = lists.unionByName(counts, allowMissingColumns=True).groupBy(*m).agg(F.first("low", True).alias("low"), F.first("high", True).alias("high"), F.max("all").alias("all"), F.max("begun").alias("begun"))
    asks = members.where(open_)
    guess = asks.where(F.col("gs") == F.col("_at")).select(RID, DUP, "_d").join(_guess_windows(slim, inside), [RID, DUP], "left").select(RID, F.col("_d").alias(DUP), "_ng", "_g")
    none = F.array().cast(f"array<struct<v:{kind},{RID}:bigint,{DUP}:int>>")
    met = join_null_safe(asks, facts, m).withColumn("_n", F.when(F.col("_at") == F.col("g0"), F.col("all")).otherwise(F.col("begun")))
    got = met.groupBy(RID, F.col("_d").alias(DUP)).agg(
        F.max("v__lb").alias("own_l"), F.max("v__ub").alias("own_h"), F.max("p__ub").alias("before"), F.sum("_n").alias("n"),
        F.array_distinct(F.flatten(F.collect_list(F.coalesce("low", none)))).alias("low"), F.array_distinct(F.flatten(F.collect_list(F.coalesce("high", none)))).alias("high"),
    )
    # Whoever has no row possibly before it has none in a frame that ends with it.
    alone = (F.col("before") == 0) & F.lit(spec.hi == 0)
    got = got.join(guess, [RID, DUP], "left")
    other = lambda x: (x[RID] != F.col(RID)) | (x[DUP] != F.col(DUP))
    of = lambda c, asc: F.when(alone, F.array().cast(f"array<{kind}>")).otherwise(F.transform(F.slice(F.sort_array(F.filter(c, other), asc=asc), 1, k), lambda x: x["v"]))
    got = got.select(RID, DUP, F.lit(1).cast("long").alias("_nc"), F.when(alone, zero).otherwise(F.col("n") - 1).alias("_np"), F.coalesce("_ng", zero).alias("_ng"), "_g", F.col("own_l").alias("_cl"), F.col("own_h").alias("_ch"), of("low", True).alias("_pl"), of("high", False).alias("_ph"))
    if spec.agg in ("min", "max"):
        got = got.withColumns({"_least": F.array_min("_pl"), "_most": F.array_max("_ph"), "_pl": F.array_min("_pl"), "_ph": F.array_max("_ph")})
    return _from_members(got, (RID, DUP), spec)


def _partition_pairs(rf: RangeFrame, base: DataFrame, spec: WindowSpec, extra: Sequence[str]) -> DataFrame:
    """Owners of uncertain keys meet all rows whose keys overlap theirs, and rank them: for frames without the owner, where
    a member's own position decides, and for registered aggregates."""
    base = base.withColumnsRenamed({"g0": "g__lb", "gs": "g__sg", "g1": "g__ub"})
    owners = base.where("g__lb < g__ub").select(RID, *extra, "g__lb", "g__sg", "g__ub", F.col("_m_sg").alias("o_m_sg"))
    pairs = overlap_pairs(owners, base, ("g__lb", "g__ub"), ("g__lb", "g__ub"))
    for c in extra:
        pairs = pairs.where(F.col(c).eqNullSafe(F.col(f"s_{c}")))
    tg, sg = (Triple(*(F.col(f"{x}g__{e}") for e in ("lb", "sg", "ub"))) for x in ("", "s_"))
    eq = req(tg, sg)
    same = F.col(RID) == F.col(f"s_{RID}")
    zero = F.lit(0).cast("long")
    inside = pairs.select(
        F.col(RID).alias("owner"),
        F.col(f"s_{RID}").alias(RID),
        F.when(eq.lb | same, F.col("s__m_lb")).otherwise(zero).alias("_m_lb"),
        F.when(eq.sg | same, F.col("s__m_sg")).otherwise(zero).alias("_m_sg"),
        F.col("s__m_ub").alias("_m_ub"),
        F.col("s__lo").alias("_lo"),
        F.col("s__sg").alias("_sg"),
        F.col("s__hi").alias("_hi"),
        *[F.col(f"s_v__{e}").alias(f"v__{e}") for e in ("lb", "sg", "ub")],
        "o_m_sg",
        # Copies of a row follow one another for certain only where they share a partition for certain.
        (tg.lb == tg.ub).cast("long").alias("tight"),
    )
    ev = _events(inside, (RID,), ("owner",))
    w = W.partitionBy("owner").orderBy("point", "kind").rowsBetween(W.unboundedPreceding, -1)
    ev = ev.withColumns({n: F.coalesce(F.sum(c).over(w), zero) for n, c in {"s_end": "w_end", "s_start": "w_start", "s_guess": "w_guess"}.items()})
    ranked = inside.join(_paired(ev, ("owner", RID)), ["owner", RID])
    unit = ranked.withColumn(DUP, F.explode(F.sequence(F.lit(0), F.col("_m_ub").cast("int") - 1)))
    d = F.col(DUP).cast("long")
    unit = unit.select("owner", RID, DUP, "o_m_sg", *[(d < F.col(c)).cast("long").alias(c) for c in ("_m_lb", "_m_sg")], (F.col("_p_lb") + F.when(F.col("tight") == 1, d).otherwise(zero)).alias("p__lb"), (F.col("_p_sg") + d).alias("p__sg"), (F.col("_p_ub") + d).alias("p__ub"), *[f"v__{e}" for e in ("lb", "sg", "ub")])
    me = unit.where(F.col(RID) == F.col("owner")).select(F.col("owner"), F.col(DUP).alias("o_dup"), F.col("_m_sg").alias("o_sg"), F.col("p__lb").alias("o__lb"), F.col("p__sg").alias("o__sg"), F.col("p__ub").alias("o__ub"))
    met = unit.join(me, "owner")
    t, s = (Triple(*(F.col(f"{x}__{e}") for e in ("lb", "sg", "ub"))) for x in ("o", "p"))
    self_ = (F.col(RID) == F.col("owner")) & (F.col(DUP) == F.col("o_dup"))
    c, p, g = membership(spec, t, s, F.col("_m_lb"), self_, (F.col("_m_sg") > 0) & (F.col("o_sg") > 0))
    flags = met.select(F.col("owner").alias(RID), F.col("o_dup").alias(DUP), c.alias("is_certain"), p.alias("is_possible"), g.alias("is_guess"), *[f"v__{e}" for e in ("lb", "sg", "ub")])
    return _bounds(flags, (RID, DUP), spec)


def _unbounded(members: DataFrame, spec: WindowSpec) -> DataFrame:
    """All preceding rows and the row itself: running sums over positions, no pairs. Count and sum."""
    if spec.agg not in ("sum", "count") or spec.hi != 0:
        raise ValueError("an unbounded start has sum and count up to the row itself")
    p = list(spec.partition)
    one = F.lit(1).cast("long")
    lo = one if spec.agg == "count" else F.col("v__lb")
    hi = one if spec.agg == "count" else F.col("v__ub")
    sg = one if spec.agg == "count" else F.col("v__sg")
    zero = F.lit(0).cast("long")
    sure = F.when(F.col("_m_lb") > 0, 1).otherwise(0)
    # Certain members end at or before the owner's low position; possible ones start at or before its high one.
    # As possible they count what they may add: nothing or more for high, nothing or less for low.
    x = members.withColumns({"c_lo": sure * lo, "c_hi": sure * hi, "up": F.greatest(hi, zero), "down": F.least(lo, zero)})
    ask, give = 2, 1
    ev = F.array(
        F.struct(F.col("p__ub").alias("at"), F.lit(give).alias("k"), F.col("c_lo").alias("a"), F.col("c_hi").alias("b"), (F.col("c_lo") * 0 - F.when(F.col("_m_lb") > 0, F.col("down")).otherwise(zero)).alias("c"), (F.col("c_hi") * 0 - F.when(F.col("_m_lb") > 0, F.col("up")).otherwise(zero)).alias("d"), zero.alias("e"), zero.alias("f")),
        F.struct(F.col("p__lb").alias("at"), F.lit(give).alias("k"), zero.alias("a"), zero.alias("b"), zero.alias("c"), zero.alias("d"), F.col("down").alias("e"), F.col("up").alias("f")),
        F.struct(F.col("p__lb").alias("at"), F.lit(ask).alias("k"), zero.alias("a"), zero.alias("b"), zero.alias("c"), zero.alias("d"), zero.alias("e"), zero.alias("f")),
        F.struct(F.col("p__ub").alias("at"), F.lit(ask + 1).alias("k"), zero.alias("a"), zero.alias("b"), zero.alias("c"), zero.alias("d"), zero.alias("e"), zero.alias("f")),
    )
    long = x.select(RID, DUP, *p, F.explode(ev).alias("v")).select(RID, DUP, *p, "v.*").withColumn("_b", F.floor(F.col("at") / 65536))
    got = running_sums(long, ["_b"], ["at", "k", RID, DUP], {f"s_{c}": c for c in "abcdef"}, p)
    at_low, at_high = F.col("k") == ask, F.col("k") == ask + 1
    # low = certain low values + downs of those possible but not certain; high likewise.
    pick = got.where("k >= 2").groupBy(RID, DUP).agg(*[F.max(F.when(at_low, F.col(f"s_{c}"))).alias(f"l{c}") for c in "abcd"], *[F.max(F.when(at_high, F.col(f"s_{c}"))).alias(f"h{c}") for c in "ef"])
    own = x.select(RID, DUP, "_m_lb", "_m_sg", "p__lb", "p__ub", "c_lo", "c_hi", "up", "down", lo.alias("v_lo"), hi.alias("v_hi"))
    j = own.join(pick, [RID, DUP])
    # The row itself is a certain member, whatever the sums took it for.
    own_in_c = (F.col("p__ub") <= F.col("p__lb")) & (F.col("_m_lb") > 0)
    low = F.col("la") + F.col("he") + F.col("lc") + F.when(own_in_c, zero).otherwise(F.col("v_lo") - F.col("down"))
    high = F.col("lb") + F.col("hf") + F.col("ld") + F.when(own_in_c, zero).otherwise(F.col("v_hi") - F.col("up"))
    g = members.where("_m_sg > 0").withColumn("_b", F.floor(F.col("p__sg") / 65536)).withColumn("_v", sg)
    guess = running_sums(g, ["_b"], ["p__sg", RID, DUP], {"_before": "_v"}, p).select(RID, DUP, (F.col("_before") + F.col("_v")).alias("_guess"))
    out = j.join(guess, [RID, DUP], "left").select(RID, DUP, low.cast("long").alias("x__lb"), F.col("_guess").cast("long").alias("_g"), high.cast("long").alias("x__ub"))
    return out.select(RID, DUP, "x__lb", F.least(F.greatest(F.coalesce("_g", "x__lb"), "x__lb"), "x__ub").alias("x__sg"), "x__ub", F.lit(-1).cast("long").alias("x_certain"), F.lit(-1).cast("long").alias("x_possible"), F.lit(0).alias("x_maybe_empty"))


def window(rf: RangeFrame, agg: str, arg: str | None, keys: Sequence[str], lo: int | None, hi: int, partition: Sequence[str] = (), desc: Sequence[str] = (), method: str = "auto", into: str = "x", rank_method: str = "auto", ties: bool = True, width: int | None = None, chunk: int = 4096, index: DataFrame | None = None, detail: bool = False, ranked: bool = False) -> RangeFrame:
    """Adds the aggregate as an attribute. ranked: rf has positions already, by the same keys and partition (the
    result of rank, or of a window before), so windows in sequence rank once. Frame: rows lo to hi around each row, lo None for all before.
    naive: all pairs. rewrite: pairs, then two orders per owner; with an index (see band_index) the pairs come from it.
    bucket: pairs at the ends of windows, summaries of what lies between. pairs: band join on positions (also for
    registered aggregates). auto: pairs if ranges of positions are short on average, else bucket. onepass: the sweep. detail keeps the counts of members (and numerators and denominators of avg)."""
    spec = WindowSpec(agg, arg, tuple(keys), 0 if lo is None else lo, hi, tuple(desc), tuple(partition), ties)
    if ranked and any(not rf.attr(p).certain for p in partition):
        raise ValueError("windows of uncertain partitions have positions for each partition, and can't share them")
    if any(not rf.attr(p).certain for p in partition):
        if lo is None:
            raise ValueError("an unbounded start needs certain partitions")
        got = _uncertain_partition(rf, spec)
        unit = rf.split()
    else:
        unit = rf if ranked else rank(rf, keys, desc, partition, rank_method, ties=ties)
        members = _members(unit, spec)
        if lo is None:
            got = _unbounded(members, spec)
        elif method == "onepass":
            got = _onepass(members, spec, chunk)
        elif (method in ("naive", "rewrite") or index is not None) and agg in AGGREGATES and (done := _compared(members, spec, width, index)) is not None:
            # The rewrite has no row for an owner without members.
            got = done if method == "naive" or (agg == "avg" and index is None) else done.where("x_certain > 0 or x_possible > 0")
        elif method in ("naive", "rewrite"):
            flags = _flag(_all_pairs(members, spec) if index is None else _band(members, spec, width, index), spec)
            got = _rewrite_fill(flags, spec) if method == "rewrite" and agg in AGGREGATES and agg != "avg" else _bounds(flags, (RID, DUP), spec)
        elif agg in _CUSTOM and (done := _compared(members, spec, width, index)) is not None:
            got = done.where("x_certain > 0 or x_possible > 0")
        elif index is not None or agg not in AGGREGATES:
            got = _bounds(_flag(_band(members, spec, width, index), spec), (RID, DUP), spec)
        elif method == "pairs":
            got = _bounds(_flag(_band(members, spec, width, None), spec), (RID, DUP), spec)
        else:
            # Positions are read several times below; written once, their lineage ends there. What they count tells which
            # plan is cheaper: a pair for each row within reach, or the fixed work of the summaries.
            reach = Observation()
            members = materialise(members.observe(reach, F.count(F.lit(1)).alias("n"), F.sum(F.col("p__ub") - F.col("p__lb")).alias("w")))
            n, wide = reach.get["n"], reach.get["w"] or 0
            if method == "auto" and 2 * wide <= PAIRS_A_ROW * n:
                got = _bounds(_flag(_band(members, spec, width, None), spec), (RID, DUP), spec)
            else:
                got = _summarised(members, spec, width, rf.df.agg(F.sum("_m_ub")).first()[0] or 0)
    more = [c for c in got.columns if c.startswith("x_") and not c.startswith("x__")]
    got = got.select(RID, DUP, *[F.col(f"x__{e}").alias(f"{into}__{e}") for e in ("lb", "sg", "ub")], *([F.col(c).alias(c.replace("x_", f"{into}_", 1)) for c in more] if detail else []))
    ends = [f"{into}__{e}" for e in ("lb", "sg", "ub")]
    if spec.has_self or lo is None:
        met = unit.df.join(by_sort(got), [RID, DUP])
    else:  # a window without any member has no row yet
        met = unit.df.join(by_sort(got), [RID, DUP], "left")
        if agg in ("sum", "count"):
            met = met.fillna(0, ends)
    out = RangeFrame(met, (*unit.attrs, Attr(into, False)), True)
    extra = [c for c in got.columns if c not in out.columns] if detail else []
    return out.with_df(out.df.select(*out.columns, *extra))


def _group_boxes(m: DataFrame, spec: WindowSpec, width: int) -> DataFrame:
    """Windows on values whose frame holds the owner. Rows of equal key ranges see the same members, so ranges meet
    ranges, each with the totals of its rows; a row then adds itself as a certain member, which its range may have
    counted as a possible one."""
    key = [f"p__{e}" for e in ("lb", "sg", "ub")]
    lb, sg, ub, zero = F.col("v__lb"), F.col("v__sg"), F.col("v__ub"), F.lit(0).cast("long")
    sure, guess = F.col("_m_lb") >= 1, F.col("_m_sg") > 0
    fold = {"min": F.min, "max": F.max}.get(spec.agg, F.sum)
    # What rows add as certain members (c) and as possible ones (p), to the low and to the high bound.
    values = {"sum": (lb, ub, F.least(lb, zero), F.greatest(ub, zero)), "count": (F.lit(1).cast("long"), F.lit(1).cast("long"), zero, F.lit(1).cast("long"))}
    cl, ch, pl, ph = values.get(spec.agg, (lb, ub, lb, ub))
    g = F.lit(1).cast("long") if spec.agg == "count" else sg
    boxes = m.groupBy(*key).agg(
        fold(F.when(sure, cl)).alias("cl"), fold(F.when(sure, ch)).alias("ch"), fold(pl).alias("al"), fold(ph).alias("ah"),
        fold(F.when(~sure, pl)).alias("ul"), fold(F.when(~sure, ph)).alias("uh"), fold(F.when(guess, g)).alias("g"),
    )
    owners = boxes.select(*key, (F.col("p__lb") + spec.lo).alias("o_lo"), (F.col("p__ub") + spec.hi).alias("o_hi"))
    met = band_pairs(owners, boxes, ("o_lo", "o_hi"), ("p__lb", "p__ub"), width)
    t, s = (Triple(*(F.col(f"{x}p__{e}") for e in ("lb", "sg", "ub"))) for x in ("", "s_"))
    c = (s.lb >= t.ub + spec.lo) & (s.ub <= t.lb + spec.hi)
    near = (s.sg >= t.sg + spec.lo) & (s.sg <= t.sg + spec.hi)
    got = met.groupBy(*key).agg(
        fold(F.when(c, F.col("s_cl"))).alias("_cl"), fold(F.when(c, F.col("s_ch"))).alias("_ch"), fold(F.when(c, F.col("s_ul")).otherwise(F.col("s_al"))).alias("_pl"),
        fold(F.when(c, F.col("s_uh")).otherwise(F.col("s_ah"))).alias("_ph"), fold(F.when(near, F.col("s_g"))).alias("_g"),
    )
    rows = m.join(got, key)
    if spec.agg in ("sum", "count"):
        both = lambda a, b: F.coalesce(a, zero) + F.coalesce(b, zero)
        mine = sure & (F.col("p__lb") >= F.col("p__ub") + spec.lo) & (F.col("p__ub") <= F.col("p__lb") + spec.hi)
        low = both(F.col("_cl"), F.col("_pl")) + F.when(mine, zero).otherwise(cl - pl)
        high = both(F.col("_ch"), F.col("_ph")) + F.when(mine, zero).otherwise(ch - ph)
    elif spec.agg == "min":
        low, high = F.least("_cl", "_pl", lb), F.least("_ch", ub)
    else:
        low, high = F.greatest("_cl", lb), F.greatest("_ch", "_ph", ub)
    x = F.when(guess, F.col("_g"))
    if spec.agg in ("sum", "count"):
        x = F.coalesce(x, zero)
    return rows.select(RID, DUP, low.alias("x__lb"), F.least(F.greatest(F.coalesce(x, low), low), high).alias("x__sg"), high.alias("x__ub"))


def group_window(rf: RangeFrame, agg: str, arg: str | None, key: str, lo: int, hi: int, method: str = "bucket", into: str = "x", width: int | None = None) -> RangeFrame:
    """Range frames on values: members whose key lies within [key + lo, key + hi]. There is no limit on
    how many, so every possible member may count."""
    unit = rf.split()
    k = unit.c(key)
    v = unit.c(arg) if arg else rlit(F.lit(1).cast("long"))
    m = unit.df.select(RID, DUP, *MULT, k.lb.alias("p__lb"), k.sg.alias("p__sg"), k.ub.alias("p__ub"), v.lb.alias("v__lb"), v.sg.alias("v__sg"), v.ub.alias("v__ub"))
    wide = WindowSpec(agg, arg, (key,), lo, hi)
    if method != "naive" and wide.has_self and agg in ("sum", "count", "min", "max"):
        got = _group_boxes(m, wide, width or max(1, hi - lo + 1)).select(RID, DUP, *[F.col(f"x__{e}").alias(f"{into}__{e}") for e in ("lb", "sg", "ub")])
        out = RangeFrame(unit.df.join(got, [RID, DUP]), (*unit.attrs, Attr(into, False)), True)
        return out.with_df(out.df.select(*out.columns))
    pairs = _all_pairs(m, wide) if method == "naive" else _band(m, wide, width or max(1, hi - lo + 1), None)
    flags = _flag(pairs, wide)
    # No slot limit: a frame as large as any group of members.
    big = WindowSpec(agg, arg, (key,), -(1 << 28), 1 << 28)
    got = _bounds(flags, (RID, DUP), big).select(RID, DUP, *[F.col(f"x__{e}").alias(f"{into}__{e}") for e in ("lb", "sg", "ub")])
    out = RangeFrame(unit.df.join(got, [RID, DUP]), (*unit.attrs, Attr(into, False)), True)
    return out.with_df(out.df.select(*out.columns))
