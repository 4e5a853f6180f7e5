"""Windows by comparing rows block by block, where a join would list each pair as a row.

Owners and members are dealt in blocks. A task compares a block of owners with one of members, array by array, and hands on
what an owner's bounds need: counts, what its certain members add, and of its possible ones the few that push furthest, from
both ends. Such parts add up, so no task holds more than two blocks, and what is moved follows the number of blocks.
Registered aggregates take whole lists of members; there a task has all members that a block of owners may reach, and hands the
lists on a few at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import DUP, MULT, RID
from .joins import by_sort
from .prefix import join_null_safe

#: Rows of a block, and owners of a block whose members come as lists. A member is dealt to each block within whose reach it is, so
#: that small blocks move wide ranges many times.
BLOCK, LISTED = 8192, 8192
#: Values of the lists that are handed on at once.
VALUES = 1 << 19
#: Values are compared as 64-bit whole numbers; other types go by joins.
WHOLE = ("tinyint", "smallint", "int", "bigint")
#: Levels of the index; a member of level l spans fewer than 2^l buckets beside its first.
LEVELS = 40

COLUMNS = (RID, DUP, *MULT, *[f"{c}__{e}" for c in "pv" for e in ("lb", "sg", "ub")])
_IDS = f"{RID} long, {DUP} int, _nc long, _np long, _ng long"
PARTS = f"{_IDS}, _cl long, _ch long, _g long, _pl array<long>, _ph array<long>"
LISTS = f"{_IDS}, _cl array<long>, _ch array<long>, _g array<long>, _pl array<long>, _ph array<long>"


def level_index(members: DataFrame, low: str, high: str, width: int) -> DataFrame:
    """The range index: each member once, at the level of its length and by its first bucket there (_level, _k)."""
    first, last = F.floor(F.col(low) / width), F.floor(F.col(high) / width)
    level = F.when(last > first, F.length(F.bin(last - first))).otherwise(F.lit(0)).cast("int")
    return members.withColumns({"_level": level, "_k": F.call_function("shiftright", first, level)})


def _dealt(rows: DataFrame, parts: Column) -> Column:
    return F.pmod(F.xxhash64(RID, DUP), parts).cast("int")


def deal_all(members: DataFrame, on: Sequence[str]) -> DataFrame:
    """Each block of owners (_o) with each block of members (_s) of its partition."""
    if on:
        sizes = members.groupBy(*on).agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("_n"))
        members = join_null_safe(members, sizes, on)
    else:
        members = members.withColumn("_n", F.lit(-(-members.count() // BLOCK) or 1))
    at, every = _dealt(members, F.col("_n")), F.explode(F.sequence(F.lit(0), F.col("_n") - 1))
    own = members.select(*on, *COLUMNS, at.alias("_o"), every.alias("_s"), F.lit(True).alias("_own"))
    return own.unionByName(members.select(*on, *COLUMNS, every.alias("_o"), at.alias("_s"), F.lit(False).alias("_own")))


def deal_near(members: DataFrame, index: DataFrame, lo: int, hi: int, on: Sequence[str], width: int, listed: bool) -> DataFrame:
    """Blocks of owners by low position (_b, _o), with the members that the index has within their reach; these are cut, too
    (_s), unless they are to be listed."""
    step = LISTED if listed else BLOCK
    owners = members.withColumn("_b", F.floor(F.col("p__lb") / step))
    blocks = owners.groupBy(*on, "_b").agg((F.min("p__lb") + lo).alias("_from"), (F.max("p__ub") + hi).alias("_to"), F.ceil(F.count(F.lit(1)) / step).cast("int").alias("_n"))
    blocks = blocks.withColumn("_m", F.lit(1) if listed else (1 + F.greatest(F.col("_to") - F.col("_from"), F.lit(0)) / BLOCK).cast("int"))
    a, b = F.floor(F.col("_from") / width), F.floor(F.col("_to") / width)
    shift = lambda x, n: F.call_function("shiftright", x, n)
    # A member begins in a node that the reach meets, or in the one before.
    nodes = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(LEVELS)), lambda n: F.transform(F.sequence(shift(a, n) - 1, shift(b, n)), lambda x: F.struct(n.alias("_level"), x.alias("_k")))))
    asks = blocks.where("_to >= _from").select(*on, "_b", "_from", "_to", "_n", "_m", F.explode(nodes).alias("_x")).select(*on, "_b", "_from", "_to", "_n", "_m", "_x.*")
    met = join_null_safe(index, by_sort(asks), [*on, "_level", "_k"]).where("p__ub >= _from and p__lb <= _to")
    met = met.select(*on, *COLUMNS, "_b", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)).alias("_o"), _dealt(met, F.col("_m")).alias("_s"), F.lit(False).alias("_own"))
    own = join_null_safe(owners, by_sort(blocks), [*on, "_b"])
    own = own.select(*on, *COLUMNS, "_b", _dealt(own, F.col("_n")).alias("_o"), F.explode(F.sequence(F.lit(0), F.col("_m") - 1)).alias("_s"), F.lit(True).alias("_own"))
    return own.unionByName(met)


def _compare(agg: str, lo: int, hi: int, listed: bool) -> Callable[[pa.Table], Iterator[pa.Table]]:
    """Tables of parts; but for lists there is one."""
    size, inside = hi - lo + 1, lo <= 0 <= hi
    names = [x.split()[0] for x in (LISTS if listed else PARTS).split(", ")]
    fold = {"min": np.min, "max": np.max}.get(agg, np.sum)
    kinds = [pa.int64(), pa.int32(), *[pa.int64()] * 3, *[pa.list_(pa.int64()) if listed else pa.int64()] * 3, *[pa.list_(pa.int64())] * 2]

    def made(out: list[list]) -> pa.Table:
        def column(x: list, kind: pa.DataType) -> pa.Array:
            if not pa.types.is_list(kind) or not x:
                return pa.array(x, kind)
            ends = np.cumsum([0, *map(len, x)]).astype(np.int32)
            return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(x), pa.int64()))

        return pa.table([column(x, k) for x, k in zip(out, kinds, strict=True)], names=names)

    def run(t: pa.Table) -> Iterator[pa.Table]:
        own = np.asarray(t.column("_own"))
        whole = lambda c, rows: np.asarray(pc.fill_null(t.column(c), 0)).astype(np.int64)[rows]
        given = lambda c, rows: np.asarray(t.column(c).is_valid())[rows]
        s_rid, s_dup, must, can = (whole(c, ~own) for c in (RID, DUP, "_m_lb", "_m_sg"))
        must, can = must >= 1, can > 0
        first, guess, last = (whole(f"p__{e}", ~own) for e in ("lb", "sg", "ub"))
        (vl, vg, vh), (okl, okg, okh) = ([f(f"v__{e}", ~own) for e in ("lb", "sg", "ub")] for f in (whole, given))
        place = {x: i for i, x in enumerate(zip(s_rid.tolist(), s_dup.tolist(), strict=True))}
        # Members that can push a bound, worst first: one order for the low, one for the high.
        lows, highs = np.argsort(vl, kind="stable"), np.argsort(-vh, kind="stable")
        if agg == "sum":
            lows, highs = lows[vl[lows] < 0], highs[vh[highs] > 0]
        lows, highs = lows[okl[lows]], highs[okh[highs]]

        def worst(order: np.ndarray, maybe: np.ndarray, v: np.ndarray) -> np.ndarray:
            if agg == "count":
                return v[:0]
            some = order[:512][maybe[order[:512]]]
            return v[some[:size] if len(some) >= size else order[maybe[order]][:size]]

        def total(rows: np.ndarray, ok: np.ndarray, v: np.ndarray) -> int | None:
            rows = rows[ok[rows]]
            return int(fold(v[rows])) if len(rows) else None

        out: list[list] = [[] for _ in names]
        held = 0
        ids = [whole(c, own).tolist() for c in (RID, DUP, "_m_sg", "p__lb", "p__sg", "p__ub")]
        for rid, dup, real, low, mid, high in zip(*ids, strict=True):
            sure = must & (first >= high + lo) & (last <= low + hi)
            maybe = (last >= low + lo) & (first <= high + hi)
            me = place.get((rid, dup))
            if me is not None:
                sure[me] = maybe[me] = inside
            maybe &= ~sure
            c = np.flatnonzero(sure)
            g = np.flatnonzero(can & (guess >= mid + lo) & (guess <= mid + hi)) if real > 0 else c[:0]
            if listed:
                p = np.flatnonzero(maybe)
                got = (vl[c[okl[c]]], vh[c[okh[c]]], vg[g[okg[g]]], vl[p[okl[p]]], vh[p[okh[p]]])
                n = len(p)
            else:
                got = (total(c, okl, vl), total(c, okh, vh), total(g, okg, vg), worst(lows, maybe, vl), worst(highs, maybe, vh))
                n = int(np.count_nonzero(maybe))
            for column, x in zip(out, (rid, dup, len(c), n, len(g), *got), strict=True):
                column.append(x)
            held += sum(map(len, got)) if listed else 0
            if held > VALUES:
                yield made(out)
                out, held = [[] for _ in names], 0
        yield made(out)

    return run


def gathered(dealt: DataFrame, on: Sequence[str], agg: str, lo: int, hi: int) -> DataFrame:
    """(RID, DUP, _nc, _np, _ng, _cl, _ch, _g, _pl, _ph) of each owner: the parts of all its blocks together."""
    by = [*on, *[c for c in ("_b", "_o", "_s") if c in dealt.columns]]
    compare = _compare(agg, lo, hi, False)

    def run(t: pa.Table) -> pa.Table:
        return next(compare(t))

    parts = dealt.groupBy(*by).applyInArrow(run, PARTS)
    fold = {"min": F.min, "max": F.max}.get(agg, F.sum)
    got = parts.groupBy(RID, DUP).agg(*[F.sum(c).alias(c) for c in ("_nc", "_np", "_ng")], *[fold(c).alias(c) for c in ("_cl", "_ch", "_g")], *[F.flatten(F.collect_list(c)).alias(c) for c in ("_pl", "_ph")])
    if agg in ("min", "max"):
        low, high = F.array_min("_pl"), F.array_max("_ph")
        got = got.withColumns({"_least": low, "_most": high, "_pl": low, "_ph": high})
    return got


def listed(dealt: DataFrame, on: Sequence[str], lo: int, hi: int) -> DataFrame:
    """The same columns with whole lists of values, for registered aggregates."""
    compare = _compare("", lo, hi, True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in compare(pa.Table.from_batches(list(batches))):
            yield from part.combine_chunks().to_batches()

    return dealt.groupBy(*on, "_b", "_o", "_s").applyInArrow(run, LISTS)
