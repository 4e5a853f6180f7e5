"""What overlaps a range, summarised: how many members there are, and the few of least low and of greatest high value.

A window of uncertain position may meet very many members, yet its bounds take only as many as it has slots. Members that begin
within an owner's range of positions overlap it. Such a range is two pieces within a chunk of 1,024 positions, split where its ends
first differ as binary numbers: a stretch up to the end of a block and one from the start of the next. Over several chunks it is the
rest of the first, the start of the last, and a range of whole chunks, likewise. Each piece is a running summary, made chunk by chunk.
Members that began before the owner's range and end in it or after it overlap it, too: their spans are split alike, and the owner's
first position adds up the pieces it lies in. The two kinds are disjoint and are all that overlap; no rows are paired, so that many
that begin or end at one position cost no more than others.

A row makes two pieces for each size of chunk, whatever its range; pairs would follow n times the width of ranges.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .joins import by_sort
from .prefix import join_null_safe

FAN = 4
#: Cells of a chunk are 2^BITS. Pieces below that have the level of their block; FROM and UPTO are those that cut a whole chunk.
BITS = 10
FROM, UPTO = BITS, BITS + 1


def _top(lists: Column, k: int, low: bool) -> Column:
    return F.slice(F.sort_array(lists, asc=low), 1, k)


def _merge(df: DataFrame, keys: Sequence[str], k: int) -> DataFrame:
    """Summaries (n, low, high) of each key; lists of k at most."""
    got = df.groupBy(*keys).agg(F.sum("n").alias("n"), F.flatten(F.collect_list("low")).alias("low"), F.flatten(F.collect_list("high")).alias("high"))
    return got.withColumns({"low": _top(F.col("low"), k, True), "high": _top(F.col("high"), k, False)})


def _at_level(nodes: Column, level: int) -> Column:
    return F.transform(nodes, lambda x: F.struct(F.lit(level).alias("level"), x.alias("node")))


def _cover(first: Column, last: Column, levels: int) -> Column:
    """Nodes (level, node) that cover the cells first to last: at each level what doesn't fill a node of the next."""
    nodes = []
    some = lambda a, b: F.when(a < b, F.sequence(a, b - 1)).otherwise(F.array().cast("array<bigint>"))
    for level in range(levels + 1):
        # [lo, hi), from the cells and not from the level below, so that the expression stays small; once all is covered it
        # is empty at each level above.
        lo, hi = F.ceil(first / FAN**level), F.floor((last + 1) / FAN**level)
        up, down = F.ceil(first / FAN ** (level + 1)), F.floor((last + 1) / FAN ** (level + 1))
        if level == levels:
            here = some(lo, hi)
        else:
            here = F.when(up >= down, some(lo, hi)).otherwise(F.concat(some(lo, up * FAN), some(down * FAN, hi)))
        nodes.append(_at_level(here, level))
    return F.concat(*nodes)


def tiers_for(cells: int) -> int:
    """Sizes of chunks so that the largest holds all cells."""
    n = 1
    while cells > 1 << BITS * n:
        n += 1
    return n


def _pieces(first: Column, last: Column, tiers: int) -> Column:
    """Pieces (tier, level, cell) of the cells first to last (none if last is before first); cells of a tier are chunks of the one below."""
    shift = lambda x, n: F.call_function("shiftright", x, F.lit(n))
    piece = lambda tier, level, cell: F.struct(F.lit(tier).alias("tier"), level.cast("int").alias("level"), cell.alias("cell"))
    none = F.array().cast("array<struct<tier:int,level:int,cell:bigint>>")
    out = []
    for t in range(tiers):
        # The first and last cells of this tier, from the cells: each tier above takes one off at both ends.
        a, b = first, last
        for _ in range(t):
            a, b = shift(a, BITS) + 1, shift(b, BITS) - 1
        differ = F.length(F.bin(a.bitwiseXOR(b))) - 1
        inside = F.when(a == b, F.array(piece(t, F.lit(0), a))).otherwise(F.array(piece(t, differ, a), piece(t, differ, b)))
        over = F.array(piece(t, F.lit(FROM), a), piece(t, F.lit(UPTO), b))
        out.append(F.when(a > b, none).when(shift(a, BITS) == shift(b, BITS), inside).otherwise(over))
    return F.concat(*out)


def _running(x: np.ndarray, size: int, back: bool, k: int) -> np.ndarray:
    """At each cell the k least ranks from the start of its block up to it (back: from it to the end of its block)."""
    x = x.reshape(-1, size, k)
    x = x[:, ::-1] if back else x
    step = 1
    while step < size:
        x = np.concatenate([x[:, :step], np.sort(np.concatenate([x[:, step:], x[:, :-step]], 2), 2)[:, :, :k]], 1)
        step *= 2
    return (x[:, ::-1] if back else x).reshape(-1, k)


def _counted(n: np.ndarray, size: int, back: bool) -> np.ndarray:
    n = n.reshape(-1, size)
    return (np.cumsum(n[:, ::-1], 1)[:, ::-1] if back else np.cumsum(n, 1)).reshape(-1)


def _run(x: np.ndarray, level: int, begun: bool, run: Callable) -> np.ndarray:
    """Running summaries of the blocks of a level. begun: the piece that a cell starts or ends; else what the pieces put at cells
    give to each cell they cover."""
    if level >= BITS:
        return run(x, len(x), (level == FROM) == begun)
    # A cell in the left block of a pair starts a piece that goes to the end of the block; one in the right block ends one.
    halves = x.reshape(-1, 2, 1 << level, *x.shape[1:])
    both = [run(halves[:, i].reshape(-1, *x.shape[1:]), 1 << level, (i == 0) == begun) for i in (0, 1)]
    return np.stack([y.reshape(halves[:, 0].shape) for y in both], 1).reshape(x.shape)


def _chunk(k: int, begun: bool, names: Sequence[str]) -> Callable[[pa.Table], pa.Table]:
    """The asked summaries of one chunk, from those of its cells."""
    cells = 1 << BITS

    def run(t: pa.Table) -> pa.Table:
        asks, rows = t.filter(t.column("_asks")), t.filter(pc.invert(t.column("_asks")))
        at, level = (np.asarray(asks.column(c)).astype(np.int64) for c in ("cell", "level"))
        at &= cells - 1
        put, put_level = (np.asarray(rows.column(c)).astype(np.int64) for c in ("cell", "level"))
        put &= cells - 1
        levels = np.unique(level) if begun else np.unique(put_level)
        n, counts = np.zeros(len(at), np.int64), np.asarray(rows.column("n")).astype(np.int64)

        def each(fill: Callable, run: Callable, add: Callable) -> None:
            for one in levels:
                x = _run(fill(slice(None) if begun else put_level == one), int(one), begun, run)
                some = level == one if begun else np.ones(len(at), bool)
                add(some, x[at[some]])

        def cell_counts(some) -> np.ndarray:
            x = np.zeros(cells, np.int64)
            np.add.at(x, put[some], counts[some])
            return x

        def add_counts(some: np.ndarray, x: np.ndarray) -> None:
            n[some] += x

        each(cell_counts, _counted, add_counts)
        lists = []
        for name, way in (("low", "ascending"), ("high", "descending")):
            column = rows.column(name).combine_chunks()
            column = column if isinstance(column, pa.ListArray) else pa.concat_arrays(column.chunks)
            values, parent = column.flatten(), np.asarray(pc.list_parent_indices(column))
            if not len(values):
                lists.append(pa.array([[]] * len(at), column.type))
                continue
            order = np.asarray(pc.sort_indices(pa.table({"v": values.field("v")}), sort_keys=[("v", way)])).astype(np.int64)
            rank = np.empty(len(order), np.int64)
            rank[order] = np.arange(len(order))
            place = np.arange(len(parent)) - np.asarray(column.value_lengths()).cumsum()[parent] + np.asarray(column.value_lengths())[parent]
            no = len(order)
            best = np.full((len(at), k), no)

            def cell_lists(some, rank=rank, parent=parent, place=place, no=no) -> np.ndarray:
                x = np.full((cells, k), no)
                mine = np.ones(len(parent), bool) if isinstance(some, slice) else some[parent]
                x[put[parent[mine]], place[mine]] = rank[mine]
                return np.sort(x, 1)

            def add_lists(some: np.ndarray, x: np.ndarray, best=best) -> None:
                best[some] = np.sort(np.concatenate([best[some], x], 1), 1)[:, :k]

            each(cell_lists, lambda x, size, back: _running(x, size, back, k), add_lists)
            full = best < no
            offsets = pa.array(np.concatenate([[0], full.sum(1).cumsum()]).astype(np.int32))
            lists.append(pa.ListArray.from_arrays(offsets, values.take(pa.array(order[best[full]])), type=column.type))
        got = asks.select([c for c in names if c not in ("n", "low", "high")])
        for name, x in zip(("n", "low", "high"), (pa.array(n), *lists), strict=True):
            got = got.append_column(name, x)
        return got.filter(pa.array(n > 0))

    return run


def _asked(cells: DataFrame, asks: DataFrame, on: Sequence[str], k: int, begun: bool) -> DataFrame:
    """The summaries (n, low, high) of asked pieces (begun) or cells (on, tier, level, cell), chunk by chunk."""
    key = [*on, "tier", "level", "cell"]
    both = cells.select(*key, "n", "low", "high", F.lit(False).alias("_asks")).unionByName(asks.select(*key, F.lit(True).alias("_asks")), allowMissingColumns=True)
    both = both.withColumn("_chunk", F.call_function("shiftright", F.col("cell"), F.lit(BITS)))
    shape = dict(cells.dtypes)
    names = [*key, "n", "low", "high"]
    return both.groupBy(*on, "tier", "_chunk").applyInArrow(_chunk(k, begun, names), ", ".join(f"`{c}` {shape[c]}" for c in names))


def summaries(owners: DataFrame, members: DataFrame, ids: Sequence[str], on: Sequence[str], k: int, cells: int) -> DataFrame:
    """(ids, n, low, high) of the members that overlap each owner's range. members: n, low and high (arrays of one entry or none)
    and their range (_c0, _c1), from 0; owners: ids and range; cells: how many positions there may be."""
    on, tiers = list(on), tiers_for(cells + 1)
    key = [*on, "tier", "level", "cell"]
    up = lambda c: F.explode(F.array(*[F.struct(F.lit(t).alias("tier"), F.lit(0).alias("level"), F.call_function("shiftright", F.col(c), F.lit(BITS * t)).alias("cell")) for t in range(tiers)])).alias("x")
    owners = owners.select(*ids, *on, F.greatest(F.col("_c0"), F.lit(0).cast("long")).alias("_c0"), F.least(F.col("_c1"), F.lit(cells).cast("long")).alias("_c1"))  # nothing lies beyond
    # Members by the position at which they begin, then by its chunks.
    begun = _merge(members.select(*on, F.col("_c0").alias("node"), "n", "low", "high"), [*on, "node"], k)
    begun = _merge(begun.select(*on, up("node"), "n", "low", "high").select(*on, "x.*", "n", "low", "high"), key, k)
    asks = owners.select(*ids, *on, F.explode(_pieces(F.col("_c0"), F.col("_c1"), tiers)).alias("x")).select(*ids, *on, "x.*")
    inner = join_null_safe(asks, by_sort(_asked(begun, asks.select(*key).distinct(), on, k, True)), key).select(*ids, "n", "low", "high")
    # Members by the pieces of what follows their first position; an owner's first position adds up those it lies in.
    span = members.where("_c1 > _c0").select(*on, F.explode(_pieces(F.col("_c0") + 1, F.col("_c1"), tiers)).alias("x"), "n", "low", "high").select(*on, "x.*", "n", "low", "high")
    span = _merge(span, key, k)
    above = owners.select(*on, "_c0").distinct().select(*on, "_c0", up("_c0")).select(*on, "_c0", "x.*")
    across = join_null_safe(above, by_sort(_asked(span, above.select(*key).distinct(), on, k, False)), key).select(*on, "_c0", "n", "low", "high")
    across = _merge(across, [*on, "_c0"], k)
    outer = join_null_safe(owners.select(*ids, *on, "_c0"), by_sort(across), [*on, "_c0"]).select(*ids, "n", "low", "high")
    return _merge(inner.unionByName(outer), ids, k)
