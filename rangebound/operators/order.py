"""Sorting as data: each row's range of positions, and top-k as a selection on it.

A row's low position counts rows certainly before it, its high position rows possibly before it.
A row is certainly before another if its high corner precedes the other's low corner, possibly if
its low corner precedes the other's high corner. The order goes on to the remaining attributes and
the row id, so corners never tie.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.expr import Triple, rlit, rlex_lt, rlt
from ..plans.joins import by_sort
from ..plans.prefix import bucket_count, join_null_safe, ordered, running_sums, splitters, with_bucket
from ..schema import DUP, MULT, RID, Attr, RangeFrame

METHODS = ("auto", "naive", "rewrite", "onepass", "dist", "cdf")


@dataclass(frozen=True)
class RankSpec:
    """keys: attributes in order; desc: those of them that descend; partition: certain attributes;
    compare: form of the comparison; ties: whether the remaining attributes break ties before the row id does."""

    keys: tuple[str, ...]
    desc: tuple[str, ...] = ()
    partition: tuple[str, ...] = ()
    compare: str = "corner"
    ties: bool = True


def _reverse(c: Column, kind: str) -> Column:
    if kind in ("tinyint", "smallint", "int", "bigint", "float", "double", "boolean") or kind.startswith("decimal"):
        return -(c.cast("int") if kind == "boolean" else c.cast("bigint") if kind in ("tinyint", "smallint", "int", "bigint") else c)
    if kind == "date":
        return -F.unix_date(c).cast("bigint")
    if kind.startswith("timestamp"):
        return -F.unix_micros(c.cast("timestamp"))
    raise ValueError(f"a {kind} key can't descend here; add a column that does")


def order_keys(rf: RangeFrame, spec: RankSpec) -> list[Triple]:
    """Ascending triples: the keys, then the remaining attributes, then the row id."""
    kinds = dict(rf.df.dtypes)
    out = []
    for k in spec.keys:
        t = rf.c(k)
        out.append(t.down(lambda c, k=k: _reverse(c, kinds[rf.attr(k).columns[0]])) if k in spec.desc else t)
    if spec.ties:
        skip = ("array", "map", "struct", "variant", "binary")
        out += [rf.c(a.name) for a in rf.attrs if a.name not in spec.keys and a.name not in spec.partition and not kinds[a.columns[0]].startswith(skip)]
    return [*out, *[rlit(F.col(i)) for i in rf.ids]]


def corners(rf: RangeFrame, spec: RankSpec) -> DataFrame:
    """(ids, partition, multiplicities, _lo, _sg, _hi): the row's corners as structs that compare as the order does."""
    keys = order_keys(rf, spec)
    end = lambda e: F.struct(*[getattr(k, e).alias(f"k{i}") for i, k in enumerate(keys)])
    return rf.df.select(*rf.ids, *spec.partition, *MULT, end("lb").alias("_lo"), end("sg").alias("_sg"), end("ub").alias("_hi"))


def _events(rows: DataFrame, ids: Sequence[str], partition: Sequence[str]) -> DataFrame:
    """Starts (weight: most copies) at low corners, ends (least copies) at high ones, and guesses;
    a row that is certain has one event for all three. `own` is what a row must not count of itself."""
    zero = F.lit(0).cast("long")

    def event(point: str, start: Column, end: Column, guess: Column, own: Column, kind: int) -> Column:
        return F.struct(F.col(point).alias("point"), start.alias("w_start"), end.alias("w_end"), guess.alias("w_guess"), own.alias("own"), F.lit(kind).alias("kind"))

    m_lb, m_sg, m_ub = (F.col(c) for c in MULT)
    one = F.array(event("_lo", m_ub, m_lb, m_sg, zero, 0))
    three = F.array(event("_lo", m_ub, zero, zero, zero, 1), event("_sg", zero, zero, m_sg, zero, 2), event("_hi", zero, m_lb, zero, m_ub, 3))
    return rows.select(*ids, *partition, F.explode(F.when(F.col("_lo") == F.col("_hi"), one).otherwise(three)).alias("e")).select(*ids, *partition, "e.*")


def _paired(summed: DataFrame, ids: Sequence[str]) -> DataFrame:
    k = F.col("kind")
    return summed.groupBy(*ids).agg(
        F.max(F.when(k <= 1, F.col("s_end"))).alias("_p_lb"),
        F.max(F.when((k == 0) | (k == 2), F.col("s_guess"))).alias("_p_sg"),
        F.max(F.when((k == 0) | (k == 3), F.col("s_start") - F.col("own"))).alias("_p_ub"),
    )


def _kinds(rows: DataFrame, column: str) -> list[str]:
    return [f.dataType.simpleString() for f in rows.schema[column].dataType.fields]


SUMS = {"s_end": "w_end", "s_start": "w_start", "s_guess": "w_guess"}


def _dist(rows: DataFrame, ids: Sequence[str], partition: Sequence[str], buckets: int | None) -> DataFrame:
    cuts = splitters(rows, "_lo", RID, bucket_count(rows, buckets))
    ev = with_bucket(_events(rows, ids, partition), "point", cuts, _kinds(rows, "_lo"))
    return _paired(running_sums(ev, ["_b"], ["point", "kind"], SUMS, partition), ids)


def _cdf(rows: DataFrame, ids: Sequence[str], partition: Sequence[str], buckets: int | None) -> DataFrame:
    """For keys of few values, without splitters of rows: a bucket is a value of the keys and a stretch of row ids, so
    that a hot value is dealt out too. The sums at a bucket's start are running sums over the distinct buckets."""
    n_keys = len(_kinds(rows, "_lo")) - len(ids)
    span = rows.agg(F.min(RID), F.max(RID)).first()
    wide = max(1.0, ((span[1] or 0) - (span[0] or 0) + 1) / bucket_count(rows, buckets))
    stretch = F.floor((F.col(f"point.k{n_keys}").cast("double") - float(span[0] or 0)) / wide)
    ev = _events(rows, ids, partition).withColumns({f"_v{i}": F.col(f"point.k{i}") for i in range(n_keys)} | {"_s": stretch})
    return _paired(running_sums(ev, [*[f"_v{i}" for i in range(n_keys)], "_s"], ["point", "kind"], SUMS, partition, many=True), ids)


def _rewrite(rows: DataFrame, ids: Sequence[str], partition: Sequence[str]) -> DataFrame:
    """Classical plan: union of end points, one window over all of them, regrouping."""
    zero = F.lit(0).cast("long")
    base = [*ids, *partition]
    starts = rows.select(*base, F.col("_lo").alias("point"), F.lit(1).alias("kind"), F.col("_m_ub").alias("w_start"), zero.alias("w_end"), zero.alias("w_guess"), zero.alias("own"))
    guesses = rows.select(*base, F.col("_sg").alias("point"), F.lit(2).alias("kind"), zero.alias("w_start"), zero.alias("w_end"), F.col("_m_sg").alias("w_guess"), zero.alias("own"))
    ends = rows.select(*base, F.col("_hi").alias("point"), F.lit(3).alias("kind"), zero.alias("w_start"), F.col("_m_lb").alias("w_end"), zero.alias("w_guess"), F.col("_m_ub").alias("own"))
    w = W.partitionBy(*partition).orderBy("point", "kind").rowsBetween(W.unboundedPreceding, -1)
    return _paired(starts.unionByName(guesses).unionByName(ends).withColumns({n: F.coalesce(F.sum(c).over(w), zero) for n, c in SUMS.items()}), ids)


def _naive(rows: DataFrame, rf: RangeFrame, spec: RankSpec) -> DataFrame:
    """Every pair of rows is compared."""
    t = rows.select(*[F.col(c).alias(f"t_{c}") for c in rows.columns])
    other = [F.col(i) != F.col(f"t_{i}") for i in rf.ids]
    differ = other[0] if len(other) == 1 else other[0] | other[1]
    for p in spec.partition:
        differ = differ & F.col(p).eqNullSafe(F.col(f"t_{p}"))
    pairs = t.join(rows, differ, "left")
    if spec.compare == "corner":
        sure, guess, maybe = F.col("_hi") < F.col("t__lo"), F.col("_sg") < F.col("t__sg"), F.col("_lo") < F.col("t__hi")
    else:
        n = len(rows.schema["_lo"].dataType.fields)
        part = lambda pre: [Triple(*(F.col(f"{pre}{e}.k{i}") for e in ("_lo", "_sg", "_hi"))) for i in range(n)]
        got = rlex_lt(part(""), part("t_"), spec.compare)
        sure, guess, maybe = got.lb, got.sg, got.ub
    count = lambda cond, m: F.coalesce(F.sum(F.when(cond, F.col(m))), F.lit(0)).cast("long")
    got = pairs.groupBy(*[f"t_{i}" for i in rf.ids]).agg(count(sure, "_m_lb").alias("_p_lb"), count(guess, "_m_sg").alias("_p_sg"), count(maybe, "_m_ub").alias("_p_ub"))
    return got.select(*[F.col(f"t_{i}").alias(i) for i in rf.ids], "_p_lb", "_p_sg", "_p_ub")


def sweep_positions(rows: list[tuple], before_end: int = 0, before_start: int = 0, pending: list[tuple] = (), stop_at: int | None = None) -> Iterator[tuple]:
    """One pass over (low corner, high corner, m_lb, m_ub, id) by low corner, with a heap of rows
    whose high corner has not been passed. Yields (id, low, high) with None for the bound that is
    not known in this bucket; pending: (high corner, m_lb, m_ub, id) of rows that began before.

    With stop_at = k, the pass ends when k rows are certainly before the next; rows that wait then get
    k as their high position."""
    wait = [(hi, m_lb, m_ub, rid, None) for hi, m_lb, m_ub, rid in pending]
    heapq.heapify(wait)
    end_sum, start_sum = before_end, before_start
    for lo, hi, m_lb, m_ub, rid in rows:
        while wait and wait[0][0] < lo:
            _, e_lb, e_ub, e_rid, low = heapq.heappop(wait)
            yield e_rid, low, start_sum - e_ub
            end_sum += e_lb
        if stop_at is not None and end_sum >= stop_at:
            for _, _, _, e_rid, low in wait:
                yield e_rid, low, stop_at
            return
        start_sum += m_ub
        heapq.heappush(wait, (hi, m_lb, m_ub, rid, end_sum))
    while wait:
        _, e_lb, e_ub, e_rid, low = heapq.heappop(wait)
        yield e_rid, low, start_sum - e_ub
        end_sum += e_lb


def _onepass(rows: DataFrame, ids: Sequence[str], partition: Sequence[str], buckets: int | None) -> DataFrame:
    """The sweep, bucket by bucket: each starts from the sums of those before it, and takes over the
    rows that began before and end in it. The guess comes from running sums."""
    cuts = splitters(rows, "_lo", RID, bucket_count(rows, buckets))
    kinds = _kinds(rows, "_lo")
    placed = with_bucket(with_bucket(rows, "_lo", cuts, kinds), "_hi", cuts, kinds, "_h")
    part = list(partition)
    base = [*ids, *part, "_lo", "_hi", "_m_lb", "_m_ub"]
    here = placed.select(*base, F.col("_b"), F.lit(True).alias("own"), (F.col("_h") > F.col("_b")).alias("leaves"))
    later = placed.where("_h > _b").select(*base, F.col("_h").alias("_b"), F.lit(False).alias("own"), F.lit(False).alias("leaves"))
    both = here.unionByName(later)
    totals = both.groupBy(*part, "_b").agg(F.sum(F.when(F.col("own"), F.col("_m_ub")).otherwise(0)).alias("s"), F.sum(F.when(~F.col("leaves"), F.col("_m_lb")).otherwise(0)).alias("e"))
    before = W.partitionBy(*part).orderBy("_b").rowsBetween(W.unboundedPreceding, -1)
    sums = totals.select(*part, "_b", F.coalesce(F.sum("s").over(before), F.lit(0)).alias("s0"), F.coalesce(F.sum("e").over(before), F.lit(0)).alias("e0"))
    names = list(ids)

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        key = lambda v: ordered(v.values() if isinstance(v, dict) else v)
        keys = list(zip(*[pdf[i] for i in names], strict=True))
        own, pend = [], []
        for lo, hi, a, b, mine, rid in zip(pdf["_lo"], pdf["_hi"], pdf["_m_lb"], pdf["_m_ub"], pdf["own"], keys, strict=True):
            if mine:
                own.append((key(lo), key(hi), a, b, rid))
            else:
                pend.append((key(hi), a, b, rid))
        own.sort()
        out = []
        leaves = dict(zip(keys, pdf["leaves"], strict=True))
        for rid, low, high in sweep_positions(own, int(pdf["e0"].iloc[0]), int(pdf["s0"].iloc[0]), pend):
            out.append((*rid, low, None if leaves[rid] else high))
        frame = pd.DataFrame(out, columns=[*names, "low", "high"])
        return frame.astype({"low": "Int64", "high": "Int64"})

    schema = ", ".join([f"{i} long" if i == RID else f"{i} int" for i in names] + ["low long", "high long"])
    got = join_null_safe(both, sums, [*part, "_b"]).groupBy(*part, "_b").applyInPandas(sweep, schema)
    bounds = got.groupBy(*names).agg(F.max("low").alias("_p_lb"), F.max("high").alias("_p_ub"))
    zero = F.lit(0).cast("long")
    ev = with_bucket(rows.select(*ids, *part, F.col("_sg").alias("point"), F.col("_m_sg").alias("w"), zero.alias("kind")), "point", cuts, kinds)
    guess = running_sums(ev, ["_b"], ["point"], {"_p_sg": "w"}, part).select(*names, "_p_sg")
    return bounds.join(guess, names)


def _one_range(rf: RangeFrame, spec: RankSpec) -> bool:
    """Whether the first key alone may be a range."""
    rest = [*spec.keys[1:], *([a.name for a in rf.attrs if a.name not in spec.keys and a.name not in spec.partition] if spec.ties else [])]
    return bool(spec.keys) and all(rf.attr(k).certain for k in rest)


def _attributewise(rows: DataFrame, ids: Sequence[str], partition: Sequence[str], buckets: int | None) -> DataFrame:
    """Keys of which the first alone may be a range. Guesses and high positions are those of corners. A low position
    counts what ends below the row's low value and, for rows that are points, the points of that value before it: so at
    a value ranges begin first, then come points in their order, then ranges end."""
    names = [f.name for f in rows.schema["_lo"].dataType.fields]

    def end(c: str, side: int) -> Column:
        at = F.when(F.col("_lo.k0").eqNullSafe(F.col("_hi.k0")), F.lit(1)).otherwise(F.lit(side))
        return F.struct(F.col(f"{c}.k0").alias("k0"), at.alias("k1"), *[F.col(f"{c}.{n}").alias(f"k{i}") for i, n in enumerate(names[1:], 2)])

    flagged = rows.select(*ids, *partition, *MULT, end("_lo", 0).alias("_lo"), end("_lo", 0).alias("_sg"), end("_hi", 2).alias("_hi"))
    low = _dist(flagged, ids, partition, buckets).select(*ids, "_p_lb")
    return _dist(rows, ids, partition, buckets).drop("_p_lb").join(low, list(ids)).select(*ids, "_p_lb", "_p_sg", "_p_ub")


def rank_weighted(rf: RangeFrame, spec: RankSpec, method: str = "auto", buckets: int | None = None) -> DataFrame:
    """(ids, _p_lb, _p_sg, _p_ub): positions of box rows, before copies are split."""
    if method not in METHODS:
        raise ValueError(f"method is one of {METHODS}")
    if spec.compare != "corner" and method not in ("auto", "naive"):
        raise ValueError("the attribute-wise comparison has no total order of corners; only naive and auto count it")
    rows = corners(rf, spec)
    if spec.compare == "attributewise" and method == "auto" and _one_range(rf, spec):
        return _attributewise(rows, rf.ids, spec.partition, buckets)
    if method == "naive" or spec.compare != "corner":
        return _naive(rows, rf, spec)
    if method == "rewrite":
        return _rewrite(rows, rf.ids, spec.partition)
    if method == "cdf":
        return _cdf(rows, rf.ids, spec.partition, buckets)
    if method == "onepass":
        return _onepass(rows, rf.ids, spec.partition, buckets)
    return _dist(rows, rf.ids, spec.partition, buckets)


def rank(rf: RangeFrame, keys: Sequence[str], desc: Sequence[str] = (), partition: Sequence[str] = (), method: str = "auto", compare: str = "corner", into: str = "pos", ties: bool = True, limit: int | None = None, buckets: int | None = None) -> RangeFrame:
    """Adds each row's range of positions as an attribute. The result has a row for each possible
    copy (at most `limit` of a row)."""
    spec = RankSpec(tuple(keys), tuple(desc), tuple(partition), compare, ties)
    placed = rf.with_df(rf.df.join(by_sort(rank_weighted(rf, spec, method, buckets)), list(rf.ids)))
    was_unit = rf.unit
    out = placed.split(limit)
    dup = F.lit(0) if was_unit else F.col(DUP).cast("long")
    attrs = (*rf.attrs, Attr(into, False))
    df = out.df.withColumns({f"{into}__{e}": F.col(f"_p_{e}") + dup for e in ("lb", "sg", "ub")})
    got = RangeFrame(df, attrs, True)
    return got.with_df(df.select(*got.columns))


def select_positions(rf: RangeFrame, low: int, high: int, into: str = "pos", cap: bool = True) -> RangeFrame:
    """Rows whose position may lie in [low, high)."""
    pos = rf.c(into)
    above, below = rlt(pos, rlit(high)), Triple(pos.lb >= low, pos.sg >= low, pos.ub >= low)
    t = Triple(above.lb & below.lb, above.sg & below.sg, above.ub & below.ub)
    df = rf.df.where(t.ub).withColumns({m: F.when(c, F.col(m)).otherwise(F.lit(0).cast("long")) for m, c in zip(MULT, (t.lb, t.sg, t.ub), strict=True)})
    if cap:
        df = df.withColumn(f"{into}__ub", F.least(F.col(f"{into}__ub"), F.lit(high).cast("long"))).withColumn(f"{into}__sg", F.least(F.col(f"{into}__sg"), F.lit(high).cast("long")))
    return rf.with_df(df)


#: Most rows that a cut reads to the driver; beyond, it is found by running sums.
CUT_ROWS = 10_000


def cut(rf: RangeFrame, spec: RankSpec, k: int) -> tuple | None:
    """High corner at which k rows are certain; None where fewer than k are certain."""
    sure = corners(rf, spec).where("_m_lb > 0").select(RID, "_hi", "_m_lb")
    if k <= CUT_ROWS:
        n = 0
        for r in sure.select("_hi", "_m_lb").orderBy("_hi").limit(k).collect():
            n += r["_m_lb"]
            if n >= k:
                return tuple(r["_hi"])
        return None
    cuts = splitters(sure, "_hi", RID, bucket_count(sure))
    got = running_sums(with_bucket(sure, "_hi", cuts, _kinds(sure, "_hi")), ["_b"], ["_hi"], {"before": "_m_lb"})
    at = got.where((F.col("before") < k) & (F.col("before") + F.col("_m_lb") >= k)).select("_hi").first()
    return None if at is None else tuple(at[0])


def prune(rf: RangeFrame, spec: RankSpec, k: int) -> RangeFrame:
    """Only rows that may be among the first k: those whose low corner isn't after the cut. The
    bound on the first key is a plain comparison, which reaches the scan."""
    at = cut(rf, spec, k)
    if at is None:
        return rf
    keys = order_keys(rf, spec)
    kinds = _kinds(corners(rf, spec), "_lo")
    lits = [F.lit(v).cast(t) for v, t in zip(at, kinds, strict=True)]
    low = F.struct(*[x.lb.alias(f"k{i}") for i, x in enumerate(keys)])
    first = rf.c(spec.keys[0])
    kind = dict(rf.df.dtypes)[rf.attr(spec.keys[0]).columns[0]]
    plain = first.ub >= -lits[0] if spec.keys[0] in spec.desc and kind in ("int", "bigint", "double") else keys[0].lb <= lits[0]
    if at[0] is not None:  # nulls come first
        rf = rf.with_df(rf.df.where(plain | first.lb.isNull() | first.ub.isNull()))
    return rf.with_df(rf.df.where(low <= F.struct(*[x.alias(f"k{i}") for i, x in enumerate(lits)])))


def _topk_onepass(rf: RangeFrame, spec: RankSpec, k: int) -> DataFrame:
    """The sweep over what the cut lets through, at most the rows that overlap the first k certain ones: the cut
    is where the sweep of a whole input would stop, and rows that wait there end at position k at most."""
    got = _onepass(corners(prune(rf, spec, k), spec), rf.ids, (), None)
    return got.withColumn("_p_ub", F.least(F.col("_p_ub"), F.lit(k).cast("long")))


def topk(rf: RangeFrame, keys: Sequence[str], k: int, desc: Sequence[str] = (), offset: int = 0, method: str = "auto", cap: bool = True, ties: bool = True) -> RangeFrame:
    """Rows that may be at positions offset to offset + k - 1; those that certainly are keep m_lb = 1.
    select: ranks all rows. prune: ranks what the cut lets through. onepass: the sweep with early stop.
    Nulls come first, ascending and descending."""
    spec = RankSpec(tuple(keys), tuple(desc), (), "corner", ties)
    most = offset + k
    if k <= 0:
        got = rank(rf, keys, desc, ties=ties)
        return got.with_df(got.df.where(F.lit(False)))
    if method == "select":
        ranked = rank(rf, keys, desc, ties=ties, limit=most)
    elif method == "onepass":
        placed = rf.with_df(rf.df.join(_topk_onepass(rf, spec, most), list(rf.ids)))
        out = placed.split(most)
        df = out.df.withColumns({f"pos__{e}": F.col(f"_p_{e}") + (F.lit(0) if rf.unit else F.col(DUP).cast("long")) for e in ("lb", "sg", "ub")})
        ranked = RangeFrame(df, (*rf.attrs, Attr("pos", False)), True)
        ranked = ranked.with_df(df.select(*ranked.columns))
    else:
        ranked = rank(prune(rf, spec, most), keys, desc, ties=ties, limit=most)
    return select_positions(ranked, offset, most, cap=cap)
