"""Closure algebra: what range frames compose with besides order. Bounds hold for all operators."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.expr import Triple, rand, req, rlit
from ..plans.joins import overlap_pairs
from ..plans.prefix import bucket_count, join_null_safe, running_sums, splitters, with_bucket
from ..schema import DUP, MULT, RID, Attr, RangeFrame
from .order import RankSpec, corners, rank


def _scaled(rf_m: Triple, t: Triple) -> dict[str, Column]:
    zero = F.lit(0).cast("long")
    return {c: F.when(cond, m).otherwise(zero) for c, m, cond in zip(MULT, (rf_m.lb, rf_m.sg, rf_m.ub), (t.lb, t.sg, t.ub), strict=True)}


def select(rf: RangeFrame, cond: Triple) -> RangeFrame:
    """Multiplicities times the condition's truth; the possible condition is a filter that reaches the scan."""
    return rf.with_df(rf.df.where(cond.ub).withColumns(_scaled(rf.m, cond)).where("_m_ub > 0"))


def project(rf: RangeFrame, **exprs: Triple | str) -> RangeFrame:
    """New attributes from triples, or attributes by name; certain ones stay one column."""
    cols, attrs = [], []
    for name, e in exprs.items():
        if isinstance(e, str):
            a = rf.attr(e)
            attrs.append(Attr(name, a.certain))
            cols += [F.col(c).alias(n) for c, n in zip(a.columns, Attr(name, a.certain).columns, strict=True)]
        else:
            attrs.append(Attr(name, False))
            cols += e.alias(name)
    return RangeFrame(rf.df.select(*rf.ids, *cols, *MULT), tuple(attrs), rf.unit)


def widen(rf: RangeFrame, names: Sequence[str]) -> RangeFrame:
    """Certain attributes of that name become triples with equal ends."""
    return project(rf, **{a.name: (rf.c(a.name) if a.name in names and a.certain else a.name) for a in rf.attrs})


def union(a: RangeFrame, b: RangeFrame) -> RangeFrame:
    """Union all. A row's new id has its side in the last bit; ids below 2^62 stay unique, and hashed ones lose a bit."""
    mixed = [x.name for x in a.attrs if not x.certain or not b.attr(x.name).certain]
    a, b = widen(a, mixed), widen(b, mixed)
    sides = [x.df.withColumn(RID, F.shiftleft(RID, 1).bitwiseOR(F.lit(i).cast("long"))) for i, x in enumerate((a, b))]
    cols = [c for c in a.columns]
    return RangeFrame(sides[0].select(*cols).unionByName(sides[1].select(*cols)), a.attrs, a.unit)


def _aligned(rf: RangeFrame, prefix: str) -> RangeFrame:
    attrs = tuple(Attr(prefix + a.name, a.certain) for a in rf.attrs)
    cols = [F.col(c).alias(n) for a, x in zip(rf.attrs, attrs, strict=True) for c, n in zip(a.columns, x.columns, strict=True)]
    return RangeFrame(rf.df.select(F.col(RID).alias(f"{prefix}{RID}"), *cols, *[F.col(c).alias(f"{prefix}{c}") for c in MULT]), attrs)


def _soft_pairs(a: RangeFrame, r: RangeFrame, b: RangeFrame, on: Sequence[tuple[str, str]], prefix: str) -> tuple:
    """Pairs of a and r (b with the prefix) whose keys may be equal, and how sure that is. The first pair of uncertain
    keys, whole numbers, is joined by overlap; the others filter."""
    hard = [(x, y) for x, y in on if a.attr(x).certain and b.attr(y).certain]
    soft = [(x, y) for x, y in on if (x, y) not in hard]
    other = lambda y: Triple(*(F.col(f"{prefix}{c}") for c in (b.attr(y).columns * 3 if b.attr(y).certain else b.attr(y).columns)))
    x, y = soft[0]
    left = a.df.withColumns({"_l0": a.c(x).lb, "_l1": a.c(x).ub})
    right = r.df.withColumns({"_r0": other(y).lb, "_r1": other(y).ub})
    pairs = overlap_pairs(left, right, ("_l0", "_l1"), ("_r0", "_r1"))
    pairs = pairs.select(*[c for c in pairs.columns if not c.startswith("s_")], *[F.col(f"s_{c}").alias(c) for c in right.columns])
    for p, q in hard:
        pairs = pairs.where(F.col(p) == F.col(f"{prefix}{q}"))
    t = rand(*[req(a.c(p), other(q)) for p, q in soft])
    return pairs.where(t.ub), t


def _pair_rows(pairs: DataFrame, t: Triple, a: RangeFrame, r: RangeFrame, prefix: str, left: bool = False) -> RangeFrame:
    zero = F.lit(0).cast("long")
    ms = {}
    for c, ok in zip(MULT, (t.lb, t.sg, t.ub), strict=True):
        other = F.coalesce(F.col(f"{prefix}{c}"), F.lit(1).cast("long")) if left else F.col(f"{prefix}{c}")
        ms[c] = F.when(ok, F.col(c) * other).otherwise(zero)
    # One id for the pair; an explicit hash, as two ids don't fit one number.
    rid = F.xxhash64(*[F.col(i) for i in a.ids], F.col(f"{prefix}{RID}"))
    out = RangeFrame(pairs, (*a.attrs, *r.attrs))
    return out.with_df(pairs.withColumns(ms).withColumn(RID, rid).select(*out.columns))


def join(a: RangeFrame, b: RangeFrame, on: Sequence[tuple[str, str]], prefix: str = "r_", how: str = "inner") -> RangeFrame:
    """Equi join; attributes of b get the prefix. Certain keys join by equality, whole-number ranges where they overlap.
    Null keys meet nothing. how="left" keeps unmatched rows of a, with nulls for certain attributes of b (b's attributes
    must be certain then)."""
    r = _aligned(b, prefix)
    if all(a.attr(x).certain and b.attr(y).certain for x, y in on):
        pairs = a.df.join(r.df, [F.col(p) == F.col(f"{prefix}{q}") for p, q in on], how)
        return _pair_rows(pairs, rlit(F.lit(True)), a, r, prefix, how == "left")
    if how != "inner":
        raise ValueError("an uncertain key has an inner join only")
    pairs, t = _soft_pairs(a, r, b, on, prefix)
    return _pair_rows(pairs, t, a, r, prefix)


def theta_join(a: RangeFrame, b: RangeFrame, cond: Callable[[Callable[[str], Triple]], Triple] | None = None, prefix: str = "r_") -> RangeFrame:
    """All pairs that may meet a condition over the triples of both sides (cond gets a function from attribute names
    to triples); without one, the cross product. It compares all pairs: equal or overlapping keys belong in join.
    Rows of a are dealt by id to all cores, however few files they come from."""
    r = _aligned(b, prefix)
    dealt = a.df.repartition(4 * a.df.sparkSession.sparkContext.defaultParallelism, *a.ids)
    both = RangeFrame(dealt.crossJoin(r.df), (*a.attrs, *r.attrs))
    t = cond(both.c) if cond else rlit(F.lit(True))
    return _pair_rows(both.df.where(t.ub), t, a, r, prefix)


def semi_join(a: RangeFrame, b: RangeFrame, on: Sequence[tuple[str, str]], anti: bool = False) -> RangeFrame:
    """Rows of a with (anti: without) a match in b. A row certainly has one if some certain row of b certainly matches,
    possibly if some row may. Keys may be ranges; null keys have no match."""
    keys = [y for _, y in on]
    if all(a.attr(x).certain and b.attr(y).certain for x, y in on):
        seen = b.df.groupBy(*keys).agg(F.max(F.col("_m_lb") > 0).alias("_c"), F.max(F.col("_m_sg") > 0).alias("_g"))
        seen = seen.select(*[F.col(k).alias(f"_k_{k}") for k in keys], "_c", "_g", F.lit(True).alias("_p"))
        got = a.df.join(seen, [F.col(x) == F.col(f"_k_{y}") for x, y in on], "left")
    else:
        one = b.project(*dict.fromkeys(keys)).canonicalize()  # equal keys of b count once
        pairs, t = _soft_pairs(a, _aligned(one, "_r_"), one, on, "_r_")
        seen = pairs.groupBy(*a.ids).agg(F.max(t.lb & (F.col("_r__m_lb") > 0)).alias("_c"), F.max(t.sg & (F.col("_r__m_sg") > 0)).alias("_g")).withColumn("_p", F.lit(True))
        got = a.df.join(seen, list(a.ids), "left")
    t = Triple(*(F.coalesce(c, F.lit(False)) for c in ("_c", "_g", "_p")))
    if anti:
        t = Triple(~t.ub, ~t.sg, ~t.lb)
    df = got.withColumns(_scaled(a.m, t)).where("_m_ub > 0")
    return a.with_df(df.select(*a.columns))


def anti_join(a: RangeFrame, b: RangeFrame, on: Sequence[tuple[str, str]]) -> RangeFrame:
    return semi_join(a, b, on, anti=True)


def distinct(rf: RangeFrame) -> RangeFrame:
    """Distinct values. A row of certain values is there once at most; an uncertain row may hold several values,
    and is certain only if it overlaps no other row."""
    unsure = [a for a in rf.attrs if not a.certain]
    one = rf.canonicalize()
    if not unsure:
        return one.with_df(one.df.withColumns({c: F.least(F.col(c), F.lit(1).cast("long")) for c in MULT}))
    a = unsure[0].name
    keys = [x.name for x in rf.attrs if x.certain]
    left = one.df.withColumns({"_lo": F.col(f"{a}__lb"), "_hi": F.col(f"{a}__ub")})
    pairs = overlap_pairs(left.select(RID, *keys, "_lo", "_hi"), left.select(RID, *keys, "_lo", "_hi"), ("_lo", "_hi"), ("_lo", "_hi"))
    for k in keys:
        pairs = pairs.where(F.col(k).eqNullSafe(F.col(f"s_{k}")))
    met = pairs.groupBy(RID).agg(F.count(F.lit(1)).alias("_n"))
    point = F.col(f"{a}__lb") == F.col(f"{a}__ub")
    for x in unsure[1:]:
        point = point & (F.col(f"{x.name}__lb") == F.col(f"{x.name}__ub"))
    cap = lambda c: F.least(F.col(c), F.lit(1).cast("long"))
    # Rows that overlap can be equal to one another: only one that overlaps none is sure to be a value of its own.
    df = one.df.join(met, RID).withColumns({"_m_lb": F.when(point | (F.col("_n") == 1), cap("_m_lb")).otherwise(F.lit(0).cast("long")), "_m_sg": cap("_m_sg"), "_m_ub": F.when(point, cap("_m_ub")).otherwise(F.col("_m_ub"))})
    df = df.withColumn("_m_sg", F.greatest(F.col("_m_sg"), F.col("_m_lb")))
    return one.with_df(df.select(*one.columns))


def _weighted(t: Triple, m: Triple, agg: str) -> tuple[Column, Column, Column]:
    """Low, guess and high of an aggregate over a group's certain members (m.lb > 0 may be false)."""
    zero = F.lit(0).cast("long")
    if agg == "count":
        return F.sum(m.lb), F.sum(m.sg), F.sum(m.ub)
    if agg == "sum":
        return F.sum(F.least(t.lb * m.lb, t.lb * m.ub)), F.sum(t.sg * m.sg), F.sum(F.greatest(t.ub * m.lb, t.ub * m.ub))
    sure, some = m.lb > 0, m.ub > 0
    if agg == "min":
        return F.min(F.when(some, t.lb)), F.min(F.when(m.sg > 0, t.sg)), F.coalesce(F.min(F.when(sure, t.ub)), F.max(F.when(some, t.ub)))
    if agg == "max":
        return F.coalesce(F.max(F.when(sure, t.lb)), F.min(F.when(some, t.lb))), F.max(F.when(m.sg > 0, t.sg)), F.max(F.when(some, t.ub))
    if agg == "avg":
        # Sound hull of the mean: between the least and the greatest value a member may have.
        return F.min(F.when(some, t.lb)).cast("double"), F.sum(t.sg * m.sg) / F.nullif(F.sum(m.sg), zero), F.max(F.when(some, t.ub)).cast("double")
    raise ValueError(agg)


def aggregate(rf: RangeFrame, keys: Sequence[str], aggs: dict[str, tuple[str, str | None]], _into_key: str | None = None) -> RangeFrame:
    """Group by; aggs: new attribute -> (aggregate, attribute). Certain keys: one hash aggregate. One
    whole-number key may be a range: groups are those of the guessed keys, a group's key is the hull of its
    members', and rows that overlap it count as possible members."""
    soft = [k for k in keys if not rf.attr(k).certain]
    if len(soft) > 1:
        raise ValueError("one group key may be uncertain")
    ones = F.lit(1).cast("long")

    def measure(source, value_of, m: Triple, group: list[str]):
        cols = []
        for name, (agg, arg) in aggs.items():
            low, sg, high = _weighted(value_of(arg) if arg else rlit(ones), m, agg)
            cols += [low.alias(f"{name}__lb"), F.least(F.greatest(F.coalesce(sg, low), low), high).alias(f"{name}__sg"), high.alias(f"{name}__ub")]
        there = F.max((m.lb > 0).cast("long")), F.max((m.sg > 0).cast("long"))
        return source.groupBy(*group).agg(*cols, there[0].alias("_m_lb"), there[1].alias("_m_sg"))

    new = tuple(Attr(n, False) for n in aggs)
    if not soft:
        got = measure(rf.df, rf.c, rf.m, list(keys))
        got = got.withColumn("_m_ub", ones) if keys else got.withColumns({c: ones for c in MULT})
        got = got.withColumn("_m_sg", F.greatest("_m_sg", "_m_lb"))
        rid = F.xxhash64(*keys) if keys else F.lit(0).cast("long")
        out = RangeFrame(got, (*(Attr(k) for k in keys), *new))
        return out.with_df(got.withColumn(RID, rid).select(*out.columns))
    k = soft[0]
    hard = [x for x in keys if x != k]
    kt = rf.c(k)
    groups = rf.df.groupBy(*hard, F.col(f"{k}__sg").alias("_g")).agg(F.min(kt.lb).alias("_lo"), F.max(kt.ub).alias("_hi"))
    # What a row's low multiplicity may count on: only groups that hold its whole key range, alone.
    rows = rf.df.withColumns({"_r0": kt.lb, "_r1": kt.ub})
    pairs = overlap_pairs(groups, rows, ("_lo", "_hi"), ("_r0", "_r1"))
    for h in hard:
        pairs = pairs.where(F.col(h).eqNullSafe(F.col(f"s_{h}")))
    mine = F.col(f"s_{k}__sg") == F.col("_g")
    # Equal keys are sure only for a group whose hull is a point.
    sure = mine & (F.col("_lo") == F.col("_hi"))
    zero = F.lit(0).cast("long")
    m = Triple(F.when(sure, F.col("s__m_lb")).otherwise(zero), F.when(mine, F.col("s__m_sg")).otherwise(zero), F.col("s__m_ub"))
    value = lambda a: Triple(*(F.col(f"s_{c}") for c in (rf.attr(a).columns * 3 if rf.attr(a).certain else rf.attr(a).columns)))
    group = [*hard, "_g", "_lo", "_hi"]
    got = measure(pairs, value, m, group).join(rf.df.groupBy(*hard, F.col(f"{k}__sg").alias("_g")).agg(F.sum("_m_ub").alias("_m_ub")), [*hard, "_g"])
    # A group's rows may fall apart into as many groups as they are.
    got = got.withColumn("_m_ub", F.when(F.col("_lo") == F.col("_hi"), ones).otherwise(F.col("_m_ub"))).withColumn("_m_sg", F.greatest("_m_sg", "_m_lb"))
    got = got.withColumns({f"{k}__lb": F.col("_lo"), f"{k}__sg": F.col("_g"), f"{k}__ub": F.col("_hi"), RID: F.xxhash64(*hard, "_g")})
    out = RangeFrame(got, (*(Attr(h) for h in hard), Attr(k, False), *new))
    return out.with_df(got.select(*out.columns))


def grouping_sets(rf: RangeFrame, sets: Sequence[Sequence[str]], aggs: dict[str, tuple[str, str | None]]) -> RangeFrame:
    """Union of aggregates over certain keys; a key that a set leaves out is null."""
    every = list(dict.fromkeys(k for s in sets for k in s))
    kinds = dict(rf.df.dtypes)
    parts = []
    for i, s in enumerate(sets):
        got = aggregate(rf, list(s), aggs)
        df = got.df.withColumns({k: F.lit(None).cast(kinds[k]) for k in every if k not in s}).withColumn(RID, F.xxhash64(F.lit(i), F.col(RID)))
        out = RangeFrame(df, (*(Attr(k) for k in every), *(Attr(n, False) for n in aggs)))
        parts.append(out.with_df(df.select(*out.columns)))
    first = parts[0]
    for p in parts[1:]:
        first = first.with_df(first.df.unionByName(p.df))
    return first


def rollup(rf: RangeFrame, keys: Sequence[str], aggs: dict[str, tuple[str, str | None]]) -> RangeFrame:
    return grouping_sets(rf, [keys[:i] for i in range(len(keys), -1, -1)], aggs)


def cube(rf: RangeFrame, keys: Sequence[str], aggs: dict[str, tuple[str, str | None]]) -> RangeFrame:
    return grouping_sets(rf, [[k for i, k in enumerate(keys) if b >> i & 1] for b in range(2 ** len(keys) - 1, -1, -1)], aggs)


def _against(a: RangeFrame, b: RangeFrame) -> tuple:
    """By row of canonical a: what rows of b may, and what rows of b certainly do, equal it."""
    x, y = a.canonicalize(), b.canonicalize()
    soft = [n.name for n in x.attrs if not n.certain or not y.attr(n.name).certain]
    hard = [n.name for n in x.attrs if n.name not in soft]
    s = y.df.select(*[F.col(c).alias(f"s_{c}") for c in y.df.columns])
    if soft:
        k = soft[0]
        l_, r_ = x.c(k), y.c(k)
        pairs = overlap_pairs(x.df.withColumns({"_l0": l_.lb, "_l1": l_.ub}), y.df.withColumns({"_r0": r_.lb, "_r1": r_.ub}), ("_l0", "_l1"), ("_r0", "_r1"))
        for h in hard:
            pairs = pairs.where(F.col(h).eqNullSafe(F.col(f"s_{h}")))
    else:
        cond = F.lit(True)
        for h in hard:
            cond = cond & F.col(h).eqNullSafe(F.col(f"s_{h}"))
        pairs = x.df.join(s, cond)
    sure, maybe, guess = F.lit(True), F.lit(True), F.lit(True)
    for n in soft:
        tb = Triple(*(F.col(f"s_{c}") for c in (y.attr(n).columns * 3 if y.attr(n).certain else y.attr(n).columns)))
        t = req(x.c(n), tb)
        sure, guess, maybe = sure & t.lb, guess & t.sg, maybe & t.ub
    zero = F.lit(0).cast("long")
    got = pairs.groupBy(RID).agg(F.sum(F.when(maybe, F.col("s__m_ub")).otherwise(zero)).alias("_may"), F.sum(F.when(guess, F.col("s__m_sg")).otherwise(zero)).alias("_gs"), F.sum(F.when(sure, F.col("s__m_lb")).otherwise(zero)).alias("_must"))
    return x, x.df.join(got, RID, "left").fillna(0, ["_may", "_gs", "_must"])


def difference(a: RangeFrame, b: RangeFrame) -> RangeFrame:
    """Bag difference: at least what is left if all that may be equal is taken, at most what is left if
    only what certainly is."""
    x, df = _against(a, b)
    zero = F.lit(0).cast("long")
    low = F.greatest(zero, F.col("_m_lb") - F.col("_may"))
    high = F.greatest(zero, F.col("_m_ub") - F.col("_must"))
    sg = F.least(F.greatest(zero, F.col("_m_sg") - F.col("_gs"), low), high)
    df = df.withColumns({"_m_lb": low, "_m_sg": sg, "_m_ub": high}).where("_m_ub > 0")
    return x.with_df(df.select(*x.columns))


def intersect(a: RangeFrame, b: RangeFrame) -> RangeFrame:
    """Bag intersection, on certain rows exact; an uncertain row is only possible."""
    x, df = _against(a, b)
    high = F.least(F.col("_m_ub"), F.col("_may"))
    low = F.least(F.col("_m_lb"), F.col("_must"))
    sg = F.least(F.greatest(F.least(F.col("_m_sg"), F.col("_gs")), low), high)
    df = df.withColumns({"_m_lb": low, "_m_sg": sg, "_m_ub": high}).where("_m_ub > 0")
    return x.with_df(df.select(*x.columns))


def _smaller(rf: RangeFrame, keys: Sequence[str]) -> DataFrame:
    """(ids, n_lb, n_sg, n_ub, d_lb, d_sg, d_ub): rows, and distinct keys, that are smaller than a row's key for certain, by
    guess and possibly. Equal keys don't count. Weights are summed by distinct point, then along the order of points."""
    spec = RankSpec(tuple(keys), ties=False)
    rows = corners(rf, spec)
    n = len(keys)
    point = lambda c: F.struct(*[F.col(f"{c}.k{i}").alias(f"k{i}") for i in range(n)])
    rows = rows.select(*rf.ids, *MULT, point("_lo").alias("_lo"), point("_sg").alias("_sg"), point("_hi").alias("_hi"))
    sure = F.col("_lo") == F.col("_hi")
    zero = F.lit(0).cast("long")
    m_lb, m_sg, m_ub = (F.col(c) for c in MULT)

    def event(at: str, **weights: Column) -> Column:
        return F.struct(F.col(at).alias("at"), *[weights.get(w, zero).cast("long").alias(w) for w in ("low", "guess", "high", "sure", "point", "wide")])

    ends = F.array(event("_lo", high=m_ub, point=sure.cast("long"), wide=F.when(sure, zero).otherwise(m_ub)), event("_sg", guess=m_sg), event("_hi", low=m_lb, sure=(sure & (m_lb > 0)).cast("long")))
    at = rows.select(F.explode(ends).alias("e")).select("e.*").groupBy("at").agg(F.sum("low").alias("low"), F.sum("guess").alias("guess"), F.sum("high").alias("high"), F.max("sure").alias("d_sure"), F.max(F.least("guess", F.lit(1))).alias("d_guess"), F.max("point").alias("d_point"), F.sum("wide").alias("wide"))
    kinds = [f.dataType.simpleString() for f in at.schema["at"].dataType.fields]
    cuts = splitters(at.withColumn("_id", F.xxhash64("at")), "at", "_id", bucket_count(at))
    sums = running_sums(with_bucket(at, "at", cuts, kinds), ["_b"], ["at"], {f"s_{c}": c for c in ("low", "guess", "high", "d_sure", "d_guess", "d_point", "wide")})
    ask = rows.select(*rf.ids, sure.alias("_sure"), F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(c).alias("at")) for i, c in enumerate(("_lo", "_sg", "_hi"))])).alias("q")).select(*rf.ids, "_sure", "q.*")
    of = lambda i, c: F.max(F.when(F.col("i") == i, F.col(c)))
    own = (~F.col("_sure")).cast("long")  # a wide row starts before its own end
    got = join_null_safe(ask, sums, ["at"]).groupBy(*rf.ids, "_sure").agg(of(0, "s_low").alias("n_lb"), of(1, "s_guess").alias("n_sg"), (of(2, "s_high") - own).alias("n_ub"), of(0, "s_d_sure").alias("d_lb"), of(1, "s_d_guess").alias("d_sg"), (of(2, "s_d_point") + of(2, "s_wide") - own).alias("d_ub"))
    return got.drop("_sure")


def ranking(rf: RangeFrame, keys: Sequence[str], kind: str, n: int = 4) -> RangeFrame:
    """row_number, rank, dense_rank, ntile and percent_rank bounds (into attribute of that name). rank counts rows with
    smaller keys, dense_rank distinct smaller keys: at least those that certainly exist, at most those that may."""
    one = F.lit(1).cast("long")
    if kind in ("row_number", "ntile"):
        ranked = rank(rf, keys)
        pos = ranked.c("pos")
    else:
        unit = rf.split()
        ranked = unit.with_df(unit.df.join(_smaller(unit, keys), [RID, DUP]))
        pre = "d" if kind == "dense_rank" else "n"
        pos = Triple(*(F.col(f"{pre}_{e}") for e in ("lb", "sg", "ub")))
    if kind in ("ntile", "percent_rank"):
        total = ranked.df.agg(F.sum("_m_lb").alias("_n0"), F.sum("_m_sg").alias("_n1"), F.sum("_m_ub").alias("_n2"))
        ranked = ranked.with_df(ranked.df.crossJoin(F.broadcast(total)))  # one row
    if kind == "ntile":
        t = Triple(F.greatest(one, F.floor(pos.lb * n / F.col("_n2")) + 1), F.floor(pos.sg * n / F.greatest(F.col("_n1"), one)) + 1, F.least(F.lit(n).cast("long"), F.floor(pos.ub * n / F.greatest(F.col("_n0"), pos.ub + 1)) + 1))
    elif kind == "percent_rank":
        t = Triple(pos.lb / F.greatest(F.col("_n2") - 1, one), pos.sg / F.greatest(F.col("_n1") - 1, one), F.least(F.lit(1.0), pos.ub / F.greatest(F.col("_n0") - 1, one)))
    elif kind in ("row_number", "rank", "dense_rank"):
        t = pos.map(lambda c: c + 1)
    else:
        raise ValueError(kind)
    attrs = (*ranked.attrs, Attr(kind, False))
    out = RangeFrame(ranked.df.withColumns({f"{kind}__{e}": c for e, c in zip(("lb", "sg", "ub"), (t.lb, F.least(F.greatest(t.sg, t.lb), t.ub), t.ub), strict=True)}), attrs, True)
    return out.with_df(out.df.select(*out.columns))


def end_values(rf: RangeFrame, arg: str, keys: Sequence[str], partition: Sequence[str] = ()) -> DataFrame:
    """first_value and last_value of each partition's order: the hull of the rows that may come first, and last.
    (partition, first__lb/sg/ub, last__lb/sg/ub); a partition without a certain row may be empty."""
    part = list(partition)
    ranked = rank(rf, keys, partition=part)
    pos, v = ranked.c("pos"), ranked.c(arg)
    # A row may be last only if all rows that certainly exist may come before it.
    sizes = ranked.df.groupBy(*part).agg(F.sum("_m_lb").alias("_n0"))
    rows = join_null_safe(ranked.df, sizes, part) if part else ranked.df.crossJoin(F.broadcast(sizes))  # one row
    first, last = pos.lb == 0, pos.ub >= F.col("_n0") - 1
    hull = lambda cond, name: [F.min(F.when(cond, v.lb)).alias(f"{name}__lb"), F.max(F.when(cond, v.ub)).alias(f"{name}__ub")]
    live = F.col("_m_sg") > 0
    guess = [F.min_by(v.sg, F.when(live, pos.sg)).alias("first__sg"), F.max_by(v.sg, F.when(live, pos.sg)).alias("last__sg")]
    return rows.groupBy(*part).agg(*hull(first, "first"), *hull(last, "last"), *guess)


def neighbour(rf: RangeFrame, arg: str, keys: Sequence[str], shift: int, into: str = "x") -> RangeFrame:
    """lag (shift < 0) and lead (shift > 0): the hull of the rows that may be at that position."""
    from .window import window

    low = window(rf, "min", arg, keys, shift, shift, into="_a")
    high = window(rf, "max", arg, keys, shift, shift, into="_b")
    df = low.df.join(high.df.select(RID, DUP, "_b__ub"), [RID, DUP]).withColumns({f"{into}__lb": F.col("_a__lb"), f"{into}__sg": F.col("_a__sg"), f"{into}__ub": F.col("_b__ub")})
    out = RangeFrame(df, (*(a for a in low.attrs if a.name != "_a"), Attr(into, False)), True)
    return out.with_df(df.select(*out.columns))
