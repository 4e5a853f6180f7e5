"""What the bounds are compared with: the guess world, sampled worlds, exact enumeration, and
probability-threshold top-k over independent rows with uniform values."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.order import RankSpec, order_keys, prune, topk
from ..schema import DUP, RID, RangeFrame
from .det import AGG
from .worlds import few_rows, sample_worlds, worlds_of

GRID = 8


def baseline_det(rf: RangeFrame, query: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """The query on the guess world."""
    return query(rf.guess())


def baseline_sampled(rf: RangeFrame, query: Callable[[DataFrame], DataFrame], samples: int, value: str, seed: int = 0) -> DataFrame:
    """The query on sampled worlds at once (it must treat world_id as a partition); least and
    greatest of its `value` by row. These bounds may miss worlds."""
    got = query(sample_worlds(rf, samples, seed))
    return got.groupBy(RID, DUP).agg(F.min(value).alias(f"{value}__lb"), F.max(value).alias(f"{value}__ub"), F.count(F.lit(1)).alias("worlds"))


def positions(keys: Sequence[str], desc: Sequence[str] = ()) -> Callable[[DataFrame], DataFrame]:
    order = [F.col(k).desc() if k in desc else F.col(k) for k in keys]
    return lambda df: df.withColumn("pos", (F.row_number().over(W.partitionBy(*([c for c in ("world_id",) if c in df.columns])).orderBy(*order, RID, DUP)) - 1).cast("long"))


def windowed(agg: str, arg: str, keys: Sequence[str], lo: int, hi: int, partition: Sequence[str] = ()) -> Callable[[DataFrame], DataFrame]:
    def run(df: DataFrame) -> DataFrame:
        w = W.partitionBy(*[c for c in ("world_id",) if c in df.columns], *partition).orderBy(*keys, RID, DUP).rowsBetween(lo, hi)
        return df.withColumn("x", AGG[agg](arg).over(w))

    return run


def sampled_topk(rf: RangeFrame, keys: Sequence[str], k: int, samples: int, desc: Sequence[str] = ()) -> DataFrame:
    """Rows by how many of the sampled worlds have them among the first k."""
    got = positions(keys, desc)(sample_worlds(rf, samples)).where(F.col("pos") < k)
    return got.groupBy(RID, DUP).agg(F.count(F.lit(1)).alias("worlds"), (F.count(F.lit(1)) / samples).alias("share"))


def exact_bounds(rf: RangeFrame, query: Callable[[list[tuple]], dict[tuple, float]], limit: int = 20_000) -> DataFrame:
    """Tight bounds by enumeration: query maps a world (list of (rid, copy, values...)) to values by
    (rid, copy). No solver is at hand, so this is for frames of a few rows."""
    rows = few_rows(rf)
    low: dict[tuple, float] = {}
    high: dict[tuple, float] = {}
    for world in worlds_of(rows, [(a.name, a.certain) for a in rf.attrs], limit):
        for key, v in query(world).items():
            low[key], high[key] = min(v, low.get(key, v)), max(v, high.get(key, v))
    out = [(*k, int(low[k]), int(high[k])) for k in sorted(low)]
    return rf.df.sparkSession.createDataFrame(out, f"{RID} long, {DUP} int, lb long, ub long")


def exact_positions(rf: RangeFrame, key: str) -> DataFrame:
    """Tight positions (RID, DUP, lb, ub) of rows that occur once at most, at any size. Rows vary independently, so a
    row comes first when it has its least value and every other that may be absent or later is; it comes last likewise.
    Each row is tried at both ends against all others, in blocks of rows that the executors hold."""
    t = rf.c(key)
    rows = rf.df.where("_m_ub > 0").select(RID, t.lb.alias("a"), t.ub.alias("b"), F.col("_m_lb").alias("ml"))
    n = max(1, rows.count() // 2000)
    block = F.pmod(F.xxhash64(RID), F.lit(n)).cast("int")
    asks = rows.withColumns({"_i": block, "_j": F.explode(F.sequence(F.lit(0), F.lit(n - 1)))})
    others = rows.withColumns({"_j": block, "_i": F.explode(F.sequence(F.lit(0), F.lit(n - 1)))})

    def count(me: pd.DataFrame, all_: pd.DataFrame) -> pd.DataFrame:
        a, b, ids, ml = (all_[c].to_numpy() for c in ("a", "b", RID, "ml"))
        out = []
        for rid, lo, hi in zip(me[RID], me["a"], me["b"], strict=True):
            other = ids != rid
            sooner = other & (ml > 0) & ((b < lo) | ((b == lo) & (ids < rid)))
            perhaps = other & ((a < hi) | ((a == hi) & (ids < rid)))
            out.append((rid, int(sooner.sum()), int(perhaps.sum())))
        return pd.DataFrame(out, columns=[RID, "lb", "ub"])

    met = asks.groupBy("_i", "_j").cogroup(others.groupBy("_i", "_j")).applyInPandas(count, f"{RID} long, lb long, ub long")
    return met.groupBy(RID).agg(F.sum("lb").alias("lb"), F.sum("ub").alias("ub")).select(RID, F.lit(0).alias(DUP), "lb", "ub")


def _rank_probabilities(rf: RangeFrame, keys: Sequence[str], k: int, desc: Sequence[str] = ()) -> DataFrame:
    """(_rid, place, p): chance of a row to be at each of the first k places. Values are uniform on a grid of
    GRID points of each range; a row with m_lb = 0 exists with chance 1/2. Only rows that the top-k
    cut lets through take part; their number is the overlap of the first k, and each meets all others in one group."""
    spec = RankSpec(tuple(keys), tuple(desc), (), "corner", False)
    kept = prune(rf, spec, k)
    key = order_keys(kept, spec)[0]
    rows = kept.df.where("_m_ub > 0").select(F.col(RID), key.lb.cast("double").alias("lo"), key.ub.cast("double").alias("hi"), F.when(F.col("_m_lb") > 0, 1.0).otherwise(0.5).alias("q"))
    other = rows.select(*[F.col(c).alias(f"s_{c}") for c in rows.columns])
    # Rows that start after this one ends never precede it; the rest is the overlap.
    pairs = rows.join(other, (F.col("s_lo") <= F.col("hi")) & (F.col(RID) != F.col(f"s_{RID}")), "left")

    def dp(pdf: pd.DataFrame) -> pd.DataFrame:
        me = pdf.iloc[0]
        out = np.zeros(k)
        some = pdf[pdf[f"s_{RID}"].notna()]
        for g in range(GRID):
            v = me["lo"] + (me["hi"] - me["lo"]) * (g + 0.5) / GRID
            dist = np.zeros(k)
            dist[0] = 1.0
            lo, hi = some["s_lo"].to_numpy(), some["s_hi"].to_numpy()
            pts = lo[:, None] + (hi - lo)[:, None] * (np.arange(GRID) + 0.5) / GRID
            before = (pts < v) | ((pts == v) & (some[f"s_{RID}"].to_numpy() < me[RID])[:, None])
            for p in before.mean(axis=1) * some["s_q"].to_numpy():
                dist[1:] = dist[1:] * (1 - p) + dist[:-1] * p
                dist[0] *= 1 - p
            out += dist * me["q"] / GRID
        return pd.DataFrame({RID: int(me[RID]), "place": np.arange(k), "p": out})

    return pairs.groupBy(RID).applyInPandas(dp, f"{RID} long, place int, p double")


def threshold_topk(rf: RangeFrame, keys: Sequence[str], k: int, p: float, desc: Sequence[str] = ()) -> DataFrame:
    """Rows whose chance to be among the first k is at least p. At p = 1 those are the certain members and
    at p = 0 (read: above 0) the possible ones, whatever the distribution; in between the grid counts."""
    if p >= 1 or p <= 0:
        got = topk(rf, keys, k, desc).df
        return got.where("_m_lb > 0" if p >= 1 else "_m_ub > 0").groupBy(RID).agg(F.lit(float(p)).alias("p"))
    got = _rank_probabilities(rf, keys, k, desc).groupBy(RID).agg(F.round(F.sum("p"), 9).alias("p"))
    return got.where(F.col("p") >= p)


def most_likely_per_position(rf: RangeFrame, keys: Sequence[str], k: int, desc: Sequence[str] = ()) -> DataFrame:
    """For each of the first k places the row most likely there."""
    got = _rank_probabilities(rf, keys, k, desc)
    return got.groupBy("place").agg(F.min_by(F.struct(RID, "p"), F.struct(-F.round("p", 9), RID)).alias("b")).select("place", f"b.{RID}", F.round("b.p", 6).alias("p"))


def most_likely_topk(rf: RangeFrame, keys: Sequence[str], k: int, desc: Sequence[str] = (), samples: int = 200) -> DataFrame:
    """The ordered list of k rows that most sampled worlds have (of equals, the smallest ids)."""
    got = positions(keys, desc)(sample_worlds(rf, samples)).where(F.col("pos") < k)
    lists = got.groupBy("world_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", RID))), lambda x: x[RID]).alias("ids"))
    best = lists.groupBy("ids").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "ids").limit(1)
    return best.select(F.posexplode("ids").alias("place", RID), "n")


def topk_lists(rf: RangeFrame, key: str, k: int, limit: int = 20_000) -> list[tuple[tuple[int, ...], int]]:
    """All ordered top-k lists of a tiny frame with the number of worlds that have them, most first."""
    rows = few_rows(rf)
    names = [a.name for a in rf.attrs]
    at = 2 + names.index(key)
    seen: Counter = Counter(tuple(r[0] for r in sorted(w, key=lambda r: (r[at], r[0], r[1]))[:k]) for w in worlds_of(rows, [(a.name, a.certain) for a in rf.attrs], limit))
    return sorted(seen.items(), key=lambda x: (-x[1], x[0]))


def exact_topk_lists(rf: RangeFrame, key: str, k: int, limit: int = 20_000) -> list[tuple[tuple[int, ...], float]]:
    """The same with their share of worlds."""
    lists = topk_lists(rf, key, k, limit)
    total = sum(n for _, n in lists)
    return [(ids, n / total) for ids, n in lists]
