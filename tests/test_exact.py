"""Tight windows and positions against all worlds; the quality measures; windows of uncertain partitions."""

import random

import pytest
from pyspark.sql import functions as F
from test_order import frame

from rangebound.operators import window
from rangebound.plans import baselines as B
from rangebound.plans import exact
from rangebound.plans.worlds import worlds_of

ONE = (1, 1, 1)


def small(spark, seed, n=6):
    rng = random.Random(seed)
    rows = []
    for i in range(n):
        a = rng.randint(0, 12)
        rows.append((i, (a, a, a + rng.choice([0, 0, 1, 3])), (v := rng.randint(-5, 5), v, v + rng.randint(0, 2)), ONE))
    return frame(spark, rows, ["k", "v"])


@pytest.mark.parametrize("agg,lo,hi", [("sum", -1, 0), ("min", -1, 1), ("max", 0, 1), ("count", -2, 0), ("sum", 1, 1)])
def test_tight_windows_are_those_of_all_worlds(spark, agg, lo, hi):
    fold = {"sum": sum, "min": min, "max": max, "count": len}[agg]
    for seed in (1, 2):
        rf = small(spark, seed)
        want, member = {}, {}
        for w in worlds_of([r.asDict() for r in rf.df.collect()], [("k", False), ("v", False)], 200_000):
            w = sorted(w, key=lambda r: (r[2], r[0]))
            for i, r in enumerate(w):
                inside = w[max(0, i + lo) : max(0, i + hi + 1)]
                if inside:
                    x = fold([s[3] for s in inside])
                    a, b = want.get(r[0], (x, x))
                    want[r[0]] = min(a, x), max(b, x)
                    member.setdefault(r[0], set()).update(s[0] for s in inside)
        got = {r["_rid"]: r for r in exact.tight_windows(rf, agg, "v", "k", lo, hi).collect() if r["x__lb"] is not None}
        assert {k: (r["x__lb"], r["x__ub"]) for k, r in got.items()} == want
        assert {k: set(r["member"]) for k, r in got.items()} == member
        bounds = {r["_rid"]: (r["x__lb"], r["x__ub"]) for r in window.window(rf, agg, "v", ["k"], lo, hi, ties=False).df.collect()}
        assert all(bounds[k][0] <= a and b <= bounds[k][1] for k, (a, b) in want.items())


def test_window_of_its_own_key(spark):
    rf = frame(spark, [(0, (0, 0, 4), ONE), (1, (2, 2, 2), ONE), (2, (3, 3, 6), ONE)], ["k"])
    want = {}
    for w in worlds_of([r.asDict() for r in rf.df.collect()], [("k", False)]):
        w = sorted(w, key=lambda r: (r[2], r[0]))
        for i, r in enumerate(w):
            x = sum(s[2] for s in w[max(0, i - 1) : i + 1])
            a, b = want.get(r[0], (x, x))
            want[r[0]] = min(a, x), max(b, x)
    assert {r["_rid"]: (r["x__lb"], r["x__ub"]) for r in exact.tight_windows(rf, "sum", "k", "k", -1, 0).collect()} == want


def test_exact_positions(spark):
    rng = random.Random(4)
    rows = [(i, (a := rng.randint(0, 5), a, a + rng.randint(0, 2)), (rng.randint(0, 1), 1, 1)) for i in range(5)]
    rf = frame(spark, rows, ["k"])
    seen = {}
    for w in worlds_of([r.asDict() for r in rf.df.collect()], [("k", False)], 50_000):
        for i, r in enumerate(sorted(w, key=lambda r: (r[2], r[0]))):
            a, b = seen.get(r[0], (i, i))
            seen[r[0]] = min(a, i), max(b, i)
    assert {r["_rid"]: (r["lb"], r["ub"]) for r in B.exact_positions(rf, "k").collect()} == seen


def test_quality_of_loose_and_of_sampled_windows(spark):
    rng = random.Random(9)
    rf = frame(spark, [(i, (a := 10 * i + rng.randint(0, 5), a + 1, a + rng.choice([1, 25, 40])), ONE) for i in range(40)], ["k"])
    got = {r["method"]: r for r in exact.window_quality(rf, "sum", "k", "k", -2, 0, samples=5).collect()}
    assert got["bounds"]["recall_ppm"] == 1_000_000 == got["bounds"]["membership_recall_ppm"]
    assert got["bounds"]["accuracy_ppm"] < 1_000_000 and got["sample5"]["accuracy_ppm"] == 1_000_000
    assert got["sample5"]["recall_ppm"] < 1_000_000 and got["bounds"]["n_rows"] + got["bounds"]["n_skipped"] == 40


@pytest.mark.parametrize("agg,lo,hi", [("sum", -1, 0), ("count", -1, 1), ("min", 1, 2), ("max", -1, 1), ("avg", -1, 0), ("sum", 1, 2)])
def test_uncertain_partitions_hold_all_worlds(spark, agg, lo, hi):
    """Every world's window of every row lies inside the bounds; rows of certain keys agree with the pair plan."""
    fold = {"sum": sum, "min": min, "max": max, "count": len, "avg": lambda x: sum(x) / len(x)}[agg]
    for seed in (3, 4):
        rng = random.Random(seed)
        rows = []
        for i in range(5):
            g, a = rng.randint(0, 1), rng.randint(0, 6)
            rows.append((i, (g, g, g + rng.choice([0, 0, 1])), (a, a, a + rng.choice([0, 2])), (v := rng.randint(-4, 4), v, v), (rng.randint(0, 1), 1, 1)))
        rf = frame(spark, rows, ["g", "k", "v"])
        got = {r["_rid"]: (r["x__lb"], r["x__ub"]) for r in window.window(rf, agg, "v", ["k"], lo, hi, partition=["g"], ties=False).df.collect()}
        for w in worlds_of([r.asDict() for r in rf.df.collect()], [("g", False), ("k", False), ("v", False)], 100_000):
            for g in {r[2] for r in w}:
                part = sorted((r for r in w if r[2] == g), key=lambda r: (r[3], r[0]))
                for i, r in enumerate(part):
                    inside = [s[4] for s in part[max(0, i + lo) : max(0, i + hi + 1)]]
                    if inside:
                        assert got[r[0]][0] is not None and got[r[0]][0] <= fold(inside) <= got[r[0]][1], (seed, r)


def test_a_null_partition_among_uncertain_ones(spark):
    rf = frame(spark, [(0, (0, 0, 1), (1, 1, 1), ONE), (1, (1, 1, 1), (2, 2, 2), ONE), (2, (5, 5, 5), (3, 3, 3), ONE), (3, (5, 5, 5), (4, 4, 4), ONE)], ["g", "k"])
    rf = rf.with_df(rf.df.withColumns({f"g__{e}": F.when(F.col("_rid") < 2, F.col(f"g__{e}")) for e in ("lb", "sg", "ub")}))
    got = {r["_rid"]: (r["x__lb"], r["x__ub"]) for r in window.window(rf, "count", None, ["k"], -1, 0, partition=["g"]).df.collect()}
    assert got == {0: (1, 1), 1: (1, 2), 2: (1, 1), 3: (2, 2)}
