"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Each query runs once to warm up and then $BENCH_REPEATS times into a sink that drops its rows; the mean counts. Inputs
follow the published experiments: u percent uncertain, ranges up to r cents, frames of w rows; sorts and windows have
the same ranges. Names that end in _8k or _50k are limited to the published number of rows, those that end in _sf0.01 or
_sf0.001 run over the smaller tables beside the given ones (scaling). An index is built in index_build and read in
window_rewrite_index, so that building and asking are timed apart.
"""

from __future__ import annotations

import json
import os
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from rangebound.operators import order, window
from rangebound.plans import baselines as B
from rangebound import workloads as X
from rangebound.plans.scratch import materialise
from rangebound.queries import QUERIES, orders, part_orders


def micro(u: int, r: int) -> Callable[[SparkSession, str], object]:
    return lambda s, d: orders(s, d, u, r)


SPEC = window.WindowSpec("sum", "price", ("price",), -2, 0)
_INDEX: dict[str, DataFrame] = {}


def positions_of(s: SparkSession, d: str) -> DataFrame:
    return window._members(order.rank(orders(s, d, 5, 100_000), ["price"]), SPEC)


def index_of(s: SparkSession, d: str) -> DataFrame:
    """The index as written once."""
    if d not in _INDEX:
        _INDEX[d] = materialise(window.band_index(positions_of(s, d), 16))
    return _INDEX[d]


def headline() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
    for u, r in ((5, 100_000), (5, 1_000_000), (20, 100_000)):
        tag = f"u{u}_r{r // 1000}k"
        out[f"sort_{tag}"] = lambda s, d, u=u, r=r: order.rank(orders(s, d, u, r), ["price"]).df
    base = (5, 100_000)
    out["sort_det"] = lambda s, d: B.baseline_det(orders(s, d, *base), B.positions(["price"]))
    out["sort_rewrite"] = lambda s, d: order.rank(orders(s, d, *base), ["price"], method="rewrite").df
    out["sort_onepass"] = lambda s, d: order.rank(orders(s, d, *base), ["price"], method="onepass").df
    out["sort_sample10"] = lambda s, d: B.baseline_sampled(orders(s, d, *base), B.positions(["price"]), 10, "pos")
    for k in (2, 10):
        out[f"topk_{k}"] = lambda s, d, k=k: order.topk(orders(s, d, *base), ["price"], k).df
    out["topk_det"] = lambda s, d: orders(s, d, *base).guess().orderBy("price", "_rid").limit(10)
    for w, u, r in ((3, 5, 100_000), (3, 5, 1_000_000), (3, 20, 100_000), (6, 5, 100_000)):
        out[f"window_w{w}_u{u}_r{r // 1000}k"] = lambda s, d, w=w, u=u, r=r: window.window(orders(s, d, u, r), "sum", "price", ["price"], 1 - w, 0).df
    out["window_det"] = lambda s, d: B.baseline_det(orders(s, d, *base), B.windowed("sum", "price", ["price"], -2, 0))
    out["window_onepass"] = lambda s, d: window.window(orders(s, d, *base), "sum", "price", ["price"], -2, 0, method="onepass").df
    out["window_sample10"] = lambda s, d: B.baseline_sampled(orders(s, d, *base), B.windowed("sum", "price", ["price"], -2, 0), 10, "x")
    for u, r in ((5, 100_000), (20, 100_000)):
        out[f"window_part_u{u}_8k"] = lambda s, d, u=u, r=r: window.window(part_orders(s, d, u, r, 8000), "sum", "price", ["price"], -2, 0, partition=["part"], ties=False).df
    out["window_part"] = lambda s, d: window.window(part_orders(s, d), "sum", "price", ["price"], -2, 0, partition=["part"], ties=False).df
    out["index_build"] = lambda s, d: window.band_index(positions_of(s, d), 16)
    out["window_rewrite_index"] = lambda s, d: window.window(orders(s, d, *base), "sum", "price", ["price"], -2, 0, method="rewrite", index=index_of(s, d), width=16).df
    for kind in ("connected", "unconnected"):
        for u, r in ((1, 2_000), (5, 2_000), (5, 30_000)):
            out[f"heap_{kind}_u{u}_r{r}_50k"] = lambda s, d, k=kind, u=u, r=r: X.heap_sweep(s, d, ((u, r),), 50_000, (k,))
    for sf in ("sf0.001", "sf0.01"):
        other = lambda d, sf=sf: os.path.join(os.path.dirname(d.rstrip("/")), sf)
        out[f"sort_{sf}"] = lambda s, d, o=other: order.rank(orders(s, o(d), *base), ["price"]).df
        out[f"window_{sf}"] = lambda s, d, o=other: window.window(orders(s, o(d), *base), "sum", "price", ["price"], -2, 0).df
    for name in ("wl_freq_top3", "wl_rolling_sum", "wl_busiest_days", "wl_best5", "closure_topk_join_agg", "repair_key_hull"):
        out[name] = QUERIES[name]
    return out


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    repeats = int(os.environ.get("BENCH_REPEATS", "2"))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    found: dict[str, float] = {}
    for name, q in headline().items():
        times = []
        for i in range(repeats + 1):
            t = time.time()
            q(spark, sf).write.format("noop").mode("overwrite").save()
            if i:
                times.append(time.time() - t)
        found[name] = round(sum(times) / len(times), 3)
        print(name, found[name], file=sys.stderr, flush=True)
    print(json.dumps({"metric": "mean seconds of the headline queries, summed", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": sf}))


if __name__ == "__main__":
    main()
