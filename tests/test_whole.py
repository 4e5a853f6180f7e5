"""Whole tables, against pair counting."""

import numpy as np
import pytest

import __spark_entry__ as entry
from rangebound import queries as q

SF = "/root/testdata/sf0.01"


def brute_positions(rows):
    """(rid, dup) -> (pl, pg, pu, wl, wg, wu), comparing each row with all others."""
    rid, lb, sg, ub, ml, mg, mu = (np.array(x) for x in zip(*rows, strict=True))
    out = {}
    for i in range(len(rid)):
        before = lambda a, b: (a < b[i]) | ((a == b[i]) & (rid < rid[i]))  # noqa: E731, B023
        low, guess, high = int(ml[before(ub, lb)].sum()), int(mg[before(sg, sg)].sum()), int(mu[(m := before(lb, ub)) & (rid != rid[i])].sum())
        assert not m[i] or lb[i] < ub[i]
        for d in range(mu[i]):
            out[int(rid[i]), d] = (low + d, guess + d, high + d, int(d < ml[i]), int(d < mg[i]), 1)
    return out


@pytest.fixture(scope="module")
def brute(spark):
    columns = ("_rid", "price__lb", "price__sg", "price__ub", "_m_lb", "_m_sg", "_m_ub")
    get = lambda *a: brute_positions([tuple(r) for r in q.orders(spark, SF, 20, 1_000_000, *a).df.select(*columns).collect()])
    return {"plain": get(), "doubt": get(10, 10)}


def brute_top(positions, k, offset=0):
    most = offset + k
    inside = lambda x: offset <= x < most
    return {key: (pl, min(pu, most), int(pu < most and pl >= offset) * wl, int(inside(pg)) * wg, wu) for key, (pl, pg, pu, wl, wg, wu) in positions.items() if pl < most and pu >= offset and key[1] < most}


@pytest.mark.parametrize("name", ["rank_rewrite", "rank_onepass", "rank_dist", "rank_cdf", "rank_dups_existence"])
def test_whole_orders_are_ranked(spark, brute, name):
    got = {(r[0], r[1]): tuple(r)[2:] for r in q.QUERIES[name](spark, SF).collect()}
    assert got == brute["doubt" if "dups" in name else "plain"]
    assert len({i for i, _ in got}) == spark.read.parquet(f"{SF}/orders.parquet").count()


@pytest.mark.parametrize("name", ["topk_select", "topk_select_2", "topk_prune", "topk_prune_2", "topk_onepass", "topk_onepass_2", "topk_offset"])
def test_whole_orders_have_their_top(spark, brute, name):
    got = {(r[0], r[1]): tuple(r)[2:] for r in q.QUERIES[name](spark, SF).collect()}
    want = brute_top(brute["plain"], 5, 5) if "offset" in name else brute_top(brute["doubt"], 2 if "_2" in name else 10)
    assert got == want and any(i >= 4000 for i, _ in got)


def test_whole_sql_agrees(brute):
    duckdb = pytest.importorskip("duckdb")
    db = duckdb.connect()
    db.execute(f"CREATE VIEW orders AS SELECT * FROM '{SF}/orders.parquet'")
    sql = entry.oracle_sql()
    at = lambda name: {(r[0], r[1]): r[2:] for r in db.execute(sql[name]).fetchall()}
    assert at("rank_dist") == brute["plain"] and at("rank_dups_existence") == brute["doubt"]
    assert at("topk_prune") == brute_top(brute["doubt"], 10) and at("topk_offset") == brute_top(brute["plain"], 5, 5)
