"""Registered queries of the order operators, and their SQL.

The SQL counts pairs instead of summing end points, so it is another formulation of the same semantics. Counting
pairs of a whole orders table takes too long; there it sums end points in one window, and the tests compare with pair
counting. Sums and counts are whole numbers on both sides.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import workloads as X
from .functions import expr as E
from .functions import metrics
from .operators import algebra as A
from .operators import order, window
from .plans import baselines as B
from .plans import det
from .plans import sql as S
from .plans.scratch import materialise
from .schema import DUP, RID, RangeFrame
from .sources import ingest
from .sources.ingest import cents
from .workloads import read

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

# ---- inputs ---------------------------------------------------------------------------------


def orders(s: SparkSession, d: str, u: int = 5, r: int = 100_000, e: int = 0, dup: int = 0, keep: tuple = ()) -> RangeFrame:
    return ingest.inject(read(s, d, "orders"), "o_orderkey", {"price": cents("o_totalprice")}, u, r, e, dup, keep)


def customers(s: SparkSession, d: str, u: int = 20, r: int = 10_000, e: int = 0, dup: int = 0, keep: tuple = ()) -> RangeFrame:
    return ingest.inject(read(s, d, "customer"), "c_custkey", {"bal": cents("c_acctbal")}, u, r, e, dup, keep)


def suppliers(s: SparkSession, d: str, u: int = 20, r: int = 100_000, e: int = 0, dup: int = 0) -> RangeFrame:
    return ingest.inject(read(s, d, "supplier"), "s_suppkey", {"bal": cents("s_acctbal")}, u, r, e, dup)


def box_sql(table: str, key: str, value: str, u: int, r: int, e: int = 0, d: int = 0, where: str = "", keep: str = "", per: int = 100) -> str:
    """SELECT of rid, lb, sg, ub, ml, mg, mu by the injection's arithmetic."""
    h = lambda a: f"(({key} * 7919 + {a} * 104729) % 10007)"
    wide = f"(1 + ({h(2)} * 997) % {r})"
    low = f"({value} - ({h(3)} * 997) % ({wide} + 1))"
    unsure = f"{h(1)} % {per} < {u}"
    ml = f"CASE WHEN {h(4)} % 100 < {e} THEN 0 ELSE 1 END" if e else "1"
    mu = f"CASE WHEN {h(5)} % 100 < {d} THEN 2 ELSE 1 END" if d else "1"
    extra = f", {keep}" if keep else ""
    return f"SELECT CAST({key} AS BIGINT) AS rid, CAST(CASE WHEN {unsure} THEN {low} ELSE {value} END AS BIGINT) AS lb, CAST({value} AS BIGINT) AS sg, CAST(CASE WHEN {unsure} THEN {low} + {wide} ELSE {value} END AS BIGINT) AS ub, CAST({ml} AS BIGINT) AS ml, CAST(1 AS BIGINT) AS mg, CAST({mu} AS BIGINT) AS mu{extra} FROM {table} {where}"


def money(c: str) -> str:
    return f"CAST(round({c} * 100) AS BIGINT)"


ORDERS = lambda u=5, r=100_000, e=0, d=0, keep="": box_sql("orders", "o_orderkey", money("o_totalprice"), u, r, e, d, "", keep)
CUSTOMERS = lambda u=20, r=10_000, e=0, d=0, keep="": box_sql("customer", "c_custkey", money("c_acctbal"), u, r, e, d, "", keep)
SUPPLIERS = lambda u=20, r=100_000, e=0, d=0: box_sql("supplier", "s_suppkey", money("s_acctbal"), u, r, e, d)


def rank_cte(box: str, desc: bool = False, part: str = "") -> str:
    """CTEs b (boxes) and p (unit rows with positions pl, pg, pu) by counting pairs."""
    neg = "SELECT * REPLACE (-ub AS lb, -sg AS sg, -lb AS ub) FROM b" if desc else "SELECT * FROM b"
    same = f"AND s.{part} = t.{part}" if part else ""
    return f"""WITH b AS ({box}), k AS ({neg}),
q AS (SELECT t.rid, CAST(coalesce(sum(CASE WHEN (s.ub, s.rid) < (t.lb, t.rid) THEN s.ml END), 0) AS BIGINT) AS pl,
 CAST(coalesce(sum(CASE WHEN (s.sg, s.rid) < (t.sg, t.rid) THEN s.mg END), 0) AS BIGINT) AS pg,
 CAST(coalesce(sum(CASE WHEN (s.lb, s.rid) < (t.ub, t.rid) THEN s.mu END), 0) AS BIGINT) AS pu
 FROM k t LEFT JOIN k s ON s.rid <> t.rid {same} GROUP BY t.rid),
p AS (SELECT b.*, CAST(d.d AS INTEGER) AS dup, q.pl + d.d AS pl, q.pg + d.d AS pg, q.pu + d.d AS pu,
 CAST(d.d < b.ml AS BIGINT) AS wl, CAST(d.d < b.mg AS BIGINT) AS wg, CAST(1 AS BIGINT) AS wu
 FROM b JOIN q USING (rid) JOIN (SELECT CAST(0 AS BIGINT) AS d UNION ALL SELECT 1) d ON d.d < b.mu)"""


def sums_cte(box: str) -> str:
    """The same b and p by one window over end points: a row's start precedes its guess and its end."""
    return f"""WITH b AS ({box}),
e AS (SELECT lb AS v, rid, 1 AS kind, mu AS a, 0 AS g, 0 AS z FROM b UNION ALL SELECT sg, rid, 2, 0, mg, 0 FROM b UNION ALL SELECT ub, rid, 3, 0, 0, ml FROM b),
r AS (SELECT rid, kind, sum(a) OVER w AS sa, sum(g) OVER w AS sg, sum(z) OVER w AS sz FROM e WINDOW w AS (ORDER BY v, rid, kind ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
q AS (SELECT rid, CAST(coalesce(max(CASE WHEN kind = 1 THEN sz END), 0) AS BIGINT) AS pl, CAST(coalesce(max(CASE WHEN kind = 2 THEN r.sg END), 0) AS BIGINT) AS pg,
 CAST(max(CASE WHEN kind = 3 THEN sa END) - max(b.mu) AS BIGINT) AS pu FROM r JOIN b USING (rid) GROUP BY rid),
p AS {rank_cte(box).partition("p AS ")[2]}"""


RANK_OUT = "rid AS _rid, dup AS _dup, pl AS pos__lb, pg AS pos__sg, pu AS pos__ub, wl AS _m_lb, wg AS _m_sg, wu AS _m_ub"


def rank_sql(box: str, desc: bool = False, part: str = "") -> str:
    return f"{rank_cte(box, desc, part)} SELECT {RANK_OUT} FROM p"


def ranked(rf: RangeFrame) -> DataFrame:
    return rf.df.select(RID, DUP, "pos__lb", "pos__sg", "pos__ub", "_m_lb", "_m_sg", "_m_ub")


def topk_sql(box: str, k: int, desc: bool = False, offset: int = 0) -> str:
    most = offset + k
    inside = lambda c: f"CASE WHEN {c} < {most} AND {c} >= {offset} THEN 1 ELSE 0 END"
    sure = f"CASE WHEN pu < {most} AND pl >= {offset} THEN wl ELSE 0 END"
    return f"""{rank_cte(box, desc)} SELECT rid AS _rid, dup AS _dup, pl AS pos__lb, least(pu, {most}) AS pos__ub,
 CAST({sure} AS BIGINT) AS _m_lb, CAST({inside('pg')} * wg AS BIGINT) AS _m_sg, wu AS _m_ub FROM p WHERE pl < {most} AND pu >= {offset} AND dup < {most}"""


def whole(sql: Callable[..., str], box: str, *args: int, **kwargs: int) -> str:
    """rank_sql or topk_sql with positions by sums."""
    return sql(box, *args, **kwargs).replace(rank_cte(box), sums_cte(box))


def top_rows(rf: RangeFrame) -> DataFrame:
    return rf.df.select(RID, DUP, "pos__lb", "pos__ub", "_m_lb", "_m_sg", "_m_ub")


def window_sql(box: str, agg: str, lo: int, hi: int, value: str = "", part: str = "") -> str:
    """value: low and high value columns of the members as 'vl, vh'."""
    vl, vh = (value or "lb, ub").replace(" ", "").split(",")
    same = f"AND s.{part} = t.{part}" if part else ""
    size = hi - lo + 1
    me = "s.rid = t.rid AND s.dup = t.dup"
    own = "OR" if lo <= 0 <= hi else "AND NOT"
    head = f"""{rank_cte(box, part=part)}, m AS (SELECT t.rid, t.dup, s.{vl} AS vl, s.{vh} AS vh,
 ((s.wl = 1 AND s.pl >= t.pu + ({lo}) AND s.pu <= t.pl + ({hi})) {own} ({me})) AS c,
 ((s.pu >= t.pl + ({lo}) AND s.pl <= t.pu + ({hi})) {own} ({me})) AS a
 FROM p t JOIN p s ON s.pu >= t.pl + ({lo}) AND s.pl <= t.pu + ({hi}) {same}),
n AS (SELECT rid, dup, vl, vh, c, sum(CAST(c AS BIGINT)) OVER w AS nc, row_number() OVER (PARTITION BY rid, dup, c ORDER BY vl) AS rl, row_number() OVER (PARTITION BY rid, dup, c ORDER BY vh DESC) AS rh
 FROM m WHERE a OR c WINDOW w AS (PARTITION BY rid, dup))"""
    room = f"{size} - nc"
    out = {
        "sum": f"CAST(sum(CASE WHEN c THEN vl WHEN vl < 0 AND rl <= {room} THEN vl ELSE 0 END) AS BIGINT) AS x__lb, CAST(sum(CASE WHEN c THEN vh WHEN vh > 0 AND rh <= {room} THEN vh ELSE 0 END) AS BIGINT) AS x__ub",
        "count": f"CAST(max(nc) AS BIGINT) AS x__lb, CAST(least({size}, count(*)) AS BIGINT) AS x__ub",
        "min": f"min(CASE WHEN c OR {room} > 0 THEN vl END) AS x__lb, min(CASE WHEN c THEN vh END) AS x__ub",
        "max": f"max(CASE WHEN c THEN vl END) AS x__lb, max(CASE WHEN c OR {room} > 0 THEN vh END) AS x__ub",
    }
    if agg != "avg":
        return f"{head} SELECT rid AS _rid, dup AS _dup, {out[agg]} FROM n GROUP BY rid, dup"
    # The mean that j possible values push furthest, for every j that has a slot.
    return f"""{head}, z AS (SELECT rid, dup, max(nc) AS nc, CAST(sum(CASE WHEN c THEN vl ELSE 0 END) AS BIGINT) AS sl, CAST(sum(CASE WHEN c THEN vh ELSE 0 END) AS BIGINT) AS sh FROM n GROUP BY rid, dup),
g AS (SELECT rid, dup, rl, rh, nc, vl, vh, sum(vl) OVER (PARTITION BY rid, dup ORDER BY rl) AS al, sum(vh) OVER (PARTITION BY rid, dup ORDER BY rh) AS ah FROM n WHERE NOT c),
l AS (SELECT rid, dup, sl AS s, nc AS k FROM z UNION ALL SELECT rid, dup, z.sl + g.al, g.rl + z.nc FROM g JOIN z USING (rid, dup) WHERE g.rl <= {size} - z.nc),
h AS (SELECT rid, dup, sh AS s, nc AS k FROM z UNION ALL SELECT rid, dup, z.sh + g.ah, g.rh + z.nc FROM g JOIN z USING (rid, dup) WHERE g.rh <= {size} - z.nc),
lb AS (SELECT rid, dup, s, k, row_number() OVER (PARTITION BY rid, dup ORDER BY CAST(s AS DOUBLE) / k, k) AS i FROM l),
hb AS (SELECT rid, dup, s, k, row_number() OVER (PARTITION BY rid, dup ORDER BY CAST(s AS DOUBLE) / k DESC, k) AS i FROM h)
SELECT lb.rid AS _rid, lb.dup AS _dup, CAST(lb.s AS BIGINT) AS x_low_sum, CAST(lb.k AS BIGINT) AS x_low_n, CAST(hb.s AS BIGINT) AS x_high_sum, CAST(hb.k AS BIGINT) AS x_high_n FROM lb JOIN hb USING (rid, dup) WHERE lb.i = 1 AND hb.i = 1"""


def spans(rf: RangeFrame) -> DataFrame:
    return rf.df.select(RID, DUP, "x__lb", "x__ub")


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


# ---- encoding and deterministic operators ---------------------------------------------------

add(
    "encode_injected",
    lambda s, d: orders(s, d, 5, 100_000, e=10, dup=10).df.select(RID, "price__lb", "price__sg", "price__ub", "_m_lb", "_m_sg", "_m_ub"),
    f"SELECT rid AS _rid, lb AS price__lb, sg AS price__sg, ub AS price__ub, ml AS _m_lb, mg AS _m_sg, mu AS _m_ub FROM ({ORDERS(5, 100_000, 10, 10)})",
)
add(
    "det_rank",
    lambda s, d: det.det_rank(read(s, d, "orders").select("o_orderkey", cents("o_totalprice").alias("cents")), ["cents"]).select("o_orderkey", "pos"),
    f"SELECT o_orderkey, row_number() OVER (ORDER BY {money('o_totalprice')}, o_orderkey) - 1 AS pos FROM orders",
)
add("det_topk", lambda s, d: det.det_topk(read(s, d, "orders").select("o_orderkey", cents("o_totalprice").alias("cents")), ["cents"], 10, ["cents"]), f"SELECT o_orderkey, {money('o_totalprice')} AS cents FROM orders ORDER BY cents DESC, o_orderkey LIMIT 10")
add(
    "det_window_rows",
    lambda s, d: det.det_window(read(s, d, "customer").select("c_custkey", "c_nationkey", cents("c_acctbal").alias("cents")), "sum", "cents", ["cents"], -2, 0, ["c_nationkey"]).select("c_custkey", "x"),
    f"SELECT c_custkey, CAST(sum({money('c_acctbal')}) OVER (PARTITION BY c_nationkey ORDER BY {money('c_acctbal')}, c_custkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS x FROM customer",
)
add(
    "det_group_window",
    lambda s, d: det.det_group_window(read(s, d, "part").select("p_partkey", "p_size"), "count", "p_partkey", ["p_size"], -1, 1).select("p_partkey", "x"),
    "WITH r AS (SELECT p_partkey, dense_rank() OVER (ORDER BY p_size) AS k FROM part), c AS (SELECT k, count(*) AS n FROM r GROUP BY k) SELECT p_partkey, CAST(sum(c.n) AS BIGINT) AS x FROM r JOIN c ON c.k BETWEEN r.k - 1 AND r.k + 1 GROUP BY p_partkey",
)

# ---- positions ------------------------------------------------------------------------------

add("rank_naive", lambda s, d: ranked(order.rank(suppliers(s, d), ["bal"], method="naive")), rank_sql(SUPPLIERS()))
for _m in ("rewrite", "onepass", "dist", "cdf"):
    add(f"rank_{_m}", lambda s, d, m=_m: ranked(order.rank(orders(s, d, 20, 1_000_000), ["price"], method=m)), whole(rank_sql, ORDERS(20, 1_000_000)))
add("rank_desc", lambda s, d: ranked(order.rank(customers(s, d, 20, 100_000), ["bal"], desc=["bal"])), rank_sql(CUSTOMERS(20, 100_000), desc=True))
add(
    "rank_multikey",
    lambda s, d: ranked(order.rank(ingest.inject(read(s, d, "part"), "p_partkey", {"size": F.col("p_size").cast("long")}, 20, 5, keep=("p_brand",)), ["size", "p_brand"])),
    rank_sql(box_sql("part", "p_partkey", "p_size", 20, 5, keep="p_brand")).replace("(s.ub, s.rid) < (t.lb, t.rid)", "(s.ub, s.p_brand, s.rid) < (t.lb, t.p_brand, t.rid)").replace("(s.sg, s.rid) < (t.sg, t.rid)", "(s.sg, s.p_brand, s.rid) < (t.sg, t.p_brand, t.rid)").replace("(s.lb, s.rid) < (t.ub, t.rid)", "(s.lb, s.p_brand, s.rid) < (t.ub, t.p_brand, t.rid)"),
)
add(
    "rank_attributewise",
    lambda s, d: ranked(order.rank(customers(s, d, 20, 100_000), ["bal"], compare="attributewise")),
    rank_sql(CUSTOMERS(20, 100_000)).replace("(s.ub, s.rid) < (t.lb, t.rid)", "(s.ub < t.lb OR (s.lb = s.ub AND t.lb = t.ub AND s.lb = t.lb AND s.rid < t.rid))"),
)
add("rank_partitioned", lambda s, d: ranked(order.rank(customers(s, d, 20, 100_000, keep=("c_nationkey",)), ["bal"], partition=["c_nationkey"])), rank_sql(CUSTOMERS(20, 100_000, keep="c_nationkey"), part="c_nationkey"))
add("rank_dups_existence", lambda s, d: ranked(order.rank(orders(s, d, 20, 1_000_000, e=10, dup=10), ["price"])), whole(rank_sql, ORDERS(20, 1_000_000, e=10, d=10)))

add("sql_rank", lambda s, d: S.positions(customers(s, d, 20, 100_000, 10, 10), ["bal"]), f"{rank_cte(CUSTOMERS(20, 100_000, 10, 10))} SELECT rid AS _rid, dup AS _dup, pl AS pos__lb, pg AS pos__sg, pu AS pos__ub FROM p")
add("sql_topk", lambda s, d: S.top(customers(s, d, 20, 100_000, 10, 10), ["bal"], 10), f"{rank_cte(CUSTOMERS(20, 100_000, 10, 10))} SELECT rid AS _rid, dup AS _dup, pl AS pos__lb, least(pu, 10) AS pos__ub, pu < 10 AND wl = 1 AS is_certain FROM p WHERE pl < 10")

# ---- top-k ----------------------------------------------------------------------------------

for _m in ("select", "prune", "onepass"):
    for _k in (2, 10):
        add(f"topk_{_m}" + ("" if _k == 10 else "_2"), lambda s, d, m=_m, k=_k: top_rows(order.topk(orders(s, d, 20, 1_000_000, e=10, dup=10), ["price"], k, method=m)), whole(topk_sql, ORDERS(20, 1_000_000, e=10, d=10), _k))
add("topk_offset", lambda s, d: top_rows(order.topk(orders(s, d, 20, 1_000_000), ["price"], 5, offset=5)), whole(topk_sql, ORDERS(20, 1_000_000), 5, offset=5))
add("topk_desc", lambda s, d: top_rows(order.topk(customers(s, d, 20, 100_000, 10), ["bal"], 10, desc=["bal"])), topk_sql(CUSTOMERS(20, 100_000, 10), 10, desc=True))

# ---- windows --------------------------------------------------------------------------------

for _m in ("naive", "rewrite", "bucket", "onepass"):
    add(f"window_sum_{_m}", lambda s, d, m=_m: spans(window.window(suppliers(s, d, 20, 1_000_000, 10, 10), "sum", "bal", ["bal"], -2, 0, method=m)), window_sql(SUPPLIERS(20, 1_000_000, 10, 10), "sum", -2, 0))
add("window_sum_customer", lambda s, d: spans(window.window(customers(s, d, 20, 10_000, 10, 10), "sum", "bal", ["bal"], -5, 0)), window_sql(CUSTOMERS(20, 10_000, 10, 10), "sum", -5, 0))
for _a in ("count", "min", "max"):
    add(f"window_{_a}", lambda s, d, a=_a: spans(window.window(customers(s, d, 20, 10_000, 10, 10), a, None if a == "count" else "bal", ["bal"], -2, 0)), window_sql(CUSTOMERS(20, 10_000, 10, 10), _a, -2, 0))
add(
    "window_avg",
    lambda s, d: window.window(customers(s, d, 20, 10_000, 10, 10), "avg", "bal", ["bal"], -2, 0, detail=True).df.select(RID, DUP, "x_low_sum", "x_low_n", "x_high_sum", "x_high_n"),
    window_sql(CUSTOMERS(20, 10_000, 10, 10), "avg", -2, 0),
)
for _a in ("count", "min", "max"):
    add(f"window_{_a}_rewrite", lambda s, d, a=_a: spans(window.window(suppliers(s, d, 20, 1_000_000, 10, 10), a, None if a == "count" else "bal", ["bal"], -2, 0, method="rewrite")), window_sql(SUPPLIERS(20, 1_000_000, 10, 10), _a, -2, 0))


def _indexed(s: SparkSession, d: str) -> DataFrame:
    """The rewrite whose pairs come from a range index that has been written before."""
    rf = customers(s, d, 20, 10_000, 10, 10)
    spec = window.WindowSpec("sum", "bal", ("bal",), -2, 0)
    index = materialise(window.band_index(window._members(order.rank(rf, ["bal"]), spec), 16))
    return spans(window.window(rf, "sum", "bal", ["bal"], -2, 0, method="rewrite", index=index, width=16))


add("window_sum_rewrite_index", _indexed, window_sql(CUSTOMERS(20, 10_000, 10, 10), "sum", -2, 0))
add("window_sum_wide", lambda s, d: spans(window.window(customers(s, d, 20, 1_000_000, 10, 10), "sum", "bal", ["bal"], -2, 0, method="bucket")), window_sql(CUSTOMERS(20, 1_000_000, 10, 10), "sum", -2, 0))
_GUESS = window_sql(CUSTOMERS(20, 10_000, 10, 10), "sum", -2, 0).rpartition(" SELECT ")
add(
    "window_guess",
    lambda s, d: window.window(customers(s, d, 20, 10_000, 10, 10), "sum", "bal", ["bal"], -2, 0).df.select(RID, DUP, "x__lb", "x__sg", "x__ub"),
    f"""{_GUESS[0]}, x AS (SELECT {_GUESS[2]}), g AS (SELECT t.rid AS _rid, t.dup AS _dup, CAST(sum(s.sg) AS BIGINT) AS g FROM p t JOIN p s ON s.pg BETWEEN t.pg - 2 AND t.pg WHERE t.wg = 1 AND s.wg = 1 GROUP BY t.rid, t.dup)
SELECT _rid, _dup, x__lb, least(greatest(coalesce(g, 0), x__lb), x__ub) AS x__sg, x__ub FROM x LEFT JOIN g USING (_rid, _dup)""",
)
_SUM, _MIN = (window_sql(CUSTOMERS(20, 10_000, 10), a, -2, 0) for a in ("sum", "min"))


def _sequence(s: SparkSession, d: str) -> DataFrame:
    """Two windows over one ranking."""
    one = window.window(customers(s, d, 20, 10_000, 10), "sum", "bal", ["bal"], -2, 0)
    return window.window(one, "min", "bal", ["bal"], -2, 0, into="least", ranked=True).df.select(RID, DUP, "x__lb", "x__ub", "least__lb", "least__ub")


add("window_sequence", _sequence, f"SELECT a.*, b.x__lb AS least__lb, b.x__ub AS least__ub FROM ({_SUM}) a JOIN ({_MIN}) b USING (_rid, _dup)")
window.register_aggregate(
    "positives",
    lambda sure, maybe, slots: F.size(F.filter(sure, lambda x: x > 0)).cast("long"),
    lambda sure, maybe, slots: F.size(F.filter(sure, lambda x: x > 0)) + F.least(slots, F.size(F.filter(maybe, lambda x: x > 0)).cast("long")),
)
add(
    "window_registered",
    lambda s, d: spans(window.window(customers(s, d, 20, 10_000, 10, 10), "positives", "bal", ["bal"], -2, 0)),
    f"{window_sql(CUSTOMERS(20, 10_000, 10, 10), 'sum', -2, 0).rpartition(' SELECT ')[0]} SELECT rid AS _rid, dup AS _dup, CAST(sum(CASE WHEN c AND vl > 0 THEN 1 ELSE 0 END) AS BIGINT) AS x__lb, CAST(sum(CASE WHEN c AND vh > 0 THEN 1 ELSE 0 END) + least(max(3 - nc), sum(CASE WHEN NOT c AND vh > 0 THEN 1 ELSE 0 END)) AS BIGINT) AS x__ub FROM n GROUP BY rid, dup",
)
add("window_follow", lambda s, d: spans(window.window(customers(s, d, 20, 10_000, 10), "sum", "bal", ["bal"], 0, 3)), window_sql(CUSTOMERS(20, 10_000, 10), "sum", 0, 3))
add("window_both", lambda s, d: spans(window.window(customers(s, d, 20, 10_000, 10), "sum", "bal", ["bal"], -1, 1, method="onepass")), window_sql(CUSTOMERS(20, 10_000, 10), "sum", -1, 1))
add("window_part_certain", lambda s, d: spans(window.window(customers(s, d, 20, 100_000, 10, 10, keep=("c_nationkey",)), "sum", "bal", ["bal"], -2, 0, partition=["c_nationkey"])), window_sql(CUSTOMERS(20, 100_000, 10, 10, keep="c_nationkey"), "sum", -2, 0, part="c_nationkey"))


def _uncertain_nation(s: SparkSession, d: str) -> RangeFrame:
    t = read(s, d, "customer")
    return ingest.inject(t, "c_custkey", {"bal": cents("c_acctbal"), "nat": F.col("c_nationkey").cast("long")}, 10, 2)


def _part_key(key: str, value: str, u: int) -> str:
    """Columns gl, gg, gu: a partition key that is uncertain for u percent of rows, with ranges of 1 or 2."""
    h = lambda a: f"(({key} * 7919 + {a} * 104729) % 10007)"
    wide = f"(1 + ({h(12)} * 997) % 2)"
    low = f"{value} - ({h(13)} * 997) % ({wide} + 1)"
    return f"CASE WHEN {h(11)} % 100 < {u} THEN {low} ELSE {value} END AS gl, {value} AS gg, CASE WHEN {h(11)} % 100 < {u} THEN {low} + {wide} ELSE {value} END AS gu"


def _part_sql(box: str) -> str:
    """Sums over [-2, 0] by pairs of pairs: each owner ranks the rows that may share its partition."""
    return f"""WITH b AS ({box}),
e AS (SELECT t.rid AS o, s.*, CASE WHEN s.rid = t.rid OR (t.gl = t.gu AND s.gl = s.gu AND s.gl = t.gl) THEN s.ml ELSE 0 END AS il FROM b t JOIN b s ON s.gl <= t.gu AND t.gl <= s.gu),
p AS (SELECT t.o, t.rid, t.lb, t.ub, t.il, coalesce(sum(CASE WHEN (s.ub, s.rid) < (t.lb, t.rid) THEN s.il END), 0) AS pl, coalesce(sum(CASE WHEN (s.lb, s.rid) < (t.ub, t.rid) THEN s.mu END), 0) AS pu
 FROM e t LEFT JOIN e s ON s.o = t.o AND s.rid <> t.rid GROUP BY t.o, t.rid, t.lb, t.ub, t.il),
w AS (SELECT o, pl AS ol, pu AS ou FROM p WHERE rid = o),
m AS (SELECT p.o, p.lb AS vl, p.ub AS vh, ((p.il = 1 AND p.pl >= w.ou - 2 AND p.pu <= w.ol) OR p.rid = p.o) AS c FROM p JOIN w USING (o) WHERE (p.pu >= w.ol - 2 AND p.pl <= w.ou) OR p.rid = p.o),
n AS (SELECT *, sum(CAST(c AS BIGINT)) OVER (PARTITION BY o) AS nc, row_number() OVER (PARTITION BY o, c ORDER BY vl) AS rl, row_number() OVER (PARTITION BY o, c ORDER BY vh DESC) AS rh FROM m)
SELECT o AS _rid, CAST(0 AS INTEGER) AS _dup, CAST(sum(CASE WHEN c THEN vl WHEN vl < 0 AND rl <= 3 - nc THEN vl ELSE 0 END) AS BIGINT) AS x__lb, CAST(sum(CASE WHEN c THEN vh WHEN vh > 0 AND rh <= 3 - nc THEN vh ELSE 0 END) AS BIGINT) AS x__ub FROM n GROUP BY o"""


add(
    "window_part_uncertain",
    lambda s, d: spans(window.window(_uncertain_nation(s, d), "sum", "bal", ["bal"], -2, 0, partition=["nat"], ties=False)),
    _part_sql(CUSTOMERS(10, 2, keep=_part_key("c_custkey", "c_nationkey", 10))),
)


def part_orders(s: SparkSession, d: str, u: int = 5, r: int = 100_000, most: int | None = None) -> RangeFrame:
    """Orders by price in partitions of customers, both uncertain for u percent; `most` for the published experiment's size (bench)."""
    t, k = read(s, d, "orders"), F.col("o_orderkey")
    t = t.where(k < most) if most else t
    return ingest.from_intervals(t, k, {"price": ingest.box(k, cents("o_totalprice"), u, r), "part": ingest.box(k, F.col("o_custkey") % 1000, u, 2, 100, 10)})


add("window_part_orders", lambda s, d: spans(window.window(part_orders(s, d), "sum", "price", ["price"], -2, 0, partition=["part"], ties=False)), _part_sql(ORDERS(5, 100_000, keep=_part_key("o_orderkey", "(o_custkey % 1000)", 5))))
_UNB = lambda box, low, high: f"""{rank_cte(box)} SELECT t.rid AS _rid, t.dup AS _dup, CAST(sum({low}) AS BIGINT) AS x__lb, CAST(sum({high}) AS BIGINT) AS x__ub
 FROM (SELECT t.rid, t.dup, s.lb, s.ub, ((s.wl = 1 AND s.pu <= t.pl) OR (s.rid = t.rid AND s.dup = t.dup)) AS c FROM p t JOIN p s ON s.pl <= t.pu) t GROUP BY t.rid, t.dup"""  # noqa: E731
add("window_unbounded_count", lambda s, d: spans(window.window(customers(s, d, 20, 100_000, 10), "count", None, ["bal"], None, 0)), _UNB(CUSTOMERS(20, 100_000, 10), "CASE WHEN c THEN 1 ELSE 0 END", "1"))
add("window_unbounded_sum", lambda s, d: spans(window.window(customers(s, d, 20, 100_000, 10), "sum", "bal", ["bal"], None, 0)), _UNB(CUSTOMERS(20, 100_000, 10), "CASE WHEN c THEN lb ELSE least(lb, 0) END", "CASE WHEN c THEN ub ELSE greatest(ub, 0) END"))
add(
    "group_window_sum",
    lambda s, d: spans(window.group_window(ingest.inject(read(s, d, "part"), "p_partkey", {"size": F.col("p_size").cast("long")}, 20, 3, keep=("p_partkey",)), "sum", "p_partkey", "size", -1, 1)),
    f"""WITH b AS ({box_sql("part", "p_partkey", "p_size", 20, 3)}) SELECT t.rid AS _rid, CAST(0 AS INTEGER) AS _dup,
 CAST(sum(CASE WHEN s.rid = t.rid OR (s.lb >= t.ub - 1 AND s.ub <= t.lb + 1) THEN s.rid ELSE 0 END) AS BIGINT) AS x__lb, CAST(sum(s.rid) AS BIGINT) AS x__ub
 FROM b t JOIN b s ON s.rid = t.rid OR (s.ub >= t.lb - 1 AND s.lb <= t.ub + 1) GROUP BY t.rid""",
)

# ---- closure algebra ------------------------------------------------------------------------


def _m3(rf: RangeFrame, *cols: str) -> DataFrame:
    return rf.df.select(*cols, "_m_lb", "_m_sg", "_m_ub")


add(
    "ra_select",
    lambda s, d: _m3(A.select((o := orders(s, d, 20, 1_000_000)), E.rlt(o.c("price"), E.rlit(10_000_000))), RID),
    f"SELECT rid AS _rid, CAST(CASE WHEN ub < 10000000 THEN 1 ELSE 0 END AS BIGINT) AS _m_lb, CAST(CASE WHEN sg < 10000000 THEN 1 ELSE 0 END AS BIGINT) AS _m_sg, CAST(1 AS BIGINT) AS _m_ub FROM ({ORDERS(20, 1_000_000)}) WHERE lb < 10000000",
)
add(
    "ra_project",
    lambda s, d: _m3(A.project((c := customers(s, d)), twice=c.c("bal") * E.rlit(-2) + E.rlit(7), size=c.c("bal").abs()), RID, "twice__lb", "twice__ub", "size__lb", "size__sg", "size__ub"),
    f"SELECT rid AS _rid, -2 * ub + 7 AS twice__lb, -2 * lb + 7 AS twice__ub, CASE WHEN lb <= 0 AND ub >= 0 THEN 0 ELSE least(abs(lb), abs(ub)) END AS size__lb, abs(sg) AS size__sg, greatest(abs(lb), abs(ub)) AS size__ub, ml AS _m_lb, mg AS _m_sg, mu AS _m_ub FROM ({CUSTOMERS()})",
)
add(
    "ra_union",
    lambda s, d: A.union(customers(s, d), customers(s, d, 5)).canonicalize().df.select("bal__lb", "bal__sg", "bal__ub", "_m_lb", "_m_sg", "_m_ub"),
    f"SELECT lb AS bal__lb, sg AS bal__sg, ub AS bal__ub, CAST(sum(ml) AS BIGINT) AS _m_lb, CAST(sum(mg) AS BIGINT) AS _m_sg, CAST(sum(mu) AS BIGINT) AS _m_ub FROM ({CUSTOMERS()} UNION ALL {CUSTOMERS(5)}) GROUP BY lb, sg, ub",
)
add(
    "ra_join",
    lambda s, d: _m3(A.join(orders(s, d, 20, 100_000, 10, 10, ("o_custkey",)), customers(s, d, 20, 10_000, 10, 10, keep=("c_custkey",)), [("o_custkey", "c_custkey")]), "o_custkey", "price__lb", "price__ub", "r_bal__lb", "r_bal__ub"),
    f"SELECT o.o_custkey, o.lb AS price__lb, o.ub AS price__ub, c.lb AS r_bal__lb, c.ub AS r_bal__ub, o.ml * c.ml AS _m_lb, o.mg * c.mg AS _m_sg, o.mu * c.mu AS _m_ub FROM ({ORDERS(20, 100_000, 10, 10, 'o_custkey')}) o JOIN ({CUSTOMERS(20, 10_000, 10, 10)}) c ON o.o_custkey = c.rid",
)
_PARTS = box_sql("part", "p_partkey", "p_size", 20, 3)


def _parts(s: SparkSession, d: str, u: int = 20, r: int = 3, e: int = 0) -> RangeFrame:
    return ingest.inject(read(s, d, "part"), "p_partkey", {"size": F.col("p_size").cast("long")}, u, r, e)


add(
    "ra_join_overlap",
    lambda s, d: (lambda j: j.df.groupBy("size__lb", "size__ub").agg(F.sum("_m_lb").alias("_m_lb"), F.sum("_m_sg").alias("_m_sg"), F.sum("_m_ub").alias("_m_ub")))(A.join(_parts(s, d).project("size").canonicalize(), _parts(s, d, 10, 2).project("size").canonicalize(), [("size", "size")])),
    f"SELECT a.lb AS size__lb, a.ub AS size__ub, CAST(sum(CASE WHEN a.lb = a.ub AND b.lb = b.ub THEN 1 ELSE 0 END) AS BIGINT) AS _m_lb, CAST(sum(CASE WHEN a.sg = b.sg THEN 1 ELSE 0 END) AS BIGINT) AS _m_sg, CAST(count(*) AS BIGINT) AS _m_ub FROM ({_PARTS}) a JOIN ({box_sql('part', 'p_partkey', 'p_size', 10, 2)}) b ON a.lb <= b.ub AND b.lb <= a.ub GROUP BY a.lb, a.ub",
)
for _n, _anti in (("ra_semi", False), ("ra_anti", True)):
    _sure, _poss = ("bool_or(c.lb > 0)", "bool_or(c.ub > 0)")
    add(
        _n,
        lambda s, d, anti=_anti: _m3(A.semi_join(orders(s, d, keep=("o_custkey",)), A.select((c := customers(s, d, 20, 100_000, keep=("c_custkey",))), E.rlt(E.rlit(0), c.c("bal"))), [("o_custkey", "c_custkey")], anti), RID),
        f"SELECT _rid, CAST({'1 - p' if _anti else 'c'} AS BIGINT) AS _m_lb, CAST({'1 - g' if _anti else 'g'} AS BIGINT) AS _m_sg, CAST({'1 - c' if _anti else 'p'} AS BIGINT) AS _m_ub FROM (SELECT o.rid AS _rid, CAST(coalesce(c.lb > 0, false) AS INTEGER) AS c, CAST(coalesce(c.sg > 0 AND c.ub > 0, false) AS INTEGER) AS g, CAST(coalesce(c.ub > 0, false) AS INTEGER) AS p FROM ({ORDERS(keep='o_custkey')}) o LEFT JOIN ({CUSTOMERS(20, 100_000)}) c ON o.o_custkey = c.rid) WHERE {'1 - c' if _anti else 'p'} > 0",
    )
add(
    "ra_distinct",
    lambda s, d: _m3(A.distinct(_parts(s, d).project("size")), "size__lb", "size__sg", "size__ub"),
    f"""WITH b AS (SELECT lb, sg, ub, sum(ml) AS ml, sum(mg) AS mg, sum(mu) AS mu FROM ({_PARTS}) GROUP BY lb, sg, ub)
SELECT a.lb AS size__lb, a.sg AS size__sg, a.ub AS size__ub, CAST(CASE WHEN a.lb = a.ub OR count(*) = 1 THEN least(a.ml, 1) ELSE 0 END AS BIGINT) AS _m_lb, CAST(least(a.mg, 1) AS BIGINT) AS _m_sg, CAST(CASE WHEN a.lb = a.ub THEN least(a.mu, 1) ELSE a.mu END AS BIGINT) AS _m_ub
FROM b a JOIN b c ON a.lb <= c.ub AND c.lb <= a.ub GROUP BY a.lb, a.sg, a.ub, a.ml, a.mg, a.mu""",
)
add(
    "ra_agg",
    lambda s, d: A.aggregate(customers(s, d, 20, 10_000, 10, 10, keep=("c_nationkey",)), ["c_nationkey"], {"total": ("sum", "bal"), "n": ("count", None), "least": ("min", "bal")}).df.select("c_nationkey", "total__lb", "total__ub", "n__lb", "n__sg", "n__ub", "least__lb", "least__ub", "_m_lb"),
    f"SELECT c_nationkey, CAST(sum(least(lb * ml, lb * mu)) AS BIGINT) AS total__lb, CAST(sum(greatest(ub * ml, ub * mu)) AS BIGINT) AS total__ub, CAST(sum(ml) AS BIGINT) AS n__lb, CAST(sum(mg) AS BIGINT) AS n__sg, CAST(sum(mu) AS BIGINT) AS n__ub, min(lb) AS least__lb, coalesce(min(CASE WHEN ml > 0 THEN ub END), max(ub)) AS least__ub, max(ml) AS _m_lb FROM ({CUSTOMERS(20, 10_000, 10, 10, 'c_nationkey')}) GROUP BY c_nationkey",
)
add(
    "ra_agg_overlap",
    lambda s, d: A.aggregate(_parts(s, d), ["size"], {"n": ("count", None)}).df.select("size__lb", "size__sg", "size__ub", "n__lb", "n__sg", "n__ub"),
    f"""WITH b AS ({_PARTS}), g AS (SELECT sg, min(lb) AS lo, max(ub) AS hi FROM b GROUP BY sg)
SELECT g.lo AS size__lb, g.sg AS size__sg, g.hi AS size__ub, CAST(sum(CASE WHEN b.sg = g.sg AND g.lo = g.hi THEN 1 ELSE 0 END) AS BIGINT) AS n__lb, CAST(sum(CASE WHEN b.sg = g.sg THEN 1 ELSE 0 END) AS BIGINT) AS n__sg, CAST(count(*) AS BIGINT) AS n__ub FROM g JOIN b ON b.lb <= g.hi AND b.ub >= g.lo GROUP BY g.lo, g.sg, g.hi""",
)
_AGAINST = """WITH a AS (SELECT lb, sg, ub, sum(ml) AS ml, sum(mg) AS mg, sum(mu) AS mu FROM ({a}) GROUP BY lb, sg, ub), b AS (SELECT lb, sg, ub, sum(ml) AS ml, sum(mg) AS mg, sum(mu) AS mu FROM ({b}) GROUP BY lb, sg, ub),
c AS (SELECT a.lb, a.sg, a.ub, a.ml, a.mg, a.mu, coalesce(sum(b.mu), 0) AS may, coalesce(sum(CASE WHEN a.sg = b.sg THEN b.mg END), 0) AS gs, coalesce(sum(CASE WHEN a.lb = a.ub AND b.lb = b.ub THEN b.ml END), 0) AS must FROM a LEFT JOIN b ON a.lb <= b.ub AND b.lb <= a.ub GROUP BY a.lb, a.sg, a.ub, a.ml, a.mg, a.mu)"""
add(
    "ra_diff",
    lambda s, d: _m3(A.difference(_parts(s, d).project("size"), _parts(s, d, 10, 2, 80).project("size")), "size__lb", "size__sg", "size__ub"),
    f"{_AGAINST.format(a=_PARTS, b=box_sql('part', 'p_partkey', 'p_size', 10, 2, 80))} SELECT lb AS size__lb, sg AS size__sg, ub AS size__ub, CAST(greatest(0, ml - may) AS BIGINT) AS _m_lb, CAST(least(greatest(0, mg - gs, ml - may), greatest(0, mu - must)) AS BIGINT) AS _m_sg, CAST(mu - must AS BIGINT) AS _m_ub FROM c WHERE mu - must > 0",
)
add(
    "ra_intersect",
    lambda s, d: _m3(A.intersect(_parts(s, d).project("size"), _parts(s, d, 10, 2, 80).project("size")), "size__lb", "size__sg", "size__ub"),
    f"{_AGAINST.format(a=_PARTS, b=box_sql('part', 'p_partkey', 'p_size', 10, 2, 80))} SELECT lb AS size__lb, sg AS size__sg, ub AS size__ub, CAST(least(ml, must) AS BIGINT) AS _m_lb, CAST(least(greatest(least(mg, gs), least(ml, must)), least(mu, may)) AS BIGINT) AS _m_sg, CAST(least(mu, may) AS BIGINT) AS _m_ub FROM c WHERE least(mu, may) > 0",
)
add(
    "ra_rollup",
    lambda s, d: A.rollup(customers(s, d, keep=("c_nationkey", "c_mktsegment")), ["c_mktsegment", "c_nationkey"], {"total": ("sum", "bal")}).df.select(F.coalesce("c_mktsegment", F.lit("*")).alias("segment"), F.coalesce("c_nationkey", F.lit(-1)).alias("nation"), "total__lb", "total__sg", "total__ub"),
    f"SELECT coalesce(c_mktsegment, '*') AS segment, coalesce(c_nationkey, -1) AS nation, CAST(sum(lb) AS BIGINT) AS total__lb, CAST(sum(sg) AS BIGINT) AS total__sg, CAST(sum(ub) AS BIGINT) AS total__ub FROM ({CUSTOMERS(keep='c_mktsegment, c_nationkey')}) GROUP BY ROLLUP (c_mktsegment, c_nationkey)",
)
add("ranking_row_number", lambda s, d: A.ranking(customers(s, d), ["bal"], "row_number").df.select(RID, "row_number__lb", "row_number__ub"), f"{rank_cte(CUSTOMERS())} SELECT rid AS _rid, pl + 1 AS row_number__lb, pu + 1 AS row_number__ub FROM p")
add(
    "ranking_ntile",
    lambda s, d: A.ranking(customers(s, d), ["bal"], "ntile").df.select(RID, "ntile__lb", "ntile__ub"),
    f"""{rank_cte(CUSTOMERS())}, n AS (SELECT sum(wl) AS n0, sum(wu) AS n2 FROM p) SELECT rid AS _rid, CAST(greatest(1, floor(pl * 4 / n2) + 1) AS BIGINT) AS ntile__lb, CAST(least(4, floor(pu * 4 / greatest(n0, pu + 1)) + 1) AS BIGINT) AS ntile__ub FROM p, n""",
)
_SMALLER = f"""WITH b AS ({_PARTS}), q AS (SELECT t.rid, count(CASE WHEN s.ub < t.lb THEN 1 END) AS n0, count(CASE WHEN s.lb < t.ub AND s.rid <> t.rid THEN 1 END) AS n2,
 count(DISTINCT CASE WHEN s.lb = s.ub AND s.ub < t.lb THEN s.lb END) AS d0, count(DISTINCT CASE WHEN s.lb = s.ub AND s.lb < t.ub THEN s.lb END) + count(CASE WHEN s.lb < s.ub AND s.lb < t.ub AND s.rid <> t.rid THEN 1 END) AS d2 FROM b t CROSS JOIN b s GROUP BY t.rid)"""
add("ranking_rank", lambda s, d: A.ranking(_parts(s, d), ["size"], "rank").df.select(RID, "rank__lb", "rank__ub"), f"{_SMALLER} SELECT rid AS _rid, n0 + 1 AS rank__lb, n2 + 1 AS rank__ub FROM q")
add("ranking_dense_rank", lambda s, d: A.ranking(_parts(s, d), ["size"], "dense_rank").df.select(RID, "dense_rank__lb", "dense_rank__ub"), f"{_SMALLER} SELECT rid AS _rid, d0 + 1 AS dense_rank__lb, d2 + 1 AS dense_rank__ub FROM q")
add("ranking_percent_rank", lambda s, d: A.ranking(_parts(s, d), ["size"], "percent_rank").df.select(RID, "percent_rank__lb", "percent_rank__ub"), f"{_SMALLER} SELECT rid AS _rid, n0 / ((SELECT count(*) FROM q) - 1) AS percent_rank__lb, least(1.0, n2 / ((SELECT count(*) FROM q) - 1)) AS percent_rank__ub FROM q")
_LAG = window_sql(CUSTOMERS(), "min", -1, -1)
add(
    "lag_bounds",
    lambda s, d: A.neighbour(customers(s, d), "bal", ["bal"], -1).df.select(RID, "x__lb", "x__ub"),
    f"{_LAG.rpartition(' SELECT ')[0]}, g AS (SELECT rid, min(CASE WHEN c OR 1 - nc > 0 THEN vl END) AS lo, max(CASE WHEN c OR 1 - nc > 0 THEN vh END) AS hi FROM n GROUP BY rid) SELECT p.rid AS _rid, lo AS x__lb, hi AS x__ub FROM p LEFT JOIN g USING (rid)",
)
add(
    "end_values",
    lambda s, d: A.end_values(customers(s, d, 20, 100_000, 10, 10, keep=("c_nationkey",)), "bal", ["bal"], ["c_nationkey"]),
    f"""{rank_cte(CUSTOMERS(20, 100_000, 10, 10, keep='c_nationkey'), part='c_nationkey')}, n AS (SELECT c_nationkey, sum(wl) AS n0 FROM p GROUP BY c_nationkey)
SELECT c_nationkey, min(CASE WHEN pl = 0 THEN lb END) AS first__lb, max(CASE WHEN pl = 0 THEN ub END) AS first__ub, min(CASE WHEN pu >= n0 - 1 THEN lb END) AS last__lb, max(CASE WHEN pu >= n0 - 1 THEN ub END) AS last__ub,
 arg_min(sg, pg) FILTER (WHERE wg > 0) AS first__sg, arg_max(sg, pg) FILTER (WHERE wg > 0) AS last__sg FROM p JOIN n USING (c_nationkey) GROUP BY c_nationkey""",
)
add(
    "ra_theta",
    lambda s, d: _m3(A.theta_join(suppliers(s, d, 20, 1_000_000, 10), suppliers(s, d, 5, 1_000_000), lambda c: E.rlt(c("bal"), c("r_bal"))), "bal__lb", "bal__ub", "r_bal__lb", "r_bal__ub"),
    f"SELECT a.lb AS bal__lb, a.ub AS bal__ub, b.lb AS r_bal__lb, b.ub AS r_bal__ub, CASE WHEN a.ub < b.lb THEN a.ml ELSE 0 END AS _m_lb, CASE WHEN a.sg < b.sg THEN a.mg ELSE 0 END AS _m_sg, a.mu AS _m_ub FROM ({SUPPLIERS(20, 1_000_000, 10)}) a JOIN ({SUPPLIERS(5, 1_000_000)}) b ON a.lb < b.ub",
)
for _n, _anti in (("ra_semi_overlap", False), ("ra_anti_overlap", True)):
    add(
        _n,
        lambda s, d, anti=_anti: _m3(A.semi_join(_parts(s, d), A.select((x := _parts(s, d, 10, 2, 80)), E.rlt(x.c("size"), E.rlit(30))), [("size", "size")], anti), RID),
        f"""WITH b AS (SELECT lb, sg, ub, CASE WHEN ub < 30 THEN ml ELSE 0 END AS ml, CASE WHEN sg < 30 THEN mg ELSE 0 END AS mg FROM ({box_sql('part', 'p_partkey', 'p_size', 10, 2, 80)}) WHERE lb < 30),
t AS (SELECT a.rid, bool_or(coalesce(a.lb = a.ub AND b.lb = b.ub AND a.lb = b.lb AND b.ml > 0, false)) AS c, bool_or(coalesce(a.sg = b.sg AND b.mg > 0, false)) AS g, bool_or(b.lb IS NOT NULL) AS p FROM ({_PARTS}) a LEFT JOIN b ON a.lb <= b.ub AND b.lb <= a.ub GROUP BY a.rid)
SELECT rid AS _rid, CAST({'NOT p' if _anti else 'c'} AS BIGINT) AS _m_lb, CAST({'NOT g' if _anti else 'g'} AS BIGINT) AS _m_sg, CAST(1 AS BIGINT) AS _m_ub FROM t WHERE {'NOT c' if _anti else 'p'}""",
    )

# ---- workloads ------------------------------------------------------------------------------

for _n, (_q, _sql) in X.WORKLOADS.items():
    add(_n, _q, _sql)

# ---- baselines and measures -----------------------------------------------------------------

add(
    "base_det",
    lambda s, d: B.baseline_det(customers(s, d), B.positions(["bal"])).select(RID, "pos"),
    f"SELECT c_custkey AS _rid, row_number() OVER (ORDER BY {money('c_acctbal')}, c_custkey) - 1 AS pos FROM customer",
)
_SAMPLED = lambda n: f"""WITH b AS ({CUSTOMERS(20, 100_000)}), w AS (SELECT rid, w.w AS w, lb + ((((rid + w.w * 613) * 7919 + 60 * 104729) % 10007) * 997) % (ub - lb + 1) AS v FROM b CROSS JOIN (SELECT CAST(range AS BIGINT) AS w FROM range({n})) w),
p AS (SELECT rid, row_number() OVER (PARTITION BY w ORDER BY v, rid) - 1 AS pos FROM w) SELECT rid AS _rid, min(pos) AS pos__lb, max(pos) AS pos__ub, count(*) AS worlds FROM p GROUP BY rid"""  # noqa: E731
for _k in (10, 20):
    add(f"base_sampled{_k}", lambda s, d, k=_k: B.baseline_sampled(customers(s, d, 20, 100_000), B.positions(["bal"]), k, "pos").drop(DUP), _SAMPLED(_k))
_TOP = lambda cond: f"{rank_cte(SUPPLIERS(20, 1_000_000))} SELECT rid AS _rid FROM p WHERE {cond}"
add("base_threshold_certain", lambda s, d: B.threshold_topk(suppliers(s, d, 20, 1_000_000), ["bal"], 10, 1.0).select(RID), _TOP("pu < 10 AND wl = 1"))
add("base_threshold_possible", lambda s, d: B.threshold_topk(suppliers(s, d, 20, 1_000_000), ["bal"], 10, 0.0).select(RID), _TOP("pl < 10"))
add("base_threshold_half", lambda s, d: B.threshold_topk(suppliers(s, d, 20, 1_000_000), ["bal"], 10, 0.5))
add(
    "base_most_likely_list",
    lambda s, d: B.most_likely_topk(suppliers(s, d, 20, 1_000_000), ["bal"], 3),
    _SAMPLED(200).replace(CUSTOMERS(20, 100_000), SUPPLIERS(20, 1_000_000)).replace("SELECT rid, row_number()", "SELECT rid, w, row_number()").rpartition(" SELECT ")[0]
    + ", l AS (SELECT list(rid ORDER BY pos) AS ids FROM p WHERE pos < 3 GROUP BY w), best AS (SELECT ids, count(*) AS n FROM l GROUP BY ids ORDER BY n DESC, ids LIMIT 1) SELECT CAST(generate_subscripts(ids, 1) - 1 AS INTEGER) AS place, unnest(ids) AS _rid, n FROM best",
)
add("base_most_likely_pos", lambda s, d: B.most_likely_per_position(suppliers(s, d, 20, 1_000_000), ["bal"], 5))
add(
    "base_exact_bounds",
    X.exact_positions,
    f"""WITH b AS ({SUPPLIERS(60, 1_000_000, 30)}), q AS (SELECT t.rid, CAST(coalesce(sum(CASE WHEN (s.ub, s.rid) < (t.lb, t.rid) THEN s.ml END), 0) AS BIGINT) AS lb, CAST(coalesce(sum(CASE WHEN (s.lb, s.rid) < (t.ub, t.rid) THEN s.mu END), 0) AS BIGINT) AS ub FROM b t LEFT JOIN b s ON s.rid <> t.rid GROUP BY t.rid)
SELECT rid AS _rid, CAST(0 AS INTEGER) AS _dup, lb, ub, lb AS pos__lb, ub AS pos__ub FROM q""",
)


_REGIONS = box_sql("(SELECT n_regionkey, CAST(floor(sum(s_acctbal) / 1000) AS BIGINT) AS v FROM supplier JOIN nation ON n_nationkey = s_nationkey GROUP BY n_regionkey)", "n_regionkey", "v", 100, 5)
add(
    "wl_sales_top2",
    X.sales_top2,
    f"""WITH RECURSIVE f AS (SELECT *, row_number() OVER (ORDER BY rid) AS i FROM ({_REGIONS})), o AS (SELECT i, rid, unnest(range(lb, ub + 1)) AS v FROM f),
w AS (SELECT CAST(0 AS BIGINT) AS i, CAST([] AS STRUCT(v BIGINT, rid BIGINT)[]) AS xs UNION ALL SELECT o.i, list_append(xs, {{'v': o.v, 'rid': o.rid}}) FROM w JOIN o ON o.i = w.i + 1),
t AS (SELECT list_transform(list_sort(xs)[1:2], lambda x: x.rid) AS ids FROM w WHERE i = (SELECT max(i) FROM f)),
n AS (SELECT count(*) AS n FROM t), l AS (SELECT ids, count(*) AS k FROM t GROUP BY ids ORDER BY k DESC, ids LIMIT 1),
e AS (SELECT unnest(ids) AS _rid, generate_subscripts(ids, 1) - 1 AS place FROM t), c AS (SELECT place, _rid, count(*) AS k FROM e GROUP BY place, _rid),
r AS (SELECT *, row_number() OVER (PARTITION BY place ORDER BY k DESC, _rid) AS i FROM c), m AS (SELECT _rid, sum(k) AS k FROM c GROUP BY _rid)
SELECT 'likeliest list' AS semantics, CAST(generate_subscripts(ids, 1) - 1 AS INTEGER) AS place, unnest(ids) AS _rid, CAST(k AS BIGINT) AS worlds FROM l UNION ALL SELECT 'likeliest at place', CAST(place AS INTEGER), _rid, CAST(k AS BIGINT) FROM r WHERE i = 1
UNION ALL SELECT 'certain member', NULL, _rid, CAST(k AS BIGINT) FROM m, n WHERE k = n.n UNION ALL SELECT 'possible member', NULL, _rid, CAST(k AS BIGINT) FROM m""",
)


def _sort_quality(s: SparkSession, d: str) -> DataFrame:
    """Positions against tight ones: those of the pair count, which no world can exceed and some world reaches."""
    rf = suppliers(s, d, 20, 1_000_000)
    tight = order.rank(rf, ["bal"], method="naive").df
    parts = {"bounds": order.rank(rf, ["bal"]).df, "sample20": B.baseline_sampled(rf, B.positions(["bal"]), 20, "pos")}
    out = [metrics.quality(b, tight, [RID, DUP], "pos__lb", "pos__ub").withColumn("method", F.lit(n)) for n, b in parts.items()]
    return out[0].unionByName(out[1])


_PPM = lambda b0, b1: f"""count(*) AS n_rows, {', '.join(f"CAST(floor(avg({x}) * 1000000 + 0.5) AS BIGINT) AS {n}" for n, x in (
    ('recall_ppm', f"CASE WHEN pl = pu THEN CASE WHEN least({b1}, pu) >= greatest({b0}, pl) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END ELSE greatest(least({b1}, pu) - greatest({b0}, pl), 0)::DOUBLE / (pu - pl) END"),
    ('accuracy_ppm', f"CASE WHEN {b0} = {b1} THEN CASE WHEN least({b1}, pu) >= greatest({b0}, pl) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END ELSE greatest(least({b1}, pu) - greatest({b0}, pl), 0)::DOUBLE / ({b1} - {b0}) END"),
    ('formula_ppm', f"CASE WHEN greatest({b1}, pu) = least({b0}, pl) THEN 1.0::DOUBLE ELSE (greatest({b1}, pu) - least({b0}, pl))::DOUBLE / nullif(greatest(least({b1}, pu) - greatest({b0}, pl), 0), 0) END"),
    ('size_ratio_ppm', f"CASE WHEN pl = pu AND {b0} = {b1} THEN 1.0::DOUBLE ELSE ({b1} - {b0})::DOUBLE / nullif(pu - pl, 0) END"),
))}"""  # noqa: E731
_TIGHT = rank_cte(SUPPLIERS(20, 1_000_000))
add(
    "quality_sort",
    _sort_quality,
    f"""WITH t AS ({_TIGHT} SELECT rid, pl, pu FROM p), s AS ({_SAMPLED(20).replace(CUSTOMERS(20, 100_000), SUPPLIERS(20, 1_000_000))})
SELECT {_PPM('pl', 'pu')}, 'bounds' AS method FROM t UNION ALL SELECT {_PPM('s.pos__lb', 's.pos__ub')}, 'sample20' FROM t JOIN s ON s._rid = t.rid""",
)
add("quality_iceberg", X.quality_iceberg)
add("quality_crimes", X.quality_crimes)
add("quality_healthcare", X.quality_healthcare)
add("quality_curve", X.quality_curve)
add("soundness_sort", lambda s, d: metrics.soundness(order.rank((rf := customers(s, d, 20, 100_000)), ["bal"]).df, B.positions(["bal"])(B.sample_worlds(rf, 20)), [RID, DUP], "pos"), "SELECT CAST(20 * count(*) AS BIGINT) AS n, CAST(1.0 AS DOUBLE) AS inside FROM customer")
add("heap_trace", X.heap_trace)
add("heap_sweep", X.heap_sweep)
add(
    "stream_tumbling_bounds",
    X.stream_tumbling,
    """WITH e AS (SELECT epoch(ts) // 1 AS t, event_id FROM events), r AS (SELECT CAST(floor(epoch(ts)) AS BIGINT) - (event_id * 7919) % 300 AS a, CAST(floor(epoch(ts)) AS BIGINT) + (event_id * 104729) % 300 AS b FROM events),
w AS (SELECT unnest(range(a - (a % 3600), b - (b % 3600) + 1, 3600)) AS s, a, b FROM r) SELECT CAST(s AS BIGINT) AS start_s, CAST(sum(CASE WHEN s <= a AND b < s + 3600 THEN 1 ELSE 0 END) AS BIGINT) AS n_certain, CAST(count(*) AS BIGINT) AS n_possible FROM w GROUP BY s""",
)
