"""Experiment workloads on the given tables, with their SQL."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.heaps import ConnectedHeap, UnconnectedHeaps
from .operators import algebra as A
from .operators import order, window
from .plans import baselines as B
from .plans import exact
from .schema import DUP, RID, RangeFrame
from .sources import ingest
from .sources.ingest import cents
from .streaming import bounds


#: Order ids of a heap trace; about 1,000 line items of the given tables.
ORDERS_PER_TRACE = 250


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _top(rf: RangeFrame, *cols: str) -> DataFrame:
    return rf.df.select(*cols, "pos__lb", "pos__ub", "_m_lb", "_m_sg", "_m_ub")


def _counts(df: DataFrame, key: str, u: int, r: int) -> RangeFrame:
    """Rows per key, counted first; the count is then uncertain."""
    return ingest.inject(df.groupBy(key).agg(F.count(F.lit(1)).alias("n")), key, {"n": F.col("n")}, u, r)


def _day(df: DataFrame, ts: str) -> DataFrame:
    return df.select(F.datediff(F.to_date(ts), F.lit("1970-01-01").cast("date")).cast("long").alias("day"))


def x11_frequency_top3(s: SparkSession, d: str) -> DataFrame:
    """The three most frequent part sizes, frequency uncertain."""
    return _top(order.topk(_counts(read(s, d, "part").select(F.col("p_size").cast("long").alias("size")), "size", 20, 5), ["n"], 3, desc=["n"]), RID)


def x12_rolling_sum(s: SparkSession, d: str) -> DataFrame:
    """Orders of a day and the three days that follow, counts uncertain."""
    daily = _day(read(s, d, "orders"), "o_orderdate").groupBy("day").agg(F.count(F.lit(1)).alias("n"))
    rf = ingest.inject(daily, "day", {"n": F.col("n")}, 20, 3, keep=("day",))
    return window.window(rf, "sum", "n", ["day"], 0, 3).df.select("day", "x__lb", "x__sg", "x__ub")


def x13_busiest_days(s: SparkSession, d: str) -> DataFrame:
    return _top(order.topk(_counts(_day(read(s, d, "lineitem"), "l_shipdate"), "day", 20, 5), ["n"], 3, desc=["n"]), RID)


def x14_neighbour_min(s: SparkSession, d: str) -> DataFrame:
    """Least order year among neighbours by uncertain price, in one priority class."""
    o = read(s, d, "orders").where(F.col("o_orderpriority") == "1-URGENT").withColumn("year", F.year("o_orderdate").cast("long"))
    rf = ingest.inject(o, "o_orderkey", {"price": cents("o_totalprice")}, 20, 100_000, keep=("year",))
    return window.window(rf, "min", "year", ["price"], -1, 1, ties=False).df.select(RID, "x__lb", "x__ub")


def _segment(s: SparkSession, d: str) -> RangeFrame:
    c = read(s, d, "customer").where(F.col("c_mktsegment") == "BUILDING")
    return ingest.inject(c, "c_custkey", {"bal": cents("c_acctbal")}, 20, 100_000)


def x15_best5(s: SparkSession, d: str) -> DataFrame:
    return _top(order.topk(_segment(s, d), ["bal"], 5, desc=["bal"]), RID)


def x16_running_rank(s: SparkSession, d: str) -> DataFrame:
    return window.window(_segment(s, d), "count", None, ["bal"], None, 0, desc=["bal"]).df.select(RID, "x__lb", "x__ub")


def x19_closure(s: SparkSession, d: str) -> DataFrame:
    """Possible and certain cheapest orders, joined to customers, counted by nation."""
    o = ingest.inject(read(s, d, "orders"), "o_orderkey", {"price": cents("o_totalprice")}, 20, 1_000_000, keep=("o_custkey",))
    top = order.topk(o, ["price"], 50, ties=False)
    c = ingest.from_certain(read(s, d, "customer").select("c_custkey", "c_nationkey"), "c_custkey")
    joined = A.join(top.project("price", "o_custkey"), c, [("o_custkey", "c_custkey")])
    return A.aggregate(joined, ["r_c_nationkey"], {"n": ("count", None)}).df.select("r_c_nationkey", "n__lb", "n__ub")


def x20_repair(s: SparkSession, d: str) -> DataFrame:
    """Line items of one order and number that disagree become one row with the hull of their values; then the ten dearest."""
    li = read(s, d, "lineitem").select("l_orderkey", F.col("l_linenumber").cast("long").alias("l_linenumber"), cents("l_extendedprice").alias("price"))
    rf = ingest.from_repairs(li, ("l_orderkey", "l_linenumber"), ("price",), F.col("l_orderkey") * 16 + F.col("l_linenumber"))
    return _top(order.topk(rf, ["price"], 10, desc=["price"], ties=False), RID, "price__lb", "price__ub")


def x20_impute(s: SparkSession, d: str) -> DataFrame:
    """Every tenth value of an event is blanked and becomes its type's range."""
    e = read(s, d, "events").select("event_id", "event_type", F.when((F.col("event_id") * 7919) % 10 == 3, None).otherwise(cents("value")).alias("value"))
    return ingest.from_imputation(e, "event_id", "value", "event_type").df.select(RID, "value__lb", "value__sg", "value__ub")


def x21_labels(s: SparkSession, d: str) -> DataFrame:
    """Documents in order of a quality that is unknown, 0 to 1, where no label is given; the worst first."""
    labels = read(s, d, "labels").groupBy("doc_id").agg(F.max("quality").cast("long").alias("q"))
    docs = read(s, d, "documents").select("doc_id").join(labels, "doc_id", "left")
    rf = ingest.from_intervals(docs, "doc_id", {"q": (F.coalesce("q", F.lit(0)).cast("long"), F.coalesce("q", F.lit(0)).cast("long"), F.coalesce("q", F.lit(1)).cast("long"))})
    return order.rank(rf, ["q"], method="cdf").df.select(RID, "pos__lb", "pos__ub")


def exact_positions(s: SparkSession, d: str) -> DataFrame:
    """Exact positions of all suppliers, row by row against all others, beside the bounds."""
    rf = ingest.inject(read(s, d, "supplier"), "s_suppkey", {"bal": cents("s_acctbal")}, 60, 1_000_000, e=30)
    return B.exact_positions(rf, "bal").join(order.rank(rf, ["bal"]).df.select(RID, DUP, "pos__lb", "pos__ub"), [RID, DUP])


def sales_top2(s: SparkSession, d: str) -> DataFrame:
    """The two regions of least supplier balance, in thousands, each known to lie in a range: the list that most worlds have, who
    most often holds each place, and who is certainly and possibly among the two. All worlds of the five regions are tried."""
    by = read(s, d, "supplier").join(read(s, d, "nation"), F.col("n_nationkey") == F.col("s_nationkey")).groupBy("n_regionkey").agg(F.floor(F.sum("s_acctbal") / 1000).cast("long").alias("v"))
    rf = ingest.inject(by, "n_regionkey", {"v": F.col("v")}, 100, 5)
    lists = B.topk_lists(rf, "v", 2)
    out = [("likeliest list", i, r, n) for ids, n in lists[:1] for i, r in enumerate(ids)]
    held: dict[tuple[int, int], int] = {}
    for ids, n in lists:
        for place, r in enumerate(ids):
            held[place, r] = held.get((place, r), 0) + n
    for place in range(2):
        n, r = max((n, -r) for (p, r), n in held.items() if p == place)
        out.append(("likeliest at place", place, -r, n))
    total = sum(n for _, n in lists)
    for r in sorted({r for _, r in held}):
        n = sum(v for (_, x), v in held.items() if x == r)
        out += [("possible member", None, r, n)] + ([("certain member", None, r, n)] if n == total else [])
    return s.createDataFrame(out, f"semantics string, place int, {RID} long, worlds long")


def heap_trace(s: SparkSession, d: str) -> DataFrame:
    """The same pops from connected and unconnected heaps over line item prices, and the comparisons each made. All
    line items are replayed, in traces of a fixed number of order ids, so traces don't grow with the table."""
    li = read(s, d, "lineitem").select(F.expr(f"l_orderkey div {ORDERS_PER_TRACE}").alias("part"), (F.col("l_orderkey") * 16 + F.col("l_linenumber")).alias("k"), cents("l_extendedprice").alias("v"), F.col("l_quantity").cast("long").alias("q"))

    def replay(pdf: pd.DataFrame) -> pd.DataFrame:
        recs = sorted(zip(pdf["k"], pdf["v"], pdf["q"], strict=True))
        out = []
        for name, kind in (("connected", ConnectedHeap), ("unconnected", UnconnectedHeaps)):
            h = kind([lambda r: r[1], lambda r: r[2], lambda r: -r[1]])
            pops = 0
            for i, r in enumerate(recs):
                h.insert(r)
                if len(h) > 64:
                    pops = (pops * 31 + int(h.pop(i % 3)[1])) % 1_000_000_007
            while len(h):
                pops = (pops * 31 + int(h.pop(0)[1])) % 1_000_000_007
            out.append((int(pdf["part"].iloc[0]), name, len(recs), pops, h.ops))
        return pd.DataFrame(out, columns=["part", "kind", "n", "digest", "ops"])

    return li.groupBy("part").applyInPandas(replay, "part long, kind string, n long, digest long, ops long")


#: Share of uncertain rows in percent, and largest range, of the heap experiment.
HEAP_SETTINGS = tuple((u, r) for u in (1, 5) for r in (2_000, 15_000, 30_000))


def heap_sweep(s: SparkSession, d: str, settings: tuple = HEAP_SETTINGS, most: int | None = None, kinds: tuple[str, ...] = ("connected", "unconnected")) -> DataFrame:
    """The sweep of sum windows over [-2, 0] by price (ranges up to r dollars), with connected and unconnected heaps: comparisons, largest heap
    and a digest of the bounds. Chunks of 1,000 orders by id are swept each on its own; `most` orders in all (bench)."""
    o = read(s, d, "orders")
    if most:
        o = o.orderBy("o_orderkey").limit(most)
    parts = []
    for u, r in settings:
        rf = ingest.inject(o, "o_orderkey", {"price": cents("o_totalprice")}, u, 100 * r)
        parts.append(rf.df.select(F.lit(u).alias("u"), F.lit(r).alias("r"), F.expr(f"{RID} div 1000").alias("part"), RID, F.col("price__lb").alias("lo"), F.col("price__ub").alias("hi")))
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        recs = list(zip(pdf["lo"].tolist(), pdf["hi"].tolist(), pdf[RID].tolist(), strict=True))
        starts, ends = sorted((a, i) for a, _, i in recs), sorted((b, i) for _, b, i in recs)
        low = [bisect_left(ends, (a, i)) for a, _, i in recs]
        high = [bisect_left(starts, (b, i)) - (a < b) for a, b, i in recs]
        out = []
        for name in kinds:
            got, n = window.sweep_windows([(p, q, 1, a, b, True, i) for (a, b, i), p, q in zip(recs, low, high, strict=True)], "sum", -2, 0, name == "connected")
            digest = sum(x[0] * 31 + x[1] * 7 + x[2] for x in got) % 1_000_000_007
            out.append((int(pdf["u"].iloc[0]), int(pdf["r"].iloc[0]), int(pdf["part"].iloc[0]), name, len(recs), digest, n["ops"], n["widest"]))
        return pd.DataFrame(out, columns=["u", "r", "part", "kind", "n", "digest", "ops", "widest"])

    each = rows.groupBy("u", "r", "part").applyInPandas(sweep, "u int, r int, part long, kind string, n long, digest long, ops long, widest long")
    return each.groupBy("u", "r", "kind").agg(F.sum("n").alias("n"), F.sum("digest").alias("digest"), F.sum("ops").alias("ops"), F.max("widest").alias("widest"))


def quality_iceberg(s: SparkSession, d: str) -> DataFrame:
    """Orders of a day and the three that follow; one day in a hundred is only known to lie within ten days."""
    daily = _day(read(s, d, "orders"), "o_orderdate").groupBy("day").agg(F.count(F.lit(1)).alias("n"))
    return exact.window_quality(ingest.inject(daily, "day", {"at": F.col("day")}, 1, 10, keep=("n",)), "sum", "n", "at", 0, 3)


def quality_crimes(s: SparkSession, d: str) -> DataFrame:
    """Least order year among neighbours by price, one price in a thousand uncertain."""
    o = read(s, d, "orders").where(F.col("o_orderpriority") == "1-URGENT").withColumn("year", F.year("o_orderdate").cast("long"))
    return exact.window_quality(ingest.inject(o, "o_orderkey", {"price": cents("o_totalprice")}, 1, 1_000_000, keep=("year",), per=1000), "min", "year", "price", -1, 1)


def quality_healthcare(s: SparkSession, d: str) -> DataFrame:
    """Sum of a balance and the two below it in one segment, one balance in a hundred uncertain."""
    c = read(s, d, "customer").where(F.col("c_mktsegment") == "BUILDING")
    return exact.window_quality(ingest.inject(c, "c_custkey", {"bal": cents("c_acctbal")}, 1, 50_000), "sum", "bal", "bal", -2, 0)


def quality_curve(s: SparkSession, d: str) -> DataFrame:
    """The same windows over all customers, by share of uncertain rows and by range."""
    out = None
    for u, r in ((1, 1_000), (5, 1_000), (20, 1_000), (5, 2_000), (5, 5_000)):
        got = exact.window_quality(ingest.inject(read(s, d, "customer"), "c_custkey", {"bal": cents("c_acctbal")}, u, r), "sum", "bal", "bal", -2, 0).withColumns({"u": F.lit(u), "r": F.lit(r)})
        out = got if out is None else out.unionByName(got)
    return out


def _event_ranges(df: DataFrame) -> DataFrame:
    t = F.unix_seconds(F.col("ts").cast("timestamp"))
    return df.select("event_id", F.timestamp_seconds(t - (F.col("event_id") * 7919) % 300).alias("ts_lb"), F.timestamp_seconds(t + (F.col("event_id") * 104729) % 300).alias("ts_ub"))


def stream_tumbling(s: SparkSession, d: str) -> DataFrame:
    """Hourly counts of events whose time is known to ten minutes, run as a stream."""
    from .plans.scratch import scratch_dir

    path = f"{d}/events.parquet"
    at = s._jvm.org.apache.hadoop.fs.Path(path)
    folder = at.getFileSystem(s._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()
    stream = s.readStream.schema(s.read.parquet(path).schema)
    # A stream's source is a folder; a single file is picked from its own.
    source = stream.parquet(path) if folder else stream.option("pathGlobFilter", "events.parquet").parquet(d)
    got = bounds.run_available(bounds.group_bounds(_event_ranges(source), "ts_lb", "ts_ub", 3600, watermark="2 hours"), scratch_dir(s))
    return got.select(F.unix_seconds("win_start").alias("start_s"), "n_certain", "n_possible")


def _sql() -> dict[str, str]:
    from . import queries as q

    top = lambda box, k, desc, extra="": q.topk_sql(box, k, desc).replace("SELECT rid AS _rid, dup AS _dup,", f"SELECT rid AS _rid,{extra}")
    freq = "(SELECT CAST(p_size AS BIGINT) AS size, count(*) AS n FROM part GROUP BY p_size)"
    day = lambda c: f"CAST(date_diff('day', DATE '1970-01-01', CAST({c} AS DATE)) AS BIGINT)"
    ship = f"(SELECT {day('l_shipdate')} AS day, count(*) AS n FROM lineitem GROUP BY 1)"
    daily = f"(SELECT {day('o_orderdate')} AS day, count(*) AS n FROM orders GROUP BY 1)"
    building = q.box_sql("customer", "c_custkey", q.money("c_acctbal"), 20, 100_000, where="WHERE c_mktsegment = 'BUILDING'")
    urgent = q.box_sql("orders", "o_orderkey", q.money("o_totalprice"), 20, 100_000, where="WHERE o_orderpriority = '1-URGENT'", keep="CAST(year(o_orderdate) AS BIGINT) AS y")
    repair = f"SELECT l_orderkey * 16 + l_linenumber AS rid, min({q.money('l_extendedprice')}) AS lb, min({q.money('l_extendedprice')}) AS sg, max({q.money('l_extendedprice')}) AS ub, CAST(1 AS BIGINT) AS ml, CAST(1 AS BIGINT) AS mg, CAST(1 AS BIGINT) AS mu FROM lineitem GROUP BY l_orderkey, l_linenumber"
    # Only rows that may be among the first k are ranked by pairs; the rest can't change their positions below k.
    return {
        "wl_freq_top3": top(q.box_sql(freq, "size", "n", 20, 5), 3, True),
        "wl_busiest_days": top(q.box_sql(ship, "day", "n", 20, 5), 3, True),
        "wl_best5": top(building, 5, True),
        "wl_rolling_sum": f"WITH b AS ({q.box_sql(daily, 'day', 'n', 20, 3)}) SELECT rid AS day, CAST(sum(lb) OVER w AS BIGINT) AS x__lb, CAST(sum(sg) OVER w AS BIGINT) AS x__sg, CAST(sum(ub) OVER w AS BIGINT) AS x__ub FROM b WINDOW w AS (ORDER BY rid ROWS BETWEEN CURRENT ROW AND 3 FOLLOWING)",
        "wl_neighbour_min": q.window_sql(urgent, "min", -1, 1, "y,y").replace("rid AS _rid, dup AS _dup,", "rid AS _rid,"),
        "wl_running_rank": q._UNB(building, "CASE WHEN c THEN 1 ELSE 0 END", "1").replace("k AS (SELECT * FROM b)", "k AS (SELECT * REPLACE (-ub AS lb, -sg AS sg, -lb AS ub) FROM b)").replace("t.rid AS _rid, t.dup AS _dup,", "t.rid AS _rid,"),
        "impute_hull": "WITH e AS (SELECT event_id, event_type, CASE WHEN (event_id * 7919) % 10 = 3 THEN NULL ELSE CAST(round(value * 100) AS BIGINT) END AS v FROM events), g AS (SELECT event_type, min(v) AS lo, max(v) AS hi FROM e GROUP BY event_type) SELECT event_id AS _rid, coalesce(v, lo) AS value__lb, coalesce(v, lo) AS value__sg, coalesce(v, hi) AS value__ub FROM e JOIN g USING (event_type)",
        "label_unknown_rank": """WITH l AS (SELECT doc_id, max(quality) AS q FROM labels GROUP BY doc_id), b AS (SELECT doc_id AS rid, coalesce(q, 0) AS lb, coalesce(q, 1) AS ub FROM documents LEFT JOIN l USING (doc_id))
SELECT t.rid AS _rid, CAST(coalesce(sum(CASE WHEN (s.ub, s.rid) < (t.lb, t.rid) THEN 1 END), 0) AS BIGINT) AS pos__lb, CAST(coalesce(sum(CASE WHEN (s.lb, s.rid) < (t.ub, t.rid) THEN 1 END), 0) AS BIGINT) AS pos__ub FROM b t LEFT JOIN b s ON s.rid <> t.rid GROUP BY t.rid""",
        "repair_key_hull": f"""WITH f AS ({repair}), c AS (SELECT lb FROM f ORDER BY lb DESC LIMIT 1 OFFSET 9), b AS (SELECT f.* FROM f WHERE ub >= (SELECT lb FROM c)), k AS (SELECT *, -ub AS l, -lb AS u FROM b),
p AS (SELECT t.rid, t.lb, t.ub, CAST(coalesce(sum(CASE WHEN (s.u, s.rid) < (t.l, t.rid) THEN 1 END), 0) AS BIGINT) AS pl, CAST(coalesce(sum(CASE WHEN (s.l, s.rid) < (t.u, t.rid) THEN 1 END), 0) AS BIGINT) AS pu, CAST(coalesce(sum(CASE WHEN (-s.sg, s.rid) < (-t.sg, t.rid) THEN 1 END), 0) AS BIGINT) AS pg FROM k t LEFT JOIN k s ON s.rid <> t.rid GROUP BY t.rid, t.lb, t.ub)
SELECT rid AS _rid, lb AS price__lb, ub AS price__ub, pl AS pos__lb, least(pu, 10) AS pos__ub, CAST(pu < 10 AS BIGINT) AS _m_lb, CAST(pg < 10 AS BIGINT) AS _m_sg, CAST(1 AS BIGINT) AS _m_ub FROM p WHERE pl < 10""",
        "closure_topk_join_agg": f"""WITH f AS ({q.ORDERS(20, 1_000_000, keep='o_custkey')}), c AS (SELECT ub FROM f ORDER BY ub, rid LIMIT 1 OFFSET 49), k AS (SELECT f.* FROM f WHERE lb <= (SELECT ub FROM c)),
p AS (SELECT t.rid, t.o_custkey, coalesce(sum(CASE WHEN (s.ub, s.rid) < (t.lb, t.rid) THEN 1 END), 0) AS pl, coalesce(sum(CASE WHEN (s.lb, s.rid) < (t.ub, t.rid) THEN 1 END), 0) AS pu FROM k t LEFT JOIN k s ON s.rid <> t.rid GROUP BY t.rid, t.o_custkey)
SELECT c_nationkey AS r_c_nationkey, CAST(sum(CASE WHEN pu < 50 THEN 1 ELSE 0 END) AS BIGINT) AS n__lb, CAST(count(*) AS BIGINT) AS n__ub FROM p JOIN customer ON c_custkey = o_custkey WHERE pl < 50 GROUP BY c_nationkey""",
    }


class _Lazy(dict):
    """The SQL needs queries, which need the workloads; so it is made on first use."""

    def items(self):
        sql = _sql()
        return [(k, (f, sql.get(k))) for k, f in FUNCTIONS.items()]


FUNCTIONS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "wl_freq_top3": x11_frequency_top3,
    "wl_rolling_sum": x12_rolling_sum,
    "wl_busiest_days": x13_busiest_days,
    "wl_neighbour_min": x14_neighbour_min,
    "wl_best5": x15_best5,
    "wl_running_rank": x16_running_rank,
    "closure_topk_join_agg": x19_closure,
    "repair_key_hull": x20_repair,
    "impute_hull": x20_impute,
    "label_unknown_rank": x21_labels,
}
WORKLOADS = _Lazy()
