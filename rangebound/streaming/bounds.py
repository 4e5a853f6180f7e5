"""Counts and sums over windows of events whose time is only known to lie in a range.

An event is certainly in a window that holds its whole range, possibly in each that it meets. A watermark follows the
late end of the ranges, by way of the windows' starts: an event's last window starts at most a window's width before its
late end. With append output a window is given out, and its state freed, once the watermark has passed its start by
the window's width and the longest range; complete output keeps all windows, and frees nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def candidate_windows(df: DataFrame, ts_lb: str, ts_ub: str, width: int, slide: int | None = None) -> DataFrame:
    """A row for each window (start: whole seconds) that an event may be in, with is_certain."""
    slide = slide or width
    a, b = F.unix_seconds(F.col(ts_lb).cast("timestamp")), F.unix_seconds(F.col(ts_ub).cast("timestamp"))
    first = (F.floor((a - width) / slide) + 1) * slide
    last = F.floor(b / slide) * slide
    out = df.withColumn("start_s", F.explode(F.sequence(first, last, F.lit(slide))))
    return out.withColumns({"is_certain": (F.col("start_s") <= a) & (b < F.col("start_s") + width), "win_start": F.timestamp_seconds("start_s")})


def group_bounds(df: DataFrame, ts_lb: str, ts_ub: str, width: int, slide: int | None = None, keys: tuple[str, ...] = (), value: str | None = None, watermark: str | None = None, longest: int = 0) -> DataFrame:
    """Certain and possible count (and sum bounds of a certain value) by window and key; for batch and streaming frames.
    watermark: how late an event may come; longest: seconds of the longest range, as an event is in windows as
    early as that before its late end. Rows beyond both are dropped, and counted (see run_available)."""
    c = candidate_windows(df, ts_lb, ts_ub, width, slide)
    if watermark and df.isStreaming:
        c = c.withWatermark("win_start", f"{longest + width} seconds {watermark}")
    one = F.col("is_certain").cast("long")
    aggs = [F.sum(one).alias("n_certain"), F.count(F.lit(1)).alias("n_possible")]
    if value:
        v, zero = F.col(value), F.lit(0).cast("long")
        aggs += [F.sum(F.when(F.col("is_certain"), v).otherwise(F.least(v, zero))).alias("sum_lb"), F.sum(F.when(F.col("is_certain"), v).otherwise(F.greatest(v, zero))).alias("sum_ub")]
    return c.groupBy(*keys, "win_start").agg(*aggs)


def session_bounds(df: DataFrame, ts_lb: str, ts_ub: str, gap: str, keys: tuple[str, ...]) -> DataFrame:
    """Sessions by the latest and by the earliest times: the number of events in each."""
    late = df.groupBy(*keys, F.session_window(F.col(ts_ub).cast("timestamp"), gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).withColumn("by", F.lit("latest"))
    early = df.groupBy(*keys, F.session_window(F.col(ts_lb).cast("timestamp"), gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).withColumn("by", F.lit("earliest"))
    return late.unionByName(early).select(*keys, "by", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def run_available(streaming: DataFrame, path: str, mode: str = "complete", late: list[int] | None = None) -> DataFrame:
    """Runs a streaming aggregate over what is there now; the result from files all executors see. complete: the last
    whole result; append: the windows that are closed. late: gets the number of rows dropped behind the watermark."""
    parts: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        target = f"{path}/result-{number}"
        batch.write.mode("overwrite").parquet(target)
        parts.append(target)

    q = streaming.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    if late is not None:
        late.append(sum(int(op.numRowsDroppedByWatermark) for p in q.recentProgress for op in p.stateOperators))
    spark = streaming.sparkSession
    if not parts:
        return spark.createDataFrame([], streaming.schema)
    return spark.read.schema(streaming.schema).parquet(*(parts if mode == "append" else parts[-1:]))


def stream_window(df: DataFrame, key: str, rid: str, ts_lb: str, ts_ub: str, value: str, before: int, watermark: str, longest: int) -> DataFrame:
    """For a stream: sum bounds over the values of events that come within `before` seconds before each event or with it.
    (key, rid, x__lb, x__ub), given out once the watermark has passed an event's late end by `longest` seconds, the longest
    range: no event still to come can lie in its window then. The state of a key is the events whose window is
    open, or that an open one reaches. Values are certain; times are ranges."""
    slim = df.select(F.col(key).alias("key"), F.col(rid).alias("rid"), F.unix_seconds(F.col(ts_lb).cast("timestamp")).alias("a"), F.unix_seconds(F.col(ts_ub).cast("timestamp")).alias("b"), F.col(value).cast("long").alias("v"), F.col(ts_ub).cast("timestamp").alias("late")).withWatermark("late", watermark)

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(state.get) if state.exists else [[], [], [], [], []]
        a, b, v, ids, done = (list(x) for x in held)
        for t in batches:
            a += t["a"].tolist()
            b += t["b"].tolist()
            v += t["v"].tolist()
            ids += t["rid"].tolist()
            done += [0] * len(t)
        now = state.getCurrentWatermarkMs() // 1000 - longest
        out = []
        for i in range(len(a)):
            if done[i] or b[i] >= now:
                continue
            low = high = v[i]
            for j in range(len(a)):
                if j != i and a[j] <= b[i] and b[j] >= a[i] - before:
                    sure = a[j] >= b[i] - before and b[j] <= a[i]
                    low += v[j] if sure else min(v[j], 0)
                    high += v[j] if sure else max(v[j], 0)
            done[i] = 1
            out.append((k[0], ids[i], low, high))
        # An event may go once it has been given out and no open window reaches back to it.
        first = min([x for x, d in zip(a, done, strict=True) if not d] + [now])
        keep = [i for i in range(len(a)) if not done[i] or b[i] >= first - before]
        if keep:
            state.update(tuple([x[i] for i in keep] for x in (a, b, v, ids, done)))
            state.setTimeoutTimestamp((max(now, max(b[i] for i in keep)) + longest + before + 1) * 1000)
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["key", "rid", "x__lb", "x__ub"])

    kind = dict(slim.dtypes)["key"]
    return slim.groupBy("key").applyInPandasWithState(step, f"key {kind}, rid long, x__lb long, x__ub long", "a array<long>, b array<long>, v array<long>, id array<long>, done array<long>", "append", GroupStateTimeout.EventTimeTimeout)
