"""Streaming forms: stateless coding, windowed costs, sessions, drift, budgets, and joins; each has a batch twin."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxpress.functions.scalar import quantize
from ctxpress.functions.tokens import token_count
from ctxpress.operators.quant import Grid
from ctxpress.sources.metadata import MetadataStore

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def timed(df: DataFrame) -> DataFrame:
    """Event time has to be an instant for a watermark."""
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_events(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return timed(spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path))


def as_records(events: DataFrame) -> DataFrame:
    """Adds text: an event as a line for a prompt, with its token cost; works on batches and streams."""
    line = F.concat_ws(" ", F.col("event_type"), F.concat(F.lit("user"), F.col("user_id").cast("string")), F.format_string("%.2f", F.col("value")), F.col("props"))
    return events.withColumn("text", line).withColumn("tokens", token_count(line, "estimated"))


def coded(events: DataFrame, grid: Grid) -> DataFrame:
    """Values as codes of a frozen grid; clipped marks what is outside it."""
    return events.withColumn("q", quantize(F.col("value"), grid.lo, grid.hi, grid.bits)).withColumn("clipped", (F.col("value") < grid.lo) | (F.col("value") > grid.hi))


def with_coded_tokens(records: DataFrame, grid: Grid) -> DataFrame:
    """Adds coded_tokens: the cost of a record's line that has the code in place of the value."""
    q = quantize(F.col("value"), grid.lo, grid.hi, grid.bits)
    line = F.concat_ws(" ", F.col("event_type"), F.concat(F.lit("user"), F.col("user_id").cast("string")), q.cast("string"), F.col("props"))
    return records.withColumn("coded_tokens", token_count(line, "estimated"))


def tumbling_cost(records: DataFrame, size: str = "1 hour", late: str | None = None) -> DataFrame:
    r = records.withWatermark("ts", late) if late else records
    t = r.groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("records"), F.sum("tokens").alias("tokens"))
    return t.select(F.col("window.start").alias("start"), "event_type", "records", "tokens")


def sliding_ratio(records: DataFrame, size: str = "6 hours", slide: str = "1 hour", late: str | None = None) -> DataFrame:
    """Tokens of records before and after coding; records needs tokens and coded_tokens."""
    r = records.withWatermark("ts", late) if late else records
    t = r.groupBy(F.window("ts", size, slide)).agg(F.sum("tokens").alias("before"), F.sum("coded_tokens").alias("after"))
    return t.select(F.col("window.start").alias("start"), "before", "after", F.round(F.try_divide(F.col("before"), F.col("after")), 6).alias("ratio"))


def session_cost(records: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    r = records.withWatermark("ts", late) if late else records
    t = r.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("records"), F.sum("tokens").alias("tokens"))
    return t.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "records", "tokens")


def deduplicated(events: DataFrame, late: str) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def watched(records: DataFrame, name: str) -> DataFrame:
    """The same stream; each micro-batch reports its rows and its oldest and newest event time under ``name``.

    With the watermark of the query's progress (numRowsDroppedByWatermark) this shows what comes too late.
    """
    return records.observe(name, F.count("*").alias("records"), F.min("ts").alias("oldest"), F.max("ts").alias("newest"))


def drift(events: DataFrame, grid: Grid, size: str = "1 day") -> DataFrame:
    """(start, records, outside, share): where the share gets too high, a new grid is due."""
    t = coded(events, grid).groupBy(F.window("ts", size)).agg(F.count("*").alias("records"), F.count_if("clipped").alias("outside"))
    return t.select(F.col("window.start").alias("start"), "records", "outside", F.round(F.col("outside") / F.col("records"), 6).alias("share"))


def refit_on_drift(store: MetadataStore, name: str, grid: Grid, most: float):
    """foreachBatch handler that widens the grid when a micro-batch has too many values outside it.

    A new grid is version ``batch_id`` of ``name``; the newest earlier version is the state, so a stream that starts again goes on with it.
    """

    def handle(batch: DataFrame, batch_id: int) -> None:
        before = store.latest(name, batch_id)
        g = grid if before is None else Grid(**store.get(name, before).first().asDict())
        x = F.col(g.column)
        r = batch.agg(F.count(x).alias("n"), F.count_if((x < g.lo) | (x > g.hi)).alias("out"), F.min(x).alias("lo"), F.max(x).alias("hi")).first()
        if r["n"] and r["out"] / r["n"] > most:
            wider = (g.column, float(min(g.lo, r["lo"])), float(max(g.hi, r["hi"])), g.bits)
            store.put(name, batch_id, batch.sparkSession.createDataFrame([wider], "column string, lo double, hi double, bits int"))

    return handle


def top_ngrams_handler(store: MetadataStore, name: str, k: int):
    """foreachBatch handler: running counts (gram, freq) in update mode come in, the ``k`` most frequent go out as version ``batch_id``.

    The newest earlier version is all the state there is: counts only grow, so what ``k`` others have passed comes back only
    by a new row of its own. A batch that is run again, or a stream that starts again, gives the same versions.
    """

    def handle(batch: DataFrame, batch_id: int) -> None:
        rows, before = batch.select("gram", "freq"), store.latest(name, batch_id)
        if before is not None:
            rows = rows.unionByName(store.get(name, before))
        store.put(name, batch_id, rows.groupBy("gram").agg(F.max("freq").alias("freq")).orderBy(F.desc("freq"), "gram").limit(k))

    return handle


def user_budget(records: DataFrame, limit: int, late: str = "7 days") -> DataFrame:
    """(user_id, day, tokens, over) as updates: token budgets of users that start anew every day.

    Every day that a micro-batch touches is emitted. A day is closed a day after its end (so for any time zone) by a watermark
    of ``late``: rows that come after that are left out. Closed days leave the state with the user's next rows, and a timer
    removes the state of a user without any.
    """

    def run(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        used = dict(zip(*state.get)) if state.exists else {}
        closed = pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms") - pd.Timedelta(days=2)
        touched = set()
        for f in frames:
            for day, n in f.groupby(f["ts"].dt.strftime("%Y-%m-%d"))["tokens"].sum().items():
                if pd.Timestamp(day) > closed:
                    used[day] = used.get(day, 0) + int(n)
                    touched.add(day)
        days, tokens = sorted(touched), [used[d] for d in sorted(touched)]
        used = {d: n for d, n in used.items() if pd.Timestamp(d) > closed}
        if used:
            state.update((list(used), list(used.values())))
            state.setTimeoutTimestamp((pd.Timestamp(max(used)) + pd.Timedelta(days=2)).value // 10**6)
        elif state.exists:
            state.remove()
        yield pd.DataFrame({"user_id": [key[0]] * len(days), "day": days, "tokens": tokens, "over": [v > limit for v in tokens]})

    return records.withWatermark("ts", late).groupBy("user_id").applyInPandasWithState(run, "user_id long, day string, tokens long, over boolean", "days array<string>, used array<long>", "update", "EventTimeTimeout")


def with_dictionary(records: DataFrame, versions: DataFrame) -> DataFrame:
    """Stream joined with a static table by event type; the static side is small and broadcast."""
    return records.join(F.broadcast(versions), "event_type", "left")


def followed_by(first: DataFrame, then: DataFrame, within: str, late: str) -> DataFrame:
    """Pairs of a user's events (a before b, no longer apart than ``within``) from two streams or two batches."""
    a = first.select(F.col("user_id"), F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"))
    b = then.select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"))
    if first.isStreaming:
        a, b = a.withWatermark("a_ts", late), b.withWatermark("b_ts", late)
    return a.join(b, F.expr(f"user_id = b_user AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {within}")).select("user_id", "a_id", "b_id", "a_ts", "b_ts")


def drain(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over all there is and returns what it has emitted, for tests and small sinks."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)
