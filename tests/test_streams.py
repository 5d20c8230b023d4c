"""Streams against their batch twins."""

import datetime

import pytest
from pyspark.sql import functions as F

from ctxpress.operators.quant import Grid
from ctxpress.sources.metadata import MetadataStore
from ctxpress.streaming import streams


@pytest.fixture()
def folder(spark, sf, tmp_path):
    path = str(tmp_path / "events")
    spark.read.parquet(f"{sf}/events.parquet").orderBy("ts").coalesce(1).write.parquet(path)
    return path


def rows(df, *cols):
    return sorted(map(tuple, df.select(*cols).collect()))


def test_tumbling_and_sliding_equal_batch(spark, folder, tmp_path):
    s, b = streams.stream_events(spark, folder), streams.timed(spark.read.parquet(folder))
    got = streams.drain(streams.tumbling_cost(streams.as_records(s)), "tumbling", "complete", str(tmp_path / "c1"))
    assert rows(got, "start", "event_type", "records", "tokens") == rows(streams.tumbling_cost(streams.as_records(b)), "start", "event_type", "records", "tokens")
    one = lambda d: streams.with_coded_tokens(streams.as_records(d), Grid("value", 0.0, 400.0, 8))
    got = streams.drain(streams.sliding_ratio(one(s)), "sliding", "complete", str(tmp_path / "c2"))
    assert rows(got, "start", "before", "after") == rows(streams.sliding_ratio(one(b)), "start", "before", "after")


def test_closed_sessions_equal_batch(spark, folder, tmp_path):
    s, b = streams.as_records(streams.stream_events(spark, folder)), streams.as_records(streams.timed(spark.read.parquet(folder)))
    got = rows(streams.drain(streams.session_cost(s, late="1 hour"), "sessions", "append", str(tmp_path / "c")), "user_id", "start", "end", "records", "tokens")
    every = rows(streams.session_cost(b), "user_id", "start", "end", "records", "tokens")
    last = max(r[2] for r in every)
    assert set(got) <= set(every) and {r for r in every if r[2] < last - datetime.timedelta(hours=3)} <= set(got)


def test_repeated_events_are_dropped_within_the_watermark(spark, folder, tmp_path):
    s = streams.stream_events(spark, folder)
    got = streams.drain(streams.deduplicated(s.unionByName(s), "1 hour").select("event_id"), "dedup", "append", str(tmp_path / "c"))
    assert got.count() == spark.read.parquet(folder).count()


def test_user_budget_state_equals_batch(spark, folder, tmp_path):
    s, b = streams.as_records(streams.stream_events(spark, folder)), streams.as_records(streams.timed(spark.read.parquet(folder)))
    got = streams.drain(streams.user_budget(s, 60), "budget", "update", str(tmp_path / "c"))
    want = {(r[0], r[1]): r[2] for r in b.groupBy("user_id", F.date_format("ts", "yyyy-MM-dd")).agg(F.sum("tokens")).collect()}
    found = {(r["user_id"], r["day"]): r["tokens"] for r in got.collect()}
    assert found and all(want[k] == v for k, v in found.items())


def test_user_budget_emits_every_day(spark, folder, tmp_path):
    whole = spark.read.parquet(folder)
    many = str(tmp_path / "many")
    for part in (0, 1):  # two files, each with rows of most days: the second comes after the first in every user's state
        whole.where(F.col("event_id") % 2 == part).coalesce(1).write.mode("append").parquet(many)
    for i, path in enumerate((folder, many)):
        s, b = streams.as_records(streams.stream_events(spark, path)), streams.as_records(streams.timed(spark.read.parquet(path)))
        got = streams.drain(streams.user_budget(s, 60, "60 days"), f"every{i}", "update", str(tmp_path / f"every{i}"))
        want = {(r[0], r[1]): r[2] for r in b.groupBy("user_id", F.date_format("ts", "yyyy-MM-dd")).agg(F.sum("tokens")).collect()}
        last: dict = {}
        for r in got.collect():  # of the updates of a day the last is the largest
            last[r["user_id"], r["day"]] = max(r["tokens"], last.get((r["user_id"], r["day"]), 0))
        assert last == want


def test_interval_join_equals_batch(spark, folder, tmp_path):
    pick = lambda d, t: d.where(F.col("event_type") == t)
    s1, s2, b = streams.stream_events(spark, folder), streams.stream_events(spark, folder), streams.timed(spark.read.parquet(folder))
    got = streams.drain(streams.followed_by(pick(s1, "signup"), pick(s2, "purchase"), "1 DAY", "2 days"), "pairs", "append", str(tmp_path / "c"))
    assert rows(got, "a_id", "b_id") == rows(streams.followed_by(pick(b, "signup"), pick(b, "purchase"), "1 DAY", "2 days"), "a_id", "b_id")


def test_state_of_a_user_without_rows_goes(spark, tmp_path):
    """The timer removes the state of users whose days are closed; the others keep theirs."""
    t = lambda day, user: (day * 10 + user, datetime.datetime(2024, 1, day), user, "view", 1.0, "x")
    path, left = str(tmp_path / "e"), []
    for rows_ in ([t(1, 1), t(1, 2)], [t(20, 2)], [t(21, 2)], [t(22, 2)]):
        spark.createDataFrame(rows_, streams.EVENTS).coalesce(1).write.mode("append").parquet(path)
        s = streams.as_records(streams.stream_events(spark, path))
        q = streams.user_budget(s, 60, "1 day").writeStream.format("noop").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
        left.append(q.lastProgress["stateOperators"][0]["numRowsTotal"])
    assert left[0] == 2 and left[-1] == 1


def test_drift_and_refit(spark, folder, tmp_path):
    store = MetadataStore(spark, str(tmp_path / "store"))
    handle = streams.refit_on_drift(store, "grid", Grid("value", 0.0, 10.0, 8), 0.1)
    q = streams.stream_events(spark, folder).writeStream.foreachBatch(handle).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    top = spark.read.parquet(folder).agg(F.max("value")).first()[0]
    assert store.get("grid").first()["hi"] == top
    handle = streams.refit_on_drift(store, "grid", Grid("value", 0.0, 10.0, 8), 0.1)  # as after a restart: the stored grid holds
    handle(spark.read.parquet(folder), 7)
    assert store.latest("grid") < 7


def test_running_top_ngrams(spark, folder, tmp_path):
    """A stream in three runs, each with a new handler, ends with the counts of one run."""
    store, path = MetadataStore(spark, str(tmp_path / "store")), str(tmp_path / "parts")
    for part in range(3):
        spark.read.parquet(folder).where(F.col("event_id") % 3 == part).coalesce(1).write.mode("append").parquet(path)
        s = streams.stream_events(spark, path).groupBy(F.concat_ws(" ", "event_type", F.col("user_id") % 7).alias("gram")).agg(F.count("*").alias("freq"))
        q = s.writeStream.outputMode("update").foreachBatch(streams.top_ngrams_handler(store, "top", 5)).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
        have = spark.read.parquet(path).groupBy(F.concat_ws(" ", "event_type", F.col("user_id") % 7)).count().collect()
        assert sorted(map(tuple, store.get("top").collect()), key=lambda e: (-e[1], e[0])) == sorted(map(tuple, have), key=lambda e: (-e[1], e[0]))[:5]
    assert store.latest("top") == 2 and store.latest("top", 2) == 1 and store.latest("nothing") is None
