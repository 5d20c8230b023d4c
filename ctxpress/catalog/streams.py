"""Batch twins of the streaming operators; the tests hold the streams against them."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxpress.catalog import query
from ctxpress.operators.quant import Grid
from ctxpress.sources.tables import load
from ctxpress.streaming import streams


def estimate_sql(line: str) -> str:
    return f"(list_sum(list_transform(regexp_extract_all({line}, '[\\p{{L}}\\p{{M}}]+'), lambda r: ceil(len(r) / 4.0))) + list_sum(list_transform(regexp_extract_all({line}, '\\p{{N}}+'), lambda r: ceil(len(r) / 3.0))) + len(regexp_extract_all({line}, '[^\\s\\p{{L}}\\p{{M}}\\p{{N}}]')))::BIGINT"


GRID = Grid("value", 0.0, 400.0, 8)
CODE = "greatest(0, least(255, round(value / 400.0::DOUBLE * 255)::INTEGER))"
EST = estimate_sql("event_type || ' user' || user_id || ' ' || printf('%.2f', value) || ' ' || props")
EST_CODED = estimate_sql(f"event_type || ' user' || user_id || ' ' || {CODE} || ' ' || props")


def records(spark, sf):
    return streams.as_records(streams.timed(load(spark, sf, "events")))


def plain(df, *cols):
    return df.select(*[F.col(c).cast("timestamp_ntz").alias(c) if c in ("start", "end") else c for c in cols or df.columns])


@query(f"SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS records, sum({EST})::BIGINT AS tokens FROM events GROUP BY ALL")
def stream_tumbling_cost(spark, sf):
    return plain(streams.tumbling_cost(records(spark, sf)))


@query(f"""WITH r AS (SELECT ts, {EST} AS t, {EST_CODED} AS c FROM events), x AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR * unnest(range(6)) AS start, t, c FROM r)
SELECT start, sum(t)::BIGINT AS before, sum(c)::BIGINT AS after, round(sum(t)::BIGINT / sum(c)::BIGINT, 6) AS ratio FROM x GROUP BY start""")
def stream_sliding_ratio(spark, sf):
    """Tokens of records with values against records with their codes, in windows of six hours every hour."""
    return plain(streams.sliding_ratio(streams.with_coded_tokens(records(spark, sf), GRID)))


@query(f"""WITH r AS (SELECT user_id, ts, {EST} AS t, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
  s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM r)
SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS records, sum(t)::BIGINT AS tokens FROM s GROUP BY user_id, n""")
def stream_session_cost(spark, sf):
    return plain(streams.session_cost(records(spark, sf)))


@query("SELECT count(DISTINCT event_id) AS events FROM events")
def stream_dedup(spark, sf):
    e = load(spark, sf, "events")
    return e.union(e).dropDuplicates(["event_id"]).agg(F.count("*").alias("events"))


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS records, count(*) FILTER (WHERE value < 0 OR value > 400) AS outside, round(count(*) FILTER (WHERE value < 0 OR value > 400) / count(*)::DOUBLE, 6) AS share FROM events GROUP BY 1")
def stream_drift(spark, sf):
    return plain(streams.drift(streams.timed(load(spark, sf, "events")), GRID))


@query(f"SELECT event_id, CASE WHEN value IS NULL THEN NULL ELSE {CODE} END AS q, value < 0 OR value > 400 AS clipped FROM events")
def stream_coded(spark, sf):
    return streams.coded(load(spark, sf, "events"), GRID).select("event_id", "q", "clipped")


@query(f"SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, sum({EST})::BIGINT AS tokens, sum({EST}) > 60 AS over FROM events GROUP BY ALL")
def stream_user_budget(spark, sf):
    t = records(spark, sf).groupBy("user_id", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.sum("tokens").alias("tokens"))
    return t.withColumn("over", F.col("tokens") > 60)


@query("SELECT event_type, count(*) AS records, any_value(rank) AS rank FROM events JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) AS rank FROM (SELECT DISTINCT event_type FROM events)) USING (event_type) GROUP BY event_type")
def stream_static_join(spark, sf):
    from pyspark.sql import Window

    e = load(spark, sf, "events", "event_type")
    static = e.distinct().withColumn("rank", F.row_number().over(Window.orderBy("event_type")).cast("long"))
    return streams.with_dictionary(e, static).groupBy("event_type").agg(F.count("*").alias("records"), F.first("rank").alias("rank"))


@query("""SELECT a.user_id, a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY
WHERE a.event_type = 'signup' AND b.event_type = 'purchase'""")
def stream_interval_join(spark, sf):
    """Purchases within a day of a signup of the same user."""
    e = streams.timed(load(spark, sf, "events", "event_id", "user_id", "ts", "event_type"))
    t = streams.followed_by(e.where(F.col("event_type") == "signup"), e.where(F.col("event_type") == "purchase"), "1 DAY", "2 days")
    return t.select("user_id", "a_id", "b_id")
