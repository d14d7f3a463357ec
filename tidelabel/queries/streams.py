"""Streaming queries; their DuckDB twins compute the finished tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from tidelabel.streaming import votes as S

QUERIES, ORACLES = {}, {}


def add(name, fn, sql):
    QUERIES[name], ORACLES[name] = fn, sql


VOTES = f"v as (select event_id % {S.TASKS} as row_id, user_id::varchar as annotator, {S.VOTE} as label, ts from events where event_type <> 'signup')"
add("stream_tumbling", lambda spark, d: S.streamed(spark, d, S.tumbling).withColumn("start", F.col("start").cast("date")), "select ts::date as start, event_type, count(*) as n from events group by 1, 2")
add("stream_sliding", lambda spark, d: S.streamed(spark, d, S.sliding).withColumn("start", F.col("start").cast("date")), "select s as start, count(*) as n from (select unnest([ts::date, (ts::date - 1)::date]) as s from events) group by 1")
add(
    "stream_session", lambda spark, d: S.streamed(spark, d, S.sessions).select("user_id", F.unix_micros("start").alias("start"), "n"),
    "select user_id, epoch_us(min(ts)) as start, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as s from (select *, case when lag(ts) over (partition by user_id order by ts, event_id) is null or ts - lag(ts) over (partition by user_id order by ts, event_id) >= interval 6 hours then 1 else 0 end as fresh from events)) group by user_id, s",
)
add(
    "stream_majority", lambda spark, d: S.run_once(S.quorum(S.votes_of(S.event_stream(spark, d)))).select("row_id", "label", "n"),
    f"with {VOTES}, a as (select * from (select *, row_number() over (partition by row_id, annotator order by ts, label) as k from v) where k = 1), f as (select * exclude (k), row_number() over (partition by row_id order by ts, annotator) as k from a) select row_id, (case when sum(label) * 2 > count(*) then 1 else 0 end)::integer as label, count(*)::integer as n from f where k <= 3 group by row_id",
)
add(
    "stream_join", lambda spark, d: S.run_once(S.with_suggestions(S.votes_of(S.event_stream(spark, d)), spark.range(S.TASKS).selectExpr("id as row_id", "cast(id % 2 as int) as suggestion"))),
    f"with {VOTES} select row_id, annotator, label::integer as label, (row_id % 2)::integer as suggestion from v",
)
add(
    "stream_interval_join", lambda spark, d: S.run_once(S.interval_join(S.event_stream(spark, d).where("event_type = 'error'"), S.event_stream(spark, d).where("event_type = 'purchase'"))),
    "select p.event_id, e.event_id as error_id from events p join events e on p.user_id = e.user_id and e.ts between p.ts - interval 1 hour and p.ts where p.event_type = 'purchase' and e.event_type = 'error'",
)
QUERIES["stream_dedup"] = lambda spark, d: S.run_once(S.first_votes(S.votes_of(S.event_stream(spark, d))))
add("batch_majority", lambda spark, d: S.quorum_batch(S.votes_of(spark.read.schema(S.TABLES["events"]).parquet(f"{d}/events.parquet"))), ORACLES["stream_majority"])
