"""Annotators' votes as a stream: windows, deduplication, joins, and a quorum that closes a row.

Every stream function has a batch twin over the same rows; with everything available at
once and no row later than the watermark, both give the same.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tidelabel.schema import TABLES
from tidelabel.sources.sinks import shared_folder

TASKS, QUORUM = 50, 3
#: The label that an event type votes for; other types abstain.
VOTE = "case event_type when 'error' then 0 when 'signup' then null else 1 end"


def votes_of(events: DataFrame) -> DataFrame:
    """(row_id, annotator, label, ts) of events."""
    return events.selectExpr(f"event_id % {TASKS} as row_id", "cast(user_id as string) as annotator", f"cast({VOTE} as int) as label", "ts").where("label is not null")


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(TABLES["events"]).option("maxFilesPerTrigger", 16).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")


def run_once(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that is there, written by micro-batches to a Parquet folder and read back."""
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")
    # complete and update results: each batch replaces the result so far
    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/out-{mode}")

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out-{mode}")


def tumbling(events: DataFrame) -> DataFrame:
    w = events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame) -> DataFrame:
    w = events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame) -> DataFrame:
    w = events.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "n")


def first_votes(votes: DataFrame) -> DataFrame:
    """A stream's votes, one of each annotator and row within a day."""
    return votes.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["row_id", "annotator"])


def with_suggestions(votes: DataFrame, suggestions: DataFrame) -> DataFrame:
    """Votes with the static suggestion of their row; Spark broadcasts the suggestions only below its size limit."""
    return votes.join(suggestions, "row_id").select("row_id", "annotator", "label", "suggestion")


def interval_join(errors: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """Streams joined on the user, each purchase with errors of the time before it; watermarks bound what is kept."""
    e = errors.selectExpr("event_id as error_id", "user_id", "ts as error_ts").withWatermark("error_ts", "10 minutes")
    p = purchases.selectExpr("event_id", "user_id as buyer", "ts").withWatermark("ts", "10 minutes")
    near = F.expr(f"buyer = user_id and error_ts >= ts - interval {within} and error_ts <= ts")
    return p.join(e, near).select("event_id", "error_id")


def quorum(votes: DataFrame, size: int = QUORUM, patience: str = "1 day") -> DataFrame:
    """(row_id, label, n): closes a row by its first ``size`` annotators; a row that waits too long closes with what it has.

    State holds at most ``size`` votes a row and then a mark that it is closed.
    """
    wait = int(pd.Timedelta(patience).total_seconds() * 1000)

    def step(key, frames, state: GroupState):
        (row_id,) = key
        closed, annotators, labels = state.get if state.exists else (False, [], [])
        seen = dict(zip(annotators, labels))
        if state.hasTimedOut:
            state.remove()
            if seen and not closed:
                yield decided(row_id, seen)
            return
        rows = pd.concat(list(frames)).sort_values(["ts", "annotator"]) if not closed else None
        if closed:
            for _ in frames:
                pass
            return
        for r in rows.itertuples():
            if len(seen) < size and str(r.annotator) not in seen:
                seen[str(r.annotator)] = int(r.label)
        done = len(seen) >= size
        state.update((done, list(seen), list(seen.values())))
        if done:
            yield decided(row_id, seen)
        else:
            state.setTimeoutTimestamp(int(rows.ts.max().timestamp() * 1000) + wait)

    def decided(row_id, seen):
        counts = pd.Series(list(seen.values())).value_counts()
        label = min(counts[counts == counts.max()].index)
        return pd.DataFrame({"row_id": [row_id], "label": [int(label)], "n": [len(seen)]})

    return votes.withWatermark("ts", "10 minutes").groupBy("row_id").applyInPandasWithState(step, "row_id long, label int, n int", "closed boolean, annotators array<string>, labels array<int>", "append", GroupStateTimeout.EventTimeTimeout)


def quorum_batch(votes: DataFrame, size: int = QUORUM) -> DataFrame:
    """The same for a finished table: first vote of each annotator, first ``size`` annotators, majority."""
    one = votes.withColumn("k", F.row_number().over(Window.partitionBy("row_id", "annotator").orderBy("ts", "label"))).where("k = 1")
    few = one.withColumn("k", F.row_number().over(Window.partitionBy("row_id").orderBy("ts", "annotator"))).where(F.col("k") <= size)
    counts = few.groupBy("row_id", "label").agg(F.count("*").alias("c"))
    best = counts.groupBy("row_id").agg(F.max(F.struct("c", (-F.col("label")).alias("low"))).alias("m"), F.sum("c").cast("int").alias("n"))
    return best.select("row_id", (-F.col("m.low")).cast("int").alias("label"), "n")


def streamed(spark: SparkSession, sf_dir: str, fn: Callable[[DataFrame], DataFrame], mode: str = "complete") -> DataFrame:
    return run_once(fn(event_stream(spark, sf_dir)), mode)
