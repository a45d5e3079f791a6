"""Streams: windowed usage metrics, duplicate questions, per-user budgets, questions against the enriched catalog.

Each query here runs its stream over what is there now and returns the sink's rows.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.text import digest, tokens, tokens_sql
from ..plans import spanner
from ..registry import query
from ..sources.catalog import from_parquet, questions


def events(spark: SparkSession, sf: str) -> DataFrame:
    """The event table as a file stream, with event time."""
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf}/event[s].parquet").withColumn("at", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str) -> DataFrame:
    """The sink's rows. Appended rows, as many as the stream's, are files in the shared folder; the other modes keep a row per
    group, in the driver's memory."""
    if mode == "append":
        from ..sources.sinks import scratch

        at = scratch(df.sparkSession, "drained")
        df.writeStream.format("parquet").option("path", f"{at}/rows").option("checkpointLocation", f"{at}/checkpoint").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
        return df.sparkSession.read.schema(df.schema).parquet(f"{at}/rows")
    name = f"s{uuid.uuid4().hex}"
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def windowed(stream: DataFrame, size: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return stream.withWatermark("at", late).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "2 hours", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("at", late).groupBy(F.session_window("at", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def without_repeats(stream: DataFrame, late: str = "10 minutes") -> DataFrame:
    """The first of equal requests within the watermark. They are told apart by what they ask, not by its digest k: among millions,
    different requests share digests."""
    same = ["user_id", "event_type", "ts"]
    return stream.withWatermark("at", late).dropDuplicatesWithinWatermark(same).select("event_id", digest(*(F.col(c).cast("string") for c in same)).alias("k"))


def budgets(stream: DataFrame, budget: int = 1000) -> DataFrame:
    """(user_id, spent, over): a running sum per user; state is one number."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        spent = (state.get[0] if state.exists else 0.0) + sum(float(b["value"].sum()) for b in batches)
        state.update((spent,))
        yield pd.DataFrame({"user_id": [key[0]], "spent": [spent], "over": [spent > budget]})

    return stream.groupBy("user_id").applyInPandasWithState(run, "user_id long, spent double, over boolean", "spent double", "update", GroupStateTimeout.NoTimeout)


def answer_questions(stream: DataFrame, answer: Callable[[DataFrame], DataFrame], sink: str, checkpoint: str) -> None:
    """Micro-batches of questions through the filter, appended to a table; a batch that runs again overwrites its own part."""

    def one(batch: DataFrame, number: int) -> None:
        answer(batch).withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def index_values(stream: DataFrame, values: str, checkpoint: str) -> None:
    """A value index that grows: each micro-batch of (col_id, value) adds what no other batch has. A batch that runs again
    overwrites its own part, so nothing is counted twice."""

    def one(batch: DataFrame, number: int) -> None:
        spark, new = batch.sparkSession, batch.where("value IS NOT NULL").distinct()
        known = spark.read.schema("col_id long, value string, len long, batch long").parquet(f"{values}/batch=*").where(F.col("batch") != number) if number else None
        if known is not None:
            new = new.join(known.select("col_id", "value"), ["col_id", "value"], "left_anti")
        new.withColumn("len", F.size(tokens("value")).cast("long")).withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{values}/batch={number}")

    stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


_TUMBLING = "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"


@query("stream_tumbling", _TUMBLING)
def _tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return drained(windowed(events(spark, sf), "6 hours"), "complete")


@query("stream_sliding", "SELECT strftime(s, '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS s FROM events) GROUP BY 1, 2")
def _sliding(spark: SparkSession, sf: str) -> DataFrame:
    return drained(windowed(events(spark, sf), "12 hours", "6 hours"), "complete")


@query("stream_sessions")
def _sessions(spark: SparkSession, sf: str) -> DataFrame:
    return drained(sessions(events(spark, sf)), "append")


@query("stream_dedup")
def _dedup(spark: SparkSession, sf: str) -> DataFrame:
    return drained(without_repeats(events(spark, sf)), "append")


@query("stream_budgets", "SELECT user_id, round(sum(value), 4) AS spent, sum(value) > 1000 AS over FROM events GROUP BY 1")
def _budgets(spark: SparkSession, sf: str) -> DataFrame:
    return drained(budgets(events(spark, sf)), "update").withColumn("spent", F.round("spent", 4))


@query("stream_value_index", f"SELECT token, count(*) AS df FROM (SELECT value, unnest(list_distinct({tokens_sql('value')})) AS token FROM (SELECT DISTINCT p_name AS value FROM part WHERE p_name IS NOT NULL)) GROUP BY token")
def _value_index(spark: SparkSession, sf: str) -> DataFrame:
    """Document frequencies of the part names' tokens from an index that a stream fills."""
    from ..plans.valueindex import postings, token_stats
    from ..sources.sinks import scratch

    schema = spark.read.parquet(f"{sf}/part.parquet").schema
    stream = spark.readStream.schema(schema).parquet(f"{sf}/par[t].parquet").select(F.lit(0).cast("long").alias("col_id"), F.col("p_name").alias("value"))
    at = scratch(spark, "values")
    index_values(stream, f"{at}/values", f"{at}/checkpoint")
    return token_stats(postings(spark.read.parquet(f"{at}/values")))


@query("stream_questions")
def _questions(spark: SparkSession, sf: str) -> DataFrame:
    """Conversation turns of users as questions, by the words that they share with column names of the catalog."""
    from ..functions.text import expanded
    from ..sources.sinks import scratch

    columns = from_parquet(spark, sf).columns.select("col_id", tokens(expanded("column_name")).alias("cw"))

    def answer(batch: DataFrame) -> DataFrame:
        asked = batch.select(F.concat_ws("-", "conv_id", "turn").alias("qid"), tokens("text").alias("qt"))
        scores = asked.crossJoin(F.broadcast(columns)).select("qid", "col_id", F.size(F.array_intersect("qt", "cw")).cast("double").alias("score"))
        return spanner.top_k(scores, 3)

    schema = spark.read.parquet(f"{sf}/conversations.parquet").schema
    stream = spark.readStream.schema(schema).parquet(f"{sf}/conversation[s].parquet").where("role = 'user'")
    at = scratch(spark, "questions")
    answer_questions(stream, answer, f"{at}/out", f"{at}/checkpoint")
    return spark.read.parquet(f"{at}/out").select("qid", "col_id", "score", "rank")
