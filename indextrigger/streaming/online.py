"""The streaming twin: word counts of closed windows, deduplication, alerts by feature, and batch equality."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import bursts as B
from ..functions.bursts import tail_values
from ..plans.topics import topic_burst
from ..sources.staging import shared_folder

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def event_source(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of files with a fixed schema."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def windowed_counts(events: DataFrame, length: str = "4 hours", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """``win_start, event_type, n, total_value`` of windows that the watermark has closed."""
    win = F.window("ts", length, slide) if slide else F.window("ts", length)
    got = events.withWatermark("ts", late).groupBy(win.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total_value"))
    return got.select(F.unix_seconds("w.start").alias("win_start"), "event_type", "n", F.round("total_value", 4).alias("total_value"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """``user_id, session_start, n`` of sessions that ended before the watermark."""
    got = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return got.select("user_id", F.unix_seconds("w.start").alias("session_start"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def paired_within(clicks: DataFrame, errors: DataFrame, seconds: int = 3600, late: str = "1 hour") -> DataFrame:
    """Two streams joined by user: each error with the clicks of the ``seconds`` before it; watermarks bound the state of both."""
    a = clicks.withWatermark("ts", late).select(F.col("event_id").alias("click_id"), F.col("user_id").alias("click_user"), F.col("ts").alias("clicked"))
    b = errors.withWatermark("ts", late).select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("failed"))
    near = F.expr(f"click_user = user_id AND failed >= clicked AND failed <= clicked + INTERVAL {seconds} SECONDS")
    return a.join(b, near).select("click_id", "error_id")


def bursty_topics(spark: SparkSession, sf_dir: str, topics: DataFrame, threshold: float = 0.6, late: str = "1 hour") -> DataFrame:
    """The streaming twin of bursts and topics: ``topic_id, win, rate`` of the windows that the watermark closes.

    Closed counts of the stream go through the batch functions against the rates of all counts closed so far,
    then through the static topics; a window's rate is what the batch method gives for the same windows.
    """
    feed = event_source(spark, sf_dir).select("ts", F.explode(F.array("event_type", F.concat(F.lit("k"), F.get_json_object("props", "$.k")))).alias("feature")).where("feature IS NOT NULL")
    closed = feed.withWatermark("ts", late).groupBy(F.window("ts", "4 hours").alias("w"), "feature").agg(F.count(F.lit(1)).alias("n"))
    origin = F.unix_seconds(F.lit("2024-01-01").cast("timestamp"))
    counts = drained(closed.select("feature", F.floor((F.unix_seconds("w.start") - origin) / 14400).cast("int").alias("win"), "n"))
    totals = B.window_totals(counts)
    p = B.burst_probability(counts, totals, B.expected_rate(counts, totals))
    return topic_burst(topics, p, threshold).where("bursty").select("topic_id", "win", "rate")


def enriched(events: DataFrame, names: DataFrame) -> DataFrame:
    """A stream joined with a static table of features (``event_type`` and more)."""
    return events.join(names, "event_type", "left")


ALERT = T.StructType([T.StructField("feature", T.StringType()), T.StructField("seen", T.LongType()), T.StructField("n", T.LongType()), T.StructField("p", T.DoubleType())])
_STATE = T.StructType([T.StructField("occurrences", T.LongType()), T.StructField("batches", T.LongType())])


def online_alerts(words: DataFrame, threshold: float = 0.95) -> DataFrame:
    """``feature, n, total`` per arriving cell -> alerts where a count is beyond the rate learnt so far.

    The state of a feature is two numbers: its occurrences and the words it was counted among.
    """

    def step(key: tuple[Any, ...], parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        hits, words_ = state.get if state.exists else (0, 0)
        for part in parts:
            out = []
            for n, total in zip(part.n, part.total):
                if words_ and hits:
                    p = float(tail_values([n], [total], [hits / words_], "strict")[0])
                    if p > threshold:
                        out.append((key[0], words_, int(n), p))
                hits, words_ = hits + int(n), words_ + int(total)
            yield pd.DataFrame(out, columns=[f.name for f in ALERT])
        state.update((hits, words_))

    return words.groupBy("feature").applyInPandasWithState(step, ALERT, _STATE, "append", GroupStateTimeout.NoTimeout)


def drained(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all that is there (``availableNow``) and returns what it wrote, as a table.

    Each batch goes to a folder named by its number, so a batch that is repeated after a failure
    replaces itself; with a checkpoint a later call goes on where this one stopped.
    """
    spark = stream.sparkSession
    base = checkpoint or f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    schema = stream.schema

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    started = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    started.awaitTermination()
    got = spark.read.schema(T.StructType([*schema.fields, T.StructField("batch", T.IntegerType())])).parquet(f"{base}/out")
    if mode == "complete":
        got = got.join(got.agg(F.max("batch").alias("batch")), "batch")
    return got.drop("batch")


def session_topics(spark: SparkSession) -> DataFrame:
    """Three given topics of the session stream."""
    return spark.createDataFrame([(1, ["click", "error"]), (2, ["k1", "k2", "k3"]), (3, ["k10"])], "topic_id int, features array<string>")


QUERIES = {
    "stream_tumbling_counts": lambda s, d: drained(event_source(s, d).groupBy(F.window("ts", "4 hours").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("win_start"), "event_type", "n"), "complete"),
    "stream_closed_windows": lambda s, d: drained(windowed_counts(event_source(s, d))),
    "stream_sliding_counts": lambda s, d: drained(windowed_counts(event_source(s, d), "4 hours", "2 hours")),
    "stream_sessions": lambda s, d: drained(sessions(event_source(s, d))),
    "stream_deduplicated": lambda s, d: drained(deduplicated(event_source(s, d)).select("event_id", "event_type")),
    "stream_enriched": lambda s, d: drained(enriched(event_source(s, d), s.createDataFrame([("click", "page"), ("error", "fault")], "event_type string, kind string")).select("event_id", "kind")),
    "stream_stream_join": lambda s, d: drained(paired_within(event_source(s, d).where("event_type = 'click'"), event_source(s, d).where("event_type = 'error'"))),
    "stream_bursty_topics": lambda s, d: bursty_topics(s, d, session_topics(s)).select("topic_id", "win", (F.round("rate", 6) + F.lit(0.0)).alias("rate")),
}
SQL = {
    "stream_tumbling_counts": "SELECT CAST(floor(epoch(ts) / 14400) * 14400 AS BIGINT) AS win_start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_deduplicated": "SELECT event_id, event_type FROM events",
    "stream_closed_windows": "SELECT CAST(floor(epoch(ts) / 14400) * 14400 AS BIGINT) AS win_start, event_type, count(*) AS n, round(sum(value), 4) AS total_value FROM events GROUP BY 1, 2 HAVING floor(min(epoch(ts)) / 14400) * 14400 + 14400 <= (SELECT max(epoch(ts)) - 3600 FROM events)",
    "stream_sliding_counts": """SELECT win_start, event_type, count(*) AS n, round(sum(value), 4) AS total_value FROM (SELECT CAST(floor(epoch(ts) / 7200) * 7200 AS BIGINT) - unnest([0, 7200]) AS win_start, event_type, value FROM events)
 WHERE win_start + 14400 <= (SELECT max(epoch(ts)) - 3600 FROM events) GROUP BY 1, 2""",
    "stream_sessions": """SELECT user_id, CAST(floor(min(t)) AS BIGINT) AS session_start, count(*) AS n FROM (SELECT user_id, t, sum(opens) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS session FROM
 (SELECT user_id, epoch(ts) AS t, CASE WHEN epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts) <= 1800 THEN 0 ELSE 1 END AS opens FROM events)) GROUP BY user_id, session HAVING max(t) + 1800 <= (SELECT max(epoch(ts)) - 3600 FROM events)""",
    "stream_enriched": "SELECT event_id, CASE event_type WHEN 'click' THEN 'page' WHEN 'error' THEN 'fault' END AS kind FROM events",
    "stream_stream_join": "SELECT a.event_id AS click_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3600 SECONDS",
    "stream_bursty_topics": """WITH tokens AS (SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 14400) AS INT) AS win, unnest([event_type, 'k' || json_extract_string(props, '$.k')]) AS feature FROM events),
 counts AS (SELECT feature, win, count(*) AS n FROM tokens WHERE feature IS NOT NULL AND epoch(TIMESTAMP '2024-01-01') + (win + 1) * 14400 <= (SELECT max(epoch(ts)) - 3600 FROM events) GROUP BY 1, 2),
 totals AS (SELECT win, sum(n) AS total FROM counts GROUP BY win), rates AS (SELECT feature, sum(n) * 1.0 / (SELECT sum(total) FROM totals) AS pe FROM counts GROUP BY feature),
 p AS (SELECT feature, win, coalesce(list_sum(list_transform(range(0, n), lambda k: exp(lgamma(total + 1) - lgamma(k + 1) - lgamma(total - k + 1) + k * ln(pe) + (total - k) * ln(1 - pe)))), 0) AS p FROM counts JOIN totals USING (win) JOIN rates USING (feature)),
 topics(topic_id, feature) AS (VALUES (1, 'click'), (1, 'error'), (2, 'k1'), (2, 'k2'), (2, 'k3'), (3, 'k10'))
 SELECT topic_id, win, round(rate, 6) AS rate FROM (SELECT topic_id, win, sum(p) / (SELECT count(*) FROM topics t WHERE t.topic_id = o.topic_id) AS rate FROM topics o JOIN p USING (feature) GROUP BY topic_id, win) WHERE rate > 0.6""",
}
