"""What the method is compared with: events from bursts alone, and ways that end without events."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bursts import burst_runs
from ..functions.text import select_documents
from ..params import TopicParams
from .events import event_score, pearson, ranked
from .topics import extract_topics, topic_burst


def run_events(rate: DataFrame, pvi: DataFrame) -> DataFrame:
    """``topic_id, win, rate, bursty`` -> scored events: each run of windows in which a topic bursts."""
    runs = burst_runs(rate.where("bursty"), "topic_id")
    cells = runs.withColumn("win", F.explode(F.sequence("start_win", "end_win"))).join(rate.select("topic_id", "win", "rate"), ["topic_id", "win"])
    cells = cells.select(F.struct("topic_id", "start_win").alias("run"), "win", F.col("rate").alias("intensity"))
    scored = event_score(cells, pvi, "run")
    return ranked(scored.select(F.col("run.topic_id").alias("topic_id"), "start_win", "end_win", "n_win", "intensity_norm", "pvi_norm", "comovement", "score"), "topic_id")


def baseline_events(pairs: DataFrame, influence: DataFrame, p: DataFrame, pvi: DataFrame, params: TopicParams = TopicParams()) -> DataFrame:
    """Word groups found without the index; each run of windows in which one bursts is an event."""
    topics = extract_topics(pairs, influence, replace(params, influence="off"))
    return run_events(topic_burst(topics, p, params.burst_threshold), pvi)


def occurrence_events(topics: DataFrame, p: DataFrame, pvi: DataFrame, threshold: float) -> DataFrame:
    """Every run of an impact topic is an event of its own."""
    return run_events(topic_burst(topics, p, threshold), pvi)


def topics_then_index(pairs: DataFrame, influence: DataFrame, p: DataFrame, change: DataFrame, params: TopicParams = TopicParams()) -> DataFrame:
    """Topics first, by co-occurrence; the correlation of their strength with the index change afterwards."""
    topics = extract_topics(pairs, influence, replace(params, influence="off"))
    return series_correlation(topic_burst(topics, p).select("topic_id", "win", F.col("rate").alias("x")), change, "topic_id")


def correlated_keywords(p: DataFrame, index: DataFrame, k: int) -> DataFrame:
    """The features whose series go most with the index: a list of words, without events."""
    got = series_correlation(p.select("feature", "win", F.col("p").alias("x")), index.select("win", F.col("value").alias("y")), "feature")
    return got.orderBy(F.desc(F.abs("corr")), "feature").limit(k)


def series_correlation(series: DataFrame, index: DataFrame, key: str) -> DataFrame:
    """``key, corr`` over all windows of the index; absent cells count 0, constant series 0."""
    y = [c for c in index.columns if c != "win"][-1]
    known = index.where(F.col(y).isNotNull()).select("win", F.col(y).alias("y"))
    cells = series.select(key).distinct().crossJoin(F.broadcast(known))  # a row per window of the index
    full = cells.join(series, [key, "win"], "left").fillna(0.0, ["x"])
    flat = (F.stddev_pop("x") <= 1e-12) | (F.stddev_pop("y") <= 1e-12)
    return full.groupBy(key).agg(F.when(flat, 0.0).otherwise(F.coalesce(pearson(F.col("x"), F.col("y")), F.lit(0.0))).alias("corr"))


def search_documents(docs: DataFrame, phrases: list[str]) -> DataFrame:
    """Plain keyword search: the documents in order of time."""
    return select_documents(docs, phrases).orderBy("ts", "doc_id")
