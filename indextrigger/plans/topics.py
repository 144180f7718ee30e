"""Impact topics: groups of words whose objective counts shared documents, shared bursts and the index."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..params import TopicParams
from ..sources.staging import bounded
from .graph import connected

TOPIC_SCHEMA = "features array<string>, doc_coherence double, time_coherence double, influence double, objective double"


def feature_influence(p: DataFrame, pvi: DataFrame, normalise: bool = False) -> DataFrame:
    """``feature, influence``: the volatility levels of the windows in which the feature bursts, added up.

    Sums are rounded to nine places, so that ties do not depend on the order in which rows are added.
    """
    got = p.where("bursty").select("feature", "win").join(F.broadcast(pvi.select("win", "pvi")), "win").groupBy("feature").agg(F.round(F.sum("pvi"), 9).alias("influence"))
    got = p.select("feature").distinct().join(got, "feature", "left").fillna(0.0, ["influence"])
    if not normalise:
        return got
    whole = got.agg(F.sum("influence").alias("whole"))
    return got.crossJoin(F.broadcast(whole)).select("feature", F.when(F.col("whole") > 0, F.col("influence") / F.col("whole")).otherwise(0.0).alias("influence"))


def pair_objectives(pairs: DataFrame, influence: DataFrame, how: str = "sum") -> DataFrame:
    """Both directions of each pair: ``word, partner, jaccard, rho, word_influence, partner_influence, objective``."""
    both = pairs.select(F.col("f").alias("word"), F.col("g").alias("partner"), "jaccard", "rho").unionByName(pairs.select(F.col("g").alias("word"), F.col("f").alias("partner"), "jaccard", "rho"))
    both = both.join(influence.select(F.col("feature").alias("word"), F.col("influence").alias("word_influence")), "word")
    both = both.join(influence.select(F.col("feature").alias("partner"), F.col("influence").alias("partner_influence")), "partner")
    a, b = F.col("word_influence"), F.col("partner_influence")
    factor = {"sum": a + b, "candidate": b, "mean": (a + b) / 2, "off": F.lit(1.0)}[how]
    return both.withColumn("objective", F.col("jaccard") * F.col("rho") * factor)


def best_partners(objectives: DataFrame) -> DataFrame:
    """The partner of each word with the best objective; ties fall to the lesser name."""
    order = Window.partitionBy("word").orderBy(F.desc("objective"), "partner")
    return objectives.withColumn("r", F.row_number().over(order)).where("r = 1").drop("r")


@dataclass
class Neighbours:
    """The affinities of each word, as rows of neighbours: memory follows the pairs, not the square of the words."""

    starts: np.ndarray
    others: np.ndarray
    jaccard: np.ndarray
    rho: np.ndarray

    @classmethod
    def of(cls, n: int, a: np.ndarray, b: np.ndarray, jaccard: np.ndarray, rho: np.ndarray) -> "Neighbours":
        """From each pair of different words once."""
        rows, others = np.concatenate([a, b]), np.concatenate([b, a])
        order = np.lexsort((others, rows))
        starts = np.searchsorted(rows[order], np.arange(n + 1))
        return cls(starts, others[order], np.concatenate([jaccard, jaccard])[order], np.concatenate([rho, rho])[order])

    def row(self, i: int) -> slice:
        return slice(self.starts[i], self.starts[i + 1])


def greedy_topics(names: list[str], jaccard: np.ndarray, rho: np.ndarray, influence: np.ndarray, params: TopicParams) -> list[dict]:
    """:func:`greedy_from` for square matrices of the affinities."""
    a, b = np.triu_indices(len(names), 1)
    some = (jaccard[a, b] > 0) | (rho[a, b] > 0)
    return greedy_from(names, Neighbours.of(len(names), a[some], b[some], jaccard[a, b][some], rho[a, b][some]), influence, params)


def greedy_from(names: list[str], near: Neighbours, influence: np.ndarray, params: TopicParams) -> list[dict]:
    """The topics of one component, by running sums of the pair values.

    The seed is the unused word of most influence (or the better word of the best pair);
    the unused word that lifts the objective most is added while it rises.
    """
    n = len(names)
    free = np.ones(n, bool)
    cap = params.max_topic_size or n
    how = params.influence
    documents, bursts = params.factors != "no_documents", params.factors != "no_time"
    affinity = (near.jaccard if documents else 1.0) * (near.rho if bursts else 1.0)
    linked = affinity > params.min_link
    rows = np.repeat(np.arange(n), np.diff(near.starts))
    topics = []

    def factor(total: np.ndarray, size: int, added: np.ndarray) -> np.ndarray:
        return {"sum": total + added, "candidate": added, "mean": (total + added) / (size + 1), "off": np.ones(len(added))}[how]

    def first_word() -> int:
        if params.seed == "pair":
            open_ = free[rows] & free[near.others]
            value = np.where(open_, affinity * factor(influence[rows], 1, influence[near.others]), 0.0) if len(rows) else np.zeros(1)
            return int(rows[value.argmax()]) if value.max() > 0 else int(free.argmax())
        return int(np.where(free, influence, -np.inf).argmax())

    while free.any():
        seed = first_word()
        members: list[int] = []
        sum_j, sum_r, able = np.zeros(n), np.zeros(n), np.zeros(n, bool)  # of each word with the members
        in_j = in_r = total = 0.0

        def take(i: int) -> None:
            nonlocal in_j, in_r, total
            in_j, in_r, total = in_j + sum_j[i], in_r + sum_r[i], total + influence[i]
            own = near.row(i)
            sum_j[near.others[own]] += near.jaccard[own]
            sum_r[near.others[own]] += near.rho[own]
            able[near.others[own][linked[own]]] = True
            members.append(i)
            free[i] = False

        take(seed)
        best = -np.inf
        while len(members) < cap:
            k = len(members)
            pairs = k * (k + 1) / 2
            at = np.flatnonzero(able & free)
            if not len(at):
                break
            value = ((in_j + sum_j[at]) / pairs if documents else 1.0) * ((in_r + sum_r[at]) / pairs if bursts else 1.0) * factor(total, k, influence[at])
            value = np.round(value, 12)  # ties by name, whatever the order of the sums
            pick = int(value.argmax())
            if value[pick] <= (params.min_pair_objective if k == 1 else best):
                break
            best = float(value[pick])
            take(int(at[pick]))
        k = len(members)
        if k == 1:
            if params.singleton == "drop":
                continue
            doc = time = 1.0 if params.singleton == "self" else 0.0
        else:
            doc, time = in_j / (k * (k - 1) / 2), in_r / (k * (k - 1) / 2)
        impact = {"sum": total, "candidate": influence[members[-1]], "mean": total / k, "off": 1.0}[how]
        objective = (doc if documents else 1.0) * (time if bursts else 1.0) * impact
        topics.append({"features": sorted(names[i] for i in members), "doc_coherence": float(doc), "time_coherence": float(time), "influence": float(impact), "objective": float(objective)})
    return topics


def extract_topics(pairs: DataFrame, influence: DataFrame, params: TopicParams = TopicParams(), max_local_rows: int = 2_000_000) -> DataFrame:
    """``topic_id, features, doc_coherence, time_coherence, influence, objective``, ranked by objective.

    A candidate needs an affinity with a member, so topics never leave a component of the
    affinity graph, and the components are worked on independently with equal results. A
    component of more than ``max_local_rows`` words and pairs is refused.
    """
    affinity = {"all": F.col("jaccard") * F.col("rho"), "no_documents": F.col("rho"), "no_time": F.col("jaccard")}[params.factors]
    edges = pairs.where(affinity > params.min_link).select(F.col("f").alias("a"), F.col("g").alias("b"))
    labels = connected(influence.select(F.col("feature").alias("id")), edges)
    words = labels.join(influence.withColumnRenamed("feature", "id"), "id").select("component", F.col("id").alias("f"), F.lit(None).cast("string").alias("g"), F.lit(None).cast("double").alias("jaccard"), F.lit(None).cast("double").alias("rho"), "influence")
    inside = pairs.join(labels.select(F.col("id").alias("f"), "component"), "f").join(labels.select(F.col("id").alias("g"), F.col("component").alias("other")), "g").where("component = other")
    rows = words.unionByName(inside.select("component", "f", "g", "jaccard", "rho", F.lit(None).cast("double").alias("influence")))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf[pdf.g.isna()].sort_values("f")
        names = own.f.tolist()
        at = {w: i for i, w in enumerate(names)}
        links = pdf[pdf.g.notna()]
        near = Neighbours.of(len(names), links.f.map(at).to_numpy(int), links.g.map(at).to_numpy(int), links.jaccard.to_numpy(float), links.rho.to_numpy(float))
        return pd.DataFrame(greedy_from(names, near, own.influence.to_numpy(float), params), columns=["features", "doc_coherence", "time_coherence", "influence", "objective"])

    return numbered(bounded(rows, "component", max_local_rows).groupBy("component").applyInPandas(work, TOPIC_SCHEMA))


def numbered(topics: DataFrame) -> DataFrame:
    order = Window.orderBy(F.desc("objective"), F.array_join("features", " "))  # as many rows as topics
    return topics.select(F.row_number().over(order).alias("topic_id"), *topics.columns)


def members_of(topics: DataFrame) -> DataFrame:
    """``topic_id, size, feature``."""
    return topics.select("topic_id", F.size("features").alias("size"), F.explode("features").alias("feature"))


def coherence(topics: DataFrame, pairs: DataFrame, value: str) -> DataFrame:
    """``topic_id`` and the mean of a pair value over all pairs of words of the topic; 1 for one word."""
    m = members_of(topics)
    both = m.select("topic_id", "size", F.col("feature").alias("f")).join(m.select("topic_id", F.col("feature").alias("g")), "topic_id").where("f < g")
    got = both.join(pairs.select("f", "g", value), ["f", "g"], "left").groupBy("topic_id").agg((F.sum(F.coalesce(value, F.lit(0.0))) / F.count(F.lit(1))).alias(value))
    return topics.select("topic_id").join(got, "topic_id", "left").fillna(1.0, [value])


def topic_objective(topics: DataFrame, pairs: DataFrame, influence: DataFrame, how: str = "sum") -> DataFrame:
    """The three factors and their product for any set of topics (``topic_id, features``)."""
    impact = members_of(topics).join(influence, "feature", "left").groupBy("topic_id").agg({"sum": F.sum("influence"), "mean": F.avg("influence"), "off": F.lit(1.0)}[how].alias("influence")) if how != "off" else topics.select("topic_id", F.lit(1.0).alias("influence"))
    out = coherence(topics, pairs, "jaccard").join(coherence(topics, pairs, "rho"), "topic_id").join(impact, "topic_id")
    return out.withColumn("objective", F.col("jaccard") * F.col("rho") * F.col("influence"))


def rank_topics(topics: DataFrame, k: int) -> DataFrame:
    return topics.orderBy(F.desc("objective"), "topic_id").limit(k)


def topic_burst(topics: DataFrame, p: DataFrame, threshold: float = 0.7) -> DataFrame:
    """``topic_id, win, rate, bursty``: the mean probability of the topic's words, absent cells counting 0."""
    rate = members_of(topics).join(p.select("feature", "win", "p"), "feature").groupBy("topic_id", "win").agg((F.sum("p") / F.first("size")).alias("rate"))
    return rate.withColumn("bursty", F.col("rate") > threshold)


def compare_partners(spark, word: str, partners: list[tuple[str, float, float, float]]) -> DataFrame:
    """Partners of one word by (name, document similarity, temporal similarity, influence): objectives without and with the index."""
    return partner_values(spark.createDataFrame([(word, *p) for p in partners], "word string, partner string, jaccard double, rho double, influence double"))


def partner_values(rows: DataFrame) -> DataFrame:
    """``word, partner, jaccard, rho, influence`` (of the partner) plus the objectives without and with the index."""
    plain = F.col("jaccard") * F.col("rho")
    return rows.withColumn("without_index", plain).withColumn("with_index", plain * F.col("influence"))
