"""Scores of chains and events, overlap and merging of chains, and ranked events."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..params import ChainParams
from ..sources.staging import bounded, dealt
from .graph import connected


def pearson(x: Column, y: Column) -> Column:
    """Correlation as an aggregate; null for a constant series, where division by zero would be an error."""
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))


def event_intensity(members: DataFrame, rate: DataFrame, key: str = "event_id", sizes: DataFrame | None = None) -> DataFrame:
    """``key, win, topic_id`` -> ``key, win, intensity``: the mean rate of the event's topics in a window.

    With ``sizes`` (``topic_id, size``) the sum of the rates is divided by the words of the topics instead.
    """
    cells = members.select(key, "win", "topic_id").distinct().join(rate.select("topic_id", "win", "rate"), ["topic_id", "win"], "left")
    value = F.coalesce("rate", F.lit(0.0))
    if sizes is not None:
        return cells.join(sizes, "topic_id").groupBy(key, "win").agg((F.sum(value) / F.sum("size")).alias("intensity"))
    return cells.groupBy(key, "win").agg(F.avg(value).alias("intensity"))


def event_score(intensity: DataFrame, pvi: DataFrame, key: str = "event_id") -> DataFrame:
    """Norms, co-movement and their product; one window or a constant series has co-movement 0."""
    both = intensity.join(F.broadcast(pvi.select("win", "pvi")), "win", "left").fillna(0.0, ["pvi"])
    x, y = F.col("intensity"), F.col("pvi")
    flat = (F.stddev_pop(x) <= 1e-9) | (F.stddev_pop(y) <= 1e-9)
    comove = F.when(flat, 0.0).otherwise(F.coalesce(pearson(x, y), F.lit(0.0)))
    out = both.groupBy(key).agg(F.min("win").alias("start_win"), F.max("win").alias("end_win"), F.count(F.lit(1)).alias("n_win"), F.sqrt(F.sum(x * x)).alias("intensity_norm"), F.sqrt(F.sum(y * y)).alias("pvi_norm"), comove.alias("comovement"))
    return out.withColumn("score", F.col("intensity_norm") * F.col("pvi_norm") * F.col("comovement"))


def chain_overlap(chains: DataFrame) -> DataFrame:
    """``a, b, shared, overlap``, a < b: shared groups over the smaller number of groups; pairs that share none are not made."""
    sizes = chains.groupBy("chain_id").agg(F.count(F.lit(1)).alias("size"))
    a, b = (chains.select("win", "group_id", F.col("chain_id").alias(x)) for x in "ab")
    shared = a.join(b, ["win", "group_id"]).where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    out = shared.join(sizes.select(F.col("chain_id").alias("a"), F.col("size").alias("sa")), "a").join(sizes.select(F.col("chain_id").alias("b"), F.col("size").alias("sb")), "b")
    return out.select("a", "b", "shared", (F.col("shared") / F.least("sa", "sb")).alias("overlap"))


def agglomerate(n: int, similarity: np.ndarray, merge_at: float, linkage: str) -> np.ndarray:
    """Labels from merging the most similar clusters until none reaches ``merge_at``; ties to the lowest indices.

    A merge updates one row of cluster similarities from the two that it joins. The best of every row is
    kept with its place, and sought again only where it was one of the two.
    """
    sim = np.triu(similarity.astype(float), 1)
    sim = sim + sim.T
    np.fill_diagonal(sim, -np.inf)
    sizes, label, rows = np.ones(n), np.arange(n), np.arange(n)
    at = sim.argmax(axis=1) if n else rows
    best = sim[rows, at]
    for _ in range(n - 1):
        i = int(best.argmax())
        j = int(at[i])
        if round(best[i], 12) < merge_at:
            break
        i, j = min(i, j), max(i, j)
        joined = {"single": np.maximum(sim[i], sim[j]), "complete": np.minimum(sim[i], sim[j]), "average": (sizes[i] * sim[i] + sizes[j] * sim[j]) / (sizes[i] + sizes[j])}[linkage]
        joined[[i, j]] = -np.inf
        sim[i], sim[:, i] = joined, joined
        sim[j], sim[:, j] = -np.inf, -np.inf
        sizes[i] += sizes[j]
        label[label == label[j]] = label[i]
        lost = np.flatnonzero((at == i) | (at == j) | (rows == i) | (rows == j))
        at[lost] = sim[lost].argmax(axis=1)
        nearer = (joined > best) | ((joined == best) & (at > i))
        nearer[lost] = False
        at[nearer] = i
        best[nearer], best[lost] = joined[nearer], sim[lost, at[lost]]
    return label


def merge_chains(overlap: DataFrame, chains: DataFrame, params: ChainParams = ChainParams(), max_local_rows: int = 2_000_000) -> DataFrame:
    """``chain_id, event_id``: chains clustered by overlap; the least chain names the event.

    Single linkage is the components of overlaps that reach the cut; the others work inside
    the components of any overlap, which no cluster can leave.
    """
    ids = chains.select(F.col("chain_id").alias("id")).distinct()
    if params.linkage == "single":
        got = connected(ids, overlap.where(F.col("overlap") >= params.merge_at))
        return got.select(F.col("id").alias("chain_id"), F.col("component").alias("event_id"))
    labels = connected(ids, overlap)
    rows = labels.select("component", F.col("id").alias("a"), F.lit(None).cast("int").alias("b"), F.lit(None).cast("double").alias("overlap"))
    rows = rows.unionByName(overlap.select("a", "b", "overlap").join(labels.withColumnRenamed("id", "a"), "a").select("component", "a", "b", "overlap"))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        own = np.sort(pdf[pdf.b.isna()].a.to_numpy(int))
        at = {c: i for i, c in enumerate(own)}
        sim = np.eye(len(own))
        links = pdf[pdf.b.notna()]
        a, b = links.a.map(at).to_numpy(int), links.b.astype(int).map(at).to_numpy(int)
        sim[a, b] = sim[b, a] = links.overlap
        labels_ = agglomerate(len(own), sim, params.merge_at, params.linkage)
        return pd.DataFrame({"chain_id": own, "event_id": own[labels_]})

    return dealt(bounded(rows, "component", max_local_rows), "component").groupBy("component").applyInPandas(work, "chain_id int, event_id int")


def event_members(chains: DataFrame, merged: DataFrame, groups: DataFrame) -> DataFrame:
    """``event_id, win, group_id, topic_id``."""
    cells = chains.join(merged, "chain_id").select("event_id", "win", "group_id").distinct()
    return cells.join(groups.select("win", "group_id", F.explode("topics").alias("topic_id")), ["win", "group_id"])


def assemble_events(chains: DataFrame, merged: DataFrame, groups: DataFrame, rate: DataFrame, pvi: DataFrame) -> DataFrame:
    """Ranked events: the united groups of merged chains, scored anew."""
    members = event_members(chains, merged, groups)
    intensity = event_intensity(members, rate)
    parts = members.select("event_id", "win", "group_id").distinct().groupBy("event_id").agg(F.sort_array(F.collect_list(F.struct("win", "group_id"))).alias("groups"))
    return ranked(event_score(intensity, pvi).join(parts, "event_id"))


def ranked(events: DataFrame, key: str = "event_id") -> DataFrame:
    order = Window.orderBy(F.desc(F.round("score", 9) + F.lit(0.0)), "start_win", key)  # as many rows as events
    return events.withColumn("rank", F.row_number().over(order))


def rank_events(events: DataFrame, k: int) -> DataFrame:
    return events.orderBy("rank").limit(k)


def event_waves(members: DataFrame, rate: DataFrame, pvi: DataFrame) -> DataFrame:
    """``event_id, win, intensity, wave, pvi``: the intensity of each event scaled to [0, 1] beside the index level."""
    x = event_intensity(members, rate)
    w = Window.partitionBy("event_id")
    lo, hi = F.min("intensity").over(w), F.max("intensity").over(w)
    return x.withColumn("wave", F.when(hi > lo, (F.col("intensity") - lo) / (hi - lo)).otherwise(1.0)).join(F.broadcast(pvi.select("win", "pvi")), "win")


def describe_events(members: DataFrame, topics: DataFrame) -> DataFrame:
    """``event_id, win, n_topics, words``: what an event is about in each of its windows."""
    cells = members.select("event_id", "win", "topic_id").distinct().join(topics.select("topic_id", "features"), "topic_id")
    return cells.groupBy("event_id", "win").agg(F.count(F.lit(1)).alias("n_topics"), F.array_join(F.sort_array(F.array_distinct(F.flatten(F.collect_list("features")))), " ").alias("words"))
