"""The whole method over one stream and one index."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import bursts as B
from ..functions.volatility import index_levels
from ..params import FLAGSHIP, Params
from ..sources.staging import staged
from . import affinity, chains, events, groups, topics


class Bursts(NamedTuple):
    counts: DataFrame
    totals: DataFrame
    p: DataFrame


class Result(NamedTuple):
    p: DataFrame
    pvi: DataFrame
    influence: DataFrame
    pairs: DataFrame
    topics: DataFrame
    rate: DataFrame
    gram: DataFrame
    groups: DataFrame
    links: DataFrame
    chains: DataFrame
    merged: DataFrame
    members: DataFrame
    events: DataFrame


def bursts_of(tokens: DataFrame, params: Params = FLAGSHIP) -> Bursts:
    """Counts, totals and burst probabilities of a stream; the inclusive tail gets a cell for every absent count."""
    b = params.burst
    counts = staged(B.window_counts(tokens), "counts")
    totals = B.window_totals(counts)
    rates = B.quiet_rates(counts, totals, b.quiet_rounds, b.tail, b.threshold) if b.expected == "quiet" else B.expected_rate(counts, totals, b.expected)
    cells = counts if b.tail == "strict" else B.filled_counts(counts, totals)
    p = staged(B.burst_probability(cells, totals, rates, b.tail, b.threshold, b.require_presence), "bursts")
    return Bursts(counts, totals, p)


def measured(tokens: DataFrame, index: DataFrame, params: Params = FLAGSHIP) -> tuple[Bursts, DataFrame, DataFrame, DataFrame]:
    """Bursts, levels, influence and pairs, which hang on the burst and volatility switches alone.

    The stream is read more than once: one that is costly to make should be written first.
    """
    found = bursts_of(tokens, params)
    v = params.volatility
    pvi = staged(index_levels(index, v.horizon, v.mode, v.fit, v.levels), "levels")
    influence = staged(topics.feature_influence(found.p, pvi), "influence")
    pairs = staged(affinity.component_affinities(tokens, found.p, params.burst.sparsify), "pairs")
    return found, pvi, influence, pairs


def impact_topics(tokens: DataFrame, index: DataFrame, params: Params = FLAGSHIP, known: tuple | None = None) -> tuple[Bursts, DataFrame, DataFrame, DataFrame, DataFrame]:
    """What :func:`measured` gives (``known``, if it ran before) and the topics."""
    found, pvi, influence, pairs = known or measured(tokens, index, params)
    return found, pvi, influence, pairs, staged(topics.extract_topics(pairs, influence, params.topic, params.max_local_rows), "topics")


def run(tokens: DataFrame, index: DataFrame, params: Params = FLAGSHIP, known: tuple | None = None) -> Result:
    """Topics, groups, chains and ranked events. Stages are written, so each restarts from the one before.

    ``known`` is what :func:`impact_topics` gave for the same stream, index and switches, if it ran before.
    """
    if known is None:
        tokens = staged(tokens, "tokens")
    found, pvi, influence, pairs, tops = known or impact_topics(tokens, index, params)
    rate = staged(topics.topic_burst(tops, found.p, params.topic.burst_threshold), "rates")
    gram = staged(groups.topic_gram(tops, tokens, rate), "gram")
    grouped = staged(groups.group_topics(gram, params.group), "groups")
    links = staged(chains.group_links(grouped, tops, params.chain.link_threshold, params.chain.weight), "links")
    paths = staged(chains.discover_chains(grouped, links, rate, pvi, params.chain, params.max_local_rows), "chains")
    merged = staged(events.merge_chains(events.chain_overlap(paths), paths, params.chain, params.max_local_rows), "merged")
    members = events.event_members(paths, merged, grouped)
    return Result(found.p, pvi, influence, pairs, tops, rate, gram, grouped, links, paths, merged, members, events.assemble_events(paths, merged, grouped, rate, pvi))


def with_words(result: Result) -> DataFrame:
    """Events with the words they hold over all windows, as a flat table."""
    words = events.describe_events(result.members, result.topics).groupBy("event_id").agg(F.array_join(F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.split("words", " "))))), " ").alias("words"))
    return result.events.join(words, "event_id").select("rank", "event_id", "start_win", "end_win", "n_win", "score", "comovement", "words")
