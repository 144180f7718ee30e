"""Links between groups of adjacent windows, and chains grown from the most volatile windows."""

from __future__ import annotations

import math
from collections import defaultdict
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import ChainParams
from ..sources.staging import bounded

CHAIN_SCHEMA = "chain_id int, seed_win int, win int, group_id int, position int, score double"


def group_links(groups: DataFrame, topics: DataFrame, threshold: float = 0.0, weight: str = "objective") -> DataFrame:
    """``win, group_id, next_group_id, similarity`` of groups of adjacent windows above the threshold.

    Shared over united topics, each weighed by its objective (or 1); two groups without weight have similarity 0.
    """
    value = F.col("objective") if weight == "objective" else F.lit(1.0)
    rows = groups.select("win", "group_id", F.explode("topics").alias("topic_id")).join(topics.select("topic_id", value.alias("v")), "topic_id")
    sums = rows.groupBy("win", "group_id").agg(F.sum("v").alias("total"))
    after = rows.select((F.col("win") - 1).alias("win"), F.col("group_id").alias("next_group_id"), "topic_id")
    shared = rows.join(after, ["win", "topic_id"]).groupBy("win", "group_id", "next_group_id").agg(F.sum("v").alias("shared"))
    out = shared.join(sums, ["win", "group_id"]).join(sums.select((F.col("win") - 1).alias("win"), F.col("group_id").alias("next_group_id"), F.col("total").alias("other")), ["win", "next_group_id"])
    union = F.col("total") + F.col("other") - F.col("shared")
    out = out.select("win", "group_id", "next_group_id", F.when(union > 0, F.col("shared") / union).otherwise(0.0).alias("similarity"))
    return out.where(F.col("similarity") > threshold)


@dataclass
class Chain:
    """A chain with running sums, so that a trial costs the topics of the new group only."""

    seed: int
    groups: list[tuple[int, int]]
    cells: dict[int, tuple[float, int]] = field(default_factory=dict)
    sums: tuple[float, float, float, float, float, int] = (0.0, 0.0, 0.0, 0.0, 0.0, 0)
    score: float = 0.0
    held: set[tuple[int, int]] = field(default_factory=set)

    def with_group(self, win: int, total: float, count: int, level: float) -> tuple[tuple[float, int], tuple, float]:
        sx, sxx, sy, syy, sxy, n = self.sums
        s, c = self.cells.get(win, (0.0, 0))
        if c:
            x = s / c
            sx, sxx, sxy = sx - x, sxx - x * x, sxy - x * level
        else:
            sy, syy, n = sy + level, syy + level * level, n + 1
        cell = (s + total, c + count)
        x = cell[0] / cell[1]
        sums = (sx + x, sxx + x * x, sy, syy, sxy + x * level, n)
        return cell, sums, score_of(sums)

    def take(self, group: tuple[int, int], found: tuple) -> None:
        self.cells[group[0]], self.sums, self.score = found
        self.groups.append(group)
        self.held.add(group)

    def copy(self) -> "Chain":
        return Chain(self.seed, list(self.groups), dict(self.cells), self.sums, self.score, set(self.held))


def score_of(sums: tuple) -> float:
    """Norm of the intensities times norm of the levels times their correlation; 0 where that is undefined."""
    sx, sxx, sy, syy, sxy, n = sums
    vx, vy = n * sxx - sx * sx, n * syy - sy * sy
    if n < 2 or vx <= 1e-12 * max(n * sxx, 1e-300) or vy <= 1e-12 * max(n * syy, 1e-300):
        return 0.0
    r = max(-1.0, min(1.0, (n * sxy - sx * sy) / math.sqrt(vx * vy)))
    return math.sqrt(max(sxx, 0.0)) * math.sqrt(max(syy, 0.0)) * r


def probe(groups: dict[tuple[int, int], list[int]], links: dict[tuple[int, int], dict[int, float]], back: dict[tuple[int, int], dict[int, float]], rate: dict[tuple[int, int], float], pvi: dict[int, float], params: ChainParams) -> list[Chain]:
    """All chains, seed windows by falling level (then number), groups by number, chains by birth.

    A group is used once a chain takes it; used groups are passed over by later visits but
    one visit may serve several chains, so chains of one seed window can share groups.
    """
    by_win = defaultdict(list)
    for win, g in sorted(groups):
        by_win[win].append(g)
    used: set[tuple[int, int]] = set()
    chains: list[Chain] = []
    worth = {key: (sum(rate.get((t, key[0]), 0.0) for t in topics), len(topics)) for key, topics in groups.items()}
    for seed in sorted(by_win, key=lambda w: (-pvi.get(w, 0.0), w)):
        start: dict[int, list[Chain]] = {}
        for g in by_win[seed]:
            if (seed, g) in used:
                continue
            chain = Chain(seed, [])
            chain.take((seed, g), chain.with_group(seed, *worth[seed, g], pvi.get(seed, 0.0)))
            start[g] = [chain]
            chains.append(chain)
            used.add((seed, g))
        for step, table in ((1, links), (-1, back)):
            win, front = seed, {g: list(cs) for g, cs in start.items()}
            while front:
                ahead: dict[int, list[Chain]] = defaultdict(list)
                for g in by_win.get(win + step, []):
                    if (win + step, g) in used:
                        continue
                    near = table.get((win + step, g), {})
                    for own in sorted(front):
                        if near.get(own, 0.0) <= params.link_threshold:
                            continue
                        for chain in list(front[own]):
                            if (win + step, g) in chain.held:
                                continue
                            found = chain.with_group(win + step, *worth[win + step, g], pvi.get(win + step, 0.0))
                            if params.require_gain and not found[2] > chain.score:
                                continue
                            if params.branching == "fork":
                                if params.beam and sum(map(len, ahead.values())) >= params.beam:
                                    continue
                                chain = chain.copy()
                                chains.append(chain)
                                if own in start and win == seed:
                                    start[own].append(chain)
                            chain.take((win + step, g), found)
                            ahead[g].append(chain)
                            used.add((win + step, g))
                front, win = dict(ahead), win + step
    return chains


def discover_chains(groups: DataFrame, links: DataFrame, rate: DataFrame, pvi: DataFrame, params: ChainParams = ChainParams(), max_local_rows: int = 2_000_000) -> DataFrame:
    """``chain_id, seed_win, win, group_id, position, score``.

    Chains never cross a window without links, so runs of windows between such gaps are
    independent: each run is one group of a grouped map, with the levels and rates of its
    windows. What a run holds follows windows and topics, never documents; a run of more than
    ``max_local_rows`` rows is refused.
    """
    wins = groups.select("win").distinct()
    linked = links.select("win").distinct().withColumn("on", F.lit(True))
    from pyspark.sql import Window

    order = Window.orderBy("win")  # one row per window
    gap = ~F.coalesce(F.lag("on").over(order), F.lit(False)) | (F.col("win") != F.lag("win").over(order) + 1)
    runs = wins.join(linked, "win", "left").withColumn("run", F.sum(F.coalesce(gap, F.lit(True)).cast("int")).over(order)).select("win", "run")
    cells = groups.select("win", "group_id", F.explode("topics").alias("topic_id")).join(rate.select("topic_id", "win", "rate"), ["topic_id", "win"], "left").fillna(0.0, ["rate"])
    worth = cells.join(F.broadcast(pvi.select("win", "pvi")), "win", "left").fillna(0.0, ["pvi"])
    left = worth.select("win", "group_id", "topic_id", F.lit(None).cast("int").alias("next_group_id"), F.col("rate").alias("value"), "pvi")
    right = links.select("win", "group_id", F.lit(None).cast("int").alias("topic_id"), "next_group_id", F.col("similarity").alias("value"), F.lit(0.0).alias("pvi"))
    rows = bounded(left.unionByName(right).join(F.broadcast(runs), "win"), "run", max_local_rows)

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        own, net = pdf[pdf.topic_id.notna()], pdf[pdf.next_group_id.notna()]
        members, rates, levels = defaultdict(list), {}, {}
        for w, g, t, v, y in zip(own.win, own.group_id, own.topic_id.astype(int), own.value, own.pvi):
            members[int(w), int(g)].append(t)
            rates[t, int(w)] = v
            levels[int(w)] = y
        fore, back = defaultdict(dict), defaultdict(dict)
        for w, g, h, v in zip(net.win, net.group_id, net.next_group_id.astype(int), net.value):
            fore[int(w) + 1, h][int(g)] = v
            back[int(w), int(g)][h] = v
        out = []
        for i, c in enumerate(probe(dict(members), fore, back, rates, levels, params)):
            for pos, (w, g) in enumerate(sorted(c.groups)):
                out.append((i, c.seed, w, g, pos, c.score))
        frame = pd.DataFrame(out, columns=["chain_id", "seed_win", "win", "group_id", "position", "score"])
        frame["run"] = int(pdf.run.iloc[0])
        return frame

    found = rows.groupBy("run").applyInPandas(work, CHAIN_SCHEMA + ", run int")
    ids = found.select("run", F.col("chain_id").alias("c")).distinct().withColumn("chain_id", F.row_number().over(Window.orderBy("run", "c")))
    return found.withColumnRenamed("chain_id", "c").join(ids, ["run", "c"]).select("chain_id", "seed_win", "win", "group_id", "position", "score")
