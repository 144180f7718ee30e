"""Index series: returns, volatility, and its level under a fitted logistic curve.

An index has one row per window, so ordering it in one place is safe at any data size.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def log_returns(index: DataFrame) -> DataFrame:
    """``win, value`` plus ``ret``: null for the first window and where a value is not positive."""
    before = F.lag("value").over(Window.orderBy("win"))
    return index.withColumn("ret", F.when((F.col("value") > 0) & (before > 0), F.log(F.col("value") / before)))


def index_change(index: DataFrame) -> DataFrame:
    """``win, value, change``: the plain rise or fall, the alternative to volatility."""
    return index.withColumn("change", F.col("value") - F.lag("value").over(Window.orderBy("win")))


def volatility(returns: DataFrame, horizon: int = 4, mode: str = "trailing", weights: str | None = None) -> DataFrame:
    """``win, value, ret, vi``: the population deviation of the returns around a window; null without a full horizon."""
    ends = {"trailing": (1 - horizon, 0), "centered": (-(horizon // 2), horizon - 1 - horizon // 2)}[mode]
    span = Window.orderBy("win").rowsBetween(*ends)
    if weights is None:
        vi = F.stddev_pop("ret").over(span)
    else:
        w = F.when(F.col("ret").isNotNull(), F.col(weights))
        total = F.sum(w).over(span)
        mean = F.sum(w * F.col("ret")).over(span) / total
        vi = F.sqrt(F.greatest(F.sum(w * F.col("ret") * F.col("ret")).over(span) / total - mean * mean, F.lit(0.0)))
    return returns.withColumn("vi", F.when(F.count("ret").over(span) == horizon, vi))


def volatility_within(steps: DataFrame, min_returns: int = 2) -> DataFrame:
    """``win, step, value`` -> ``win, vi``: the deviation of the finer returns inside each window."""
    before = F.lag("value").over(Window.partitionBy("win").orderBy("step"))
    finer = steps.withColumn("ret", F.log(F.col("value") / before))
    return finer.groupBy("win").agg(F.when(F.count("ret") >= min_returns, F.stddev_pop("ret")).alias("vi"))


def fit_logistic(vi: DataFrame, how: str = "moments", rounds: int = 50) -> tuple[float | None, float | None]:
    """Location and scale of the logistic curve; two numbers on the driver."""
    got = vi.agg(F.avg("vi").alias("m"), F.stddev_pop("vi").alias("s")).first()
    if got["m"] is None:
        return None, None
    mu, s = float(got["m"]), float(got["s"]) * math.sqrt(3) / math.pi
    if how == "moments" or s == 0:
        return mu, s
    x = np.sort(np.array([r["vi"] for r in vi.where("vi IS NOT NULL").select("vi").collect()]))  # one row per window
    return logistic_mle(x, rounds)


def logistic_mle(x: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Location and scale of greatest likelihood, by Newton steps from the moments."""
    mu, s = float(x.mean()), float(x.std()) * math.sqrt(3) / math.pi

    def slope(v: np.ndarray) -> np.ndarray:
        z = (x - v[0]) / math.exp(v[1])
        t = np.tanh(z / 2)
        return np.array([t.sum() / math.exp(v[1]), (z * t).sum() - len(x)])

    at = np.array([mu, math.log(s)])
    for _ in range(rounds):
        g = slope(at)
        eps = 1e-6
        h = np.stack([(slope(at + eps * e) - g) / eps for e in np.eye(2)], axis=1)
        move = np.linalg.solve(h, -g)
        at = at + np.clip(move, -0.5, 0.5)
        if np.abs(move).max() < 1e-10:
            break
    return float(at[0]), float(math.exp(at[1]))


def volatility_level(vi: DataFrame, how: str = "moments", levels: int | None = 10) -> DataFrame:
    """``vi`` plus ``pvi``: the logistic share of each volatility, cut to equal-probability levels on request.

    ``rank`` uses the empirical share in place of the curve. Without spread every known
    window gets .5; windows of unknown volatility get 0.
    """
    if how == "rank":
        share = F.percent_rank().over(Window.partitionBy(F.col("vi").isNull()).orderBy("vi"))
    else:
        mu, s = fit_logistic(vi, how)
        if mu is None:
            return vi.withColumn("pvi", F.lit(0.0))
        share = F.lit(0.5) if not s else 1 / (1 + F.exp(-(F.col("vi") - mu) / s))
    if levels:
        share = F.ceil(share * levels) / levels
    return vi.withColumn("pvi", F.when(F.col("vi").isNull(), 0.0).otherwise(share))


def index_levels(index: DataFrame, horizon: int = 4, mode: str = "trailing", fit: str = "moments", levels: int | None = 10) -> DataFrame:
    """``win, value`` -> ``win, value, ret, vi, pvi``; mode ``within`` takes ``win, step, value`` and gives ``win, vi, pvi``."""
    if mode == "within":
        return volatility_level(volatility_within(index), fit, levels)
    return volatility_level(volatility(log_returns(index), horizon, mode), fit, levels)
