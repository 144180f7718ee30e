"""Word counts by window, expected rates, burst probabilities, burst windows and runs."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Up to these the tail is a sum of column expressions; beyond them an Arrow function takes over.
COLUMN_MAX_COUNT, COLUMN_MAX_MEAN = 2_000, 500.0


def window_counts(tokens: DataFrame) -> DataFrame:
    """``feature, win, n``: one shuffle after partial sums."""
    return tokens.groupBy("feature", "win").agg(F.count(F.lit(1)).alias("n"))


def window_totals(counts: DataFrame) -> DataFrame:
    """``win, total``: words of the kept features in each window."""
    return counts.groupBy("win").agg(F.sum("n").alias("total"))


def expected_rate(counts: DataFrame, totals: DataFrame, how: str = "pooled", bursty: DataFrame | None = None) -> DataFrame:
    """``feature, pe``: the chance that a word is the feature when nothing bursts.

    ``pooled``: all its occurrences over all words. ``mean_rate``: the mean over windows of its share,
    absent windows counting 0. ``quiet``: pooled over the windows outside ``bursty`` (feature, win).
    """
    if how == "mean_rate":
        windows = totals.agg(F.count(F.lit(1)).alias("n_win"))
        shares = counts.join(totals, "win").groupBy("feature").agg(F.sum(F.col("n") / F.col("total")).alias("x"))
        return shares.crossJoin(F.broadcast(windows)).select("feature", (F.col("x") / F.col("n_win")).alias("pe"))
    whole = totals.agg(F.sum("total").alias("words"))
    pooled = counts.groupBy("feature").agg(F.sum("n").alias("n")).crossJoin(F.broadcast(whole))
    if how == "pooled":
        return pooled.select("feature", (F.col("n") / F.col("words")).alias("pe"))
    taken = bursty.select("feature", "win").join(totals, "win").join(counts, ["feature", "win"]).groupBy("feature").agg(F.sum("n").alias("bn"), F.sum("total").alias("bw"))
    quiet = pooled.join(taken, "feature", "left").fillna(0, ["bn", "bw"])
    rest = F.col("words") - F.col("bw")
    return quiet.select("feature", F.when(rest > 0, (F.col("n") - F.col("bn")) / rest).otherwise(F.col("n") / F.col("words")).alias("pe"))


def column_tail(n: Column, total: Column, pe: Column, tail: str) -> Column:
    """The binomial tail as a running sum of terms, each from the one before; inside code generation's reach."""
    ratio = pe / (1 - pe)
    first = F.exp(total * F.log1p(-pe))
    start = F.struct(first.alias("term"), F.lit(0.0).alias("below"))
    step = lambda s, k: F.struct((s["term"] * (total - k) / (k + 1) * ratio).alias("term"), (s["below"] + s["term"]).alias("below"))
    done = F.aggregate(F.when(n > 0, F.sequence(F.lit(0).cast("long"), n - 1)).otherwise(F.array().cast("array<bigint>")), start, step)
    return {"strict": done["below"], "inclusive": done["below"] + done["term"], "pmf": done["term"]}[tail]


def poisson_tail(n: Column, total: Column, pe: Column, tail: str) -> Column:
    """The Poisson approximation for rare words in large windows, as a running sum of terms.

    The first term is 0 in double precision from a mean of 745; :func:`poisson_values` takes such cells.
    """
    mean = total * pe
    start = F.struct(F.exp(-mean).alias("term"), F.lit(0.0).alias("below"))
    step = lambda s, k: F.struct((s["term"] * mean / (k + 1)).alias("term"), (s["below"] + s["term"]).alias("below"))
    done = F.aggregate(F.when(n > 0, F.sequence(F.lit(0).cast("long"), n - 1)).otherwise(F.array().cast("array<bigint>")), start, step)
    return {"strict": done["below"], "inclusive": done["below"] + done["term"], "pmf": done["term"]}[tail]


def _log_beta(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    gamma = np.frompyfunc(math.lgamma, 1, 1)
    return (gamma(a) + gamma(b) - gamma(a + b)).astype(float)


def beta_share(x: np.ndarray, a: np.ndarray, b: np.ndarray, rounds: int = 400) -> np.ndarray:
    """The regularised incomplete beta function by its continued fraction, on arrays."""
    x, a, b = (np.asarray(v, float) for v in (x, a, b))
    swap = x > (a + 1) / (a + b + 2)
    x, a, b = np.where(swap, 1 - x, x), np.where(swap, b, a), np.where(swap, a, b)
    front = np.exp(a * np.log(np.maximum(x, 1e-300)) + b * np.log1p(-np.minimum(x, 1 - 1e-16)) - _log_beta(a, b)) / a
    tiny = 1e-300
    c, d = np.ones_like(x), 1 / np.where(np.abs(1 - (a + b) * x / (a + 1)) < tiny, tiny, 1 - (a + b) * x / (a + 1))
    h = d.copy()
    for m in range(1, rounds):
        even = m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m))
        odd = -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))
        moved = 0.0
        for term in (even, odd):
            d = 1 + term * d
            c = 1 + term / c
            d, c = 1 / np.where(np.abs(d) < tiny, tiny, d), np.where(np.abs(c) < tiny, tiny, c)
            h = h * d * c
            moved = np.abs(d * c - 1).max(initial=0)
        if moved < 1e-14:
            break
    share = np.where(x <= 0, 0.0, np.minimum(front * h, 1.0))
    return np.where(swap, 1 - share, share)


def tail_values(n: np.ndarray, total: np.ndarray, pe: np.ndarray, tail: str) -> np.ndarray:
    """The tail on arrays of any size: a binomial sum is an incomplete beta function."""
    n, total, pe = (np.asarray(v, float) for v in (n, total, pe))

    def up_to(k: np.ndarray) -> np.ndarray:
        inner = (k >= 0) & (k < total)
        at = beta_share(1 - pe, np.where(inner, total - k, 1.0), np.where(inner, k + 1, 1.0))
        return np.where(k < 0, 0.0, np.where(k >= total, 1.0, at))

    if tail == "pmf":
        return np.maximum(up_to(n) - up_to(n - 1), 0.0)
    return up_to(n if tail == "inclusive" else n - 1)


def tail_function(tail: str):
    @F.pandas_udf("double")
    def of(parts: Iterator[tuple[pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for n, total, pe in parts:
            yield pd.Series(tail_values(n.to_numpy(), total.to_numpy(), pe.to_numpy(), tail))

    return of


def gamma_share(a: np.ndarray, x: np.ndarray) -> np.ndarray:
    """The regularised upper incomplete gamma function for a, x > 0, on arrays.

    Below a + 1 by the series of the lower one, above by the continued fraction; either needs a small
    multiple of the root of the larger argument in terms, and all factors are kept in logarithms.
    """
    a, x = (np.asarray(v, float) for v in (a, x))
    front = np.exp(a * np.log(x) - x - np.frompyfunc(math.lgamma, 1, 1)(a).astype(float))
    out = np.empty_like(x)
    low = x < a + 1
    s, term = a[low], 1 / a[low]
    total, k = term.copy(), 0
    while len(s) and (term > 1e-17 * total).any():
        k += 1
        term = term * x[low] / (s + k)
        total += term
    out[low] = 1 - front[low] * total
    s, z = a[~low], x[~low]
    b, tiny, k, moved = z + 1 - s, 1e-300, 0, 1.0
    c, d = np.full_like(z, 1 / tiny), 1 / b
    h = d.copy()
    while len(z) and moved > 1e-15 and k < 1_000_000:
        k += 1
        step = -k * (k - s)
        b = b + 2
        d = step * d + b
        c = b + step / c
        d, c = 1 / np.where(np.abs(d) < tiny, tiny, d), np.where(np.abs(c) < tiny, tiny, c)
        h = h * d * c
        moved = np.abs(d * c - 1).max()
    out[~low] = front[~low] * h
    return np.clip(out, 0.0, 1.0)


def poisson_values(n: np.ndarray, mean: np.ndarray, tail: str) -> np.ndarray:
    """The Poisson tail on arrays of any size: a sum of its terms is an incomplete gamma function."""
    n, mean = (np.asarray(v, float) for v in (n, mean))
    if tail == "pmf":
        return np.exp(n * np.log(mean) - mean - np.frompyfunc(math.lgamma, 1, 1)(n + 1).astype(float))
    terms = n + 1 if tail == "inclusive" else n
    return np.where(terms > 0, gamma_share(np.maximum(terms, 1.0), mean), 0.0)


def poisson_function(tail: str):
    @F.pandas_udf("double")
    def of(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for n, mean in parts:
            yield pd.Series(poisson_values(n.to_numpy(), mean.to_numpy(), tail))

    return of


def normal_tail(n: Column, total: Column, pe: Column, tail: str) -> Column:
    """Normal approximation with continuity correction, by a rational form of the error function."""
    at = n + {"strict": -0.5, "inclusive": 0.5}[tail]
    z = (at - total * pe) / F.sqrt(total * pe * (1 - pe))
    t = 1 / (1 + 0.2316419 * F.abs(z))
    poly = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    upper = F.exp(-z * z / 2) / math.sqrt(2 * math.pi) * poly
    return F.when(z >= 0, 1 - upper).otherwise(upper)


def burst_probability(counts: DataFrame, totals: DataFrame, rates: DataFrame, tail: str = "strict", threshold: float = 0.95, require_presence: bool = False, approx: str | None = None) -> DataFrame:
    """``feature, win, n, total, pe, p, bursty`` for the cells of ``counts``.

    A rate of 0 or 1, or a window without words, leaves nothing to be surprised by: the tail
    is then that of the point mass. Cells absent from ``counts`` have n = 0, which the strict
    tail makes 0; the inclusive tail needs :func:`burst_series` to fill them.
    """
    cells = counts.join(totals, "win").join(rates, "feature")
    n, total, pe = (F.col(c) for c in ("n", "total", "pe"))
    point = F.when(pe <= 0, F.lit(0)).otherwise(total)
    edge = {"strict": (n > point), "inclusive": (n >= point), "pmf": (n == point)}[tail].cast("double")
    plain = (pe > 0) & (pe < 1) & (total > 0)
    if approx == "normal":
        out = cells.withColumn("p", F.when(plain, normal_tail(n, total, pe, tail)).otherwise(edge))
    elif approx == "poisson":
        small = (n <= COLUMN_MAX_COUNT) & (total * pe <= COLUMN_MAX_MEAN)
        out = cells.where(~plain | small).withColumn("p", F.when(plain, poisson_tail(n, total, pe, tail)).otherwise(edge))
        large = cells.where(plain & ~small).withColumn("p", poisson_function(tail)(n.cast("double"), (total * pe).cast("double")))
        out = out.unionByName(large)
    elif approx:
        raise ValueError(approx)
    else:
        small = (n <= COLUMN_MAX_COUNT) & (total * -F.log1p(-F.least(pe, F.lit(1 - 1e-12))) <= COLUMN_MAX_MEAN)
        out = cells.where(~plain | small).withColumn("p", F.when(plain, column_tail(n, total, pe, tail)).otherwise(edge))
        large = cells.where(plain & ~small).withColumn("p", tail_function(tail)(n.cast("double"), total.cast("double"), pe))
        out = out.unionByName(large)
    out = out.withColumn("p", F.least(F.greatest(F.col("p"), F.lit(0.0)), F.lit(1.0)))
    present = (n > 0) if require_presence else F.lit(True)
    return out.withColumn("bursty", (F.col("p") > threshold) & present)


def filled_counts(counts: DataFrame, totals: DataFrame) -> DataFrame:
    """Counts with a row of 0 for every absent cell: features times windows, both small."""
    cells = counts.select("feature").distinct().crossJoin(F.broadcast(totals.select("win")))
    return cells.join(counts, ["feature", "win"], "left").fillna(0, ["n"])


def burst_windows(p: DataFrame) -> DataFrame:
    return p.where("bursty").select("feature", "win")


def burst_series(p: DataFrame, windows: DataFrame) -> DataFrame:
    """``feature, series``: the probabilities of all windows in order, 0 where absent."""
    cells = p.select("feature").distinct().crossJoin(F.broadcast(windows.select("win")))
    full = cells.join(p.select("feature", "win", "p"), ["feature", "win"], "left").fillna(0.0, ["p"])
    return full.groupBy("feature").agg(F.transform(F.sort_array(F.collect_list(F.struct("win", "p"))), lambda x: x["p"]).alias("series"))


def burst_runs(windows: DataFrame, key: str = "feature") -> DataFrame:
    """``key, start_win, end_win, length``: runs of consecutive burst windows."""
    rank = F.row_number().over(Window.partitionBy(key).orderBy("win"))
    runs = windows.select(key, "win", (F.col("win") - rank).alias("run"))
    return runs.groupBy(key, "run").agg(F.min("win").alias("start_win"), F.max("win").alias("end_win"), F.count(F.lit(1)).alias("length")).drop("run")


def quiet_rates(counts: DataFrame, totals: DataFrame, rounds: int = 3, tail: str = "strict", threshold: float = 0.95) -> DataFrame:
    """Rates re-estimated outside the burst windows of the round before."""
    rates = expected_rate(counts, totals, "pooled")
    for _ in range(rounds):
        bursty = burst_windows(burst_probability(counts, totals, rates, tail, threshold))
        rates = expected_rate(counts, totals, "quiet", bursty)
    return rates
