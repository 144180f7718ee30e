"""Measures, each as one tidy table ``metric, value`` (with method and dataset added by callers)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def tidy(df: DataFrame, *metrics: str) -> DataFrame:
    """One row of values -> one row for each metric."""
    pairs = [F.struct(F.lit(m).alias("metric"), F.col(m).cast("double").alias("value")) for m in metrics]
    return df.select(F.explode(F.array(*pairs)).alias("x")).select("x.metric", "x.value")


def event_quality(events: DataFrame) -> DataFrame:
    """Number and mean score of all events and of those of two windows or more, and the share with a negative score."""
    long = F.col("n_win") >= 2
    got = events.agg(
        F.count(F.lit(1)).alias("events"), F.avg("score").alias("mean_score"), F.sum(long.cast("int")).alias("long_events"), F.avg(F.when(long, F.col("score"))).alias("mean_long_score"),
        F.avg((F.col("score") < 0).cast("double")).alias("negative_share"), F.max("n_win").alias("longest"),
    )
    return tidy(got, "events", "mean_score", "long_events", "mean_long_score", "negative_share", "longest")


def dataset_size(tokens: DataFrame) -> DataFrame:
    return tidy(tokens.agg(F.count_distinct("doc_id").alias("documents"), F.count_distinct("feature").alias("features"), F.count_distinct("win").alias("windows")), "documents", "features", "windows")


def topic_sizes(topics: DataFrame) -> DataFrame:
    """``size, topics``: how many topics have how many words."""
    return topics.groupBy(F.size("features").alias("size")).agg(F.count(F.lit(1)).alias("topics"))


def event_shape(events: DataFrame, members: DataFrame) -> DataFrame:
    per_win = members.groupBy("event_id", "win").agg(F.count_distinct("topic_id").alias("n"))
    return events.select("event_id", "start_win", "end_win", "n_win").join(per_win.groupBy("event_id").agg(F.max("n").alias("most_topics")), "event_id")


def volatile_focus(members: DataFrame, rate: DataFrame, pvi: DataFrame, parts: int = 10) -> DataFrame:
    """Events and intensity in the most volatile windows against the rest."""
    from .events import event_intensity

    top = pvi.select("win", (F.ntile(parts).over(Window.orderBy(F.desc("pvi"), "win")) == 1).alias("volatile"))
    cells = top.join(event_intensity(members, rate), "win", "left")
    return cells.groupBy("volatile").agg(F.count_distinct("win").alias("windows"), F.count("event_id").alias("event_windows"), F.avg("intensity").alias("mean_intensity"))


def logistic_distance(levels: DataFrame, mu: float, s: float) -> DataFrame:
    """The greatest gap between the empirical shares of the volatility and its fitted curve."""
    known = levels.where("vi IS NOT NULL")
    share = F.cume_dist().over(Window.orderBy("vi"))
    gap = known.select(F.abs(share - 1 / (1 + F.exp(-(F.col("vi") - mu) / s))).alias("gap"))
    return tidy(gap.agg(F.max("gap").alias("logistic_distance")), "logistic_distance")


def planted_recall(bursts: DataFrame, planted: DataFrame) -> DataFrame:
    """Recall and precision of burst cells against planted (feature, win) cells, among planted features."""
    found = bursts.where("bursty").select("feature", "win").join(planted.select("feature").distinct(), "feature", "left_semi")
    hit = found.join(planted, ["feature", "win"], "left_semi").agg(F.count(F.lit(1)).alias("hit"))
    sizes = found.agg(F.count(F.lit(1)).alias("found")).crossJoin(planted.agg(F.count(F.lit(1)).alias("planted"))).crossJoin(hit)
    rates = sizes.select((F.col("hit") / F.col("planted")).alias("recall"), F.when(F.col("found") > 0, F.col("hit") / F.col("found")).otherwise(0.0).alias("precision"))
    return tidy(rates, "recall", "precision")


def pair_f1(topics: DataFrame, planted: dict[int, list[str]]) -> DataFrame:
    """F1 of pairs of planted words that share a topic."""
    spark = topics.sparkSession
    truth = spark.createDataFrame([(g, w) for g, ws in planted.items() for w in ws], "g int, feature string")
    own = topics.select("topic_id", F.explode("features").alias("feature")).join(truth, "feature", "right")
    a, b = (own.select(F.col("topic_id").alias(f"t{x}"), F.col("g").alias(f"g{x}"), F.col("feature").alias(f"f{x}")) for x in "ab")
    both = a.crossJoin(b).where("fa < fb")  # planted words only
    same_t, same_g = F.coalesce(F.expr("ta = tb"), F.lit(False)), F.expr("ga = gb")
    n = both.agg(F.sum((same_t & same_g).cast("int")).alias("tp"), F.sum(same_t.cast("int")).alias("t"), F.sum(same_g.cast("int")).alias("g"))
    return tidy(n.select((2 * F.col("tp") / (F.col("t") + F.col("g"))).alias("pair_f1")), "pair_f1")


def sketch_error(exact: DataFrame, estimate: DataFrame) -> DataFrame:
    gap = exact.select("f", "g", "jaccard").join(estimate.select("f", "g", F.col("jaccard").alias("est")), ["f", "g"], "left").select(F.abs(F.col("jaccard") - F.coalesce("est", F.lit(0.0))).alias("e"))
    return tidy(gap.agg(F.avg("e").alias("mean_error"), F.max("e").alias("max_error")), "mean_error", "max_error")


def grouping_quality(gram: DataFrame, groups: DataFrame) -> DataFrame:
    """``win, ratio``: similarity between the groups of a window over that inside them, for windows of two groups or more.

    Pairs of topics that share no document have cosine 0; a group of one topic has 1 inside.
    """
    own = groups.select("win", "group_id", F.explode("topics").alias("topic_id"))
    sizes = own.groupBy("win", "group_id").agg(F.count(F.lit(1)).alias("size"))
    totals = sizes.groupBy("win").agg(F.sum("size").alias("n"), F.count(F.lit(1)).alias("k")).where("k > 1")
    of = lambda x: own.select("win", F.col("topic_id").alias(x), F.col("group_id").alias(f"group_{x}"))
    both = gram.where("t < u").join(of("t"), ["win", "t"]).join(of("u"), ["win", "u"])
    inside = both.where("group_t = group_u").groupBy("win", F.col("group_t").alias("group_id")).agg(F.sum("cosine").alias("near"))
    across = both.where("group_t <> group_u")
    across = across.select("win", F.col("group_t").alias("group_id"), "cosine").unionByName(across.select("win", F.col("group_u").alias("group_id"), "cosine"))
    across = across.groupBy("win", "group_id").agg(F.sum("cosine").alias("far"))
    rows = sizes.join(totals, "win").join(inside, ["win", "group_id"], "left").join(across, ["win", "group_id"], "left").fillna(0.0, ["near", "far"])
    size = F.col("size")
    intra = F.when(size > 1, F.col("near") / (size * (size - 1) / 2)).otherwise(1.0)
    between = F.sum(F.col("far") / (F.col("n") - size))  # size / (n - size) times the mean over the pairs, times the sizes
    return rows.groupBy("win").agg((between / F.sum(size * intra)).alias("ratio"))


def event_overlap(events: DataFrame, planted: DataFrame) -> DataFrame:
    """For each planted interval ``plan, start, end`` the best share of windows, of both united, that an event has in common with it."""
    both = planted.join(events.select("event_id", "start_win", "end_win"), (F.col("start") <= F.col("end_win")) & (F.col("start_win") <= F.col("end")))
    shared = F.least("end", "end_win") - F.greatest("start", "start_win") + 1
    united = F.greatest("end", "end_win") - F.least("start", "start_win") + 1
    best = both.groupBy("plan").agg(F.max(shared / united).alias("overlap"))
    return planted.select("plan").join(best, "plan", "left").fillna(0.0, ["overlap"])


def stage_costs(spark, notes: list[tuple[str, float, int]]) -> DataFrame:
    """``position, stage, seconds, shuffle_bytes`` of the stages of a metered run."""
    rows = [(i, tag, seconds, moved) for i, (tag, seconds, moved) in enumerate(notes)]
    return spark.createDataFrame(rows, "position int, stage string, seconds double, shuffle_bytes long")
