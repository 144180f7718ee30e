"""Streams of words and index series over the tables.

A stream is ``doc_id, win, feature`` with one row per occurrence, or ``doc_id, ts, win,
text`` before words are cut; an index is ``win, value``. Windows are whole numbers of
fixed steps from an origin. A last window that the data do not fill is dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import text as X
from .staging import staged

HOUR, DAY, WEEK = 3600, 86_400, 604_800
EVENT_ORIGIN, ORDER_ORIGIN = "2024-01-01", "1995-01-01"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def window_of(ts: Column, origin: str, seconds: int) -> Column:
    """The number of the window that holds a time, counted from an origin in UTC."""
    start = F.lit(origin).cast("timestamp")
    return F.floor((F.unix_seconds(ts.cast("timestamp")) - F.unix_seconds(start)) / seconds).cast("int")


def full_windows(last: Column, origin: str, seconds: int, step: int) -> Column:
    """Number of windows filled by data whose last time is ``last`` on a grid of ``step`` seconds."""
    return window_of(last + F.make_interval(secs=F.lit(step)), origin, seconds)


def ranked(rows: DataFrame, order: list[str], name: str = "rank") -> DataFrame:
    """The rows with their rank from 0 in the order, nulls first.

    Ranges of the order are sorted apart; a row's rank is its place in its range plus the sizes of the
    ranges before, of which there are as many as partitions.
    """
    spread = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    place = F.monotonically_increasing_id()
    held = staged(spread.withColumn("part_", F.shiftright(place, 33)).withColumn("place_", place.bitwiseAND((1 << 33) - 1)), "ranked")
    before = F.sum("n_").over(Window.orderBy("part_").rowsBetween(Window.unboundedPreceding, -1))  # one row per partition
    sizes = held.groupBy("part_").agg(F.count(F.lit(1)).alias("n_")).select("part_", F.coalesce(before, F.lit(0)).alias("before_"))
    return held.join(F.broadcast(sizes), "part_").withColumn(name, F.col("before_") + F.col("place_")).drop("part_", "place_", "before_")


def stamped(spark: SparkSession, sf_dir: str, docs: DataFrame, id_col: str) -> DataFrame:
    """Gives the document of rank r (by id, then text) the time of the event of rank floor(r * events / documents).

    Ranks, not ids, are matched, so gaps, nulls and large ids lose no document. Without events nothing has a time.
    """
    events = ranked(read(spark, sf_dir, "events").select("event_id", "ts"), ["event_id", "ts"], "at").drop("event_id")
    counts = events.agg(F.count(F.lit(1)).alias("n_events")).crossJoin(docs.agg(F.count(F.lit(1)).alias("n_docs")))  # two one-row counts
    sized = ranked(docs, [id_col, "text"], "rank").crossJoin(F.broadcast(counts))
    sized = sized.withColumn("at", F.expr("rank * n_events div n_docs")).drop("n_events", "n_docs", "rank")
    return sized.join(events, "at").drop("at")


def text_stream(spark: SparkSession, sf_dir: str, hours: int = 12) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return stamped(spark, sf_dir, docs, "doc_id").withColumn("win", window_of(F.col("ts"), EVENT_ORIGIN, hours * HOUR))


def page_stream(spark: SparkSession, sf_dir: str, hours: int = 12) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), X.strip_html(F.col("html")).alias("text"))
    return stamped(spark, sf_dir, pages, "doc_id").withColumn("win", window_of(F.col("ts"), EVENT_ORIGIN, hours * HOUR))


def chat_stream(spark: SparkSession, sf_dir: str, hours: int = 12) -> DataFrame:
    turns = read(spark, sf_dir, "conversations").select("conv_id", F.struct("turn", "text").alias("t"))
    said = turns.groupBy("conv_id").agg(F.array_join(F.sort_array(F.collect_list("t"))["text"], "\n").alias("text"))
    chats = said.select(F.col("conv_id").alias("doc_id"), "text")
    return stamped(spark, sf_dir, chats, "doc_id").withColumn("win", window_of(F.col("ts"), EVENT_ORIGIN, hours * HOUR))


def order_stream(spark: SparkSession, sf_dir: str, days: int = 7) -> DataFrame:
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate")
    windows = orders.agg(full_windows(F.max("o_orderdate"), ORDER_ORIGIN, days * DAY, DAY).alias("n_win"))
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    parts = read(spark, sf_dir, "part").select("p_partkey", "p_name", "p_type", "p_brand")
    words = part_words()
    joined = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    tokens = joined.select(F.col("o_orderkey").alias("doc_id"), window_of(F.col("o_orderdate"), ORDER_ORIGIN, days * DAY).alias("win"), F.explode(words).alias("feature"))
    return tokens.crossJoin(F.broadcast(windows)).where("win < n_win").drop("n_win")  # a one-row bound


def session_stream(spark: SparkSession, sf_dir: str, hours: int = 4) -> DataFrame:
    events = read(spark, sf_dir, "events").select("ts", "user_id", "event_type", "props")
    win = window_of(F.col("ts"), EVENT_ORIGIN, hours * HOUR)
    words = F.array("event_type", F.concat(F.lit("k"), F.get_json_object("props", "$.k")))
    own = F.col("user_id") * (1 << 32) + F.col("win")  # a document is a user's window, whatever the number of windows
    tokens = events.withColumn("win", win).select(own.alias("doc_id"), "win", F.explode(words).alias("feature"))
    return tokens.where("feature IS NOT NULL")


def poll_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``win, start, end``: an index observed about every ten days, one day longer or shorter by turns, while orders last."""
    orders = read(spark, sf_dir, "orders").select(F.unix_seconds(F.col("o_orderdate").cast("timestamp")).alias("at"))
    origin = F.unix_seconds(F.lit(ORDER_ORIGIN).cast("timestamp"))
    last = orders.agg((F.max("at") + DAY - origin).alias("span"))
    wins = last.select("span", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.floor(F.col("span") / (9 * DAY)), F.lit(0)))).alias("i"))
    edge = lambda i: DAY * (10 * i + i % 2)
    full = wins.where(edge(F.col("i") + 1) <= F.col("span"))
    return full.select(F.col("i").cast("int").alias("win"), F.timestamp_seconds(origin + edge(F.col("i"))).alias("start"), F.timestamp_seconds(origin + edge(F.col("i") + 1)).alias("end"))


def poll_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The order stream cut at the observations of the index."""
    lines, orders = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), read(spark, sf_dir, "orders")
    dated = assign_irregular(orders.select("o_orderkey", F.col("o_orderdate").alias("ts")), poll_bounds(spark, sf_dir)).where("win IS NOT NULL")
    parts = read(spark, sf_dir, "part").select("p_partkey", "p_name", "p_type", "p_brand")
    joined = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(dated, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.select(F.col("o_orderkey").alias("doc_id"), "win", F.explode(part_words()).alias("feature"))


def poll_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("ts"), F.col("o_totalprice").alias("value"))
    return resampled(assign_irregular(orders, poll_bounds(spark, sf_dir)).where("win IS NOT NULL"), "avg")


def part_words() -> Column:
    return F.concat(F.split(F.lower("p_name"), " "), F.array(F.concat(F.lower("p_type"), F.lit("_t")), F.lower("p_brand")))


def assign_irregular(rows: DataFrame, bounds: DataFrame, ts: str = "ts") -> DataFrame:
    """``rows`` plus ``win`` from ``bounds`` (win, start, end), half open and disjoint.

    Each window is listed under every day that it touches and the list travels to all rows, so a row is
    compared with the windows of its day only; times outside all windows, and no time, give null.
    """
    day = lambda at: F.floor(at / DAY)
    edges = bounds.select(F.unix_seconds("start").alias("start_"), F.unix_seconds("end").alias("end_"), "win").where("start_ < end_")
    listed = edges.withColumn("day_", F.explode(F.sequence(day(F.col("start_")), day(F.col("end_") - 1))))
    at = F.unix_seconds(rows[ts].cast("timestamp"))
    inside = (day(at) == listed["day_"]) & (listed["start_"] <= at) & (at < listed["end_"])
    return rows.join(F.broadcast(listed), inside, "left").drop("day_", "start_", "end_")


def event_index(spark: SparkSession, sf_dir: str, hours: int = 12, how: str = "avg") -> DataFrame:
    events = read(spark, sf_dir, "events").select("ts", "value").withColumn("win", window_of(F.col("ts"), EVENT_ORIGIN, hours * HOUR))
    return resampled(events, how)


def order_index(spark: SparkSession, sf_dir: str, days: int = 7, how: str = "avg") -> DataFrame:
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("ts"), F.col("o_totalprice").alias("value"))
    windows = orders.agg(full_windows(F.max("ts"), ORDER_ORIGIN, days * DAY, DAY).alias("n_win"))
    dated = orders.withColumn("win", window_of(F.col("ts"), ORDER_ORIGIN, days * DAY)).crossJoin(F.broadcast(windows))
    return resampled(dated.where("win < n_win"), how)


def ship_index(spark: SparkSession, sf_dir: str, days: int = 7) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").select(F.col("l_shipdate").alias("ts"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("value"))
    windows = lines.agg(full_windows(F.max("ts"), ORDER_ORIGIN, days * DAY, DAY).alias("n_win"))
    dated = lines.withColumn("win", window_of(F.col("ts"), ORDER_ORIGIN, days * DAY)).crossJoin(F.broadcast(windows))
    return resampled(dated.where("win >= 0 AND win < n_win"), "sum")


def daily_order_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``win, step, value``: daily means inside weekly windows."""
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("ts"), F.col("o_totalprice").alias("value"))
    windows = orders.agg(full_windows(F.max("ts"), ORDER_ORIGIN, WEEK, DAY).alias("n_win"))
    daily = orders.groupBy(window_of(F.col("ts"), ORDER_ORIGIN, DAY).alias("step")).agg(F.avg("value").alias("value"))
    daily = daily.withColumn("win", F.floor(F.col("step") / 7).cast("int")).crossJoin(F.broadcast(windows))
    return daily.where("win < n_win").select("win", "step", "value")


def resampled(rows: DataFrame, how: str) -> DataFrame:
    """``win, ts, value`` -> ``win, value`` by mean, sum or the last observation."""
    value = {"avg": F.avg("value"), "sum": F.sum("value"), "last": F.max_by("value", "ts"), "min": F.min("value"), "max": F.max("value")}[how]
    return rows.groupBy("win").agg(value.alias("value"))


def planted_stream(spark: SparkSession, sf_dir: str, groups: dict[int, list[str]], shuffled: bool = False) -> DataFrame:
    """The text stream with documents that hold a chosen word moved to a chosen window; a control deals them by hash."""
    docs = text_stream(spark, sf_dir)
    win = F.col("win")
    for target, words in groups.items():
        hit = F.lower("text").rlike(r"(^|[^\p{L}])(" + "|".join(words) + r")([^\p{L}]|$)")
        win = F.when(hit, F.lit(target)).otherwise(win)
    if shuffled:
        win = F.pmod(F.xxhash64("doc_id"), F.lit(60)).cast("int")
    return docs.withColumn("win", win)
