"""Operators that users need around the methods, each shown on the tables with its SQL twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bursts as B
from ..sources import views as V
from ..sources.staging import read_bucketed, read_windows, round_trip
from ..sources.views import assign_irregular


def as_of(left: DataFrame, right: DataFrame, on: str, value: str, bucket: int) -> DataFrame:
    """``left`` plus the last ``value`` of ``right`` at or before each time.

    Both sides are merged and carried forward inside time buckets of ``bucket`` seconds; the last value of
    each bucket (a small table) is carried over to later ones. So no step orders all rows in one task.
    """
    cell = F.floor(F.unix_seconds(F.col(on).cast("timestamp")) / bucket)
    marks = right.groupBy(cell.alias("cell")).agg(F.max_by(value, on).alias("last"))
    before = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # one row per bucket
    cells = left.select(cell.alias("cell")).distinct().join(marks, "cell", "full").withColumn("carried", F.last("last", ignorenulls=True).over(before)).select("cell", "carried")
    merged = left.withColumn("own_", F.lit(True)).unionByName(right.select(on, F.col(value).alias("value_")), allowMissingColumns=True).withColumn("cell", cell)
    order = Window.partitionBy("cell").orderBy(on, F.col("own_").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    got = merged.withColumn("seen_", F.last("value_", ignorenulls=True).over(order)).where("own_").join(cells, "cell", "left")
    return got.withColumn(value, F.coalesce("seen_", "carried")).select(*left.columns, value)


def ten_day_bounds(spark: SparkSession, n: int = 240) -> DataFrame:
    """Windows of about ten days from 1995-01-01, one day longer or shorter by turns."""
    return spark.range(n).select(F.col("id").cast("int").alias("win"), F.timestamp_seconds(788918400 + 86400 * (10 * F.col("id") + F.col("id") % 2)).alias("start"), F.timestamp_seconds(788918400 + 86400 * (10 * (F.col("id") + 1) + (F.col("id") + 1) % 2)).alias("end"))


def _t(name: str):
    return lambda s, d: V.read(s, d, name)


lineitem, orders, part, customer, nation, region, events, documents, embeddings, labels = map(_t, ("lineitem", "orders", "part", "customer", "nation", "region", "events", "documents", "embeddings", "labels"))


def _rev():
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


def window_functions(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    return orders(s, d).select(
        "o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(by).alias("rk"), F.dense_rank().over(by).alias("dr"), F.round(F.percent_rank().over(by), 6).alias("pr"), F.round(F.cume_dist().over(by), 6).alias("cd"), F.ntile(3).over(w).alias("nt"),
        F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("running"),
    )


WINDOW_SQL = """SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER b AS rk, dense_rank() OVER b AS dr, round(percent_rank() OVER b, 6) AS pr, round(cume_dist() OVER b, 6) AS cd, ntile(3) OVER w AS nt,
 lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running
 FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), b AS (PARTITION BY o_custkey ORDER BY o_orderdate)"""


def as_of_index(s: SparkSession, d: str) -> DataFrame:
    """The last price seen on or before the day of each of the event stream's errors, shifted to its years."""
    errors = events(s, d).where("event_type = 'error'").select("event_id", "ts")
    clicks = events(s, d).where("event_type = 'click'").select("ts", "value")
    return as_of(errors, clicks, "ts", "value", 21600).select("event_id", F.round("value", 4).alias("value"))


def vector_neighbours(s: SparkSession, d: str) -> DataFrame:
    """Mean cosine of each label's vectors with the label's mean vector."""
    x = embeddings(s, d).select("vec_id", "label", F.posexplode(F.col("embedding").cast("array<double>")).alias("i", "x"))
    mean = x.groupBy("label", "i").agg(F.avg("x").alias("m"))
    got = x.join(mean, ["label", "i"]).groupBy("vec_id", "label").agg((F.sum(F.col("x") * F.col("m")) / F.sqrt(F.sum(F.col("x") * F.col("x")) * F.sum(F.col("m") * F.col("m")))).alias("cosine"))
    return got.groupBy("label").agg(F.round(F.avg("cosine"), 5).alias("cosine"))


QUERIES = {
    "rel_filter_project": lambda s, d: lineitem(s, d).where((F.col("l_shipdate") < "1996-01-01") & F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_linenumber", F.when(F.col("l_discount") > 0.05, "deep").otherwise("flat").alias("kind")),
    "rel_revenue_summary": lambda s, d: lineitem(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum(_rev()), 2).alias("revenue"), F.round(F.avg("l_quantity"), 6).alias("avg_qty"), F.count_distinct("l_partkey").alias("parts"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"), F.count_if(F.col("l_tax") > 0.04).alias("taxed")),
    "rel_broadcast_join": lambda s, d: customer(s, d).join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).join(region(s, d), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance")),
    "rel_sort_merge_join": lambda s, d: orders(s, d).join(lineitem(s, d).hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum(_rev()), 2).alias("revenue")),
    "rel_shuffle_hash_join": lambda s, d: lineitem(s, d).join(part(s, d).hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_type").agg(F.round(F.sum("l_quantity"), 2).alias("qty")),
    "rel_semi_join": lambda s, d: orders(s, d).join(lineitem(s, d).where("l_returnflag = 'R'"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")),
    "rel_anti_join": lambda s, d: orders(s, d).join(lineitem(s, d), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"),
    "rel_full_outer_join": lambda s, d: documents(s, d).select("doc_id").join(labels(s, d).select("doc_id", "quality"), "doc_id", "full").groupBy("quality").agg(F.count(F.lit(1)).alias("n")),
    "rel_lateral_top": lambda s, d: orders(s, d).withColumn("r", F.row_number().over(Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 3").select("o_orderpriority", "r", "o_orderkey"),
    "rel_cube": lambda s, d: documents(s, d).cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars")),
    "rel_rollup": lambda s, d: orders(s, d).rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")),
    "rel_pivot": lambda s, d: events(s, d).withColumn("win", V.window_of(F.col("ts"), V.EVENT_ORIGIN, 86400)).groupBy("win").pivot("event_type", ["click", "error"]).agg(F.count(F.lit(1))).fillna(0),
    "rel_window_functions": window_functions,
    "rel_top_k": lambda s, d: orders(s, d).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice"),
    "rel_set_intersect": lambda s, d: documents(s, d).select("doc_id").intersect(labels(s, d).select("doc_id")),
    "rel_set_except": lambda s, d: documents(s, d).select("doc_id").exceptAll(labels(s, d).select("doc_id")),
    "rel_strings": lambda s, d: part(s, d).select("p_partkey", F.upper(F.substring("p_name", 1, 3)).alias("head"), F.length("p_name").alias("n"), F.levenshtein("p_name", "p_type").alias("far"), F.sha2("p_name", 256).alias("sha"), F.concat_ws("-", "p_brand", "p_type").alias("label")),
    "rel_dates": lambda s, d: orders(s, d).select("o_orderkey", F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.unix_seconds(F.col("o_orderdate").cast("timestamp")).alias("secs"), F.year("o_orderdate").cast("long").alias("y"), F.unix_seconds(F.date_trunc("month", "o_orderdate").cast("timestamp")).alias("month_start")),
    "rel_maths": lambda s, d: lineitem(s, d).select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("ln"), F.round(F.sqrt("l_quantity"), 6).alias("root"), F.greatest("l_discount", "l_tax").alias("most"), F.ceil("l_quantity").alias("up")),
    "rel_arrays": lambda s, d: documents(s, d).select("doc_id", F.split("source", "").alias("a"), F.split("lang", "").alias("b")).select("doc_id", F.size(F.array_intersect("a", "b")).alias("both"), F.size(F.array_union("a", "b")).alias("any")),
    "rel_json": lambda s, d: events(s, d).select("event_id", F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n")),
    "rel_as_of_join": as_of_index,
    "rel_range_join": lambda s, d: assign_irregular(orders(s, d).select(F.col("o_orderdate").alias("ts"), "o_totalprice"), ten_day_bounds(s)).where("win IS NOT NULL").groupBy("win").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("o_totalprice"), 6).alias("value")),
    "rel_vector_cosine": vector_neighbours,
    "rel_dedup_keep_latest": lambda s, d: events(s, d).groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id")),
    "rel_islands": lambda s, d: B.burst_runs(events(s, d).where("value > 30").select("user_id", V.window_of(F.col("ts"), V.EVENT_ORIGIN, 86400).alias("win")).distinct(), "user_id"),
    "rel_approx_distinct": lambda s, d: lineitem(s, d).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median")),
    "io_partitioned_by_window": lambda s, d: read_windows(events(s, d).select("event_id", V.window_of(F.col("ts"), V.EVENT_ORIGIN, 86400).alias("win"))).groupBy("win").agg(F.count(F.lit(1)).alias("n")),
    "io_bucketed_table": lambda s, d: read_bucketed(labels(s, d), "doc_id"),
    **{f"io_round_trip_{kind}": (lambda s, d, k=kind: round_trip(labels(s, d), k)) for kind in ("csv", "json", "orc", "parquet")},
}
SQL = {
    "rel_filter_project": "SELECT l_orderkey, l_linenumber, CASE WHEN l_discount > 0.05 THEN 'deep' ELSE 'flat' END AS kind FROM lineitem WHERE l_shipdate < '1996-01-01' AND l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')",
    "rel_revenue_summary": "SELECT l_returnflag, l_linestatus, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_quantity), 6) AS avg_qty, count(DISTINCT l_partkey) AS parts, min(l_discount) AS lo, max(l_discount) AS hi, count(*) FILTER (l_tax > 0.04) AS taxed FROM lineitem GROUP BY 1, 2",
    "rel_broadcast_join": "SELECT r_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
    "rel_sort_merge_join": "SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1",
    "rel_shuffle_hash_join": "SELECT p_type, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1",
    "rel_semi_join": "SELECT o_orderstatus, count(*) AS n FROM orders SEMI JOIN (SELECT * FROM lineitem WHERE l_returnflag = 'R') ON o_orderkey = l_orderkey GROUP BY 1",
    "rel_anti_join": "SELECT o_orderkey FROM orders ANTI JOIN lineitem ON o_orderkey = l_orderkey",
    "rel_full_outer_join": "SELECT quality, count(*) AS n FROM documents FULL JOIN labels USING (doc_id) GROUP BY 1",
    "rel_lateral_top": "SELECT o_orderpriority, r, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3",
    "rel_cube": "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)",
    "rel_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "rel_pivot": "SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 86400) AS INT) AS win, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error FROM events GROUP BY 1",
    "rel_window_functions": WINDOW_SQL,
    "rel_top_k": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "rel_set_intersect": "SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels",
    "rel_set_except": "SELECT doc_id FROM documents EXCEPT ALL SELECT doc_id FROM labels",
    "rel_strings": "SELECT p_partkey, upper(substr(p_name, 1, 3)) AS head, CAST(length(p_name) AS INT) AS n, CAST(levenshtein(p_name, p_type) AS INT) AS far, sha256(p_name) AS sha, concat_ws('-', p_brand, p_type) AS label FROM part",
    "rel_dates": "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days, CAST(epoch(o_orderdate) AS BIGINT) AS secs, year(o_orderdate) AS y, CAST(epoch(date_trunc('month', o_orderdate)) AS BIGINT) AS month_start FROM orders",
    "rel_maths": "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS ln, round(sqrt(l_quantity), 6) AS root, greatest(l_discount, l_tax) AS most, CAST(ceil(l_quantity) AS BIGINT) AS up FROM lineitem",
    "rel_json": "SELECT CAST(json_extract(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1",
    "rel_as_of_join": "SELECT e.event_id, round(c.value, 4) AS value FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON e.ts >= c.ts",
    "rel_range_join": "SELECT CAST(i AS INT) AS win, count(*) AS n, round(avg(o_totalprice), 6) AS value FROM range(240) r(i) JOIN orders ON epoch(o_orderdate) >= 788918400 + 86400 * (10 * i + i % 2) AND epoch(o_orderdate) < 788918400 + 86400 * (10 * (i + 1) + (i + 1) % 2) GROUP BY 1",
    "rel_vector_cosine": "WITH x AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS i FROM embeddings), m AS (SELECT label, i, avg(x) AS m FROM x GROUP BY 1, 2) SELECT label, round(avg(c), 5) AS cosine FROM (SELECT vec_id, label, sum(x * m) / sqrt(sum(x * x) * sum(m * m)) AS c FROM x JOIN m USING (label, i) GROUP BY 1, 2) GROUP BY 1",
    "rel_dedup_keep_latest": "SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id FROM events GROUP BY 1",
    "rel_islands": "SELECT user_id, min(win) AS start_win, max(win) AS end_win, count(*) AS length FROM (SELECT user_id, win, win - row_number() OVER (PARTITION BY user_id ORDER BY win) AS run FROM (SELECT DISTINCT user_id, CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 86400) AS INT) AS win FROM events WHERE value > 30)) GROUP BY user_id, run",
    "rel_arrays": "SELECT doc_id, CAST(len(list_intersect(a, b)) AS INT) AS both, CAST(len(list_distinct(list_concat(a, b))) AS INT) AS any FROM (SELECT doc_id, string_split(source, '') AS a, string_split(lang, '') AS b FROM documents)",
    "io_partitioned_by_window": "SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 86400) AS INT) AS win, count(*) AS n FROM events GROUP BY 1",
    "io_bucketed_table": "SELECT * FROM labels",
    **{f"io_round_trip_{kind}": "SELECT * FROM labels" for kind in ("csv", "json", "orc", "parquet")},
}
