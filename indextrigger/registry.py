"""Queries by name and their SQL twins.

A twin is one statement that DuckDB runs on the same tables. Each is put together
from named parts (common table expressions); values are rounded to six places on both sides.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import bursts as B
from .functions import text as X
from .functions import volatility as VOL
from .operators import relational
from .params import FAITHFUL, FLAGSHIP, Params
from .plans import affinity as A
from .plans import baselines as BL
from .plans import chains as C
from .plans import events as E
from .plans import groups as G
from .plans import measures as M
from .plans import pipeline as P
from .plans import topics as T
from .sources import views as V
from .sources.staging import at_once, metered, shared_folder, staged
from .streaming import online, surface

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def rounded(df: DataFrame, places: int = 6) -> DataFrame:
    """Doubles rounded, without negative zeros."""
    return df.select(*[(F.round(F.col(c), places) + F.lit(0.0)).alias(c) if kind == "double" else F.col(c) for c, kind in df.dtypes])


# --- streams ---------------------------------------------------------------------------------------------------------

STREAMS: dict[str, Query] = {
    "text": lambda s, d: X.tokenize(V.text_stream(s, d)),
    "page": lambda s, d: X.tokenize(V.page_stream(s, d)),
    "chat": lambda s, d: X.tokenize(V.chat_stream(s, d)),
    "order": lambda s, d: V.order_stream(s, d),
    "session": lambda s, d: V.session_stream(s, d),
    "poll": lambda s, d: V.poll_stream(s, d),
}
INDEXES: dict[str, Query] = {
    "event_12h": lambda s, d: V.event_index(s, d),
    "event_4h": lambda s, d: V.event_index(s, d, 4),
    "order_week": lambda s, d: V.order_index(s, d),
    "ship_week": lambda s, d: V.ship_index(s, d),
    "order_polls": lambda s, d: V.poll_index(s, d),
}


def _scrub_sql(text: str) -> str:
    for pattern in (X.URL, X.EMAIL, X.DIGITS):
        text = f"regexp_replace({text}, '{pattern}', ' ', 'g')"
    return text


def _words_sql(text: str) -> str:
    return f"list_filter(regexp_extract_all(lower({_scrub_sql(text)}), '\\p{{L}}+'), lambda w: length(w) >= 3)"


def _stamp_sql(source: str, id_: str, text: str) -> str:
    return f"""SELECT x.{id_} AS doc_id, CAST(floor((epoch(e.ts) - epoch(TIMESTAMP '2024-01-01')) / 43200) AS INT) AS win, unnest({_words_sql(text)}) AS feature
  FROM (SELECT *, row_number() OVER (ORDER BY {id_} NULLS FIRST) - 1 AS r FROM {source}) x JOIN (SELECT ts, row_number() OVER (ORDER BY event_id NULLS FIRST, ts) - 1 AS r FROM events) e
  ON e.r = x.r * (SELECT count(*) FROM events) // (SELECT count(*) FROM {source})"""


def _html_sql(html: str) -> str:
    for pattern in (r"(?is)<script\b.*?</script\s*>", r"(?is)<style\b.*?</style\s*>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        html = f"regexp_replace({html}, '{pattern}', ' ', 'g')"
    for entity, value in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        html = f"replace({html}, '{entity}', '{value}')"
    return f"trim(regexp_replace({html}, '\\s+', ' ', 'g'))"


_DAYS = "CAST(floor((epoch({0}) - epoch(TIMESTAMP '1995-01-01')) / 604800) AS INT)"
_FULL = "(SELECT CAST(floor((epoch(max({0})) + 86400 - epoch(TIMESTAMP '1995-01-01')) / 604800) AS INT) FROM {1})"
TOKENS_SQL = {
    "text": _stamp_sql("documents", "doc_id", "x.text"),
    "page": _stamp_sql("pages", "page_id", _html_sql("x.html")),
    "chat": _stamp_sql("(SELECT conv_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM conversations GROUP BY conv_id)", "conv_id", "x.text"),
    "order": f"""SELECT * FROM (SELECT o_orderkey AS doc_id, {_DAYS.format('o_orderdate')} AS win,
    unnest(list_concat(string_split(lower(p_name), ' '), [lower(p_type) || '_t', lower(p_brand)])) AS feature
    FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey) WHERE win < {_FULL.format('o_orderdate', 'orders')}""",
    "session": """SELECT * FROM (SELECT user_id * 4294967296 + win AS doc_id, win, unnest([event_type, 'k' || json_extract_string(props, '$.k')]) AS feature FROM
    (SELECT *, CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 14400) AS INT) AS win FROM events)) WHERE feature IS NOT NULL""",
}
INDEX_SQL = {
    "event_12h": "SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 43200) AS INT) AS win, avg(value) AS value FROM events GROUP BY 1",
    "event_4h": "SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 14400) AS INT) AS win, avg(value) AS value FROM events GROUP BY 1",
    "order_week": f"SELECT * FROM (SELECT {_DAYS.format('o_orderdate')} AS win, avg(o_totalprice) AS value FROM orders GROUP BY 1) WHERE win < {_FULL.format('o_orderdate', 'orders')}",
    "ship_week": f"SELECT * FROM (SELECT {_DAYS.format('l_shipdate')} AS win, sum(l_extendedprice * (1 - l_discount)) AS value FROM lineitem GROUP BY 1) WHERE win >= 0 AND win < {_FULL.format('l_shipdate', 'lineitem')}",
}


#: Windows between observations about ten days apart, while orders last.
_POLLS = """SELECT CAST(i AS INT) AS win, 788918400 + 86400 * (10 * i + i % 2) AS a, 788918400 + 86400 * (10 * (i + 1) + (i + 1) % 2) AS b
  FROM range(10000) r(i) WHERE 788918400 + 86400 * (10 * (i + 1) + (i + 1) % 2) <= (SELECT epoch(max(o_orderdate)) + 86400 FROM orders)"""
TOKENS_SQL["poll"] = f"""SELECT o_orderkey AS doc_id, win, unnest(list_concat(string_split(lower(p_name), ' '), [lower(p_type) || '_t', lower(p_brand)])) AS feature
  FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN ({_POLLS}) w ON epoch(o_orderdate) >= a AND epoch(o_orderdate) < b"""
INDEX_SQL["order_polls"] = f"SELECT win, avg(o_totalprice) AS value FROM orders JOIN ({_POLLS}) w ON epoch(o_orderdate) >= a AND epoch(o_orderdate) < b GROUP BY win"


def with_parts(*parts: tuple[str, str], last: str) -> str:
    return "WITH " + ",\n".join(f"{name} AS ({body})" for name, body in parts) + "\n" + last


def tokens_part(stream: str) -> tuple[str, str]:
    return "tokens", TOKENS_SQL[stream]


for _name, _stream in STREAMS.items():
    query(f"{_name}_stream_windows", with_parts(tokens_part(_name), last="SELECT win, count(DISTINCT doc_id) AS docs, count(*) AS tokens, count(DISTINCT feature) AS features FROM tokens GROUP BY win"))(
        lambda s, d, f=_stream: f(s, d).groupBy("win").agg(F.count_distinct("doc_id").alias("docs"), F.count(F.lit(1)).alias("tokens"), F.count_distinct("feature").alias("features"))
    )
for _name in ("text", "order", "session"):
    query(f"{_name}_token_counts", with_parts(tokens_part(_name), last="SELECT feature, win, count(*) AS n, CAST(sum(count(*)) OVER (PARTITION BY win) AS BIGINT) AS total FROM tokens GROUP BY feature, win"))(
        lambda s, d, f=STREAMS[_name]: (lambda c: c.join(B.window_totals(c), "win").select("feature", "win", "n", "total"))(B.window_counts(f(s, d)))
    )

query("scrubbed_tokens", with_parts(tokens_part("text"), last="SELECT doc_id, count(*) AS tokens, CAST(sum(length(feature)) AS BIGINT) AS letters FROM tokens GROUP BY doc_id"))(
    lambda s, d: STREAMS["text"](s, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("tokens"), F.sum(F.length("feature")).alias("letters"))
)
_SHARE_SQL = {
    "corpus": "SELECT feature FROM tokens GROUP BY feature HAVING count(DISTINCT doc_id) * 1.0 / (SELECT count(DISTINCT doc_id) FROM tokens) BETWEEN 0.05 AND 0.8",
    "day": "SELECT feature, win FROM tokens t GROUP BY feature, win HAVING count(DISTINCT doc_id) * 1.0 / (SELECT count(DISTINCT doc_id) FROM tokens u WHERE u.win = t.win) BETWEEN 0.05 AND 0.8",
    "any_day": "SELECT DISTINCT feature FROM (SELECT feature, win FROM tokens t GROUP BY feature, win HAVING count(DISTINCT doc_id) * 1.0 / (SELECT count(DISTINCT doc_id) FROM tokens u WHERE u.win = t.win) BETWEEN 0.05 AND 0.8)",
    "mean_day": "SELECT feature FROM (SELECT feature, win, count(DISTINCT doc_id) * 1.0 / (SELECT count(DISTINCT doc_id) FROM tokens u WHERE u.win = t.win) AS share FROM tokens t GROUP BY feature, win) GROUP BY feature HAVING round(sum(share) / (SELECT count(DISTINCT win) FROM tokens), 9) BETWEEN 0.05 AND 0.8",
}
for _scope, _sql in _SHARE_SQL.items():
    query(f"share_filtered_features_{_scope}", with_parts(tokens_part("text"), last=_sql))(lambda s, d, scope=_scope: X.kept_features(STREAMS["text"](s, d), scope=scope))

#: A short list of function words of four languages, for the list variant of stop words.
STOP_WORDS = ["the", "and", "for", "with", "that", "der", "die", "und", "das", "les", "des", "une", "que", "los", "las", "por"]
query("stop_word_list", with_parts(tokens_part("text"), last=f"SELECT feature, count(*) AS n FROM tokens WHERE feature NOT IN ({', '.join(repr(w) for w in STOP_WORDS)}) GROUP BY feature"))(
    lambda s, d: X.drop_listed_stopwords(STREAMS["text"](s, d), s.createDataFrame([(w,) for w in STOP_WORDS], "feature string")).groupBy("feature").agg(F.count(F.lit(1)).alias("n"))
)
query("stemmed_vocabulary")(lambda s, d: STREAMS["text"](s, d).select("feature").distinct().withColumn("stem", X.stem(F.col("feature"))))
query("keyword_search", "SELECT doc_id FROM documents WHERE contains(lower(text), 'licensed under') OR contains(lower(text), 'worthless')")(
    lambda s, d: BL.search_documents(V.text_stream(s, d), ["licensed under", "worthless"]).select("doc_id")
)

# --- bursts ----------------------------------------------------------------------------------------------------------

_COUNTS = ("counts", "SELECT feature, win, count(*) AS n FROM tokens GROUP BY feature, win")
_TOTALS = ("totals", "SELECT win, sum(n) AS total FROM counts GROUP BY win")
_POOLED = ("rates", "SELECT feature, sum(n) * 1.0 / (SELECT sum(total) FROM totals) AS pe FROM counts GROUP BY feature")
_MEAN = ("rates", "SELECT feature, sum(n * 1.0 / total) / (SELECT count(*) FROM totals) AS pe FROM counts JOIN totals USING (win) GROUP BY feature")
_TERM = "exp(lgamma(total + 1) - lgamma(k + 1) - lgamma(total - k + 1) + k * ln(pe) + (total - k) * ln(1 - pe))"
_SUM = "coalesce(list_sum(list_transform(range(0, {0}), lambda k: " + _TERM + ")), 0)"
_TAIL_SQL = {"strict": _SUM.format("n"), "inclusive": _SUM.format("n + 1"), "pmf": _TERM.replace("k", "n").replace("n *", "n *")}
_TAIL_SQL["pmf"] = "exp(lgamma(total + 1) - lgamma(n + 1) - lgamma(total - n + 1) + n * ln(pe) + (total - n) * ln(1 - pe))"


def bursts_parts(stream: str, tail: str = "strict", rates: tuple[str, str] = _POOLED, threshold: float = 0.95) -> list[tuple[str, str]]:
    return [tokens_part(stream), _COUNTS, _TOTALS, rates, ("cells", "SELECT feature, win, n, CAST(total AS BIGINT) AS total, pe FROM counts JOIN totals USING (win) JOIN rates USING (feature)"), ("p", f"SELECT *, least(greatest({_TAIL_SQL[tail]}, 0), 1) AS p FROM cells"), ("bursty", f"SELECT feature, win, p FROM p WHERE p > {threshold}")]


def burst_table(s: SparkSession, d: str, stream: str, tail: str = "strict", how: str = "pooled") -> DataFrame:
    counts = staged(B.window_counts(STREAMS[stream](s, d)), "counts")
    totals = B.window_totals(counts)
    rates = B.quiet_rates(counts, totals, 1) if how == "quiet" else B.expected_rate(counts, totals, how)
    return B.burst_probability(counts, totals, rates, tail)


_QUIET = ("quiet", "SELECT feature, sum(n) AS bn, sum(total) AS bw FROM bursty JOIN counts USING (feature, win) JOIN totals USING (win) GROUP BY feature")
for _how, _parts, _last in (
    ("pooled", [tokens_part("order"), _COUNTS, _TOTALS, _POOLED], "SELECT feature, round(pe, 6) AS pe FROM rates"),
    ("mean", [tokens_part("order"), _COUNTS, _TOTALS, _MEAN], "SELECT feature, round(pe, 6) AS pe FROM rates"),
    ("quiet", [*bursts_parts("order"), _QUIET], "SELECT c.feature, round((sum(n) - coalesce(any_value(bn), 0)) * 1.0 / ((SELECT sum(total) FROM totals) - coalesce(any_value(bw), 0)), 6) AS pe FROM counts c LEFT JOIN quiet q USING (feature) GROUP BY c.feature"),
):
    def _rates(s: SparkSession, d: str, how: str = _how) -> DataFrame:
        counts = staged(B.window_counts(STREAMS["order"](s, d)), "counts")
        totals = B.window_totals(counts)
        return rounded(B.quiet_rates(counts, totals, 1) if how == "quiet" else B.expected_rate(counts, totals, {"mean": "mean_rate"}.get(how, how)))

    query(f"expected_rate_{_how}", with_parts(*_parts, last=_last))(_rates)
for _tail in ("strict", "inclusive", "pmf"):
    query(f"burst_probability_{_tail}", with_parts(*bursts_parts("order", _tail), last="SELECT feature, win, n, total, round(p, 6) AS p FROM p"))(lambda s, d, t=_tail: rounded(burst_table(s, d, "order", t).select("feature", "win", "n", "total", "p")))
_Z = "((n - 0.5 - total * pe) / sqrt(total * pe * (1 - pe)))"
_T = f"(1 / (1 + 0.2316419 * abs({_Z})))"
_UPPER = f"(exp(-{_Z} * {_Z} / 2) / sqrt(2 * pi()) * {_T} * (0.319381530 + {_T} * (-0.356563782 + {_T} * (1.781477937 + {_T} * (-1.821255978 + {_T} * 1.330274429)))))"
_APPROX_SQL = {
    "normal": f"CASE WHEN {_Z} >= 0 THEN 1 - {_UPPER} ELSE {_UPPER} END",
    "poisson": "coalesce(list_sum(list_transform(range(0, n), lambda k: exp(k * ln(total * pe) - total * pe - lgamma(k + 1)))), 0)",
}
for _approx, _p in _APPROX_SQL.items():
    query(f"burst_probability_{_approx}", with_parts(*bursts_parts("order")[:-2], last=f"SELECT feature, win, n, total, round(least(greatest({_p}, 0), 1), 6) AS p FROM cells"))(
        lambda s, d, a=_approx: (lambda c: rounded(B.burst_probability(c, B.window_totals(c), B.expected_rate(c, B.window_totals(c)), approx=a).select("feature", "win", "n", "total", "p")))(staged(B.window_counts(STREAMS["order"](s, d)), "counts"))
    )
# The words of a window before the share filter, as a second denominator.
_ALL_WORDS = ("totals", "SELECT win, count(*) AS total FROM tokens GROUP BY win")
_KEPT_COUNTS = ("counts", f"SELECT feature, win, count(*) AS n FROM tokens SEMI JOIN ({_SHARE_SQL['corpus']}) USING (feature) GROUP BY feature, win")
query("burst_probability_all_words", with_parts(tokens_part("text"), _KEPT_COUNTS, _ALL_WORDS, _POOLED, *bursts_parts("text")[4:-1], last="SELECT feature, win, n, total, round(p, 6) AS p FROM p"))(
    lambda s, d: (lambda all_: (lambda c, t: rounded(B.burst_probability(c, t, B.expected_rate(c, t)).select("feature", "win", "n", "total", "p")))(staged(B.window_counts(X.share_filter(all_)), "counts"), staged(all_.groupBy("win").agg(F.count(F.lit(1)).alias("total")), "totals")))(STREAMS["text"](s, d))
)
_RUNS_SQL = "SELECT {0}, min(win) AS start_win, max(win) AS end_win, count(*) AS length FROM (SELECT {0}, win, win - row_number() OVER (PARTITION BY {0} ORDER BY win) AS run FROM bursty) GROUP BY {0}, run"
for _stream in ("text", "order", "session"):
    query(f"burst_windows_{_stream}", with_parts(*bursts_parts(_stream), last="SELECT feature, win FROM bursty"))(lambda s, d, f=_stream: B.burst_windows(burst_table(s, d, f)))
    query(f"burst_runs_{_stream}", with_parts(*bursts_parts(_stream), last=_RUNS_SQL.format("feature")))(lambda s, d, f=_stream: B.burst_runs(B.burst_windows(burst_table(s, d, f))))
query("burst_series_order", with_parts(*bursts_parts("order"), last="SELECT feature, string_agg(CAST(CAST(round(coalesce(p.p, 0) * 1000) AS INT) AS VARCHAR), ',' ORDER BY win) AS series FROM (SELECT feature, win FROM rates, totals) LEFT JOIN p USING (feature, win) GROUP BY feature"))(
    lambda s, d: (lambda p: B.burst_series(p, p.select("win").distinct()).select("feature", F.array_join(F.transform("series", lambda x: F.round(x * 1000).cast("int").cast("string")), ",").alias("series")))(staged(burst_table(s, d, "order"), "bursts"))
)

# --- index -----------------------------------------------------------------------------------------------------------

_RET = ("ret", "SELECT win, value, CASE WHEN value > 0 AND lag(value) OVER (ORDER BY win) > 0 THEN ln(value / lag(value) OVER (ORDER BY win)) END AS ret FROM idx")


def _vol_part(mode: str) -> tuple[str, str]:
    span = {"trailing": "3 PRECEDING AND CURRENT ROW", "centered": "2 PRECEDING AND 1 FOLLOWING"}[mode]
    return "vol", f"SELECT *, CASE WHEN count(ret) OVER w = 4 THEN stddev_pop(ret) OVER w END AS vi FROM ret WINDOW w AS (ORDER BY win ROWS BETWEEN {span})"


_FIT = ("fit", "SELECT avg(vi) AS mu, stddev_pop(vi) * sqrt(3) / pi() AS s FROM vol")
_PVI = ("pvi", "SELECT win, vi, CASE WHEN vi IS NULL THEN 0 ELSE ceil(10 / (1 + exp(-(vi - mu) / s))) / 10 END AS pvi FROM vol, fit")
_PVIC = ("pvi", "SELECT win, vi, CASE WHEN vi IS NULL THEN 0 ELSE 1 / (1 + exp(-(vi - mu) / s)) END AS pvi FROM vol, fit")


def index_parts(name: str, level: tuple[str, str] = _PVIC) -> list[tuple[str, str]]:
    return [("idx", INDEX_SQL[name]), _RET, _vol_part("trailing"), _FIT, level]


for _name, _index in INDEXES.items():
    query(f"index_{_name}", with_parts(("idx", INDEX_SQL[_name]), last="SELECT win, round(value, 6) AS value FROM idx"))(lambda s, d, f=_index: rounded(f(s, d)))
    query(f"log_returns_{_name}", with_parts(("idx", INDEX_SQL[_name]), _RET, last="SELECT win, round(ret, 6) AS ret FROM ret"))(lambda s, d, f=_index: rounded(VOL.log_returns(f(s, d)).select("win", "ret")))
    query(f"volatility_level_{_name}", with_parts(*index_parts(_name), last="SELECT win, round(vi, 6) AS vi, round(pvi, 6) AS pvi FROM pvi"))(lambda s, d, f=_index: rounded(VOL.index_levels(f(s, d), levels=None).select("win", "vi", "pvi")))
for _mode in ("trailing", "centered"):
    query(f"volatility_{_mode}", with_parts(("idx", INDEX_SQL["order_week"]), _RET, _vol_part(_mode), last="SELECT win, round(vi, 6) AS vi FROM vol"))(lambda s, d, m=_mode: rounded(VOL.volatility(VOL.log_returns(V.order_index(s, d)), 4, m).select("win", "vi")))
query(
    "volatility_within",
    f"""WITH daily AS (SELECT CAST(floor((epoch(o_orderdate) - epoch(TIMESTAMP '1995-01-01')) / 86400) AS INT) AS step, avg(o_totalprice) AS value FROM orders GROUP BY 1),
w AS (SELECT step // 7 AS win, step, value FROM daily WHERE step // 7 < {_FULL.format('o_orderdate', 'orders')}),
r AS (SELECT win, ln(value / lag(value) OVER (PARTITION BY win ORDER BY step)) AS ret FROM w)
SELECT win, round(CASE WHEN count(ret) >= 2 THEN stddev_pop(ret) END, 6) AS vi FROM r GROUP BY win""",
)(lambda s, d: rounded(VOL.volatility_within(V.daily_order_index(s, d))))
query("volatility_levels_ten", with_parts(*index_parts("order_week", _PVI), last="SELECT win, round(pvi, 6) AS pvi FROM pvi"))(lambda s, d: rounded(VOL.index_levels(V.order_index(s, d), levels=10).select("win", "pvi")))
query("volatility_level_rank", with_parts(("idx", INDEX_SQL["order_week"]), _RET, _vol_part("trailing"), last="SELECT win, round(CASE WHEN vi IS NULL THEN 0 ELSE percent_rank() OVER (PARTITION BY vi IS NULL ORDER BY vi) END, 6) AS pvi FROM vol"))(
    lambda s, d: rounded(VOL.volatility_level(VOL.volatility(VOL.log_returns(V.order_index(s, d))), "rank", None).select("win", "pvi"))
)
query("logistic_fit", with_parts(*index_parts("order_week"), last="SELECT round(mu, 6) AS mu, round(s, 6) AS s FROM fit"))(
    lambda s, d: s.createDataFrame([tuple(round(x, 6) for x in VOL.fit_logistic(VOL.volatility(VOL.log_returns(V.order_index(s, d)))))], "mu double, s double")
)
# Newton steps on the location and the logarithm of the scale, with the exact second derivatives.
_NEWTON = """WITH RECURSIVE {0}, it(i, mu, l) AS (SELECT 0, mu, ln(s) FROM fit UNION ALL
 SELECT i + 1, mu - (d * g1 - b * g2) / (a * d - b * c), l - (a * g2 - c * g1) / (a * d - b * c) FROM
 (SELECT i, mu, l, sum(t) / exp(l) AS g1, sum(z * t) - count(*) AS g2, -sum((1 - t * t) / 2) / exp(2 * l) AS a, -(sum(t) + sum(z * (1 - t * t) / 2)) / exp(l) AS b,
  -(sum(t) + sum(z * (1 - t * t) / 2)) / exp(l) AS c, -(sum(z * t) + sum(z * z * (1 - t * t) / 2)) AS d FROM
  (SELECT i, mu, l, (vi - mu) / exp(l) AS z, (exp((vi - mu) / exp(l)) - 1) / (exp((vi - mu) / exp(l)) + 1) AS t FROM it, vol WHERE vi IS NOT NULL AND i < 40) GROUP BY i, mu, l))
SELECT round(arg_max(mu, i), 6) AS mu, round(exp(arg_max(l, i)), 6) AS s FROM it"""
_MLE_SQL = _NEWTON.format(", ".join(f"{name} AS ({body})" for name, body in index_parts("order_week")[:-1]))
query("logistic_fit_mle", _MLE_SQL)(lambda s, d: s.createDataFrame([tuple(round(x, 6) for x in VOL.fit_logistic(VOL.volatility(VOL.log_returns(V.order_index(s, d))), "mle"))], "mu double, s double"))
query("index_change", with_parts(("idx", INDEX_SQL["order_week"]), last="SELECT win, round(value - lag(value) OVER (ORDER BY win), 6) AS change FROM idx"))(lambda s, d: rounded(VOL.index_change(V.order_index(s, d)).select("win", "change")))

# --- pairs and topics ------------------------------------------------------------------------------------------------

_INC = ("inc", "SELECT DISTINCT doc_id, feature FROM tokens")
_JAC = (
    "jac",
    """SELECT f, g, shared, a.df AS df_f, b.df AS df_g, shared * 1.0 / (a.df + b.df - shared) AS jaccard FROM
    (SELECT x.feature AS f, y.feature AS g, count(*) AS shared FROM inc x JOIN inc y ON x.doc_id = y.doc_id AND x.feature < y.feature GROUP BY 1, 2)
    JOIN (SELECT feature AS f, count(*) AS df FROM inc GROUP BY 1) a USING (f) JOIN (SELECT feature AS g, count(*) AS df FROM inc GROUP BY 1) b USING (g)""",
)


def _rho_part(cells: str) -> tuple[str, str]:
    norm = f"(SELECT feature, sqrt(sum(p * p)) AS norm FROM {cells} WHERE p > 0 GROUP BY feature)"
    return "rho", f"""SELECT f, g, dot / (a.norm * b.norm) AS rho FROM (SELECT x.feature AS f, y.feature AS g, sum(x.p * y.p) AS dot FROM {cells} x JOIN {cells} y
    ON x.win = y.win AND x.feature < y.feature AND x.p > 0 AND y.p > 0 GROUP BY 1, 2) JOIN {norm} a ON a.feature = f JOIN {norm} b ON b.feature = g"""


_JAC_LAST = "SELECT f, g, shared, df_f, df_g, round(jaccard, 6) AS jaccard FROM jac"
query("jaccard_order", with_parts(tokens_part("order"), _INC, _JAC, last=_JAC_LAST))(lambda s, d: rounded(A.jaccard_pairs(STREAMS["order"](s, d))))
query("jaccard_bitmap", with_parts(tokens_part("order"), _INC, _JAC, last=_JAC_LAST))(lambda s, d: rounded(A.jaccard_pairs(STREAMS["order"](s, d), "bitmap")))
query("jaccard_text", with_parts(tokens_part("text"), ("inc", f"SELECT DISTINCT doc_id, feature FROM tokens SEMI JOIN ({_SHARE_SQL['corpus']}) USING (feature)"), _JAC, last=_JAC_LAST))(lambda s, d: rounded(A.jaccard_pairs(X.share_filter(STREAMS["text"](s, d)))))


def estimated_pairs(s: SparkSession, d: str, how: str) -> DataFrame:
    """Estimates of the order stream; theta sketches take the pairs that ever have a common probability."""
    within = A.temporal_pairs(staged(burst_table(s, d, "order"), "bursts"), False) if how == "theta" else None
    return A.jaccard_pairs(STREAMS["order"](s, d), how, within=within)


for _method in ("minhash", "theta", "sample"):
    query(f"jaccard_{_method}")(lambda s, d, m=_method: rounded(estimated_pairs(s, d, m)))
    query(f"jaccard_error_{_method}")(lambda s, d, m=_method: rounded(M.sketch_error(A.jaccard_pairs(STREAMS["order"](s, d)), estimated_pairs(s, d, m))))
for _kind, _cells in (("raw", "p"), ("sparse", "bursty")):
    query(f"temporal_cosine_{_kind}", with_parts(*bursts_parts("order"), _rho_part(_cells), last="SELECT f, g, round(rho, 6) AS rho FROM rho"))(lambda s, d, k=_kind: rounded(A.temporal_pairs(staged(burst_table(s, d, "order"), "bursts"), k == "sparse")))
_INF = ("inf", "SELECT feature, coalesce(round(sum(pvi), 9), 0) AS influence FROM (SELECT DISTINCT feature FROM p) LEFT JOIN bursty USING (feature) LEFT JOIN pvi USING (win) GROUP BY feature")


def influence_table(s: SparkSession, d: str, normalise: bool = False) -> DataFrame:
    return T.feature_influence(staged(burst_table(s, d, "order"), "bursts"), VOL.index_levels(V.order_index(s, d), levels=None), normalise)


query("feature_influence_raw", with_parts(*bursts_parts("order"), *index_parts("order_week"), _INF, last="SELECT feature, round(influence, 6) AS influence FROM inf"))(lambda s, d: rounded(influence_table(s, d)))
query("feature_influence_normalised", with_parts(*bursts_parts("order"), *index_parts("order_week"), _INF, last="SELECT feature, round(influence / (SELECT sum(influence) FROM inf), 6) AS influence FROM inf"))(lambda s, d: rounded(influence_table(s, d, True)))
_BOTH = ("duo", "SELECT f AS word, g AS partner, jaccard, coalesce(rho, 0) AS rho FROM jac LEFT JOIN rho USING (f, g) UNION ALL SELECT g, f, jaccard, coalesce(rho, 0) FROM jac LEFT JOIN rho USING (f, g)")
_FACTOR = {"sum": "(a.influence + b.influence)", "candidate": "b.influence", "mean": "(a.influence + b.influence) / 2", "off": "1.0"}


def _objective_sql(how: str, last: str) -> str:
    obj = ("obj", f"SELECT word, partner, jaccard * rho * {_FACTOR[how]} AS objective FROM duo JOIN inf a ON a.feature = word JOIN inf b ON b.feature = partner")
    return with_parts(*bursts_parts("order"), *index_parts("order_week"), _INC, _JAC, _rho_part("bursty"), _INF, _BOTH, obj, last=last)


def objective_table(s: SparkSession, d: str, how: str) -> DataFrame:
    p = staged(burst_table(s, d, "order"), "bursts")
    influence = T.feature_influence(p, VOL.index_levels(V.order_index(s, d), levels=None))
    return T.pair_objectives(A.affinities(STREAMS["order"](s, d), p), influence, how)


for _how in ("sum", "candidate", "mean", "off"):
    query(f"pair_objective_{_how}", _objective_sql(_how, "SELECT word, partner, round(objective, 6) AS objective FROM obj"))(lambda s, d, h=_how: rounded(objective_table(s, d, h).select("word", "partner", "objective")))
query("best_partner_value", _objective_sql("sum", "SELECT word, round(max(objective), 6) AS objective FROM obj GROUP BY word"))(lambda s, d: rounded(T.best_partners(objective_table(s, d, "sum")).select("word", "objective")))


def partners_of_the_first_word(s: SparkSession, d: str) -> DataFrame:
    """The comparison of the worked example for the word of most influence and all its partners on the order stream."""
    p = staged(burst_table(s, d, "order"), "bursts")
    influence = staged(T.feature_influence(p, VOL.index_levels(V.order_index(s, d), levels=None)), "influence")
    first = influence.orderBy(F.desc("influence"), "feature").limit(1).select(F.col("feature").alias("word"))
    pairs = T.pair_objectives(A.affinities(STREAMS["order"](s, d), p), influence, "candidate").join(F.broadcast(first), "word")
    return T.partner_values(pairs.select("word", "partner", "jaccard", "rho", F.col("partner_influence").alias("influence")))


_FIRST = "SELECT partner, round(jaccard * rho, 6) AS without_index, round(jaccard * rho * influence, 6) AS with_index FROM duo JOIN inf ON feature = partner WHERE word = (SELECT feature FROM inf ORDER BY influence DESC, feature LIMIT 1)"
query("worker_example", with_parts(*bursts_parts("order"), *index_parts("order_week"), _INC, _JAC, _rho_part("bursty"), _INF, _BOTH, last=_FIRST))(
    lambda s, d: rounded(partners_of_the_first_word(s, d).select("partner", "without_index", "with_index"))
)

# --- a fixed set of topics, so that SQL can check what follows from topics ---------------------------------------------

_FIXED = ("fixed", "SELECT feature, CAST(1 + (row_number() OVER (ORDER BY feature) - 1) // 5 AS INT) AS topic_id FROM (SELECT DISTINCT feature FROM tokens)")
_SIZES = ("sizes", "SELECT topic_id, count(*) AS size FROM fixed GROUP BY topic_id")
_RATE = ("rate", "SELECT topic_id, win, sum(p) / any_value(size) AS rate FROM p JOIN fixed USING (feature) JOIN sizes USING (topic_id) GROUP BY topic_id, win")


def fixed_topics(tokens: DataFrame) -> DataFrame:
    """Features in alphabetical fives, with an objective that follows from the number of the topic."""
    from pyspark.sql import Window

    rank = F.row_number().over(Window.orderBy("feature")) - 1  # one row per feature
    numbered = tokens.select("feature").distinct().withColumn("topic_id", (F.floor(rank / 5) + 1).cast("int"))
    return numbered.groupBy("topic_id").agg(F.sort_array(F.collect_list("feature")).alias("features")).withColumn("objective", 1.0 / F.col("topic_id"))


def fixed_rate(s: SparkSession, d: str, threshold: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    tokens = STREAMS["order"](s, d)
    tops = staged(fixed_topics(tokens), "fixed")
    return tokens, tops, staged(T.topic_burst(tops, staged(burst_table(s, d, "order"), "bursts"), threshold), "rates")


_fixed_parts = [*bursts_parts("order"), _FIXED, _SIZES, _RATE]
query("topic_burst_rate", with_parts(*_fixed_parts, last="SELECT topic_id, win, round(rate, 6) AS rate FROM rate"))(lambda s, d: rounded(fixed_rate(s, d, 0.6)[2].select("topic_id", "win", "rate")))
query("bursty_topics", with_parts(*_fixed_parts, last="SELECT topic_id, win FROM rate WHERE rate > 0.6"))(lambda s, d: fixed_rate(s, d, 0.6)[2].where("bursty").select("topic_id", "win"))
_VEC = ("vec", "SELECT topic_id, win, doc_id, sum(tf) * 1.0 / any_value(size) AS weight FROM (SELECT win, doc_id, feature, count(*) AS tf FROM tokens GROUP BY ALL) JOIN fixed USING (feature) JOIN sizes USING (topic_id) SEMI JOIN (SELECT topic_id, win FROM rate WHERE rate > 0.6) USING (topic_id, win) GROUP BY topic_id, win, doc_id")
_COS = ("cos", "SELECT win, t, u, dot / (a.norm * b.norm) AS cosine FROM (SELECT x.win, x.topic_id AS t, y.topic_id AS u, sum(x.weight * y.weight) AS dot FROM vec x JOIN vec y ON x.win = y.win AND x.doc_id = y.doc_id AND x.topic_id <= y.topic_id GROUP BY 1, 2, 3) JOIN (SELECT win, topic_id AS t, sqrt(sum(weight * weight)) AS norm FROM vec GROUP BY 1, 2) a USING (win, t) JOIN (SELECT win, topic_id AS u, sqrt(sum(weight * weight)) AS norm FROM vec GROUP BY 1, 2) b USING (win, u)")


def fixed_gram(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    _, tops, rate = fixed_rate(s, d, 0.6)
    return tops, rate, staged(G.topic_gram(tops, tokens_of(s, d, "orders"), rate), "gram")


query("topic_cosine_by_window", with_parts(*_fixed_parts, _VEC, _COS, last="SELECT win, t, u, round(cosine, 6) AS cosine FROM cos"))(lambda s, d: rounded(fixed_gram(s, d)[2]))


def pair_groups(rate: DataFrame) -> DataFrame:
    """Bursty topics of each window in groups of neighbours by number: ``win, group_id, topics``."""
    cells = rate.where("bursty").select("win", F.floor(F.col("topic_id") / 3).cast("int").alias("group_id"), "topic_id")
    return cells.groupBy("win", "group_id").agg(F.sort_array(F.collect_list("topic_id")).alias("topics"))


_GRP = ("grp", "SELECT win, topic_id // 3 AS group_id, topic_id, {0} AS v FROM rate WHERE rate > 0.6")
_SIM = """SELECT win, group_id, next_group_id, round(shared / (total + other - shared), 6) AS similarity FROM
 (SELECT a.win, CAST(a.group_id AS INT) AS group_id, CAST(b.group_id AS INT) AS next_group_id, sum(a.v) AS shared FROM grp a JOIN grp b ON b.win = a.win + 1 AND a.topic_id = b.topic_id GROUP BY 1, 2, 3)
 JOIN (SELECT win, group_id, sum(v) AS total FROM grp GROUP BY 1, 2) USING (win, group_id)
 JOIN (SELECT win - 1 AS win, group_id AS next_group_id, sum(v) AS other FROM grp GROUP BY 1, 2) USING (win, next_group_id)"""
for _weight, _value in (("objective", "1.0 / topic_id"), ("none", "1.0")):
    query("group_similarity" if _weight == "objective" else "group_similarity_unweighted", with_parts(*_fixed_parts, (_GRP[0], _GRP[1].format(_value)), last=_SIM))(
        lambda s, d, w=_weight: (lambda x: rounded(C.group_links(pair_groups(x[2]), x[1], 0.0, w)))(fixed_rate(s, d, 0.6))
    )
_SCORED = """SELECT topic_id, start_win, CAST(max(win) AS INT) AS end_win, count(*) AS n_win, round(sqrt(sum(rate * rate)), 6) AS intensity_norm, round(sqrt(sum(pvi * pvi)), 6) AS pvi_norm,
 round(CASE WHEN stddev_pop(rate) <= 1e-9 OR stddev_pop(pvi) <= 1e-9 THEN 0 ELSE covar_pop(rate, pvi) / (stddev_pop(rate) * stddev_pop(pvi)) END * sqrt(sum(rate * rate)) * sqrt(sum(pvi * pvi)), 6) + 0.0 AS score FROM
 (SELECT topic_id, win, rate, pvi, min(win) OVER (PARTITION BY topic_id, run) AS start_win FROM (SELECT topic_id, win, rate, win - row_number() OVER (PARTITION BY topic_id ORDER BY win) AS run FROM rate WHERE rate > 0.6) JOIN pvi USING (win)) GROUP BY topic_id, start_win"""
query("event_score_runs", with_parts(*_fixed_parts, *index_parts("order_week"), last=_SCORED))(
    lambda s, d: rounded(BL.run_events(fixed_rate(s, d, 0.6)[2], VOL.index_levels(V.order_index(s, d), levels=None)).select("topic_id", "start_win", "end_win", "n_win", "intensity_norm", "pvi_norm", "score"))
)
query(
    "keyword_index_correlation",
    with_parts(*bursts_parts("order"), ("idx", INDEX_SQL["order_week"]), ("full_", "SELECT feature, win, coalesce(p, 0) AS x, value AS y FROM (SELECT feature, win, value FROM rates, idx) LEFT JOIN p USING (feature, win)"), last="SELECT feature, round(covar_pop(x, y) / (stddev_pop(x) * stddev_pop(y)), 6) AS corr FROM full_ GROUP BY feature ORDER BY abs(covar_pop(x, y) / (stddev_pop(x) * stddev_pop(y))) DESC, feature LIMIT 10"),
)(lambda s, d: rounded(BL.correlated_keywords(staged(burst_table(s, d, "order"), "bursts"), V.order_index(s, d), 10)))


def run_chains(rate: DataFrame) -> DataFrame:
    """Each run of windows in which a topic bursts as a chain of the groups that hold the topic: ``chain_id, win, group_id``."""
    from pyspark.sql import Window

    runs = B.burst_runs(rate.where("bursty"), "topic_id")
    runs = runs.withColumn("chain_id", F.row_number().over(Window.orderBy("topic_id", "start_win")))  # one row per run of a topic
    return runs.select("chain_id", F.explode(F.sequence("start_win", "end_win")).alias("win"), F.floor(F.col("topic_id") / 3).cast("int").alias("group_id"))


_RUN_CHAINS = ("chains", """SELECT dense_rank() OVER (ORDER BY topic_id, start_win) AS chain_id, win, topic_id // 3 AS group_id FROM
 (SELECT topic_id, win, min(win) OVER (PARTITION BY topic_id, run) AS start_win FROM (SELECT topic_id, win, win - row_number() OVER (PARTITION BY topic_id ORDER BY win) AS run FROM rate WHERE rate > 0.6))""")
_OVERLAP = """SELECT CAST(x.chain_id AS INT) AS a, CAST(y.chain_id AS INT) AS b, CAST(count(*) AS INT) AS shared, round(count(*) * 1.0 / least(any_value(x.size), any_value(y.size)), 6) AS overlap
 FROM (SELECT *, count(*) OVER (PARTITION BY chain_id) AS size FROM chains) x JOIN (SELECT *, count(*) OVER (PARTITION BY chain_id) AS size FROM chains) y ON x.win = y.win AND x.group_id = y.group_id AND x.chain_id < y.chain_id GROUP BY 1, 2"""
query("chain_overlap", with_parts(*_fixed_parts, _RUN_CHAINS, last=_OVERLAP))(
    lambda s, d: rounded(E.chain_overlap(run_chains(fixed_rate(s, d, 0.6)[2]))).select("a", "b", F.col("shared").cast("int").alias("shared"), "overlap")
)

# --- the experiments: three datasets, baselines, ablations ---------------------------------------------------------------

#: Volatility inside the weeks, from daily means.
_WITHIN = [
    ("daily", f"SELECT step // 7 AS win, step, value FROM (SELECT CAST(floor((epoch(o_orderdate) - epoch(TIMESTAMP '1995-01-01')) / 86400) AS INT) AS step, avg(o_totalprice) AS value FROM orders GROUP BY 1) WHERE step // 7 < {_FULL.format('o_orderdate', 'orders')}"),
    ("vol", "SELECT win, CASE WHEN count(ret) >= 2 THEN stddev_pop(ret) END AS vi FROM (SELECT win, ln(value / lag(value) OVER (PARTITION BY win ORDER BY step)) AS ret FROM daily) GROUP BY win"),
    _FIT,
    _PVI,
]
#: Stream and parts of the index levels of the datasets that SQL can follow (the text stream is stemmed).
_FOLLOWED = {"orders": ("order", index_parts("order_week", _PVI)), "sessions": ("session", index_parts("event_4h", _PVI)), "polls": ("poll", index_parts("order_polls", _PVI)), "daily": ("order", _WITHIN)}
# Pairs that share documents or bursts, both ways.
_EITHER = ("pairs", "SELECT coalesce(a.f, b.f) AS f, coalesce(a.g, b.g) AS g, coalesce(jaccard, 0) AS jaccard, coalesce(rho, 0) AS rho FROM jac a FULL JOIN rho b ON a.f = b.f AND a.g = b.g")
_NEAR = ("duo", "SELECT f AS word, g AS partner, jaccard, rho FROM pairs UNION ALL SELECT g, f, jaccard, rho FROM pairs")
# One row is the state of the greedy search; each step adds the best word to the topic, or closes it and seeds the next.
_GREEDY = """SELECT 0 AS step, 0 AS topic, []::VARCHAR[] AS members, []::VARCHAR[] AS used, 0.0::DOUBLE AS in_j, 0.0::DOUBLE AS in_r, 0.0::DOUBLE AS total, 0.0::DOUBLE AS best
 UNION ALL SELECT step + 1, topic + CASE WHEN k = 0 THEN 1 ELSE 0 END, CASE WHEN ok THEN list_append(members, feature) ELSE [] END, CASE WHEN ok THEN list_append(used, feature) ELSE used END,
  CASE WHEN ok THEN in_j + sj ELSE 0 END, CASE WHEN ok THEN in_r + sr ELSE 0 END, CASE WHEN ok THEN total + influence ELSE 0 END, CASE WHEN ok AND k > 0 THEN value ELSE 0 END
 FROM (SELECT *, k = 0 OR (lk AND value > best) AS ok, row_number() OVER (ORDER BY (k = 0 OR lk) DESC, value DESC, feature) AS r FROM
  (SELECT *, CASE WHEN k = 0 THEN influence ELSE round((in_j + sj) / (k * (k + 1) / 2) * ((in_r + sr) / (k * (k + 1) / 2)) * {factor}, 12) END AS value FROM
   (SELECT step, topic, members, used, in_j, in_r, total, best, len(members) AS k, i.feature, any_value(influence) AS influence, coalesce(sum(d.jaccard), 0) AS sj, coalesce(sum(d.rho), 0) AS sr, coalesce(max(d.jaccard * d.rho), 0) > 0 AS lk
    FROM found JOIN inf i ON NOT list_contains(used, i.feature) LEFT JOIN duo d ON d.word = i.feature AND list_contains(members, d.partner) GROUP BY step, topic, members, used, in_j, in_r, total, best, i.feature))) WHERE r = 1"""
_TOPICS = (
    "topics",
    """SELECT CAST(row_number() OVER (ORDER BY objective DESC, features) AS INT) AS topic_id, * FROM (SELECT array_to_string(list_sort(members), ' ') AS features, n, doc_coherence, time_coherence, influence, doc_coherence * time_coherence * influence AS objective FROM
 (SELECT members, len(members) AS n, CASE WHEN len(members) = 1 THEN 1 ELSE in_j / (len(members) * (len(members) - 1) / 2) END AS doc_coherence, CASE WHEN len(members) = 1 THEN 1 ELSE in_r / (len(members) * (len(members) - 1) / 2) END AS time_coherence, {impact} AS influence,
  row_number() OVER (PARTITION BY topic ORDER BY len(members) DESC) AS r FROM found WHERE len(members) > 0) WHERE r = 1)""",
)


def topic_parts(dataset: str, influence: str = "sum", tail: str = "strict") -> list[tuple[str, str]]:
    """The topics of a dataset in SQL: bursts, levels, influence, pairs and the greedy search over them."""
    stream, levels = _FOLLOWED[dataset]
    parts = bursts_parts(stream, tail)
    if tail == "inclusive":  # a cell for every absent count, and bursts of words that are there
        parts[4] = ("cells", "SELECT feature, win, coalesce(n, 0) AS n, CAST(total AS BIGINT) AS total, pe FROM rates CROSS JOIN totals LEFT JOIN counts USING (feature, win)")
        parts[6] = ("bursty", "SELECT feature, win, p FROM p WHERE p > 0.95 AND n > 0")
    factor, impact = {"sum": ("(total + influence)", "total"), "off": ("1", "1.0")}[influence]
    search = ("found", _GREEDY.format(factor=factor))
    return [*parts, *levels, _INC, _JAC, _rho_part("p" if tail == "inclusive" else "bursty"), _INF, _EITHER, _NEAR, search, (_TOPICS[0], _TOPICS[1].format(impact=impact))]


def recursive(parts: list[tuple[str, str]], last: str) -> str:
    """The parts as tables that are worked out once, one of which refers to itself."""
    return "WITH RECURSIVE " + ",\n".join(f"{name} AS ({body})" if name == "found" else f"{name} AS MATERIALIZED ({body})" for name, body in parts) + "\n" + last


_TOPIC_ROWS = "SELECT topic_id, features, round(doc_coherence, 6) AS doc_coherence, round(time_coherence, 6) AS time_coherence, round(influence, 6) AS influence, round(objective, 6) AS objective FROM topics"
_TOPIC_RATE = ("rate", "SELECT topic_id, win, sum(p) / any_value(n) AS rate FROM (SELECT topic_id, n, unnest(string_split(features, ' ')) AS feature FROM topics) JOIN (SELECT feature, win, p FROM p) USING (feature) GROUP BY topic_id, win")
_RUN_ROWS = """SELECT CAST(row_number() OVER (ORDER BY round(intensity_norm * pvi_norm * comovement, 9) + 0.0 DESC, start_win, topic_id) AS INT) AS rank, topic_id, start_win, end_win, n_win, round(intensity_norm, 6) AS intensity_norm, round(pvi_norm, 6) AS pvi_norm, round(comovement, 6) + 0.0 AS comovement, round(intensity_norm * pvi_norm * comovement, 6) + 0.0 AS score FROM
 (SELECT topic_id, start_win, CAST(max(win) AS INT) AS end_win, count(*) AS n_win, sqrt(sum(rate * rate)) AS intensity_norm, sqrt(sum(pvi * pvi)) AS pvi_norm,
  CASE WHEN stddev_pop(rate) <= 1e-9 OR stddev_pop(pvi) <= 1e-9 THEN 0 ELSE covar_pop(rate, pvi) / (stddev_pop(rate) * stddev_pop(pvi)) END AS comovement FROM
  (SELECT topic_id, win, rate, coalesce(pvi, 0) AS pvi, min(win) OVER (PARTITION BY topic_id, run) AS start_win FROM (SELECT topic_id, win, rate, win - row_number() OVER (PARTITION BY topic_id ORDER BY win) AS run FROM rate WHERE rate > 0.7) LEFT JOIN pvi USING (win)) GROUP BY topic_id, start_win)"""
TOPIC_SQL: dict[str, str] = {}
for _data in _FOLLOWED:
    TOPIC_SQL |= {
        f"impact_topics_{_data}": recursive(topic_parts(_data), _TOPIC_ROWS),
        f"top5_topics_{_data}": recursive(topic_parts(_data), _TOPIC_ROWS + " ORDER BY topics.objective DESC, topic_id LIMIT 5"),
        f"topic_sizes_{_data}": recursive(topic_parts(_data), "SELECT CAST(n AS INT) AS size, count(*) AS topics FROM topics GROUP BY n"),
        f"baseline_events_{_data}": recursive([*topic_parts(_data, "off"), _TOPIC_RATE], _RUN_ROWS),
    }
for _data in ("orders", "sessions"):
    TOPIC_SQL[f"impact_topics_{_data}_faithful"] = recursive(topic_parts(_data, tail="inclusive"), _TOPIC_ROWS)
TOPIC_SQL["topics_then_index"] = recursive(
    [*topic_parts("orders", "off"), _TOPIC_RATE, ("full_", "SELECT topic_id, win, coalesce(rate, 0) AS x, change AS y FROM (SELECT topic_id, win, change FROM (SELECT topic_id FROM topics), (SELECT win, value - lag(value) OVER (ORDER BY win) AS change FROM idx) WHERE change IS NOT NULL) LEFT JOIN rate USING (topic_id, win)")],
    "SELECT topic_id, round(CASE WHEN stddev_pop(x) <= 1e-12 OR stddev_pop(y) <= 1e-12 THEN 0 ELSE covar_pop(x, y) / (stddev_pop(x) * stddev_pop(y)) END, 6) + 0.0 AS corr FROM full_ WHERE topic_id IN (SELECT topic_id FROM rate) GROUP BY topic_id",
)

DATASETS: dict[str, tuple[Query, Query]] = {
    "orders": (STREAMS["order"], INDEXES["order_week"]),
    "text": (lambda s, d: X.prepare_tokens(V.text_stream(s, d), stemmed=True), INDEXES["event_12h"]),
    "sessions": (STREAMS["session"], INDEXES["event_4h"]),
    "polls": (STREAMS["poll"], INDEXES["order_polls"]),  # an index observed about every ten days
    "daily": (STREAMS["order"], lambda s, d: V.daily_order_index(s, d)),  # daily values inside weekly windows
}
#: Switches that a dataset needs whatever the preset.
OWN_VOLATILITY = {"daily": "within"}


def params_of(dataset: str, params: Params) -> Params:
    mode = OWN_VOLATILITY.get(dataset)
    return params.but(volatility=replace(params.volatility, mode=mode)) if mode else params


#: Results by session, folder, dataset and switches: the stages are written, so queries of one dataset share them.
_results: dict[tuple, object] = {}


def _shared(s: SparkSession, d: str, dataset: str, params: Params, what: str, make: Callable[[DataFrame, DataFrame, Params], object]) -> object:
    own = params_of(dataset, params)
    key = (s.sparkContext.applicationId, shared_folder(s), d, dataset, own, what)
    if key not in _results:
        _results[key] = make(tokens_of(s, d, dataset), DATASETS[dataset][1](s, d), own)
    return _results[key]


def tokens_of(s: SparkSession, d: str, dataset: str) -> DataFrame:
    """The stream of a dataset, cut and joined once and written: counts, pairs and vectors all read it."""
    stream = DATASETS[dataset][0]
    key = (s.sparkContext.applicationId, shared_folder(s), d, stream)
    if key not in _results:
        _results[key] = staged(stream(s, d), "tokens")
    return _results[key]


def method(s: SparkSession, d: str, dataset: str, params: Params = FLAGSHIP) -> P.Result:
    return _shared(s, d, dataset, params, "run", lambda tokens, index, own: P.run(tokens, index, own, topics_of(s, d, dataset, params)))


def topics_of(s: SparkSession, d: str, dataset: str, params: Params = FLAGSHIP) -> tuple:
    """Bursts, levels, influence, pairs and topics of a dataset, which hang on no switch of groups and chains."""
    plain = params.but(group=FLAGSHIP.group, chain=FLAGSHIP.chain)
    return _shared(s, d, dataset, plain, "topics", lambda tokens, index, own: P.impact_topics(tokens, index, own, measured_of(s, d, dataset, plain)))


def measured_of(s: SparkSession, d: str, dataset: str, params: Params = FLAGSHIP) -> tuple:
    """Bursts, levels, influence and pairs of a dataset, which hang on no switch of topics either."""
    return _shared(s, d, dataset, params.but(group=FLAGSHIP.group, chain=FLAGSHIP.chain, topic=FLAGSHIP.topic), "measured", P.measured)


def flat_topics(topics: DataFrame) -> DataFrame:
    return rounded(topics.withColumn("features", F.array_join("features", " ")))


def flat_events(events: DataFrame) -> DataFrame:
    return rounded(events.drop("groups"))


for _data in DATASETS:
    query(f"impact_topics_{_data}", TOPIC_SQL.get(f"impact_topics_{_data}"))(lambda s, d, x=_data: flat_topics(topics_of(s, d, x)[4]))
    query(f"top5_topics_{_data}", TOPIC_SQL.get(f"top5_topics_{_data}"))(lambda s, d, x=_data: flat_topics(T.rank_topics(topics_of(s, d, x)[4], 5)))
    query(f"topic_sizes_{_data}", TOPIC_SQL.get(f"topic_sizes_{_data}"))(lambda s, d, x=_data: M.topic_sizes(topics_of(s, d, x)[4]))
    query(f"event_shape_{_data}")(lambda s, d, x=_data: M.event_shape(method(s, d, x).events, method(s, d, x).members))
    query(f"topic_groups_{_data}")(lambda s, d, x=_data: rounded(method(s, d, x).groups.withColumn("topics", F.array_join(F.col("topics").cast("array<string>"), " "))))
    query(f"group_chains_{_data}")(lambda s, d, x=_data: rounded(method(s, d, x).chains))
    query(f"trigger_events_{_data}")(lambda s, d, x=_data: flat_events(method(s, d, x).events))
    query(f"top10_events_{_data}")(lambda s, d, x=_data: rounded(P.with_words(method(s, d, x)).orderBy("rank").limit(10)))
    query(f"baseline_events_{_data}", TOPIC_SQL.get(f"baseline_events_{_data}"))(lambda s, d, x=_data: (lambda f, pvi, inf, pairs, t: rounded(BL.baseline_events(pairs, inf, f.p, pvi)))(*topics_of(s, d, x)))
for _data in ("orders", "text", "sessions"):
    # The inclusive tail on words that are present, and raw series.
    query(f"impact_topics_{_data}_faithful", TOPIC_SQL.get(f"impact_topics_{_data}_faithful"))(lambda s, d, x=_data: flat_topics(topics_of(s, d, x, FAITHFUL)[4]))
    query(f"trigger_events_{_data}_faithful")(lambda s, d, x=_data: flat_events(method(s, d, x, FAITHFUL).events))


@query("event_structure_best")
def event_structure_best(s: SparkSession, d: str) -> DataFrame:
    r = method(s, d, "orders")
    best = E.rank_events(r.events, 1).select("event_id")
    return E.describe_events(r.members.join(best, "event_id"), r.topics)


@query("event_waves_orders")
def event_waves_orders(s: SparkSession, d: str) -> DataFrame:
    r = method(s, d, "orders")
    return rounded(E.event_waves(r.members, r.rate, r.pvi))


@query("volatile_window_focus")
def volatile_window_focus(s: SparkSession, d: str) -> DataFrame:
    r = method(s, d, "orders")
    return rounded(M.volatile_focus(r.members, r.rate, r.pvi))


@query("quality_comparison")
def quality_comparison(s: SparkSession, d: str) -> DataFrame:
    """Chains and runs, each from topics with and without the index, on the three datasets.

    Runs of topics found without the index are the events of ``baseline_events_*``.
    """
    switches = {influence: FLAGSHIP.but(topic=replace(FLAGSHIP.topic, influence=influence)) for influence in (FLAGSHIP.topic.influence, "off")}

    def both(name: str) -> list[P.Result]:
        measured_of(s, d, name)  # one for both
        return at_once(s, [lambda p=params: method(s, d, name, p) for params in switches.values()])

    names = ("orders", "text", "sessions")
    out = None
    for name, results in zip(names, at_once(s, [lambda x=name: both(x) for name in names])):
        for (influence, params), r in zip(switches.items(), results):
            runs = BL.occurrence_events(r.topics, r.p, r.pvi, params.topic.burst_threshold)
            for kind, found in (("chains", r.events), ("runs", runs)):
                part = M.event_quality(found).select(F.lit(name).alias("dataset"), F.lit(influence).alias("influence"), F.lit(kind).alias("events_from"), "metric", "value")
                out = part if out is None else out.unionByName(part)
    return rounded(out)


def _ablation(name: str, **changes) -> None:
    """One row for each measure, on the order stream and on the sessions."""
    params = FLAGSHIP.but(**{k: replace(getattr(FLAGSHIP, k), **v) for k, v in changes.items()})

    def run(s: SparkSession, d: str) -> DataFrame:
        parts = [M.event_quality(method(s, d, x, params).events).select(F.lit(x).alias("dataset"), "metric", "value") for x in ("orders", "sessions")]
        return rounded(parts[0].unionByName(parts[1]))

    query(f"ablation_{name}")(run)


_ablation("no_index", topic={"influence": "off"})
_ablation("mean_influence", topic={"influence": "mean"})
_ablation("candidate_influence", topic={"influence": "candidate"})
_ablation("no_gain", chain={"require_gain": False})
_ablation("no_threshold", chain={"link_threshold": 0.0})
_ablation("unweighted", chain={"weight": "none"})
_ablation("fork", chain={"branching": "fork"})
_ablation("single_linkage", chain={"linkage": "single"})
_ablation("complete_linkage", chain={"linkage": "complete"})
_ablation("threshold_groups", group={"method": "threshold"})
_ablation("pair_seeds", topic={"seed": "pair"})
_ablation("raw_series", burst={"sparsify": False})
_ablation("inclusive_tail", burst={"tail": "inclusive", "require_presence": True})
_ablation("quiet_rates", burst={"expected": "quiet"})
_ablation("drop_documents", topic={"factors": "no_documents"})
_ablation("drop_bursts", topic={"factors": "no_time"})
_ablation("capped", topic={"max_topic_size": 8}, group={"max_k": 12})
_ablation("mle_levels", volatility={"fit": "mle"})
query("topics_then_index", TOPIC_SQL["topics_then_index"])(lambda s, d: (lambda f, pvi, inf, pairs, t: rounded(BL.topics_then_index(pairs, inf, f.p, VOL.index_change(V.order_index(s, d)))))(*topics_of(s, d, "orders")))

# --- measures ----------------------------------------------------------------------------------------------------------

for _data, _stream in (("text", "text"), ("orders", "order"), ("sessions", "session"), ("polls", "poll")):
    query(f"dataset_size_{_data}", with_parts(tokens_part(_stream), last="SELECT unnest(['documents', 'features', 'windows']) AS metric, unnest([count(DISTINCT doc_id), count(DISTINCT feature), count(DISTINCT win)])::DOUBLE AS value FROM tokens"))(lambda s, d, x=_stream: M.dataset_size(STREAMS[x](s, d)))


@query("logistic_distance", with_parts(*index_parts("order_week"), last="SELECT 'logistic_distance' AS metric, round(max(abs(share - 1 / (1 + exp(-(vi - mu) / s)))), 6) AS value FROM (SELECT vi, cume_dist() OVER (ORDER BY vi) AS share FROM vol WHERE vi IS NOT NULL), fit"))
def logistic_distance(s: SparkSession, d: str) -> DataFrame:
    levels = staged(VOL.volatility(VOL.log_returns(V.order_index(s, d))), "levels")
    return rounded(M.logistic_distance(levels, *VOL.fit_logistic(levels)))


_QUALITY = """SELECT win, round(sum(coalesce(far, 0) / (n - size)) / sum(size * CASE WHEN size > 1 THEN coalesce(near, 0) / (size * (size - 1) / 2) ELSE 1 END), 6) AS ratio FROM
 (SELECT *, sum(size) OVER (PARTITION BY win) AS n, count(*) OVER (PARTITION BY win) AS k FROM (SELECT win, topic_id // 3 AS g, count(*) AS size FROM rate WHERE rate > 0.6 GROUP BY 1, 2))
 LEFT JOIN (SELECT win, t // 3 AS g, sum(cosine) AS near FROM cos WHERE t < u AND t // 3 = u // 3 GROUP BY 1, 2) USING (win, g)
 LEFT JOIN (SELECT win, g, sum(cosine) AS far FROM (SELECT win, unnest([t // 3, u // 3]) AS g, cosine FROM cos WHERE t // 3 <> u // 3) GROUP BY 1, 2) USING (win, g)
 WHERE k > 1 GROUP BY win"""
query("grouping_quality", with_parts(*_fixed_parts, _VEC, _COS, last=_QUALITY))(lambda s, d: (lambda x: rounded(M.grouping_quality(x[2], pair_groups(x[1]))))(fixed_gram(s, d)))
query("event_intensity_features", with_parts(*_fixed_parts, last="SELECT topic_id // 3 AS event_id, win, round(sum(rate) / sum(size), 6) AS intensity FROM rate JOIN sizes USING (topic_id) WHERE rate > 0.6 GROUP BY 1, 2"))(
    lambda s, d: (lambda x: rounded(E.event_intensity(x[2].where("bursty").select(F.floor(F.col("topic_id") / 3).cast("int").alias("event_id"), "win", "topic_id"), x[2], sizes=x[1].select("topic_id", F.size("features").alias("size")))))(fixed_rate(s, d, 0.6))
)
#: Words whose documents are moved to a window each, so that there is a known answer.
PLANTED = {20: ["thing", "ing"], 40: ["reed"]}


def planted_bursts(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    tokens = staged(X.tokenize(V.planted_stream(s, d, PLANTED)), "planted")
    counts = staged(B.window_counts(tokens), "counts")
    totals = B.window_totals(counts)
    return tokens, staged(B.burst_probability(counts, totals, B.expected_rate(counts, totals)), "bursts")


def _planted_sql() -> str:
    win = "win"
    for target, words in PLANTED.items():
        win = f"CASE WHEN regexp_matches(lower(text), '(^|[^\\p{{L}}])({'|'.join(words)})([^\\p{{L}}]|$)') THEN {target} ELSE {win} END"
    return f"SELECT t.doc_id, CAST({win} AS INT) AS win, feature FROM ({TOKENS_SQL['text']}) t JOIN documents USING (doc_id)"


_PLANS = "(VALUES " + ", ".join(f"('{w}', {k})" for k, ws in PLANTED.items() for w in ws) + ") plan(feature, win)"
_PLANTED_LAST = f"""SELECT unnest(['recall', 'precision']) AS metric, unnest([round(hit / (SELECT count(*) FROM {_PLANS}), 6), round(hit / found, 6)]) AS value FROM
 (SELECT count(*) AS found, count(*) FILTER ((feature, win) IN (SELECT (feature, win) FROM {_PLANS})) AS hit FROM bursty WHERE feature IN (SELECT feature FROM {_PLANS}))"""


@query("planted_burst_recall", with_parts(("tokens", _planted_sql()), *bursts_parts("text")[1:], last=_PLANTED_LAST))
def planted_burst_recall(s: SparkSession, d: str) -> DataFrame:
    truth = s.createDataFrame([(w, k) for k, ws in PLANTED.items() for w in ws], "feature string, win int")
    return rounded(M.planted_recall(planted_bursts(s, d)[1], truth))


@query("planted_topics_and_events")
def planted_topics_and_events(s: SparkSession, d: str) -> DataFrame:
    """Pair F1 of the planted words among the found topics, and the overlap of the found events with the planted windows."""
    words = s.createDataFrame([(w,) for ws in PLANTED.values() for w in ws], "feature string")
    tokens = staged(X.tokenize(V.planted_stream(s, d, PLANTED)), "planted")
    r = P.run(tokens.join(X.kept_features(tokens).union(words).distinct(), "feature", "left_semi"), V.event_index(s, d))
    plan = s.createDataFrame([(k, k, k) for k in PLANTED], "plan int, start int, end int")
    overlap = M.event_overlap(r.events, plan).select(F.concat(F.lit("overlap_"), F.col("plan").cast("string")).alias("metric"), F.col("overlap").alias("value"))
    return rounded(M.pair_f1(r.topics, PLANTED).unionByName(overlap))


@query("stage_costs_orders")
def stage_costs_orders(s: SparkSession, d: str) -> DataFrame:
    """Seconds and shuffled bytes of each written stage of one run of the method."""
    with metered() as notes:
        P.run(*[f(s, d) for f in DATASETS["orders"]])
    return M.stage_costs(s, notes)


surface.SQL |= {
    "sql_burst_tail": with_parts(*bursts_parts("order"), last="SELECT feature, win, n, round(p, 6) AS p FROM p"),
    "aggregated_logistic_mle": _MLE_SQL,
    "table_function_runs": SQL["burst_runs_order"],
}
for _module in (relational, online, surface):
    for _name, _f in _module.QUERIES.items():
        query(_name, _module.SQL.get(_name))(_f)
