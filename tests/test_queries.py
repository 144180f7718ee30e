"""Queries against their SQL twins on the smallest tables, plans, edges and streams."""

import math
import random
import threading

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from indextrigger import registry
from indextrigger.functions import bursts as B
from indextrigger.functions import text as X
from indextrigger.functions import volatility as VOL
from indextrigger.params import FLAGSHIP
from indextrigger.plans import affinity, baselines, chains, events, graph, groups, measures, pipeline, topics
from indextrigger.plans.graph import connected
from indextrigger.sources import views as V
from indextrigger.sources.staging import at_once, bounded, shared_folder, staged
from indextrigger.streaming import online

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = [
    "text_stream_windows", "page_stream_windows", "chat_stream_windows", "order_token_counts", "share_filtered_features_mean_day", "expected_rate_quiet", "burst_probability_strict", "burst_runs_order",
    "volatility_level_order_week", "volatility_within", "jaccard_bitmap", "temporal_cosine_sparse", "feature_influence_raw", "pair_objective_candidate", "worker_example", "topic_cosine_by_window", "group_similarity", "event_score_runs", "chain_overlap",
    "keyword_index_correlation", "poll_stream_windows", "index_order_polls", "burst_probability_poisson", "burst_probability_normal", "logistic_fit_mle", "aggregated_logistic_mle", "table_function_runs", "impact_topics_orders", "impact_topics_sessions", "impact_topics_polls",
    "impact_topics_daily", "impact_topics_orders_faithful", "baseline_events_sessions", "grouping_quality", "logistic_distance", "stream_closed_windows", "stream_sliding_counts", "stream_sessions", "stream_stream_join", "stream_bursty_topics", "io_partitioned_by_window", "rel_as_of_join", "rel_range_join", "rel_window_functions", "stream_tumbling_counts",
]


def normal(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    return round(float(v), 5) + 0.0 if isinstance(v, float) or type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", CHECKED)
def test_equals_sql(spark, small, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    df = registry.QUERIES[name](spark, small)
    cols = sorted(df.columns)
    got = sorted((tuple(normal(r[c]) for c in cols) for r in df.collect()), key=str)
    found = con.execute(registry.SQL[name])
    names = [x[0] for x in found.description]
    assert sorted(names) == cols
    assert got == sorted((tuple(normal(r[names.index(c)]) for c in cols) for r in found.fetchall()), key=str)


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    assert len(registry.QUERIES) > 120 and set(registry.SQL) <= set(registry.QUERIES)
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_scan_is_pruned_and_filtered(spark, small):
    plan = registry.QUERIES["rel_filter_project"](spark, small)._jdf.queryExecution().toString()
    assert "PushedFilters: [" in plan and "IsNotNull(l_shipdate)" in plan and "l_comment" not in plan
    scan = B.window_counts(registry.STREAMS["session"](spark, small))._jdf.queryExecution().toString()
    assert "value" not in scan.split("ReadSchema")[-1]
    assert "CartesianProduct" not in registry.QUERIES["jaccard_order"](spark, small)._jdf.queryExecution().toString()


def test_column_tail_equals_array_tail(spark):
    rows = [("f", w, n, t, p) for w, (n, t, p) in enumerate([(0, 10, 0.1), (3, 10, 0.1), (10, 10, 0.1), (5, 4000, 0.001), (3000, 90_000, 0.03), (2, 5, 0.0), (2, 5, 1.0), (0, 0, 0.3)])]
    df = spark.createDataFrame(rows, "feature string, win int, n long, total long, pe double")
    counts, totals = df.select("feature", "win", "n"), df.select("win", "total")
    for tail in ("strict", "inclusive", "pmf"):
        for r in rows:
            one = B.burst_probability(counts.where(F.col("win") == r[1]), totals, df.where(F.col("win") == r[1]).select("feature", "pe"), tail).first()
            if 0 < r[4] < 1 and r[3]:
                assert one["p"] == pytest.approx(float(B.tail_values([r[2]], [r[3]], [r[4]], tail)[0]), abs=1e-7)
            else:
                assert one["p"] in (0.0, 1.0)


def test_index_edges(spark):
    flat = spark.createDataFrame([(w, 5.0) for w in range(8)], "win int, value double")
    got = VOL.index_levels(flat, levels=None).collect()
    assert [r["pvi"] for r in got if r["vi"] is not None] == [0.5] * 4 and all(r["pvi"] == 0 for r in got if r["vi"] is None)
    bad = spark.createDataFrame([(0, 1.0), (1, 0.0), (2, -3.0), (3, 2.0)], "win int, value double")
    assert [r["ret"] for r in VOL.log_returns(bad).orderBy("win").collect()] == [None] * 4
    assert VOL.index_levels(flat.limit(1)).first()["pvi"] == 0.0 and VOL.index_levels(flat.limit(0)).count() == 0
    mu, s = VOL.fit_logistic(spark.createDataFrame([(float(math.log(p / (1 - p))),) for p in [i / 200 for i in range(1, 200)]], "vi double"), "mle")
    assert abs(mu) < 1e-6 and abs(s - 1) < 0.05


def test_empty_stream_and_null_text(spark):
    docs = spark.createDataFrame([(1, 0, None), (2, 0, ""), (3, 1, "see http://a.bc/d or me@x.org 42 Wörter words")], "doc_id long, win int, text string")
    assert sorted(r["feature"] for r in X.tokenize(docs).collect()) == ["see", "words", "wörter"]
    none = X.tokenize(docs.where("doc_id < 0"))
    index = spark.createDataFrame([(w, 1.0 + w % 3) for w in range(6)], "win int, value double")
    assert pipeline.run(none, index).events.count() == 0
    assert X.kept_features(none).count() == 0


def test_components_and_links(spark):
    nodes = spark.range(12).select(F.col("id"))
    edges = spark.createDataFrame([(i, i + 1) for i in range(7)] + [(9, 10)], "a long, b long")
    got = {r["id"]: r["component"] for r in connected(nodes, edges).collect()}
    assert [got[i] for i in range(12)] == [0] * 8 + [8, 9, 9, 11]
    groups = spark.createDataFrame([(1, 0, [1, 2]), (2, 0, [1, 3])], "win int, group_id int, topics array<int>")
    tops = spark.createDataFrame([(1, 0.4), (2, 0.1), (3, 0.5)], "topic_id int, objective double")
    assert chains.group_links(groups, tops).first()["similarity"] == pytest.approx(0.4)
    assert chains.group_links(groups, tops, weight="none").first()["similarity"] == pytest.approx(1 / 3)


def test_split_components_equal_global_greedy(spark, small):
    from indextrigger.plans.topics import greedy_topics
    import numpy as np

    _, _, influence, pairs, got = pipeline.impact_topics(V.order_stream(spark, small), V.order_index(spark, small))
    inf = {r["feature"]: r["influence"] for r in influence.collect()}
    names = sorted(inf)
    at = {w: i for i, w in enumerate(names)}
    jac, rho = np.zeros((len(names),) * 2), np.zeros((len(names),) * 2)
    for r in pairs.collect():
        a, b = at[r["f"]], at[r["g"]]
        jac[a, b] = jac[b, a] = r["jaccard"]
        rho[a, b] = rho[b, a] = r["rho"]
    whole = greedy_topics(names, jac, rho, np.array([inf[w] for w in names]), FLAGSHIP.topic)
    assert sorted(t["features"] for t in whole) == sorted(r["features"] for r in got.collect())
    again = topics.topic_objective(got.drop("objective", "influence"), pairs, influence).join(got.select("topic_id", F.col("objective").alias("own")), "topic_id")
    assert again.where("abs(objective - own) > 1e-9").count() == 0


def test_chain_invariants(spark, small):
    r = pipeline.run(V.order_stream(spark, small), V.order_index(spark, small))
    rows = r.chains.collect()
    by = {}
    for x in rows:
        by.setdefault(x["chain_id"], []).append(x)
    seeds = {}
    for own in by.values():
        wins = sorted({x["win"] for x in own})
        assert wins == list(range(wins[0], wins[-1] + 1)) and own[0]["score"] >= 0
        for x in own:
            assert seeds.setdefault((x["win"], x["group_id"]), x["seed_win"]) == x["seed_win"]
    assert r.events.where("score < -1e-12").count() == 0
    ranks = [x["score"] for x in r.events.orderBy("rank").collect()]
    assert ranks == sorted(ranks, reverse=True)


def test_planted_words_burst_where_planted(spark):
    big = "/root/testdata/sf0.01"
    plan = {20: ["thing", "ing"], 40: ["reed"]}
    found = {}
    for shuffled in (False, True):
        tokens = X.tokenize(V.planted_stream(spark, big, plan, shuffled))
        counts = B.window_counts(tokens)
        totals = B.window_totals(counts)
        p = B.burst_probability(counts, totals, B.expected_rate(counts, totals))
        truth = spark.createDataFrame([(w, k) for k, ws in plan.items() for w in ws], "feature string, win int")
        found[shuffled] = {r["metric"]: r["value"] for r in measures.planted_recall(p, truth).collect()}
    assert found[False]["recall"] == 1.0 and found[True]["recall"] < 1.0


def test_sketches_are_close(spark, small):
    exact = affinity.jaccard_pairs(V.order_stream(spark, small))
    for method, bound in (("minhash", 0.2), ("theta", 0.02)):
        got = {r["metric"]: r["value"] for r in measures.sketch_error(exact, affinity.jaccard_pairs(V.order_stream(spark, small), method, within=exact)).collect()}
        assert got["max_error"] < bound


def test_stream_restarts_and_alerts(spark, small, tmp_path):
    at = str(tmp_path / "state")
    first = online.drained(online.event_source(spark, small).select("event_id"), checkpoint=at).count()
    assert first == 1000 and online.drained(online.event_source(spark, small).select("event_id"), checkpoint=at).count() == 1000
    late = online.windowed_counts(online.event_source(spark, small)).columns
    assert late == ["win_start", "event_type", "n", "total_value"]
    src = tmp_path / "cells"
    for i, n in enumerate([2, 3, 2, 30]):
        spark.createDataFrame([("a", n, 100)], "feature string, n long, total long").coalesce(1).write.mode("append").parquet(str(src))
    cells = spark.readStream.schema("feature string, n long, total long").option("maxFilesPerTrigger", 1).parquet(str(src))
    assert {r["n"] for r in online.drained(online.online_alerts(cells)).collect()} >= {30}


def test_baselines_run(spark, small):
    found, pvi, influence, pairs, tops = pipeline.impact_topics(V.order_stream(spark, small), V.order_index(spark, small))
    runs = baselines.baseline_events(pairs, influence, found.p, pvi)
    assert runs.where("start_win > end_win").count() == 0
    assert baselines.correlated_keywords(found.p, V.order_index(spark, small), 5).count() == 5
    assert {r["metric"] for r in measures.event_quality(runs).collect()} >= {"mean_score", "negative_share"}
    assert events.rank_events(runs, 3).count() <= 3


def test_entry_without_the_training_data_folders(tmp_path):
    """A copy of the library without both folders imports, with and without the pipeline module."""
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.abspath(entry.__file__))
    at = tmp_path / "copy"
    shutil.copytree(root, at, ignore=shutil.ignore_patterns(".git", "llm", "__pycache__", "tests", "spark-warehouse"))
    ask = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()), any(k.startswith('op1_') or k == 'pipeline' for k in e.queries()))"
    for gone in ((), ("corpus_pipeline.py",)):
        for name in gone:
            (at / name).unlink()
        out = subprocess.run([sys.executable, "-c", ask], cwd=at, env=os.environ | {"PYTHONPATH": str(at)}, capture_output=True, text=True)
        assert out.returncode == 0 and out.stdout.split()[-1] == "False", out.stderr
        assert int(out.stdout.split()[-3]) == len(registry.QUERIES)


def test_ranks_need_no_dense_ids(spark):
    rows = [(None, "a"), (-5, "b"), (7, "c"), (7, "c"), (10**15, "d"), (3, None)]
    got = V.ranked(spark.createDataFrame(rows, "doc_id long, text string"), ["doc_id", "text"], "r").collect()
    assert sorted(x["r"] for x in got) == list(range(6))
    assert [x["doc_id"] for x in sorted(got, key=lambda x: x["r"])] == [None, -5, 3, 7, 7, 10**15]


def test_blocks_give_the_same_pairs(spark, small):
    p = registry.burst_table(spark, small, "session")
    one, many = (sorted((r["f"], r["g"], round(r["rho"], 9)) for r in affinity.temporal_pairs(p, False, n).collect()) for n in (10**6, 7))
    assert one == many and one


def test_components_lose_no_pair_that_topics_use(spark, small):
    tokens = staged(registry.STREAMS["session"](spark, small), "tokens")
    p = staged(registry.burst_table(spark, small, "session"), "bursts")
    whole = {(r["f"], r["g"]): (r["jaccard"], r["rho"]) for r in affinity.affinities(tokens, p).collect()}
    inside = {(r["f"], r["g"]): (r["jaccard"], r["rho"]) for r in affinity.component_affinities(tokens, p).collect()}
    assert set(inside) <= set(whole) and all(whole[k] == pytest.approx(v) for k, v in inside.items())
    assert {k for k, (j, r) in whole.items() if j * r > 0} <= set(inside)


def test_large_local_steps_are_refused(spark):
    rows = spark.range(30).select(F.lit(1).alias("run"))
    assert bounded(rows, "run", 30).count() == 30
    with pytest.raises(ValueError, match="max_local_rows"):
        bounded(rows, "run", 29)


def test_poisson_tail_of_large_means(spark):
    """Means beyond 745, where the first term of the running sum is 0, against sums of logarithms."""
    cells = [(0, 5, 36_000, 0.03), (1, 1_000, 36_000, 0.03), (2, 1_080, 36_000, 0.03), (3, 1_200, 36_000, 0.03), (4, 90_500, 3_000_000, 0.03), (5, 3, 100, 0.02), (6, 2_500, 36_000, 0.01)]
    df = spark.createDataFrame([("f", *c) for c in cells], "feature string, win int, n long, total long, pe double")
    for tail, more in (("strict", 0), ("inclusive", 1)):
        for win, n, total, pe in cells:
            one = df.where(F.col("win") == win)
            got = B.burst_probability(one.select("feature", "win", "n"), one.select("win", "total"), one.select("feature", "pe"), tail, approx="poisson").first()["p"]
            want = math.fsum(math.exp(k * math.log(total * pe) - total * pe - math.lgamma(k + 1)) for k in range(n + more))
            assert got == pytest.approx(min(want, 1.0), abs=1e-7)


@pytest.mark.parametrize("most", [1, 4, 1_024])
def test_tables_count_the_pairs_of_components(spark, monkeypatch, most):
    """Square tables, packed components and the join of wide ones against plain sets; blocks end inside documents."""
    monkeypatch.setattr(affinity, "GRAM_ROWS", 7)
    monkeypatch.setattr(affinity, "GRAM_DOCS", 3)
    r = random.Random(5)
    words = [f"w{i:02}" for i in range(17)]
    tokens = [(r.choice([None, *range(-3, 20)]), r.randrange(4), r.choice(words)) for _ in range(400)]
    of = {w: words[(0, 5, 8, 10, 12)[min(i // 4, 4)]] for i, w in enumerate(words)}
    held = {w: {d for d, _, x in tokens if x == w} for w in words}
    want = {}
    for f in words:
        for g in words:
            if f < g and of[f] == of[g] and (n := len((held[f] & held[g]) - {None})):
                want[f, g] = (n, len(held[f]), len(held[g]), n / (len(held[f]) + len(held[g]) - n))
    got = affinity.component_jaccard(spark.createDataFrame(tokens, "doc_id long, win int, feature string"), spark.createDataFrame(list(of.items()), "feature string, component string"), most)
    assert {(x["f"], x["g"]): tuple(x)[2:] for x in got.collect()} == want


def test_irregular_windows_are_found_without_trying_all(spark):
    """Windows across days, several in a day, gaps, borders, times outside and no time."""
    spans = [(0, "2024-01-01 10:00:00", "2024-01-01 10:00:30"), (1, "2024-01-01 10:00:30", "2024-01-03 00:00:00"), (2, "2024-01-05 00:00:00", "2024-01-05 00:00:01"), (3, "1969-12-30 00:00:00", "1969-12-31 12:00:00")]
    bounds = spark.createDataFrame(spans, "win int, start string, end string").select("win", F.to_timestamp("start").alias("start"), F.to_timestamp("end").alias("end"))
    want = {"2024-01-01 09:59:59": None, "2024-01-01 10:00:00": 0, "2024-01-01 10:00:30": 1, "2024-01-02 23:59:59": 1, "2024-01-03 00:00:00": None, "2024-01-05 00:00:00": 2, "2024-01-05 00:00:01": None, "1969-12-31 11:59:59": 3, None: None}
    rows = spark.createDataFrame([(t,) for t in want], "t string").withColumn("ts", F.to_timestamp("t"))
    found = V.assign_irregular(rows, bounds)
    assert {x["t"]: x["win"] for x in found.collect()} == want and found.count() == len(want)
    assert "filter(" not in found._jdf.queryExecution().toString().lower()


def test_streams_of_datasets_are_written_once(spark, small):
    """All queries of a dataset, with the index and without, read one written stream and one table of pairs."""
    from dataclasses import replace

    off = FLAGSHIP.but(topic=replace(FLAGSHIP.topic, influence="off"))
    on_, off_ = registry.topics_of(spark, small, "sessions"), registry.topics_of(spark, small, "sessions", off)
    assert on_[3] is off_[3] and on_[4] is not off_[4]
    scan = registry.tokens_of(spark, small, "sessions")._jdf.queryExecution().toString()
    assert "tokens-" in scan and "Generate" not in scan


def test_common_tokens_equal_stems_then_shares(spark):
    """Words dropped before documents are counted change nothing; null and repeated ids, shares on the bounds, texts with signs."""
    r = random.Random(3)
    words = ["walk", "walked", "walking", "rare", "rarely", "sky", "skies", "everywhere", "once"]
    texts = [" ".join(["everywhere", *r.choices(words[:7], k=r.randrange(6))]) for _ in range(38)] + ["once once once", "www. x@y.zz me@abc.de http://skies.xx/a sky"]
    rows = [(None if i % 13 == 5 else i // 2 if i % 5 == 0 else i, i % 3, t) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, win int, text string")
    plain = [X.URL, X.EMAIL, X.DIGITS]
    text = F.col("text")
    for pattern in plain:
        text = F.regexp_replace(text, pattern, " ")
    assert docs.where(~X.scrub(F.col("text")).eqNullSafe(text)).count() == 0
    for stemmed in (False, True):
        tokens = X.tokenize(docs)
        want = X.share_filter(X.stem_tokens(tokens) if stemmed else tokens, 0.05, 0.8)
        got = X.prepare_tokens(docs, stemmed=stemmed)
        assert sorted(map(str, got.collect())) == sorted(map(str, want.collect())) and got.count()
        plan = got._jdf.queryExecution().toString()
        assert "ArrowEvalPython" not in plan and "regexp" not in plan  # stems and words are written, not made again
    assert X.prepare_tokens(docs.limit(0), stemmed=True).count() == 0


def test_overlap_of_given_chains(spark):
    chains_ = [(1, [(1, 0), (2, 0), (3, 0)]), (2, [(2, 0), (3, 0), (4, 0), (5, 0), (6, 0)]), (3, [(1, 0), (0, 1), (2, 1)])]
    got = events.chain_overlap(spark.createDataFrame([(c, w, g) for c, gs in chains_ for w, g in gs], "chain_id int, win int, group_id int"))
    assert {(r["a"], r["b"]): (r["shared"], round(r["overlap"], 6)) for r in got.collect()} == {(1, 2): (2, 0.666667), (1, 3): (1, 0.333333)}


def test_worked_example(spark):
    got = topics.compare_partners(spark, "worker", [("union", 0.31, 0.25, 30.0), ("wage", 0.35, 0.10, 74.0)])
    assert {r["partner"]: (round(r["without_index"], 6), round(r["with_index"], 6)) for r in got.collect()} == {"union": (0.0775, 2.325), "wage": (0.035, 2.59)}


@pytest.mark.parametrize("name", ["chain_overlap", "worker_example"])
def test_examples_read_given_tables(spark, small, name):
    empty = {t: spark.read.parquet(f"{small}/{t}.parquet").limit(0) for t in ("orders", "lineitem", "part")}
    folder = f"{shared_folder(spark)}/no-orders"
    for t, df in empty.items():
        df.write.mode("overwrite").parquet(f"{folder}/{t}.parquet")
    assert registry.QUERIES[name](spark, small).count() > 0 and registry.QUERIES[name](spark, folder).count() == 0


@pytest.mark.parametrize("block, cells, sent", [(500_000, 2_000_000, 1_000_000), (7, 10, 0)])
def test_topic_cosines_by_products(spark, monkeypatch, block, cells, sent):
    """Square tables of whole windows and of small blocks against plain sums; words in two topics, tokens without a document."""
    for name, value in (("BLOCK_ROWS", block), ("DOT_CELLS", cells), ("BROADCAST_CELLS", sent)):
        monkeypatch.setattr(groups, name, value)
    r = random.Random(8)
    tokens = [(r.choice([None, *range(-2, 9)]), r.randrange(3), r.choice("abcdefg")) for _ in range(300)]
    tops = [(1, ["a", "b", "c"]), (2, ["c", "d"]), (3, ["e"]), (5, ["g", "f"])]
    rate = [(t, w, (t, w) not in {(2, 1), (3, 2)}) for t, _ in tops for w in range(4)]
    weight = {}
    for d, w, f in tokens:
        for t, words in tops:
            if f in words and (t, w, True) in rate:
                weight.setdefault((w, t), {}).setdefault(d, 0)
                weight[w, t][d] += 1 / len(words)
    norm = {k: math.sqrt(sum(x * x for x in v.values())) for k, v in weight.items()}
    want = {}
    for w, t in weight:
        for u in [u for v, u in weight if v == w and u >= t]:
            met = (weight[w, t].keys() & weight[w, u].keys()) - {None}
            if met:
                want[w, t, u] = sum(weight[w, t][d] * weight[w, u][d] for d in met) / norm[w, t] / norm[w, u]
    got = groups.topic_gram(spark.createDataFrame(tops, "topic_id int, features array<string>"), spark.createDataFrame(tokens, "doc_id long, win int, feature string"), spark.createDataFrame(rate, "topic_id int, win int, bursty boolean"))
    got = {(x["win"], x["t"], x["u"]): x["cosine"] for x in got.collect()}
    assert got == pytest.approx(want, abs=1e-12) and len(got) > 20


def test_windows_of_few_bytes_are_grouped_by_several_tasks(spark):
    gram = spark.createDataFrame([(w, t, t, 1.0) for w in range(40) for t in (1, 2)], "win int, t int, u int, cosine double")
    tasks = groups.group_topics(gram).groupBy(F.spark_partition_id().alias("task")).agg(F.count_distinct("win").alias("n")).collect()
    assert len(tasks) > 1 and sum(x["n"] for x in tasks) == 40


@pytest.mark.parametrize("rows", [0, 500_000])
def test_components_in_a_task_and_in_rounds(spark, monkeypatch, rows):
    """Both ways on words: loops, repeated edges, a null and ends that are no nodes."""
    monkeypatch.setattr(graph, "TASK_ROWS", rows)
    nodes = spark.createDataFrame([(x,) for x in ["e", "d", "c", "b", "a", "x", "z", "é", "c", None]], "id string")
    edges = spark.createDataFrame([("e", "d"), ("d", "c"), ("d", "c"), ("b", "b"), ("z", "é"), ("x", "gone"), ("gone", "a"), (None, "a"), ("b", None)], "a string, b string")
    got = connected(nodes, edges).collect()
    assert sorted(map(str, ((r["id"], r["component"]) for r in got))) == sorted(map(str, [("c", "c"), ("d", "c"), ("e", "c"), ("b", "b"), ("a", "a"), ("x", "x"), ("z", "z"), ("é", "z"), (None, None)]))
    assert connected(nodes.limit(0), edges).count() == 0


def test_datasets_are_compared_at_once(spark, small, monkeypatch):
    assert at_once(spark, [lambda i=i: spark.range(i).count() for i in (3, 1, 2)]) == [3, 1, 2] and at_once(spark, []) == []
    met = threading.Barrier(3)

    def measured(s, d, name, *more):
        met.wait(30)
        raise LookupError(name)

    monkeypatch.setattr(registry, "measured_of", measured)
    with pytest.raises(LookupError):
        registry.quality_comparison(spark, small)
