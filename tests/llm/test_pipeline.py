"""The pipeline stage by stage on small tables."""

import collections
import math
import re

import corpus_pipeline
from pyspark.sql import functions as F

from indextrigger.llm import cotraining, decontamination, ngram_join


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, small)
        if name != "sharding":
            assert out.columns == columns
        docs = spark.createDataFrame(out.collect(), out.schema)
        if name == "near_duplicates":
            assert docs.count() == docs.select("doc_id").distinct().count() == docs.select("text").distinct().count()
        if name == "decontamination":
            again = decontamination.contamination(docs, spark.read.parquet(f"{small}/benchmark.parquet"))
            assert again.where("contaminated").count() == 0
    sizes = [r["n"] for r in docs.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()]
    assert max(sizes) - min(sizes) <= 1


def test_edges(spark, small):
    schema = "doc_id long, text string, lang string, source string, n_chars long, rank int"
    rows = [(1, "a b c d e f g", "en", "s", 1, 1), (1, "a b c d e f g", "en", "s", 1, 1), (2, None, None, None, None, None), (None, "x", "en", "s", 1, 1), (3, "", "en", "t", 0, 0)]
    docs = spark.createDataFrame(rows, schema)
    got = corpus_pipeline.near_duplicate_stage(spark, docs, small)
    assert got.columns == docs.columns and sorted((r["doc_id"] or 0) for r in got.collect()) == [0, 1, 2, 3]
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), small).count() == 0


def test_rows_that_share_an_id(spark, small):
    texts = ["a b c d e f g", "quite another text that stands under one id", "a b c d e f g", "a third text of the same id as before", "", None, ""]
    rows = [(5, texts[0], "en", "s"), (5, texts[1], "en", "s"), (1, texts[2], "en", "s"), (5, texts[3], "en", "t"), (5, texts[3], "en", "s"), (5, "", "en", "s"), (5, None, None, None), (5, "", "en", "s"), (7, texts[1], "en", "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = [tuple(r) for r in corpus_pipeline.near_duplicate_stage(spark, docs, small).collect()]
    want = [rows[2], rows[1], rows[4], rows[5], rows[6]]
    assert sorted(got, key=str) == sorted(want, key=str)
    links = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in ngram_join.jaccard_components(docs).collect())
    assert links == sorted([(5, 3, 1), (5, 4, 5), (1, 3, 1), (5, 5, 5), (5, 5, 5), (5, 0, 5), (5, 0, 5), (5, 0, 5), (7, 4, 5)])


LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
SPACED, ALNUM = re.compile("[^\x20\x09-\x0d]+"), re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def local(spark, small, name):
    return [r.asDict() for r in spark.read.parquet(f"{small}/{name}.parquet").collect()]


def ids(df):
    return sorted(r["doc_id"] for r in df.select("doc_id").collect())


def test_near_duplicate_stage_equals_brute_force(spark, small):
    rows = [r for r in local(spark, small, "documents")]
    texts = {r["doc_id"]: r["text"] for r in rows}
    extra = {9000 + i: " ".join(w if j % 23 else f"{w}{i}" for j, w in enumerate((texts[i] or "x").split(" "))) for i in range(12)}
    docs = spark.read.parquet(f"{small}/documents.parquet")
    more = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in extra.items()], docs.schema)
    texts |= extra
    sets = {}
    for i, t in texts.items():
        w = SPACED.findall((t or "").translate(LOWER))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    order = sorted(sets)
    for n, a in enumerate(order):
        for b in order[n + 1 :]:
            small_, large = sorted((len(sets[a]), len(sets[b])))
            if small_ and 100 * small_ >= 80 * large and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert ids(corpus_pipeline.near_duplicate_stage(spark, docs.unionByName(more), small)) == [i for i in order if find(i) == i]


def test_decontamination_stage_equals_brute_force(spark, small):
    windows = set()
    for r in local(spark, small, "benchmark"):
        w = ALNUM.findall((r["text"] or "").translate(LOWER))
        n = min(10, len(w))
        windows |= {tuple(w[k : k + n]) for k in range(len(w) - n + 1) if n}
    clean = []
    for r in local(spark, small, "documents"):
        w = ALNUM.findall((r["text"] or "").translate(LOWER))
        if not any(tuple(w[k : k + n]) in windows for n in {len(x) for x in windows} for k in range(len(w) - n + 1)):
            clean.append(r["doc_id"])
    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert ids(corpus_pipeline.decontamination_stage(spark, docs, small)) == sorted(clean)
    twice = docs.unionByName(docs).withColumn("items", F.lit("clash"))
    got = corpus_pipeline.decontamination_stage(spark, twice, small)
    assert ids(got) == sorted(clean * 2) and got.columns == twice.columns


def test_mixing_stage_equals_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").withColumn("rate", F.lit("clash"))
    size, own = collections.Counter(), {}
    for r in local(spark, small, "documents"):
        own[r["doc_id"]] = r["source"], len(SPACED.findall(r["text"] or ""))
        size[r["source"]] += own[r["doc_id"]][1]
    order = sorted(size, key=lambda x: (x is None, x or ""))
    weight = {x: (5, 2, 1)[i % 3] for i, x in enumerate(order)}
    full, total = set(), 1.5 * sum(size.values())
    while True:
        open_ = [x for x in order if x not in full]
        share = {x: (total - sum(2 * size[f] for f in full)) * weight[x] / sum(weight[y] for y in open_) for x in open_}
        over = {x for x in open_ if share[x] > 2 * size[x]}
        if not over:
            break
        full |= over
    rate = {x: 2.0 if x in full else share[x] / size[x] for x in order}
    first, again = (collections.Counter(ids(corpus_pipeline.mixing_stage(spark, docs, small))) for _ in range(2))
    assert first == again
    for i, (source, _) in own.items():
        assert math.floor(rate[source] + 1e-9) <= first[i] <= math.ceil(rate[source] - 1e-9)
    for x in order:
        taken = sum(n * first[i] for i, (source, n) in own.items() if source == x)
        largest = max(n for source, n in own.values() if source == x)
        assert abs(taken - rate[x] * size[x]) <= 4 * math.sqrt(sum(n * n for source, n in own.values() if source == x)) / 2 + largest


def test_sharding_stage_equals_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    got = [r.asDict() for r in corpus_pipeline.sharding_stage(spark, docs, small).collect()]
    assert sorted((r["doc_id"], r["text"] or "") for r in got) == sorted((r["doc_id"], r["text"] or "") for r in local(spark, small, "documents"))
    line = sorted(got, key=lambda r: (r["shard"], r["slot"]))
    assert [r["curve"] for r in line] == sorted(r["curve"] for r in got)
    size, rest = divmod(len(got), len({r["shard"] for r in got}))
    counts = collections.Counter(r["shard"] for r in got)
    assert sorted(counts.values(), reverse=True) == [size + 1] * rest + [size] * (len(counts) - rest)


def test_quality_stage_on_labels_it_did_not_see(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    fold = F.pmod(F.xxhash64(F.lit("fold"), "doc_id"), F.lit(3)) == 0
    model = cotraining.fit(docs, labels.where(~fold))
    rows = cotraining.scored(docs.unionByName(docs), model).join(labels.where(fold), "doc_id").collect()
    clean = [r["kept"] for r in rows if r["quality"] == 1 and not r["toxic"]]
    junk = [not r["kept"] for r in rows if r["quality"] == 0]
    assert sum(clean) >= 0.95 * len(clean) and sum(junk) >= 0.9 * len(junk)
