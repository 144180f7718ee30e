"""Each operator against a brute-force version or a round trip, with nulls, empty and long texts, ties,
repeated rows, empty tables and extra columns."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from indextrigger.llm import chat_format as chat
from indextrigger.llm import chunk_dedup, cotraining, decontamination, hilbert_sharding, ngram_join, prefix_tokens, quality_rules, source_mixing, suffix_repeats
from indextrigger.llm import kernels as K

LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
SPACED = re.compile("[^\x20\x09-\x0d]+")
ALNUM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def rng(seed):
    return random.Random(seed)


def vocabulary(r, n=300):
    return ["".join(r.choice("abcdeéß") for _ in range(r.randint(1, 7))) for _ in range(n)]


def corpus(seed=1, n=60):
    """Texts with copies, near copies, shared passages, nulls, blanks and one long text."""
    r = rng(seed)
    words = vocabulary(r)
    make = lambda k: " ".join(r.choice(words) for _ in range(k))
    bases = [make(r.randint(20, 160)) for _ in range(8)]
    out = []
    for i in range(n):
        text = r.choice(bases) if i % 2 else make(r.randint(1, 150))
        if i % 4 == 1:
            parts = text.split(" ")
            parts[r.randrange(len(parts))] = "Changed"
            text = " ".join(parts)
        out.append((i, text, r.choice(["en", "de", None]), r.choice(["a", "b", "c", None]), len(text)))
    out += [(n, None, None, None, None), (n + 1, "", "en", "a", 0), (n + 2, " \n\t ", "en", "b", 4), (n + 3, make(9000), "en", "a", 1), (n + 4, "one two", "fr", "b", 7), (n + 5, "one two", "fr", "b", 7)]
    return out


def test_mixing(spark):
    rows = corpus() + [(500, "zz " * 50, "en", "tiny", 1)]
    df = spark.createDataFrame(rows, DOCS).withColumn("target", F.lit("clash"))
    got = source_mixing.mixed_sources(df).collect()
    assert len(got) == len(rows)
    size = collections.Counter()
    for r in rows:
        size[r[3]] += len(SPACED.findall(r[1] or ""))
    order = sorted(size, key=lambda x: (x is None, x or ""))
    weight = {x: (5, 2, 1)[i % 3] for i, x in enumerate(order)}
    target, full, left = {}, set(), 1.5 * sum(size.values())
    while True:
        open_ = [x for x in order if x not in full]
        share = {x: (left - sum(2 * size[f] for f in full)) * weight[x] / sum(weight[y] for y in open_) for x in open_}
        over = {x for x in open_ if share[x] > 2 * size[x]}
        if not over:
            target = share | {f: 2 * size[f] for f in full}
            break
        full |= over
    for r in got:
        assert r["source_size"] == size[r["source"]] and r["target"] == pytest.approx(target[r["source"]])
        assert 0 <= r["copies"] <= 2 and r["rate"] - 1 < r["copies"] < r["rate"] + 1
    assert source_mixing.repeated(source_mixing.mixed_sources(df)).count() == sum(r["copies"] for r in got)
    assert source_mixing.mixed_sources(df.limit(0)).count() == 0


def test_hilbert_visits_neighbours(spark):
    bits = 3
    cells = spark.range(1 << (3 * bits)).select((F.col("id") % 8).cast("int").alias("x"), (F.floor(F.col("id") / 8) % 8).cast("int").alias("y"), F.floor(F.col("id") / 64).cast("int").alias("z"))
    got = cells.withColumn("h", hilbert_sharding.hilbert_index([F.col(c) for c in "xyz"], bits)).orderBy("h").collect()
    assert [r["h"] for r in got] == list(range(512))
    assert all(abs(a["x"] - b["x"]) + abs(a["y"] - b["y"]) + abs(a["z"] - b["z"]) == 1 for a, b in zip(got, got[1:]))


def test_sharding(spark):
    rows = corpus() + [corpus()[3]] * 3 + [(None, "x", "en", "a", 1)]
    got = hilbert_sharding.sharded(spark.createDataFrame(rows, DOCS).withColumn("slot", F.lit(1)), 7).collect()
    assert len(got) == len(rows)
    slots = collections.defaultdict(list)
    for r in got:
        raw = (r["text"] or "").encode()
        assert r["size"] == len(raw) + 8 and r["text_crc32"] == zlib.crc32(raw)
        slots[r["shard"]].append((r["slot"], r["curve"]))
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    line = [c for k in sorted(slots) for s, c in sorted(slots[k])]
    assert all(sorted(s for s, _ in v) == list(range(len(v))) for v in slots.values()) and line == sorted(line)
    assert hilbert_sharding.sharded(spark.createDataFrame([], DOCS)).count() == 0


def test_sharding_moves_rows_once(spark):
    rows = [(i, f"t {i * 7 % 50}", "en", "ab"[i % 2], 1) for i in range(200)]
    out = hilbert_sharding.sharded(spark.createDataFrame(rows, DOCS).repartition(5), 7)
    assert "row_number" not in out._jdf.queryExecution().executedPlan().toString()  # a window would shuffle the texts again
    line = [(r["curve"], r["text_crc32"], r["text"], r["doc_id"]) for r in sorted(out.collect(), key=lambda r: (r["shard"], r["slot"]))]
    assert line == sorted(line, key=lambda x: x[:2]) and len({x[3] for x in line}) == 200
    texts = [x[2] for x in line]
    assert all(a == b for a, b in zip(texts, sorted(texts, key=texts.index)))  # equal texts stand together


def test_hilbert_table(spark):
    digits, after = hilbert_sharding.curve_steps(3)
    assert len(digits) == len(after) == 8 * (max(after) + 1)
    assert all(sorted(digits[i : i + 8]) == list(range(8)) for i in range(0, len(digits), 8))


@pytest.mark.parametrize("percent", [90, 67])
def test_short_prefixes_lose_no_pair(spark, percent):
    r, pairs = np.random.default_rng(percent), []
    for i in range(300):
        a = r.integers(-(1 << 63), 1 << 63, int(r.integers(1, 400)))
        a[: len(a) // 3] = (a[: len(a) // 3] >> 60 << 60) | np.arange(len(a) // 3)  # many alike in their upper bits
        b = r.integers(-(1 << 63), 1 << 63, len(a)) if i % 5 == 0 else np.concatenate([a[r.random(len(a)) > r.random() / 3], r.integers(-(1 << 63), 1 << 63, int(r.integers(0, 20)))])
        sets = [np.unique(x) for x in (a, b)]
        if min(map(len, sets)):
            alike = 100 * len(np.intersect1d(*sets)) >= percent * len(np.union1d(*sets))
            pairs.append((alike, i % 5 == 0 and len(a) > 50, *(v for x in sets for v in (x[: ngram_join.prefix_size(len(x), percent, 2)].tolist(), len(x)))))
    df = spark.createDataFrame(pairs, "alike boolean, foreign boolean, a array<long>, n_a long, b array<long>, n_b long")
    found = [x for s in "ab" for x in (*ngram_join.brief(F.col(s), F.col(f"n_{s}")), F.col(f"n_{s}"))]
    got = df.select("alike", "foreign", ngram_join.leads_fit(*found, percent).alias("fits")).collect()
    assert all(x["fits"] for x in got if x["alike"]) and sum(x["alike"] for x in got) > 20
    assert not any(x["fits"] for x in got if x["foreign"])


def test_pairs_are_cut_by_size_before_prefixes_move(spark):
    rows = [(i, " ".join(f"w{j}" for j in range(10 + 30 * i))) for i in range(4)] + [(4, " ".join(f"w{j}" for j in range(101)))]
    named = spark.createDataFrame(rows, "doc_id long, text string")
    nodes = ngram_join.sketches(named, 3, 90, True).select(F.col("doc_id").alias("node"), F.col("n_shingles").alias("n"), "lead")
    scratch = ngram_join.Scratch(spark)
    joined = ngram_join._Join(named, nodes, 3, 90, 32, scratch)
    pairs = spark.createDataFrame([(a, b) for a in range(5) for b in range(a)], "a long, b long")
    near = joined.near(pairs, "t")
    assert [tuple(x) for x in near.collect()] == [(4, 3)]
    assert spark.read.parquet(*scratch.paths["t-fit"]).count() == 1


def brute_counts(text):
    words = SPACED.findall(text or "")
    seen, covered, lines, dup = collections.defaultdict(list), set(), set(), 0
    for i in range(len(words) - 2):
        seen[tuple(words[i : i + 3])].append(i)
    for at in seen.values():
        if len(at) > 1:
            covered |= {j for i in at for j in (i, i + 1, i + 2)}
    for line in (text or "").split("\n"):
        if SPACED.search(line):
            dup += line in lines
            lines.add(line)
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), dup, len(covered)


def test_rule_counts(spark):
    texts = [r[1] for r in corpus()] + ["a b c a b c", "x x x x x", "l\nl\nl\n\n \n", "\n\n", "#*$%&|<> é é", "a a", "w " * 400 + "z", "q\r\nq\r\n"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").withColumn("n_words", F.lit("clash"))
    for r in quality_rules.with_counts(df).collect():
        assert tuple(r[c] for c in quality_rules.COUNTS) == brute_counts(texts[r["doc_id"]]), texts[r["doc_id"]][:40]
    assert quality_rules.with_counts(df.limit(0)).count() == 0


def test_rules_learn_a_planted_rule(spark):
    r = rng(4)
    words = vocabulary(r)
    docs, labels = [], []
    for i in range(400):
        bad = i % 5 == 0
        docs.append((i, " ".join(r.choice(words) + ("##" if bad else "") for _ in range(80))))
        labels.append((i, 0 if bad else 1))
    d, m = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels + [(1, None), (None, 0)], "doc_id long, quality int")
    rules = quality_rules.learn_rules(quality_rules.labelled_sample(d, m))
    kept = {x["doc_id"]: x["kept"] for x in quality_rules.judged(d, rules).collect()}
    assert rules.rules and all(kept[i] == (i % 5 != 0) for i in kept)
    assert quality_rules.learn_rules(quality_rules.labelled_sample(d, m.limit(0))).rules == ()


def test_cotraining_held_out(spark):
    r = rng(6)
    words = vocabulary(r)
    docs, labels = [], []
    for i in range(900):
        toxic, junk = i % 7 == 0, i % 5 == 0
        parts = [r.choice(words) + ("***" if junk else "") for _ in range(r.randint(30, 120))]
        if toxic:
            parts[r.randrange(len(parts))] = r.choice(["vilest", "foulest"])
        docs.append((i, " ".join(parts), "en", f"s{i % 3}", 0))
        if i % 2:
            labels.append((i, 0 if junk else 1, int(toxic)))
    docs += [(5000, None, None, None, None), (5001, "", "en", "s", 0)]
    df = spark.createDataFrame(docs, DOCS)
    model = cotraining.fit(df, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"))
    got = {x["doc_id"]: x["kept"] for x in cotraining.scored(df.withColumn("kept", F.lit(0)), model).collect()}
    held = [i for i in range(900) if i % 2 == 0]
    assert sum(got[i] == (i % 7 != 0 and i % 5 != 0) for i in held) / len(held) > 0.95
    assert len(got) == len(docs)
    none = cotraining.fit(df, spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert all(x["kept"] for x in cotraining.scored(df, none).collect())


def test_chat_round_trip(spark):
    r = rng(2)
    pieces = ["\\", "<|turn|>", "<|", "|>", "<|end|>", "<|endoftext|>", "\n", " ", "é日", "a", "𝔘", "\\\\"]
    rows = [(c, t, r.choice(["user", "assistant", "sys<|says|>", None]), r.choice([None, *["".join(r.choice(pieces) for _ in range(r.randint(0, 9))) for _ in range(4)]]), 1) for c in [*range(40), None] for t in (0, 1, 1, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, formatted int")
    got = {x["conv_id"]: x for x in chat.digests(chat.formatted(df)).collect()}
    order = lambda x: (x[1] is not None, x[1] or 0, x[2] or "", x[3] or "")
    for c in [*range(40), None]:
        turns = [(x[2] or "", x[3] or "") for x in sorted((x for x in rows if x[0] == c), key=order)]
        loss = "".join(t for role, t in turns if role == "assistant")
        whole = "".join(f"{a}\n{b}\n" for a, b in turns)
        assert (got[c]["n_turns"], got[c]["loss_chars"]) == (len(turns), len(loss))
        assert got[c]["turns_sha256"] == hashlib.sha256(whole.encode()).hexdigest() and got[c]["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()
    assert chat.formatted(df.limit(0)).count() == 0


def test_token_counts_equal_the_library(spark):
    from tokenizers import Tokenizer

    own = Tokenizer.from_file(prefix_tokens.vocabulary_path())
    count = lambda t: len(own.encode(t, add_special_tokens=False).ids)
    r = rng(3)
    pieces = ["'ll", " ", "  ", "\n", "é", "日本", "a", "the", " 12", "²", "½", "<|endoftext|>", "!", "'", "s", "re", " \t", "𝔘", "<|endo"]
    texts = ["".join(r.choice(pieces) for _ in range(r.randint(0, 14))) for _ in range(200)] + [x[1] for x in corpus()]
    df = spark.createDataFrame(list(enumerate(texts)), "n_tokens long, text string")
    for x in prefix_tokens.token_counts(df.withColumnRenamed("n_tokens", "id"), limit=5, budget=4).collect():
        text = texts[x["id"]] or ""
        assert (x["n_bytes"], x["n_tokens"], x["over_limit"]) == (len(text.encode()), count(text), count(text) > 5)
        assert count(text[: x["budget_chars"]]) <= 4
    held = prefix_tokens.counter(prefix_tokens.vocabulary_path())
    for text in texts[:80]:
        assert [held.table(text).tokens(k) for k in range(len(text) + 1)] == [count(text[:k]) for k in range(len(text) + 1)]


@pytest.mark.parametrize("block", [1 << 20, 30])
def test_decontamination(spark, block):
    r = rng(5)
    words = vocabulary(r, 40)
    items = [(i, " ".join(r.choice(words) for _ in range(k))) for i, k in enumerate([12, 30, 10, 3, 1, 0, 9])] + [(9, None), (1, "another text of the very same item with more than ten words in it")]
    docs = [(i, (" ".join(r.choice(words) for _ in range(30)) + ("; " + (items[i % 7][1] or "").upper() if i % 3 == 0 else ""))) for i in range(60)] + [(100, None), (101, ""), (102, items[1][1])]
    got = decontamination.contamination(spark.createDataFrame(docs, "doc_id long, text string").withColumn("items", F.lit(1)), spark.createDataFrame(items, "item_id long, text string"), block).collect()
    windows = collections.defaultdict(set)
    for i, t in items:
        w = ALNUM.findall((t or "").translate(LOWER))
        n = min(10, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows[tuple(w[k : k + n])].add(str(i))
    for x in got:
        w, hit, found = ALNUM.findall((dict(docs)[x["doc_id"]] or "").translate(LOWER)), set(), set()
        for n in {len(k) for k in windows}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    found |= windows[tuple(w[k : k + n])]
                    hit |= set(range(k, k + n))
        assert (x["n_words"], x["n_hit"], x["items"], x["contaminated"]) == (len(w), len(hit), sorted(found), bool(hit))


@pytest.mark.parametrize("rare,crowd", [(8, 32), (1, 1)])
@pytest.mark.parametrize("width,percent", [(3, 90), (5, 80)])
def test_ngram_join(spark, monkeypatch, rare, crowd, width, percent):
    monkeypatch.setattr(ngram_join, "BROADCAST_IDS", 0 if rare == 1 else 1000)
    r = rng(8)
    words = vocabulary(r)
    base = [[r.choice(words) for _ in range(r.randint(3, 90))] for _ in range(6)]
    docs = []
    for i in range(90):
        parts = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 1, 2, 3, 5])):
            parts[r.randrange(len(parts))] = r.choice(words)
        docs.append((i * 3, (" " if i % 2 else "\n").join(parts).upper() if i % 5 == 0 else " ".join(parts)))
    docs += [(1000, None), (1001, ""), (1002, "  "), (1003, "one"), (1004, "ONE"), (None, docs[0][1])]
    got = {x["doc_id"]: x for x in ngram_join.jaccard_components(spark.createDataFrame(docs, "doc_id long, text string").withColumn("node", F.lit(1)), width, percent, rare, crowd).collect()}
    sets = {}
    for i, t in docs:
        w = SPACED.findall((t or "").translate(LOWER))
        sets[i] = {tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set()
    ids = [i for i, _ in docs if i is not None]
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert {i: got[i]["component_id"] for i in ids} == {i: find(i) for i in ids}
    assert all(got[i]["n_shingles"] == len(sets[i]) for i in sets)


def test_components_on_a_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 90), (90, 95)], "a long, b long")
    got = {x["node"]: x["component"] for x in ngram_join.components(links).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[100] == got[95] == got[90] == 90


def brute_repeats(texts):
    count = collections.Counter()
    for t in texts:
        b = (t or "").encode()
        count.update(b[p : p + 200] for p in range(len(b) - 199))
    out = []
    for t in texts:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - 199):
            if count[b[p : p + 200]] > 1:
                gone[p : p + 200] = b"\1" * 200
        runs = sum(1 for q in range(len(b)) if gone[q] and (q == 0 or not gone[q - 1]))
        out.append((len(b), sum(gone), runs, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()))
    return out


@pytest.mark.parametrize("classes", [8192, 1])
def test_suffix_repeats(spark, classes):
    r = rng(9)
    base = ["".join(r.choice("abcé \n") for _ in range(r.randint(0, 700))) for _ in range(15)]
    texts = []
    for _ in range(40):
        t = r.choice(base)
        if r.random() < 0.6:
            p = r.randint(0, len(t))
            t = t[:p] + r.choice(["x", "yy", r.choice(base)]) + t[p:]
        texts.append(r.choice([t, t[r.randint(0, len(t)) :], "ab" * r.randint(90, 300) if r.random() < 0.3 else t]))
    texts += [None, "", "a" * 199, "b" * 200, "c" * 201]
    got = suffix_repeats.without_repeats(spark.createDataFrame([(i if i % 9 else None, t) for i, t in enumerate(texts)], "doc_id long, text string").withColumn("key", F.lit(1)), bucket_classes=classes).collect()
    assert sorted((x["n_bytes"], x["n_removed"], x["n_spans"], x["kept_sha256"]) for x in got) == sorted(brute_repeats(texts))


def test_long_document_blocks():
    """The blocks of a long document hold every string once, under the gram that it has in the whole document."""
    data = np.frombuffer(("".join(rng(1).choice("ab ") for _ in range(6000))).encode(), np.uint8)
    whole = np.array([0, len(data)])

    def strings(parts):
        out = []
        for part, borders, shift in parts:
            _, first, counts, ahead, grams, _ = suffix_repeats.intervals(part, borders, 200)
            out += [(shift + f + k, shift + f + h, int(g)) for f, c, h, g in zip(first, counts, ahead, grams) for k in range(c)]
        return sorted(out)

    blocks = list(suffix_repeats._blocks(data, whole, 200, 2000, 1000))
    assert len(blocks) == 6 and strings(blocks) == strings([(data, whole, 0)])
    assert [x[0] for x in strings(blocks)] == list(range(len(data) - 199))


@pytest.mark.parametrize("percent", [50, 66])
def test_jaccard_below_two_thirds(spark, percent):
    r = rng(17)
    docs = [(i, " ".join(r.sample("abcdefg", r.randint(1, 4)))) for i in range(40)]
    docs += [(100, "x z"), (101, "x y z"), (102, "v"), (103, "v w")] + [(200 + i, " ".join([c, *(f"u{i}{j}" for j in range(9))])) for i, c in enumerate("xzv" * 10)]
    sets = {i: set(t.split()) for i, t in docs}
    root = {i: i for i in sets}
    for _ in sets:
        for i, a in sets.items():
            for j, b in sets.items():
                if 100 * len(a & b) >= percent * len(a | b):
                    root[i] = root[j] = min(root[i], root[j])
    for rare, crowd in ((8, 32), (2, 3)):
        got = ngram_join.jaccard_components(spark.createDataFrame(docs, "doc_id long, text string"), 1, percent, rare, crowd).collect()
        assert {x["doc_id"]: x["component_id"] for x in got} == root


def test_chunk_dedup(spark):
    r = rng(3)
    words = vocabulary(r, 5000)
    make = lambda n: " ".join(r.choice(words) + r.choice("xyz") for _ in range(n))
    passages = [make(60) for _ in range(20)]
    docs, holders = [], collections.defaultdict(list)
    for i in range(160):
        t = make(r.randint(60, 200))
        if i % 4 == 0:
            k = r.randrange(20)
            p = r.randint(0, len(t))
            t = f"{t[:p]} {passages[k]} {t[p:]}"
            holders[k].append(i)
        docs.append((i, t))
    docs += [(900, docs[1][1]), (901, None), (902, "")]
    got = {x["doc_id"]: x for x in chunk_dedup.deduplicated(spark.createDataFrame(docs, "doc_id long, text string").withColumn("own", F.lit(1))).collect()}
    later = {i for h in holders.values() for i in h[1:]}
    assert all(got[i]["n_removed"] >= 100 for i in later)
    assert all(got[i]["n_removed"] == 0 and got[i]["text"] == dict(docs)[i] for i in range(160) if i not in later)
    assert got[900]["text"] == "" and got[901]["text"] is None and got[902]["text"] == ""


def test_chunk_dedup_cuts_short_passages_and_short_copies(spark):
    r = rng(11)
    passages = [" ".join("".join(r.choice("abcdeé") for _ in range(r.randint(1, 3))) for _ in range(51)) for _ in range(60)]
    passages += [" ".join(r.choice("abcdefgh") for _ in range(51)) for _ in range(20)]  # 101 bytes
    docs = []
    for k, p in enumerate(passages):
        for copy in range(2):
            ends = ["".join(r.choice("klmnopqr ") for _ in range(r.randint(40, 150))) for _ in range(2)]
            docs.append((2 * k + copy, f"{ends[0]}{'sS'[copy]} {p} {'tT'[copy]}{ends[1]}"))
    short = ["x", "Kurz – ja", "forty bytes that are here a second time.", "z" * 90, "w" * 32 + "ß" * 31]
    docs += [(1000 + i, short[i % 5]) for i in range(15)] + [(None, "null id, once"), (None, "null id, twice"), (7000, "null id, twice"), (7000, "null id, twice")]
    got = {x["doc_id"]: x for x in chunk_dedup.deduplicated(spark.createDataFrame(docs[: len(docs) - 4], "doc_id long, text string")).collect()}
    for k, p in enumerate(passages):
        assert got[2 * k]["n_removed"] == 0
        text = docs[2 * k + 1][1]
        assert got[2 * k + 1]["text"] == text.replace(f" {p} ", ""), k
    for i in range(15):
        assert got[1000 + i]["text"] == ("" if i >= 5 else short[i])
        assert got[1000 + i]["n_removed"] == (len(short[i % 5].encode()) if i >= 5 else 0)
    odd = chunk_dedup.deduplicated(spark.createDataFrame(docs[-4:], "doc_id long, text string")).collect()
    assert sorted((x["doc_id"] or 0, x["text"]) for x in odd) == [(0, "null id, once"), (0, "null id, twice"), (7000, ""), (7000, "")]


def test_chunks_resist_insertions():
    data = "".join(rng(5).choice("abcdefgh ") for _ in range(4000)).encode()
    cut = lambda b: {b[a:e] for a, e in zip([0, *chunk_dedup.chunk_ends(np.frombuffer(b, np.uint8), np.array([0, len(b)]))[0][:-1]], chunk_dedup.chunk_ends(np.frombuffer(b, np.uint8), np.array([0, len(b)]))[0])}
    a, b = cut(data), cut(data[:1000] + b"inserted" + data[1000:])
    assert len(a - b) <= 4


def test_word_kernel_matches_patterns():
    texts = ["", "A b", "x" * 5, "é-ü 12", " lead", "trail ", "Same same"]
    raw = [t.encode() for t in texts]
    offsets = np.cumsum([0, *map(len, raw)])
    for kept, pattern in ((K.SPACED, SPACED), (K.ALNUM, ALNUM)):
        starts, ends, hashes, bounds = K.words(np.frombuffer(b"".join(raw), np.uint8), offsets, K.byte_table(kept, lower=True))
        want = [pattern.findall(t.translate(LOWER)) for t in texts]
        assert list(np.diff(bounds)) == [len(w) for w in want]
        flat = [w for ws in want for w in ws]
        assert len({(w, int(h)) for w, h in zip(flat, hashes)}) == len(set(flat)) == len(set(map(int, hashes)))


def thue_morse(letters, n=1024):
    return "".join(letters[bin(i).count("1") % 2] for i in range(n))


def test_words_that_defeat_sums_of_powers_stay_apart(spark):
    """Two words of 1,024 letters that any polynomial hash modulo 2**64 takes for one."""
    pair = [thue_morse("ab"), thue_morse("ba")]
    raw = "".join(pair).encode()
    data = np.frombuffer(raw, np.uint8)
    spans = np.array([0, 1024]), np.array([1024, 2048])
    for found in (K.slice_hashes(data, *spans), K.digests(data, *spans), K.window_hashes(data, 1024)[spans[0]], K.grams(data[:1024].astype(np.uint64), 512)[:2]):
        assert found[0] != found[1]
    docs = spark.createDataFrame(list(enumerate(pair, 1)), "doc_id long, text string")
    assert {x["doc_id"]: x["component_id"] for x in ngram_join.jaccard_components(docs, 3, 90).collect()} == {1: 1, 2: 2}
    got = sorted((x["n_bytes"], x["n_removed"], x["n_spans"], x["kept_sha256"]) for x in suffix_repeats.without_repeats(docs).collect())
    assert got == sorted(brute_repeats(pair))
    hashes = [x["hash"] for x in chunk_dedup.chunk_rows(docs, ["doc_id"]).where("at = 0").collect()]
    assert hashes[0] != hashes[1]


@pytest.mark.parametrize("width", [32, 75, 200, 333])
def test_suffix_refinement_of_any_width(width):
    r = rng(width)
    parts = ["".join(r.choice("ab") for _ in range(60)) for _ in range(6)]
    data = np.frombuffer("".join(r.choice(parts)[r.randrange(40) :] for _ in range(200)).encode(), np.uint8)
    starts = np.arange(len(data) - width + 1)
    raw = data.tobytes()
    count = collections.Counter(raw[p : p + width] for p in starts)
    assert suffix_repeats.refined(data, starts, width).tolist() == [count[raw[p : p + width]] > 1 for p in starts]


def test_benchmark_of_tens_of_megabytes_stays_small():
    r = rng(12)
    items = [(str(i), " ".join(f"w{r.randrange(10**6)}" for _ in range(1000))) for i in range(1000)]
    held = decontamination.Prints(items)
    assert held.nbytes() < 48 * 1_000_000 and len(held.grams) < 0.36 * 1_000_000


def test_empty_benchmark_and_repeated_documents(spark):
    docs = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (None, None)], "doc_id long, text string")
    none = decontamination.contamination(docs, spark.createDataFrame([], "item_id long, text string")).collect()
    assert [x["contaminated"] for x in none] == [False] * 3
    some = decontamination.contamination(docs, spark.createDataFrame([(4, "B C"), (5, None)], "item_id long, text string")).collect()
    assert sorted((x["n_words"], x["n_hit"], x["items"]) for x in some) == [(0, 0, []), (3, 2, ["4"]), (3, 2, ["4"])]


def test_edges_of_the_text_operators(spark):
    """Empty tables, null ids, repeated rows and very long texts, conversations included."""
    r = rng(21)
    long_text = "".join(r.choice("abcdefghij ") for _ in range(300_000))
    rows = [(1, "some words of a text"), (1, "some words of a text"), (None, None), (None, "x"), (2, ""), (3, long_text), (4, "new " + long_text[1000:3000])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_bytes", F.lit("clash")).withColumn("sig", F.lit(0))
    none = docs.limit(0)
    for made in (chunk_dedup.deduplicated, suffix_repeats.without_repeats, prefix_tokens.token_counts, ngram_join.jaccard_components, quality_rules.with_counts):
        assert made(none).count() == 0 and made(docs).count() == len(rows)
    cut = {(x["doc_id"], x["n_bytes"]): x["n_removed"] for x in suffix_repeats.without_repeats(docs).collect()}
    assert cut[3, 300_000] == cut[4, 2004] == 2000 and cut[1, 20] == 0
    kept = sorted((x["doc_id"] or 0, x["n_removed"]) for x in chunk_dedup.deduplicated(docs).collect())
    assert kept[-1][1] >= 1900 and kept[-2] == (3, 0) and kept[:3] == [(0, 0), (0, 0), (1, 0)]
    groups = {(x["doc_id"], x["n_shingles"]): x["component_id"] for x in ngram_join.jaccard_components(docs).collect()}
    assert groups[1, 1] == 1 and groups[2, 0] == 2 and groups[None, 0] is None
    turns = [(7, t, "user" if t % 2 else "assistant", f"turn {t}") for t in range(3000)] + [(8, 0, None, None)]
    talks = {x["conv_id"]: x for x in chat.digests(chat.formatted(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string"))).collect()}
    assert talks[7]["n_turns"] == 3000 and talks[7]["loss_chars"] == sum(len(x[3]) for x in turns[:-1] if x[2] == "assistant") and talks[8]["loss_chars"] == 0


def test_base_counts_equal_sql(spark):
    import duckdb

    from indextrigger.llm import queries

    con = duckdb.connect()
    con.execute("create view documents as select * from '/root/testdata/sf0.001/documents.parquet'")
    want = con.execute(queries.oracle_sql()["quality_base_counts"]).fetchall()
    got = quality_rules.quality_base_counts(spark, "/root/testdata/sf0.001").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_rules_go_on_after_a_refused_one(spark):
    """Symbols tell most but not surely; repeated lines tell less and surely."""
    rows = []
    for i in range(600):
        rows.append((i, "## " * 40 + " ".join(f"w{i}x{j}" for j in range(80)), int(i % 5 != 0)))
    for i in range(600, 900):
        rows.append((i, "\n".join(["the same line"] * (6 if i % 3 == 0 else 1)) + " " + " ".join(f"w{i}x{j}" for j in range(80)), int(i % 3 == 0)))
    sample = spark.createDataFrame(rows, "doc_id long, text string, bad int")
    rules = quality_rules.learn_rules(sample)
    assert rules.rules and all(quality_rules.both(rule) is not None for rule in rules.rules)
    judged = quality_rules.judged(sample, rules).where("NOT kept AND NOT base_failed").agg(F.sum("bad").alias("p"), F.count(F.lit(1)).alias("n")).first()
    assert judged["p"] >= 0.9 * judged["n"]
