"""Operator 8 [native]: quality rules learned as a decision list.

Counts of every whole text are built-in expressions. Rules come from labelled rows by
sequential covering: a rule grows by the threshold test with the best information
gain on the rows that no earlier rule covers, stops when it covers no good row, loses
its last tests again while held-out rows say so, and is kept if it is precise enough
there. The first test of a refused rule opens no further one, and the search goes on
with the next best. Each step is one aggregation of labelled counts by feature and bin. The list
becomes one ordered ``CASE`` expression over the counts.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .storage import SPACED_WORD, fresh, table, written

SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, even where the optimiser copies the expression."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def repeat_words(words: Column) -> Column:
    """Number of words in three-word windows found at least twice in the array of words.

    Windows are compared by 64-bit hashes inside one text. Only a text with a repeat is sorted.
    """

    def of_repeats(pairs: Column) -> Column:
        same = lambda x, k: F.coalesce(F.get(pairs, k)["h"] == x["h"], F.lit(False))
        starts = F.sort_array(F.transform(F.filter(pairs, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))
        nothing = F.struct(F.lit(0).alias("total"), F.lit(0).alias("end"))
        step = lambda a, i: F.struct((a["total"] + i + 3 - F.greatest(i, a["end"])).alias("total"), (i + 3).alias("end"))
        return F.aggregate(starts, nothing, step)["total"]

    def of_hashes(hashes: Column) -> Column:
        pairs = F.sort_array(F.transform(hashes, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) < F.size(hashes), let(pairs, of_repeats)).otherwise(F.lit(0))

    def of_words(w: Column) -> Column:
        window = lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2))
        return F.when(F.size(w) < 3, F.lit(0)).otherwise(let(F.transform(F.sequence(F.lit(0), F.size(w) - 3), window), of_hashes))

    return let(words, of_words).cast("long")


def dup_lines(text: Column) -> Column:
    """Number of lines with a word that equal an earlier line."""
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long")


def with_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` plus the five counts and ``n_upper``, all long; same-named input columns are replaced.

    A null or empty text has no words and all counts 0.
    """
    docs = docs.drop(*[c for c in docs.columns if c.lower() in [*COUNTS, "n_upper"] and c != text_col])
    w = fresh("words", docs)
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = docs.withColumn(w, F.regexp_extract_all(text, F.lit(SPACED_WORD), F.lit(0)))
    return out.select(
        *docs.columns,
        F.size(w).cast("long").alias("n_words"),
        F.length(F.translate(text, SPACES, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        dup_lines(text).alias("n_dup_lines"),
        repeat_words(F.col(w)).alias("n_repeat_words"),
        F.regexp_count(text, F.lit(r"\p{Lu}")).cast("long").alias("n_upper"),
    )


def base_failed(min_words: int = 50, max_repeat_percent: int = 50) -> Column:
    return (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat_percent * F.col("n_words"))


def features() -> dict[str, Column]:
    """Numbers that rules test: the counts and shares of them (0 where there are no words)."""
    share = lambda c: F.coalesce(F.col(c) / F.nullif(F.col("n_words").cast("double"), F.lit(0.0)), F.lit(0.0))
    rates = {"symbols_per_word": share("n_symbols"), "chars_per_word": share("word_chars"), "upper_per_word": share("n_upper"), "repeat_share": share("n_repeat_words"), "dup_lines_per_word": share("n_dup_lines")}
    return {**{c: F.col(c).cast("double") for c in COUNTS}, **rates}


@dataclass(frozen=True)
class Test:
    feature: str
    at_least: bool
    threshold: float
    cell: int

    def column(self, by_cell: bool = False) -> Column:
        value, bound = (F.col(f"cell_{self.feature}"), self.cell) if by_cell else (features()[self.feature], self.threshold)
        return value >= bound if self.at_least else value < bound


@dataclass(frozen=True)
class RuleList:
    """Ordered rules, each a conjunction of tests; a document that meets one is rejected."""

    rules: tuple[tuple[Test, ...], ...]

    def kept(self) -> Column:
        out = None
        for rule in self.rules:
            test = both(rule)
            out = F.when(test, F.lit(False)) if out is None else out.when(test, F.lit(False))
        return F.lit(True) if out is None else out.otherwise(F.lit(True))

    def lines(self) -> list[str]:
        return [" and ".join(f"{t.feature} {'>=' if t.at_least else '<'} {t.threshold:g}" for t in rule) for rule in self.rules]


def both(tests: tuple[Test, ...], by_cell: bool = False) -> Column:
    out = F.lit(True)
    for t in tests:
        out = out & t.column(by_cell)
    return out


def labelled_sample(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000) -> DataFrame:
    """At most ``max_rows`` labelled documents, chosen by a hash of the id: the documented bound of training.

    Rows of ``labels`` without an id or a quality are left out; of several for one id the lowest quality counts.
    """
    marks = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    marks = marks.orderBy(F.xxhash64(F.lit("rules"), "doc_id"), "doc_id").limit(max_rows)
    texts = docs.select("doc_id", "text").join(F.broadcast(marks), "doc_id")  # max_rows ids at most
    texts = texts.groupBy("doc_id", "quality").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))  # one row an id
    return texts.select("doc_id", "text", (F.col("quality") == 0).cast("int").alias("bad"))


def learn_rules(sample: DataFrame, cells: int = 32, max_rules: int = 8, max_tests: int = 4, min_precision: float = 0.9, min_gain_rows: int = 4) -> RuleList:
    """Sequential covering on ``text, bad``. No labelled rows, or no precise rule, give an empty list."""
    names = list(features())
    numbers = written(with_counts(sample).drop("text"), "rules-sample").where(~base_failed())
    numbers = numbers.select("doc_id", "bad", *[c.alias(f) for f, c in features().items()])
    steps = [i / cells for i in range(1, cells)]
    cut = numbers.agg(*[F.percentile(f, F.array(*map(F.lit, steps))).alias(f) for f in names], *[F.percentile(F.when(F.col("bad") == 1, F.col(f)), F.array(*map(F.lit, steps[:: 4]))).alias(f"bad_{f}") for f in names]).first()
    bounds = {f: sorted({float(x) for x in [*(cut[f] or []), *(cut[f"bad_{f}"] or [])]}) for f in names}
    cell = lambda f: F.size(F.filter(F.array(*map(F.lit, bounds[f])), lambda t: F.col(f) >= t)) if bounds[f] else F.lit(0)
    hold = F.pmod(F.xxhash64(F.lit("hold"), "doc_id"), F.lit(3)) == 0
    rows = written(numbers.select("bad", hold.alias("held"), *[cell(f).alias(f"cell_{f}") for f in names]), "rules-cells")
    long_form = F.explode(F.array(*[F.struct(F.lit(f).alias("feature"), F.col(f"cell_{f}").alias("cell")) for f in names])).alias("x")
    rules: list[tuple[Test, ...]] = []

    def covered(tests: tuple[Test, ...], left: Column, held: bool) -> tuple[int, int]:
        got = rows.where(left & (F.col("held") == held) & both(tests, True)).agg(F.coalesce(F.sum("bad"), F.lit(0)).alias("p"), F.count(F.lit(1)).alias("n")).first()
        return int(got["p"]), int(got["n"]) - int(got["p"])

    refused: set[tuple[str, bool]] = set()

    def best_test(left: Column, tests: tuple[Test, ...], p: int, n: int) -> tuple | None:
        """(gain, test, bad rows, good rows) of the test that tells most about the rows that a rule covers so far."""
        counts = rows.where(left & ~F.col("held") & both(tests, True)).select("bad", long_form).groupBy("x.feature", "x.cell").agg(F.sum("bad").alias("p"), F.count(F.lit(1)).alias("all"))
        table_ = {(r["feature"], r["cell"]): (int(r["p"]), int(r["all"]) - int(r["p"])) for r in counts.collect()}  # features times cells
        best = None
        for f in names:
            for k in range(1, len(bounds[f]) + 1):
                above = [v for (g, c), v in table_.items() if g == f and c >= k]
                hi = (sum(a for a, _ in above), sum(b for _, b in above))
                for at_least, (tp, tn) in ((True, hi), (False, (p - hi[0], n - hi[1]))):
                    if tp >= min_gain_rows and (tp, tn) != (p, n) and (tests or (f, at_least) not in refused):
                        gain = tp * (math.log2(tp / (tp + tn)) - math.log2(p / (p + n)))
                        if best is None or gain > best[0] + 1e-12:
                            best = (gain, Test(f, at_least, bounds[f][k - 1], k), tp, tn)
        return best if best and best[0] > 0 else None

    while len(rules) < max_rules:
        left = F.lit(True)
        for rule in rules:
            left = left & ~both(rule, True)
        tests: tuple[Test, ...] = ()
        p, n = covered((), left, False)
        if p < min_gain_rows:
            break
        while n and len(tests) < max_tests:
            best = best_test(left, tests, p, n)
            if best is None:
                break
            tests, p, n = (*tests, best[1]), best[2], best[3]
        if not tests:
            break
        worth = {}
        for size in range(1, len(tests) + 1):
            hp, hn = covered(tests[:size], left, True)
            worth[size] = (hp - hn) / (hp + hn) if hp + hn else -1.0
        size = max(worth, key=lambda k: (worth[k], -k))
        tests = tests[:size]
        hp, hn = covered(tests, left, True)
        gp, gn = covered(tests, left, False)
        if not hp or hp < min_precision * (hp + hn) or hp + gp < min_precision * (hp + hn + gp + gn):
            refused.add((tests[0].feature, tests[0].at_least))  # twice the features at most
            continue
        rules.append(tests)
    return RuleList(tuple(rules))


def judged(docs: DataFrame, rules: RuleList) -> DataFrame:
    """``docs`` plus counts, ``base_failed`` and ``kept``."""
    docs = docs.drop(*[c for c in docs.columns if c.lower() in ("base_failed", "kept")])
    return with_counts(docs).withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & rules.kept())


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    rules = learn_rules(labelled_sample(docs, table(spark, sf_dir, "labels")))
    return judged(docs, rules).select("doc_id", *COUNTS, "base_failed", "kept")


def quality_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts of every whole text and the base verdict, without rules."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return with_counts(docs).select("doc_id", *COUNTS, base_failed().alias("base_failed"))
