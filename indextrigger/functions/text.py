"""Words from texts: scrubbing, cutting, stemming, stop words and document-share filters."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from ..sources.staging import staged

#: Words that are sent to all executors with their stems; more are joined by a shuffle.
BROADCAST_WORDS = 1_000_000
URL, EMAIL, DIGITS = r"(https?://|www\.)\S+", r"[\w.+-]+@[\w-]+(\.[\w-]+)+", r"[0-9]+"


def scrub(text: Column) -> Column:
    """Web addresses, e-mail addresses and digits become spaces, in that order.

    A text without the letters that every match of a pattern has is not searched for it.
    """
    for pattern, signs in ((URL, "http|www\\."), (EMAIL, "@"), (DIGITS, None)):
        bare = F.regexp_replace(text, pattern, " ")
        text = F.when(F.rlike(text, F.lit(signs)), bare).otherwise(text) if signs else bare
    return text


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags go, a few entities are read, spaces are joined."""
    for pattern in (r"(?is)<(script|style)\b.*?</\1\s*>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        html = F.regexp_replace(html, pattern, " ")
    for entity, value in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        html = F.replace(html, F.lit(entity), F.lit(value))
    return F.trim(F.regexp_replace(html, r"\s+", " "))


def words_of(text: Column, min_len: int = 3) -> Column:
    """Lowered runs of letters of a least length, as an array; null gives none."""
    return F.filter(F.regexp_extract_all(F.lower(scrub(text)), F.lit(r"\p{L}+"), F.lit(0)), lambda w: F.length(w) >= min_len)


def tokenize(docs: DataFrame, text_col: str = "text", min_len: int = 3, extra: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, win, text`` -> ``doc_id, win, feature``, one row per occurrence."""
    return docs.select("doc_id", "win", *extra, F.explode(words_of(F.col(text_col), min_len)).alias("feature"))


def drop_listed_stopwords(tokens: DataFrame, words: DataFrame) -> DataFrame:
    """Drops the features listed in ``words`` (one column, ``feature``)."""
    return tokens.join(words, "feature", "left_anti")


def select_documents(docs: DataFrame, phrases: list[str], text_col: str = "text") -> DataFrame:
    """Documents that hold any of the phrases, whatever their case."""
    hit = F.lit(False)
    for phrase in phrases:
        hit = hit | F.contains(F.lower(F.col(text_col)), F.lit(phrase.lower()))
    return docs.where(hit)


def document_shares(tokens: DataFrame, scope: str, win_docs: str = "win") -> DataFrame:
    """``feature`` (and ``win`` for scope day) with the share of documents that hold it."""
    if scope == "corpus":
        total = tokens.agg(F.count_distinct("doc_id").alias("docs"))
        held = tokens.select("feature", "doc_id").distinct()
        return held.groupBy("feature").agg(F.count("doc_id").alias("df")).crossJoin(F.broadcast(total)).select("feature", (F.col("df") / F.col("docs")).alias("share"))
    pairs = tokens.select("feature", "doc_id", "win").distinct()
    per_day = tokens.groupBy("win").agg(F.count_distinct("doc_id").alias("docs"))
    cells = pairs.groupBy("feature", "win").agg(F.count(F.lit(1)).alias("df")).join(per_day, "win")
    return cells.select("feature", "win", (F.col("df") / F.col("docs")).alias("share"))


def kept_features(tokens: DataFrame, lo: float = 0.05, hi: float = 0.8, scope: str = "corpus") -> DataFrame:
    """Features (for scope day: feature and window) whose share of documents lies in [lo, hi].

    ``corpus``: the share over all documents. ``day``: the cell of each window on its own.
    ``any_day``: some window lies inside the bounds. ``mean_day``: the mean over windows that
    have documents, absent ones counting 0. Shares are compared at nine places, so that a share
    on a bound does not hang on the order in which windows are added.
    """
    shares = document_shares(tokens, scope)
    inside = F.round("share", 9).between(lo, hi)
    if scope == "corpus":
        return shares.where(inside).select("feature")
    if scope == "day":
        return shares.where(inside).select("feature", "win")
    if scope == "any_day":
        return shares.where(inside).select("feature").distinct()
    windows = tokens.agg(F.count_distinct("win").alias("n_win"))
    mean = shares.groupBy("feature").agg(F.sum("share").alias("total")).crossJoin(F.broadcast(windows))
    return mean.withColumn("share", F.col("total") / F.col("n_win")).where(inside).select("feature")


def share_filter(tokens: DataFrame, lo: float = 0.05, hi: float = 0.8, scope: str = "corpus") -> DataFrame:
    kept = kept_features(tokens, lo, hi, scope)
    return tokens.join(kept, kept.columns, "left_semi")


def prepare_tokens(docs: DataFrame, lo: float = 0.05, hi: float = 0.8, scope: str = "corpus", stemmed: bool = False, stopwords: DataFrame | None = None) -> DataFrame:
    """The words of documents, stemmed on request, with a document share in [lo, hi].

    The words are cut once and written, as stems and shares are counted over them before any is kept.
    """
    tokens = staged(tokenize(docs), "words")
    if stopwords is not None:
        tokens = drop_listed_stopwords(tokens, stopwords)
    if scope == "corpus":
        return common_tokens(tokens, lo, hi, stemmed)
    if stemmed:
        tokens = stem_tokens(tokens)
    return share_filter(tokens, lo, hi, scope)


def common_tokens(tokens: DataFrame, lo: float, hi: float, stemmed: bool) -> DataFrame:
    """The words, or their stems, with a share of documents in [lo, hi], from a written table of tokens.

    A word occurs at least as often as it has documents, so a word (or all words of a stem) with fewer
    occurrences than the share asks for goes before documents are counted; what stays is a small table.
    """
    docs = tokens.agg(F.count_distinct("doc_id")).first()[0]
    if not docs:
        return tokens.limit(0)
    vocabulary = tokens.groupBy("feature").agg(F.count(F.lit(1)).alias("n"))
    vocabulary = staged(vocabulary.withColumn("stem", stem(F.col("feature")) if stemmed else F.col("feature")), "vocabulary")
    share = lambda n: F.round(n / F.lit(docs), 9)
    often = vocabulary.groupBy("stem").agg(F.sum("n").alias("n")).where(share(F.col("n")) >= lo).select("stem")
    words = staged(vocabulary.join(often, "stem", "left_semi").select("feature", "stem"), "often")
    found = tokens.join(F.broadcast(words) if words.count() <= BROADCAST_WORDS else words, "feature")
    found = found.select(*[F.col("stem").alias("feature") if c == "feature" else F.col(c) for c in tokens.columns])
    held = found.select("feature", "doc_id").distinct().groupBy("feature").agg(F.count("doc_id").alias("df"))
    return found.join(F.broadcast(staged(held.where(share(F.col("df")).between(lo, hi)).select("feature"), "kept")), "feature", "left_semi")


def stem_tokens(tokens: DataFrame) -> DataFrame:
    """Stems the vocabulary once, writes it and joins it back, so Python sees each word once."""
    stems = staged(tokens.select("feature").distinct().withColumn("stem", stem(F.col("feature"))), "stems")
    joined = tokens.join(stems, "feature")
    return joined.select(*[F.col("stem").alias("feature") if c == "feature" else F.col(c) for c in tokens.columns])


@F.pandas_udf(StringType())
def stem(words: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for part in words:
        yield part.map(lambda w: None if w is None else porter(w))


# Suffix tables of the public Porter stemming algorithm.
_STEP2 = (("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble"))
_STEP3 = (("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", ""))
_STEP4 = ("al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ou", "ism", "ate", "iti", "ous", "ive", "ize")


def _shape(word: str) -> str:
    """``c`` and ``v`` for each letter: y is a vowel after a consonant."""
    out = ""
    for i, ch in enumerate(word):
        vowel = ch in "aeiou" or (ch == "y" and i > 0 and out[-1] == "c")
        out += "v" if vowel else "c"
    return out


def _measure(stem_: str) -> int:
    shape = _shape(stem_)
    return sum(1 for a, b in zip(shape, shape[1:]) if a == "v" and b == "c")


def _double(word: str) -> bool:
    return len(word) > 1 and word[-1] == word[-2] and _shape(word)[-1] == "c"


def _short_end(word: str) -> bool:
    return len(word) > 2 and _shape(word)[-3:] == "cvc" and word[-1] not in "wxy"


def porter(word: str) -> str:
    """The stem of a lowered word; words of one or two letters stay."""
    if len(word) <= 2:
        return word
    if word.endswith("sses") or word.endswith("ies"):
        word = word[:-2]
    elif word.endswith("s") and not word.endswith("ss"):
        word = word[:-1]
    if word.endswith("eed"):
        word = word[:-1] if _measure(word[:-3]) > 0 else word
    else:
        for end in ("ed", "ing"):
            if word.endswith(end) and "v" in _shape(word[: -len(end)]):
                word = word[: -len(end)]
                if word.endswith(("at", "bl", "iz")):
                    word += "e"
                elif _double(word) and word[-1] not in "lsz":
                    word = word[:-1]
                elif _measure(word) == 1 and _short_end(word):
                    word += "e"
                break
    if word.endswith("y") and "v" in _shape(word[:-1]):
        word = word[:-1] + "i"
    for table in (_STEP2, _STEP3):
        found = max((x for x in table if word.endswith(x[0])), key=lambda x: len(x[0]), default=None)
        if found and _measure(word[: -len(found[0])]) > 0:
            word = word[: -len(found[0])] + found[1]
    end = max((e for e in (*_STEP4, "ion") if word.endswith(e)), key=len, default=None)
    if end and _measure(word[: -len(end)]) > 1 and (end != "ion" or word[-4:-3] in ("s", "t")):
        word = word[: -len(end)]
    if word.endswith("e"):
        m = _measure(word[:-1])
        if m > 1 or (m == 1 and not _short_end(word[:-1])):
            word = word[:-1]
    return word[:-1] if _double(word) and word[-1] == "l" and _measure(word[:-1]) > 1 else word
