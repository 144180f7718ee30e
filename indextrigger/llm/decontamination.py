"""Operator 7: benchmark decontamination by winnowing.

Both sides are winnowed alike: of every six consecutive five-word grams the one with the
least hash is kept. A span of ten words holds six grams, so each shared span of ten words
or more has a kept gram in common. Kept grams of a document are looked up among those of the
benchmark, and only the windows around a hit are extended: looked up by their hash and
then compared word by word. Items of fewer than ten words are one window of their own
length, looked up at every position.

The benchmark travels to the executors in blocks of at most ``BLOCK_WORDS`` words, as sorted
arrays of about 40 bytes a word: all of it at once if it fits, else one pass over the
documents for each block, whose findings are added up row by row. Documents are never
shuffled, whatever the size of either side.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .arrow_rows import with_arrow_columns
from .storage import table

WINDOW, GRAM = 10, 5
SPAN = WINDOW - GRAM + 1
#: Words of the benchmark that one pass carries to the executors; a longer item makes a block alone.
BLOCK_WORDS = 2_000_000
LOWERED = K.byte_table(K.ALNUM, lower=True)
_NONE = np.uint64(2**64 - 1)


@dataclass
class Windows:
    """The different windows of one length: sorted hashes, a place of each among the words, and its items."""

    hashes: np.ndarray
    places: np.ndarray
    item_bounds: np.ndarray
    items: np.ndarray


class Prints:
    """Windows and kept grams of one block of items, in arrays."""

    def __init__(self, items: list[tuple[str, str]]):
        self.names = sorted({item for item, _ in items})
        number = {item: i for i, item in enumerate(self.names)}
        raw = [text.encode() for _, text in items]
        offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
        _, _, self.words, bounds = K.words(np.frombuffer(b"".join(raw), np.uint8), offsets, LOWERED)
        sizes, owners = np.diff(bounds), np.array([number[item] for item, _ in items], np.int32)
        self.windows: dict[int, Windows] = {}
        for n in sorted({min(WINDOW, int(k)) for k in sizes if k}):
            rows = np.flatnonzero(sizes >= n if n == WINDOW else sizes == n)
            counts = sizes[rows] - n + 1
            first = np.repeat(bounds[rows] - np.concatenate([[0], np.cumsum(counts)[:-1]]), counts)
            places = first + np.arange(counts.sum())
            self.windows[n] = windows(K.grams(self.words, n)[places], places, np.repeat(owners[rows], counts))
        grams, kept = winnowed(self.words, np.repeat(bounds[1:], sizes))
        self.grams = np.unique(grams[kept])

    def nbytes(self) -> int:
        held = [self.words, self.grams, *[x for w in self.windows.values() for x in (w.hashes, w.places, w.item_bounds, w.items)]]
        return sum(x.nbytes for x in held)


def windows(hashes: np.ndarray, places: np.ndarray, owners: np.ndarray) -> Windows:
    order = np.lexsort((owners, hashes))
    hashes, places, owners = hashes[order], places[order], owners[order]
    new = np.concatenate([[True], hashes[1:] != hashes[:-1]])
    pairs = np.flatnonzero(new | np.concatenate([[True], owners[1:] != owners[:-1]]))  # an item once a window
    heads = np.flatnonzero(new)
    bounds = np.searchsorted(pairs, np.concatenate([heads, [len(hashes)]]))
    return Windows(hashes[heads], places[heads].astype(np.int32), bounds.astype(np.int32), owners[pairs])


def winnowed(words: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All grams, and the places of those that are the least of some six neighbours of one text.

    ``ends`` has, for every word, the end of its text. Of texts of fewer than ten words nothing is needed.
    """
    if len(words) < WINDOW:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    grams = K.grams(words, GRAM)
    at = np.arange(len(grams))
    inside = at + GRAM <= ends[: len(at)]
    grams[~inside] = _NONE
    least = K.sliding_least(grams, SPAN)
    wide = np.zeros(SPAN - 1, np.uint64)
    kept = K.sliding_least(np.concatenate([wide, least, wide]), SPAN, greatest=True) == grams
    return grams, np.flatnonzero(kept & inside)


def found_at(values: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which values are in a sorted array, and where there."""
    if not len(known):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.searchsorted(known, values)
    at[at == len(known)] = 0
    hit = np.flatnonzero(known[at] == values)
    return hit, at[hit]


def occurrences(words: np.ndarray, bounds: np.ndarray, prints: Prints) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(window length, first words, numbers of the windows) of the benchmark's windows in the texts of a piece."""
    ends = np.repeat(bounds[1:], np.diff(bounds))
    for n, held in prints.windows.items():
        if n < WINDOW:
            at = np.flatnonzero(np.arange(max(len(words) - n + 1, 0)) + n <= ends[: max(len(words) - n + 1, 0)])
            own = K.grams(words, n)[at]
        else:
            grams, kept = winnowed(words, ends)
            kept = kept[found_at(grams[kept], prints.grams)[0]]
            at = np.unique((kept[:, None] - np.arange(SPAN)[None, :]).ravel())
            at = at[at >= 0]
            at = at[at + WINDOW <= ends[at]]
            own = np.full(len(at), np.uint64(WINDOW), np.uint64)
            for j in range(WINDOW):
                own = K.followed(own, words[at + j])
            own = K.mixed(own)
        hit, number = found_at(own, held.hashes)
        at, places = at[hit], held.places[number].astype(np.int64)
        same = np.ones(len(at), bool)
        for j in range(n):
            same &= words[at + j] == prints.words[places + j]
        if same.any():
            yield n, at[same], number[same]


def merged_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


FOUND = T.StructType(
    [
        T.StructField("n_words", T.LongType()),
        T.StructField("hit_starts", T.ArrayType(T.LongType(), False)),
        T.StructField("hit_ends", T.ArrayType(T.LongType(), False)),
        T.StructField("items", T.ArrayType(T.StringType(), False)),
    ]
)


def benchmark_blocks(benchmark: DataFrame, block_words: int = BLOCK_WORDS) -> Iterator[list[tuple[str, str]]]:
    """Items in blocks of a checked number of words; a null id is the word null, a null text has no words.

    Items are dealt by a running count of words over parts of the table, so no block passes the
    bound unless one item does.
    """
    rows = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    rows = rows.withColumn("words", F.regexp_count("text", F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"))).where("words > 0")
    total = rows.agg(F.sum("words")).first()[0] or 0
    if total <= block_words:
        yield [(r["item"], r["text"]) for r in rows.collect()]
        return
    parts = F.pmod(F.xxhash64("item", "text"), F.lit(-(-4 * total // block_words)))
    held: list[int] = []
    size = 0
    for r in rows.groupBy(parts.alias("part")).agg(F.sum("words").alias("words")).orderBy("part").collect():  # about four counts a block
        if held and size + r["words"] > block_words:
            yield [(x["item"], x["text"]) for x in rows.where(parts.isin(held)).collect()]
            held, size = [], 0
        held.append(r["part"])
        size += r["words"]
    yield [(x["item"], x["text"]) for x in rows.where(parts.isin(held)).collect()]


def contamination(docs: DataFrame, benchmark: DataFrame, block_words: int = BLOCK_WORDS, text_col: str = "text") -> DataFrame:
    """``docs`` plus ``n_words, n_hit, n_items, items, hit_starts, hit_ends, contaminated``.

    Hit spans are word ranges, merged. A null or empty text has no words and no hits; an
    empty benchmark leaves all documents clean; repeated rows are judged alike. Same-named
    columns of the input are replaced.
    """
    added = ["n_hit", "n_items", "contaminated", *[f.name for f in FOUND]]
    docs = docs.drop(*[c for c in docs.columns if c.lower() in added and c != text_col])
    spark, out, first = docs.sparkSession, docs, True
    for items in benchmark_blocks(benchmark, block_words):
        shipped = spark.sparkContext.broadcast(Prints(items))  # at most block_words words
        out, first = with_arrow_columns(out, FOUND, _pass(shipped, text_col, first)), False
    spans = F.zip_with("hit_starts", "hit_ends", lambda a, b: b - a)
    n_hit = F.aggregate(spans, F.lit(0).cast("long"), lambda a, x: a + x)
    out = out.withColumn("n_hit", n_hit).withColumn("n_items", F.size("items").cast("long"))
    return out.withColumn("contaminated", F.col("n_hit") > 0)


def _pass(shipped, text_col: str, first: bool):
    def kernel(batch: pa.RecordBatch) -> list[pa.Array]:
        prints = shipped.value
        data, offsets, _ = K.text_column(batch.column(batch.schema.get_field_index(text_col)))
        n = len(offsets) - 1
        before = None if first else [batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("hit_starts", "hit_ends", "items")]
        counts = np.zeros(n, np.int64)
        spans: list[list[tuple[int, int]]] = [[] for _ in range(n)]
        items: list[list[str]] = [[] for _ in range(n)]
        for row, end, raw, cuts in K.pieces(data, offsets):
            _, _, words, bounds = K.words(raw, cuts, LOWERED)
            counts[row:end] = np.diff(bounds)
            for d, found, names in _findings(words, bounds, prints):
                spans[row + d], items[row + d] = found, names
        if before:
            for i, (a, b, c) in enumerate(zip(*before)):
                if a:
                    spans[i], items[i] = merged_spans([*spans[i], *zip(a, b)]), sorted({*items[i], *c})
        return [
            pa.array(counts),
            pa.array([[a for a, _ in s] for s in spans], pa.list_(pa.int64())),
            pa.array([[b for _, b in s] for s in spans], pa.list_(pa.int64())),
            pa.array(items, pa.list_(pa.string())),
        ]

    return kernel


def _findings(words: np.ndarray, bounds: np.ndarray, prints: Prints) -> Iterator[tuple[int, list[tuple[int, int]], list[str]]]:
    """Document, hit spans and sorted items of the documents of a piece that have any."""
    change = np.zeros(len(words) + 1, np.int64)
    pairs = []
    for n, at, number in occurrences(words, bounds, prints):
        np.add.at(change, at, 1)
        np.add.at(change, at + n, -1)
        held = prints.windows[n]
        lengths = held.item_bounds[number + 1] - held.item_bounds[number]
        first = np.repeat(held.item_bounds[number] - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths)
        docs = np.searchsorted(bounds, at, "right") - 1
        pairs.append(np.unique(np.repeat(docs, lengths) * len(prints.names) + held.items[first + np.arange(lengths.sum())]))
    if not pairs:
        return
    hit = np.cumsum(change[:-1]) > 0
    new = np.zeros(len(words), bool)
    new[bounds[:-1][bounds[:-1] < len(words)]] = True
    starts = np.flatnonzero(hit & (new | ~np.concatenate([[False], hit[:-1]])))
    ends = np.flatnonzero(hit & np.concatenate([new[1:] | ~hit[1:], [True]])) + 1
    owner = np.searchsorted(bounds, starts, "right") - 1
    found = np.unique(np.concatenate(pairs))
    item_docs = found // len(prints.names)
    for d in np.unique(item_docs).tolist():
        a, b = np.searchsorted(owner, [d, d + 1])
        names = prints.names
        own = found[np.searchsorted(item_docs, d) : np.searchsorted(item_docs, d, "right")] % len(names)
        yield d, [(int(x - bounds[d]), int(y - bounds[d])) for x, y in zip(starts[a:b], ends[a:b])], sorted(names[i] for i in own.tolist())


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = contamination(docs, table(spark, sf_dir, "benchmark").select("item_id", "text"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")
