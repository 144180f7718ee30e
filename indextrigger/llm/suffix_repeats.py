"""Operator 5: removing repeated byte strings by bucket-pointer refinement.

A byte goes if it lies in a 200-byte string that starts anywhere else as well, in the same
document or another. The suffixes of a corpus are too many to sort, so they are
bucketed in three steps, each only on what the one before left open:

1. Every 200-byte string belongs to its least 50-gram (by hash, leftmost of equals).
   This depends on the string alone, so equal strings belong to equal grams at equal
   offsets. Neighbouring strings of one gram make an *interval*: one row for about 75
   suffixes. Intervals are bucketed by their gram; singletons are final.
2. Buckets are refined by a second, unrelated hash of the whole interval (128 bits with
   that of the gram). An interval that occurs twice is removed as a whole. A bucket that
   falls into several classes is left open, with one context (the bytes of its interval)
   for each class.
3. The suffixes of open contexts are refined by bucket pointers: buckets of grams get
   dense identifiers; sorting pairs of identifiers at i and i + step gives those of
   strings ``step`` bytes longer, which the next round sorts in turn, until the
   full width is reached (50, 100, 200 bytes; any other width takes its own steps).
   Suffixes alone in their bucket drop out between the rounds.

The texts are shuffled once, by a key from their hash and length; the reading of
contexts and the final cut share that exchange.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .arrow_rows import exploded_by_arrow
from .storage import table, written

#: The least width of strings: a gram is a quarter, and holds eight bytes at least.
LEAST_WIDTH = 32
#: Open classes of one gram that one task refines; a bucket of more is counted by a shuffle of its suffixes.
BUCKET_CLASSES = 8192
#: Bytes of contexts that are refined together.
REFINED_BYTES = 1 << 20
_INDEX_BITS = np.uint64(24)
_INDEX = np.uint64((1 << 24) - 1)
_BLOCK = 1 << 23

INTERVALS = T.StructType([T.StructField("key", T.LongType()), *[T.StructField(c, T.IntegerType()) for c in ("n_bytes", "first", "count", "ahead")], T.StructField("gram", T.LongType()), T.StructField("whole", T.LongType())])
CONTEXTS = T.StructType([T.StructField("gram", T.LongType()), T.StructField("classes", T.LongType()), T.StructField("key", T.LongType()), T.StructField("n_bytes", T.IntegerType()), T.StructField("first", T.IntegerType()), T.StructField("sure", T.BooleanType()), T.StructField("bytes", T.BinaryType())])
SPANS = T.StructType([T.StructField("key", T.LongType()), T.StructField("n_bytes", T.IntegerType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())])


def gram_of(width: int) -> int:
    return width // 4


def rounds(width: int) -> tuple[list[int], list[list[int]]]:
    """Bytes that each round adds, and before and after each the offsets in a string whose identifiers it needs."""
    steps, span = [], gram_of(width)
    while span < width:
        steps.append(min(span, width - span))
        span += steps[-1]
    offsets = [[0]]
    for step in reversed(steps):
        offsets.append(sorted({o + s for o in offsets[-1] for s in (0, step)}))
    return steps, offsets[::-1]


def intervals(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
    """Document, first string, number of strings, offset of the gram in the first, gram hash, interval hash."""
    n, gram = len(data), gram_of(width)
    span = width - gram + 1
    if n < width:
        return tuple(np.zeros(0, np.int64) for _ in range(4)) + (np.zeros(0, np.uint64),) * 2
    at = np.arange(n - gram + 1)
    grams = K.window_hashes(data, gram)
    ends = np.repeat(offsets[1:], np.diff(offsets))
    grams[at + gram > ends[: len(at)]] = np.uint64(2**64 - 1)
    least = K.sliding_least((grams & ~_INDEX) | at.astype(np.uint64), span)
    starts = np.flatnonzero(np.arange(len(least)) + width <= ends[: len(least)])
    owner = (least[starts] & _INDEX).astype(np.int64)
    if not len(starts):
        return intervals(data[:0], offsets[:1], width)
    new = np.concatenate([[True], (owner[1:] != owner[:-1]) | (starts[1:] != starts[:-1] + 1)])
    new[1:] |= np.isin(starts[1:], offsets)
    heads = np.flatnonzero(new)
    counts = np.diff(np.concatenate([heads, [len(starts)]]))
    first, owner = starts[heads], owner[heads]
    ahead = owner - first
    whole = K.digests(data, first, first + counts - 1 + width)
    whole = K.mixed(whole ^ (ahead.astype(np.uint64) << np.uint64(32)) ^ counts.astype(np.uint64))
    docs = np.searchsorted(offsets, first, "right") - 1
    return docs, first - offsets[docs], counts, ahead, grams[owner], whole


def _blocks(raw: np.ndarray, cuts: np.ndarray, width: int, most: int = int(_INDEX), step: int = _BLOCK) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """A piece, or the overlapping blocks of one document too long for the packed positions."""
    if len(raw) <= most:
        yield raw, cuts, 0
        return
    for at in range(0, len(raw) - width + 1, step):
        part = raw[at : at + step + width - 1]
        yield part, np.array([0, len(part)]), at


def all_intervals(texts: DataFrame, width: int) -> DataFrame:
    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        keys = np.asarray(batch.column(0))
        data, offsets, _ = K.text_column(batch.column(1))
        for row, _, raw, cuts in K.pieces(data, offsets):
            for part, borders, shift in _blocks(raw, cuts, width):
                docs, first, counts, ahead, grams, whole = intervals(part, borders, width)
                sizes = np.diff(offsets)[row + docs]
                yield [pa.array(x) for x in (keys[row + docs], sizes.astype(np.int32), (first + shift).astype(np.int32), counts.astype(np.int32), ahead.astype(np.int32), grams.view(np.int64), whole.view(np.int64))]

    return exploded_by_arrow(texts, INTERVALS, kernel)


def dense(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket identifiers from 0 in order of the values, and the size of the bucket of each."""
    _, ids, counts = np.unique(values, return_inverse=True, return_counts=True)
    return ids, counts[ids]


def refined(data: np.ndarray, starts: np.ndarray, width: int) -> np.ndarray:
    """Whether the string of ``width`` bytes at each start occurs at another of the starts.

    Starts are positions in ``data``; their strings may overlap.
    """
    steps, offsets = rounds(width)
    repeated = np.zeros(len(starts), bool)
    alive = np.arange(len(starts))

    def places(wanted: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """The positions at the wanted offsets of living strings, in order, and the slot of every byte among them."""
        mark = np.zeros(len(data) + 1, bool)
        for o in wanted:
            mark[starts[alive] + o] = True
        return np.flatnonzero(mark), np.cumsum(mark, dtype=np.int32) - 1

    where, slot = places(offsets[0])
    ids, sizes = dense(K.window_hashes(data, gram_of(width))[where])
    for o in offsets[0]:
        alive = alive[sizes[slot[starts[alive] + o]] > 1]
    for step, wanted in zip(steps, offsets[1:]):
        shorter, shorter_slot = ids, slot
        where, slot = places(wanted)
        ids, sizes = dense(shorter[shorter_slot[where]] << 32 | shorter[shorter_slot[where + step]])
        for o in wanted:
            alive = alive[sizes[slot[starts[alive] + o]] > 1]
    repeated[alive] = True
    return repeated


def _flat(column: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of contexts end to end, their starts of strings, and the context of each start."""
    lengths = np.fromiter(map(len, column), np.int64, len(column))
    begins = np.concatenate([[0], np.cumsum(lengths)])
    rows = np.repeat(np.arange(len(column)), lengths - width + 1)
    within = np.arange(len(rows)) - np.repeat(np.concatenate([[0], np.cumsum(lengths - width + 1)])[:-1], lengths - width + 1)
    return np.frombuffer(b"".join(column), np.uint8), begins[rows] + within, rows


def refine_open(contexts: DataFrame, width: int) -> DataFrame:
    """Contexts with all classes of a gram in one partition -> spans of repeated strings in the open ones."""
    rows = contexts.repartition("gram").sortWithinPartitions("gram")

    def spans(held: list[tuple]) -> pa.RecordBatch:
        keys, sizes, firsts, sure, bodies = zip(*held)
        data, starts, owner = _flat(list(bodies), width)
        hit = refined(data, starts, width) & ~np.array(sure)[owner]
        where = np.flatnonzero(hit)
        heads = np.flatnonzero(np.concatenate([[True], (where[1:] != where[:-1] + 1) | (owner[where[1:]] != owner[where[:-1]])])) if len(where) else where
        tails = np.concatenate([heads[1:], [len(where)]])[: len(heads)] - 1
        origin = np.searchsorted(owner, np.arange(len(held)))
        doc = owner[where[heads]]
        first = np.array(firsts, np.int64)[doc] - origin[doc]
        columns = [np.array(keys, np.int64)[doc], np.array(sizes, np.int32)[doc], (first + where[heads]).astype(np.int32), (first + where[tails] + width).astype(np.int32)]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=[f.name for f in SPANS])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, last = [], 0, None
        for batch in batches:
            names = ("gram", "key", "n_bytes", "first", "sure", "bytes")
            for gram, *row in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in names)):
                if gram != last and size > REFINED_BYTES:
                    yield spans(held)
                    held, size = [], 0
                last = gram
                held.append(tuple(row))
                size += len(row[-1])
        if held:
            yield spans(held)

    return rows.mapInArrow(run, SPANS)


def refine_spread(contexts: DataFrame, width: int) -> DataFrame:
    """The same for grams with very many classes: one row a suffix, counted by hash with partial sums."""
    suffixes = T.StructType([*SPANS.fields[:3], T.StructField("sure", T.BooleanType()), T.StructField("head", T.LongType()), T.StructField("tail", T.LongType())])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        held = {c: batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("key", "n_bytes", "first", "sure", "bytes")}
        for lo in range(0, len(held["key"]), 4096):
            part = {c: v[lo : lo + 4096] for c, v in held.items()}
            data, starts, owner = _flat(part["bytes"], width)
            origin = np.searchsorted(owner, np.arange(len(part["key"])))
            half = -(-width // 2)
            halves = K.window_hashes(data, half).view(np.int64)
            at = np.array(part["first"], np.int64)[owner] + np.arange(len(owner)) - origin[owner]
            ends = [halves[starts], halves[starts + width - half]]
            yield [pa.array(x) for x in (np.array(part["key"], np.int64)[owner], np.array(part["n_bytes"], np.int32)[owner], at.astype(np.int32), np.array(part["sure"], bool)[owner], *ends)]

    rows = exploded_by_arrow(contexts, suffixes, kernel)
    twice = rows.groupBy("head", "tail").agg(F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    return rows.where("NOT sure").join(twice, ["head", "tail"], "left_semi").select("key", "n_bytes", "start", (F.col("start") + width).alias("end"))


def repeated_spans(texts: DataFrame, width: int, bucket_classes: int = BUCKET_CLASSES) -> DataFrame:
    """``key, n_bytes, text`` -> ``key, n_bytes, start, end`` of repeated strings, overlapping."""
    found = written(all_intervals(texts.where(F.col("n_bytes") >= width).select("key", "text"), width), "intervals")
    # What is counted by a key is written before it is joined, so that a key with very many rows can be split.
    twice = written(found.groupBy("gram").agg(F.count(F.lit(1)).alias("c")).where("c > 1").drop("c"), "twice")
    bucketed = written(found.join(twice, "gram", "left_semi"), "bucketed")
    classes = bucketed.groupBy("gram", "whole").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("key", "n_bytes", "first", "count")).alias("own"))
    classes = written(classes, "classes")
    certain = bucketed.join(classes.where("c > 1").select("gram", "whole"), ["gram", "whole"], "left_semi")
    certain = certain.select("key", "n_bytes", F.col("first").alias("start"), (F.col("first") + F.col("count") + (width - 1)).alias("end")).distinct()
    several = written(classes.groupBy("gram").agg(F.count(F.lit(1)).alias("classes")).where("classes > 1"), "several")
    asked = classes.join(several, "gram").groupBy("own.key", "own.n_bytes").agg(F.collect_list(F.struct("gram", "classes", F.col("own.first").alias("first"), F.col("own.count").alias("count"), (F.col("c") > 1).alias("sure"))).alias("asked"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            out = []
            fields = ("key", "n_bytes", "text", "asked")
            for key, size, text, wanted in zip(*(batch.column(batch.schema.get_field_index(c)) for c in fields)):
                own = key.as_py(), size.as_py()
                if own == last:  # another copy of the same text
                    continue
                last, raw = own, text.as_py().encode()
                out += [(w["gram"], w["classes"], *own, w["first"], w["sure"], raw[w["first"] : w["first"] + w["count"] + width - 1]) for w in wanted.as_py()]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*out), arrow)], schema=arrow)

    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(CONTEXTS)
    contexts = texts.join(asked, ["key", "n_bytes"]).select("key", "n_bytes", "text", "asked", *[c for c in texts.columns if c not in ("key", "n_bytes", "text")]).mapInArrow(kernel, CONTEXTS)
    narrow = refine_open(contexts.where(F.col("classes") <= bucket_classes), width)
    if not several.where(F.col("classes") > bucket_classes).isEmpty():
        narrow = narrow.unionByName(refine_spread(contexts.where(F.col("classes") > bucket_classes), width))
    return certain.unionByName(narrow)


CUT = T.StructType([T.StructField("doc_id", T.LongType()), *[T.StructField(c, T.LongType()) for c in ("n_bytes", "n_removed", "n_spans")], T.StructField("kept_sha256", T.StringType())])


def without_repeats(docs: DataFrame, width: int = 200, keep_text: bool = False, bucket_classes: int = BUCKET_CLASSES) -> DataFrame:
    """``doc_id, text`` -> ``doc_id, n_bytes, n_removed, n_spans, kept_sha256`` (and ``kept``, bytes), one row per input row.

    Strings are judged on the input, every copy of a repeated string goes, and strings never
    cross documents. A null text counts as empty; texts under ``width`` bytes keep
    everything; two equal texts lose everything. Ids are only carried: they may be null or
    repeated. ``width`` is ``LEAST_WIDTH`` bytes or more. Empty input gives no rows.
    """
    if width < LEAST_WIDTH:
        raise ValueError(f"strings of {LEAST_WIDTH} bytes or more are told apart, not of {width}")
    text = F.coalesce("text", F.lit(""))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("key"), F.octet_length(text).alias("n_bytes"), text.alias("text"))
    spans = repeated_spans(texts, width, bucket_classes).groupBy("key", "n_bytes").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    schema = T.StructType([*CUT.fields, *([T.StructField("kept", T.BinaryType())] if keep_text else [])])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        out = []
        fields = ("doc_id", "text", "spans")
        for doc, text_, found in zip(*(batch.column(batch.schema.get_field_index(c)) for c in fields)):
            raw = text_.as_py().encode()
            at = removed = runs = 0
            digest, kept, end = hashlib.sha256(), [], -1
            for s in sorted((x["start"], x["end"]) for x in found.as_py() or ()):
                if s[0] > end:
                    digest.update(raw[at : s[0]])
                    kept.append(raw[at : s[0]])
                    runs, removed = runs + 1, removed + s[1] - s[0]
                    end = at = s[1]
                elif s[1] > end:
                    removed += s[1] - end
                    end = at = s[1]
            digest.update(raw[at:])
            kept.append(raw[at:])
            out.append((doc.as_py(), len(raw), removed, runs, digest.hexdigest(), *([b"".join(kept)] if keep_text else [])))
        if out:
            yield [pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()))]

    return exploded_by_arrow(texts.join(spans, ["key", "n_bytes"], "left"), schema, kernel)


def op5_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
