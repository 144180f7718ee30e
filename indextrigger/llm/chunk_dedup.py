"""Operator 1: substring dedup by content-defined chunks.

A gear hash rolls over the bytes; a place is a cut if its hash is the least of any
``WINDOW`` neighbouring ones. That depends on the bytes around it alone, so an insertion
moves the chunks near it and no others, and no two cuts are further apart than the window.
A chunk is known by a hash of its bytes and of the 32 before it, which set its first cut.
Any string of ``32 + 2 * WINDOW - 1`` = 101 bytes, the least that 51 words can have, thus holds a
whole chunk with the same hash wherever it stands (unless it repeats a few bytes over and over).

The first document and position that has a chunk keeps it, every later one is a duplicate.
Neighbouring duplicates of one holder form a run. The holder sends a 128-bit digest of the
run and the bytes around it, and the run is extended byte by byte to the ends of the match.
A run can miss no more than the bytes sent, as a longer match would hold another chunk.
Short matches recur by chance, so only joined matches of at least ``min_run`` bytes are cut
out, and documents that are matches from end to end. Cuts never split a character.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .arrow_rows import exploded_by_arrow
from .storage import table, written

GEAR = np.random.default_rng(7).integers(0, 2**32, 256, dtype=np.uint32)
#: A cut has the least hash of so many neighbouring places.
WINDOW = 35
_ROLL = 32
_LEAST_ID = -(1 << 63)
#: Bytes of the holder before and after a run that its match can reach.
_BEFORE, _AFTER = _ROLL + 2 * WINDOW + 3, 2 * WINDOW + 3

_long, _int = T.LongType(), T.IntegerType()


def gear_hashes(data: np.ndarray) -> np.ndarray:
    """The gear hash after each byte: the sum of the codes of the last 32 bytes, each shifted by its age."""
    h, span = GEAR[data], 1
    while span < _ROLL:
        rolled = h.copy()
        rolled[span:] += h[:-span] << np.uint32(span)
        h, span = rolled, span * 2
    return h


def _opens(data: np.ndarray) -> np.ndarray:
    """Whether a character starts after each byte."""
    return np.append((data[1:] & 0xC0) != 0x80, True)


def chunk_ends(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ends of the chunks of all documents of a piece, and the number of chunks of each document."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(len(offsets) - 1, np.int64)
    opens = _opens(data)
    hashes = np.where(opens, gear_hashes(data), np.uint32(2**32 - 1))
    least = K.sliding_least(hashes.astype(np.uint64) << np.uint64(32) | np.arange(n, dtype=np.uint64), WINDOW)
    sizes = np.diff(offsets)
    begins, ends = np.repeat(offsets[:-1], sizes), np.repeat(offsets[1:], sizes)
    at = np.arange(len(least))
    least = (least[(at >= begins[: len(at)] + _ROLL - 1) & (at + WINDOW <= ends[: len(at)])] & np.uint64(2**32 - 1)).astype(np.int64)
    places = least[np.flatnonzero(np.diff(least, prepend=-1))]
    places = places[opens[places]]
    # Equal hashes side by side come from a few bytes repeated over and over: one cut a window is enough.
    tied = np.flatnonzero((np.diff(hashes[places]) == 0) & (np.diff(places) < WINDOW) & (np.diff(begins[places]) == 0)) + 1
    if len(tied):
        kept, last, before = np.ones(len(places), bool), 0, -1
        for i in tied.tolist():
            if i - 1 != before:
                last = places[i - 1]
            kept[i] = places[i] - last >= WINDOW
            if kept[i]:
                last = places[i]
            before = i
        places = places[kept]
    cuts = np.union1d(places + 1, offsets[1:][sizes > 0])
    return cuts, np.diff(np.searchsorted(cuts, offsets, "right"))


def chunk_rows(texts: DataFrame, ids: list[str]) -> DataFrame:
    """``ids, text`` -> a row for each chunk with its place, size and hash."""
    schema = T.StructType([*[T.StructField(c, _long) for c in ids], T.StructField("at", _int), T.StructField("size", _int), T.StructField("hash", _long)])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        own = [np.asarray(batch.column(i)) for i in range(len(ids))]
        data, offsets, _ = K.text_column(batch.column(len(ids)))
        for row, end, raw, cuts in K.pieces(data, offsets):
            ends, counts = chunk_ends(raw, cuts)
            docs = np.repeat(np.arange(end - row), counts)
            starts = np.concatenate([[0], ends[:-1]]) if len(ends) else ends
            hashes = K.digests(raw, np.maximum(starts - _ROLL, cuts[docs]), ends).view(np.int64)
            yield [*[pa.array(x[row + docs]) for x in own], *[pa.array(x.astype(np.int32)) for x in (starts - cuts[docs], ends - starts)], pa.array(hashes)]

    return exploded_by_arrow(texts.select(*ids, "text"), schema, kernel)


def duplicate_runs(chunks: DataFrame, ids: list[str]) -> DataFrame:
    """Runs of neighbouring chunks that stand elsewhere too: ``ids, start, size, n`` and the place in the first holder.

    That place is null for chunks that the document holds first.
    """
    place, held = F.struct(*ids, "at"), [f"first_{c}" for c in ids]
    alike = Window.partitionBy("hash").orderBy(*ids, "at")
    every = alike.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    found = chunks.withColumns({"here": place, "prev": F.lag(place).over(alike), "first": F.first(place).over(every), "last": F.last(place).over(every)})
    found = found.where("first <> last AND NOT here <=> prev")  # rows alike in id and text are one document
    later = F.col("here") != F.col("first")
    found = found.select(*ids, "at", "size", *[F.when(later, F.col(f"first.{c}")).alias(f"first_{c}") for c in (*ids, "at")])
    line = Window.partitionBy(*ids).orderBy("at")
    follows = F.lag(F.col("at") + F.col("size")).over(line) == F.col("at")
    for c in held:
        follows &= F.lag(c).over(line).eqNullSafe(F.col(c))
    follows &= F.lag(F.col("first_at") + F.col("size")).over(line).eqNullSafe(F.col("first_at"))
    found = found.withColumn("new", F.when(follows, 0).otherwise(1)).withColumn("run", F.sum("new").over(line))
    return found.groupBy(*ids, "run").agg(F.min("at").alias("start"), F.sum("size").cast("int").alias("size"), F.count(F.lit(1)).alias("n"), *[F.first(c).alias(c) for c in held], F.min("first_at").alias("first_start")).drop("run")


def holders_bytes(texts: DataFrame, asked: DataFrame, ids: list[str]) -> DataFrame:
    """For each run asked of a holder, the digest of its bytes and the bytes before and after it."""
    schema = T.StructType([*[T.StructField(f"first_{c}", _long) for c in ids], T.StructField("first_start", _int), T.StructField("size", _int), *[T.StructField(c, T.BinaryType()) for c in ("digest", "before", "after")]])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        at = batch.schema.get_field_index
        columns = [batch.column(at(c)) for c in (*ids, "text", "asked")]
        for row in range(len(columns[0])):
            *own, text, runs = (c[row].as_py() for c in columns)
            raw, out = (text or "").encode(), []
            for r in runs:
                s, e = r["first_start"], r["first_start"] + r["size"]
                out.append((*own, s, r["size"], xxhash.xxh3_128_digest(raw[s:e]), raw[max(0, s - _BEFORE) : s], raw[e : e + _AFTER]))
            yield [pa.array(c, t) for c, t in zip(zip(*out), [pa.int64()] * len(ids) + [pa.int32()] * 2 + [pa.binary()] * 3)]

    # All columns of the texts are kept, so that the final cut uses the same exchange.
    return exploded_by_arrow(texts.join(asked, ids).select(*texts.columns, "asked"), schema, kernel)


CUT = T.StructType([T.StructField("doc_id", T.LongType()), *[T.StructField(c, T.LongType()) for c in ("n_bytes", "n_chunks", "n_shared_chunks", "n_removed")], T.StructField("kept_sha256", T.StringType()), T.StructField("text", T.StringType())])


def deduplicated(docs: DataFrame, min_run: int = 96) -> DataFrame:
    """``doc_id, text`` -> ``doc_id, n_bytes, n_chunks, n_shared_chunks, n_removed, kept_sha256, text``, one row per input row.

    ``text`` is what stays; ``n_shared_chunks`` counts chunks that are cut out at least in part and, where
    the document is the first holder, those of runs that, with the 32 bytes before them, have ``min_run`` bytes. The first holder is the least (id, hash
    of the text, position); a null id comes before all. Rows alike in id and text count as one
    document. A null text counts as empty and stays null. Empty input gives no rows; other
    columns are ignored.
    """
    doc_id = F.col("doc_id").cast("long")
    texts = docs.select(doc_id.alias("doc_id"), F.coalesce(doc_id, F.lit(_LEAST_ID)).alias("own"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("key"), "text")
    ids = ["own", "key"]
    if texts.groupBy("own").agg(F.count(F.lit(1)).alias("c")).where("c > 1").isEmpty():  # the id alone tells documents apart
        ids, texts = ["own"], texts.drop("key")
    runs = written(duplicate_runs(chunk_rows(texts, ids), ids), "runs")
    held = [*[f"first_{c}" for c in ids], "first_start", "size"]
    asked = runs.where("first_start IS NOT NULL").select(*held).distinct().groupBy(*[F.col(f"first_{c}").alias(c) for c in ids]).agg(F.collect_list(F.struct("first_start", "size")).alias("asked"))
    answers = runs.join(holders_bytes(texts, asked, ids), held, "left")
    answer = F.when(F.col("digest").isNotNull(), F.struct("start", "size", "digest", "before", "after"))
    held_runs = F.when(F.col("first_start").isNull() & (F.col("size") + _ROLL >= min_run), F.col("n"))
    found = answers.groupBy(*ids).agg(F.sum(held_runs).alias("shared"), F.collect_list(answer).alias("found"))

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        at = batch.schema.get_field_index
        data, offsets, nulls = K.text_column(batch.column(at("text")))
        doc, shared, found = (batch.column(at(c)) for c in ("doc_id", "shared", "found"))
        for row, end, raw, cuts in K.pieces(data, offsets):
            ends, counts = chunk_ends(raw, cuts)
            last = np.cumsum(counts)
            out = []
            for d in range(end - row):
                text = raw[cuts[d] : cuts[d + 1]].tobytes()
                spans = _removed(text, found[row + d].as_py() or (), min_run)
                own_ends = ends[last[d] - counts[d] : last[d]] - cuts[d]
                touched = sum(int(np.searchsorted(own_ends, b, "left") - np.searchsorted(own_ends, a, "right")) + 1 for a, b in spans)
                kept = b"".join(text[a:b] for a, b in zip([0, *[b for _, b in spans]], [*[a for a, _ in spans], len(text)]))
                shared_chunks = min(int(counts[d]), touched + (shared[row + d].as_py() or 0))
                out.append((doc[row + d].as_py(), len(text), int(counts[d]), shared_chunks, len(text) - len(kept), hashlib.sha256(kept).hexdigest(), None if nulls[row + d] else kept.decode()))
            yield [pa.array(c, t) for c, t in zip(zip(*out), [pa.int64()] * 5 + [pa.string()] * 2)]

    return exploded_by_arrow(texts.join(found, ids, "left").select(*texts.columns, "shared", "found"), CUT, kernel)


def _alike(a: bytes, b: bytes, order: str) -> int:
    """How many bytes of two strings of one length are equal from the front (big) or the back (little)."""
    return len(a) - ((int.from_bytes(a, order) ^ int.from_bytes(b, order)).bit_length() + 7) // 8


def _matches(text: bytes, found: list[dict]) -> Iterator[tuple[int, int]]:
    """The runs that are equal to their holder's bytes, extended to whole characters of the match."""
    for r in found:
        s, e = r["start"], r["start"] + r["size"]
        if xxhash.xxh3_128_digest(text[s:e]) != r["digest"]:
            continue
        n = min(s, len(r["before"]))
        s -= _alike(text[s - n : s], r["before"][len(r["before"]) - n :], "little")
        n = min(len(text) - e, len(r["after"]))
        e += _alike(text[e : e + n], r["after"][:n], "big")
        while text[s] & 0xC0 == 0x80:
            s += 1
        while e < len(text) and text[e] & 0xC0 == 0x80:
            e -= 1
        yield s, e


def _removed(text: bytes, found: list[dict], min_run: int) -> list[tuple[int, int]]:
    """The matches, joined where they touch, that have ``min_run`` bytes or are the whole text."""
    joined: list[list[int]] = []
    for s, e in sorted(_matches(text, found)):
        if joined and s <= joined[-1][1]:
            joined[-1][1] = max(joined[-1][1], e)
        else:
            joined.append([s, e])
    return [(s, e) for s, e in joined if e - s >= min_run or e - s == len(text)]


def op1_content_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicated(table(spark, sf_dir, "documents").select("doc_id", "text"))
