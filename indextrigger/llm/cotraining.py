"""Operator 3: a quality classifier by co-training.

Two classifiers see different sides of a document: one its text (words, runs of symbols, layout
figures), one its page metadata (language, source, size). Both
start from the labelled rows. In each round both score all unlabelled documents, and
each learns from the documents of which the *other* is most sure. At the end both are
calibrated on labelled rows that nothing was fitted on, terms and bins included, and the calibrated
views are combined: their log-odds against the share of bad rows add up.

The labelled rows are a bounded sample, chosen by a hash of the id (``TRAIN_ROWS``), with at most
``MAX_TERMS`` terms, and a round hands over at most ``EXCHANGED`` documents for each class and
view, the surest of the whole corpus. Scoring covers every whole text in one pass without a shuffle,
with a model of bounded size; the rounds read a table of the columns that are on in each document.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .arrow_rows import exploded_by_arrow, with_arrow_columns
from .storage import Scratch, table, written

#: Bounds of training: labelled rows, terms of the text view, and documents handed over by a view in a round for a class.
TRAIN_ROWS, MAX_TERMS, EXCHANGED = 20_000, 4_000, 1_000
#: A term must tell the classes apart by at least this log-likelihood ratio.
LEAST_RATIO = 10.0
BINS, NAME_CELLS = 12, 32
LAYOUT = ("log_bytes", "log_words", "bytes_per_word", "lines_per_word", "upper", "symbols", "digits", "repeated_words", "repeated_lines")

_bytes = np.arange(256)
_word_table = K.byte_table(K.ALNUM, lower=True)
_mark = (_bytes > 0x20) & (_bytes < 0x7F) & ~K.ALNUM
_mark_table = K.byte_table(_mark, lower=False)
_spaced_table = K.byte_table(K.SPACED, lower=False)
_line_table = K.byte_table(_bytes != 0x0A, lower=False)


def terms(raw: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Document and hash of every term: lowered words and runs of symbols (salted, so they differ from words)."""
    docs, found = [], []
    for table_, salt in ((_word_table, 0), (_mark_table, 0x5BD1E995)):
        _, _, hashes, bounds = K.words(raw, cuts, table_)
        docs.append(np.repeat(np.arange(len(cuts) - 1), np.diff(bounds)))
        found.append(hashes ^ np.uint64(salt))
    return np.concatenate(docs), np.concatenate(found).view(np.int64)


def _distinct(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Number of different hashes in each document."""
    n = len(bounds) - 1
    docs = np.repeat(np.arange(n), np.diff(bounds))
    order = np.lexsort((hashes, docs))
    d, h = docs[order], hashes[order]
    new = np.concatenate([[True], (d[1:] != d[:-1]) | (h[1:] != h[:-1])]) if len(d) else np.zeros(0, bool)
    return np.bincount(d[new], minlength=n)


def layout(raw: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """The layout figures of every document of a piece, one row each; an empty text has zeros."""
    n_bytes = np.diff(cuts).astype(float)
    _, _, hashes, bounds = K.words(raw, cuts, _spaced_table)
    _, _, lines, line_bounds = K.words(raw, cuts, _line_table)
    n_words, n_lines = np.diff(bounds).astype(float), np.diff(line_bounds).astype(float)

    def share(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask)])
        return (total[cuts[1:]] - total[cuts[:-1]]) / np.maximum(n_bytes, 1)

    upper = ((raw >= 65) & (raw <= 90)) | ((raw >= 0x80) & (raw <= 0x9E) & (np.concatenate([[0], raw[:-1]]) == 0xC3) if len(raw) else raw > 0)
    repeated = 1 - _distinct(hashes, bounds) / np.maximum(n_words, 1)
    same_lines = 1 - _distinct(lines, line_bounds) / np.maximum(n_lines, 1)
    columns = [np.log1p(n_bytes), np.log1p(n_words), n_bytes / np.maximum(n_words, 1), n_lines / np.maximum(n_words, 1), share(upper), share(_mark[raw] if len(raw) else raw > 0), share((raw >= 48) & (raw <= 57)), np.where(n_words > 0, repeated, 0), np.where(n_lines > 0, same_lines, 0)]
    return np.stack(columns, axis=1)


def name_cell(name: str | None) -> int:
    return 0 if name is None else 1 + xxhash.xxh64_intdigest(name) % (NAME_CELLS - 1)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class Linear:
    """A logistic model over active columns, given as (row, column) pairs."""

    width: int
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))
    bias: float = 0.0

    def score(self, rows: np.ndarray, columns: np.ndarray, n: int) -> np.ndarray:
        return np.bincount(rows, self.weights[columns], minlength=n) + self.bias

    def fit(self, rows: np.ndarray, columns: np.ndarray, y: np.ndarray, used: np.ndarray, penalty: float = 1.0, steps: int = 150) -> "Linear":
        """Full-gradient descent with steps scaled to each weight; deterministic."""
        on = used[rows] > 0
        rows, columns, n = rows[on], columns[on], len(y)
        total = max(used.sum(), 1.0)
        self.weights, self.bias = np.zeros(self.width), float(np.log((y @ used + 1) / ((1 - y) @ used + 1)))
        squares, bias_square = np.full(self.width, 1e-8), 1e-8
        for _ in range(steps):
            error = (sigmoid(self.score(rows, columns, n)) - y) * used
            slope = (np.bincount(columns, error[rows], minlength=self.width) + penalty * self.weights) / total
            down = error.sum() / total
            squares += slope**2
            bias_square += down**2
            self.weights -= 0.3 * slope / np.sqrt(squares)
            self.bias -= 0.3 * down / np.sqrt(bias_square)
        return self


def calibration(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and intercept that turn scores into probabilities; Newton steps on two numbers."""
    a, b = 1.0, 0.0
    prior = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    for _ in range(50):
        p = sigmoid(a * z + b)
        g = np.array([((p - prior) * z).sum() + 1e-3 * (a - 1), (p - prior).sum()])
        w = p * (1 - p)
        h = np.array([[(w * z * z).sum() + 1e-3, (w * z).sum()], [(w * z).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = a - float(np.clip(step[0], -2, 2)), b - float(np.clip(step[1], -2, 2))
        if np.abs(step).max() < 1e-8:
            break
    return max(a, 0.0), b


@dataclass
class CoTrained:
    """Both views, their calibration, and the probability from which a document is rejected."""

    term_hashes: np.ndarray
    bounds: np.ndarray
    size_bounds: np.ndarray
    content: Linear
    metadata: Linear
    scales: tuple[tuple[float, float], tuple[float, float]] = ((1.0, 0.0), (1.0, 0.0))
    prior: float = 0.5
    threshold: float = 0.5

    @classmethod
    def blank(cls, term_hashes: np.ndarray, bounds: np.ndarray, size_bounds: np.ndarray) -> "CoTrained":
        return cls(term_hashes, bounds, size_bounds, Linear(len(term_hashes) + len(LAYOUT) * BINS), Linear(BINS + 1 + 2 * NAME_CELLS))

    def content_cells(self, raw: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(document, column) of the terms that a document has and of the bins of its figures."""
        docs, hashes = terms(raw, cuts)
        width = len(self.term_hashes)
        pairs = np.zeros(0, np.int64)
        if width and len(hashes):
            at = np.searchsorted(self.term_hashes, hashes)
            at[at == width] = 0
            hit = self.term_hashes[at] == hashes
            pairs = np.unique(docs[hit] * width + at[hit])
        figures = layout(raw, cuts)
        n, k = figures.shape
        bins = np.stack([width + j * BINS + np.searchsorted(self.bounds[j], figures[:, j], "right") for j in range(k)], axis=1)
        rows = np.concatenate([pairs // max(width, 1), np.repeat(np.arange(n), k)])
        order = np.argsort(rows, kind="stable")
        return rows[order], np.concatenate([pairs % max(width, 1), bins.ravel()])[order]

    def metadata_cells(self, langs: list, sources: list, sizes: list) -> tuple[np.ndarray, np.ndarray]:
        n = len(langs)
        known = np.array([-1.0 if x is None else float(x) for x in sizes])
        cells = [np.where(known < 0, BINS, np.searchsorted(self.size_bounds, known, "right"))]
        cells.append(BINS + 1 + np.fromiter(map(name_cell, langs), np.int64, n))
        cells.append(BINS + 1 + NAME_CELLS + np.fromiter(map(name_cell, sources), np.int64, n))
        return np.repeat(np.arange(n), 3), np.stack(cells, axis=1).ravel()

    def combined(self, scores: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        odds = [a * z + b for (a, b), z in zip(self.scales, scores)]
        both = odds[0] + odds[1] - np.log(self.prior / (1 - self.prior))
        return sigmoid(odds[0]), sigmoid(odds[1]), sigmoid(both)


METADATA = ("lang", "source", "n_chars")


def with_metadata(docs: DataFrame) -> DataFrame:
    """``docs`` with all metadata columns; those that are missing are null."""
    kinds = {"lang": "string", "source": "string", "n_chars": "long"}
    for c in METADATA:
        docs = docs.withColumn(c, (F.col(c) if c in docs.columns else F.lit(None)).cast(kinds[c]))
    return docs


def training_rows(docs: DataFrame, labels: DataFrame, train_rows: int) -> DataFrame:
    """``doc_id, bad, text, lang, source, n_chars``: a bounded sample of labelled documents.

    Of rows that share an id the least text stands for all, so that the sample has one row for each id.
    """
    marks = labelled(labels).orderBy(F.xxhash64(F.lit("fit"), "doc_id"), "doc_id").limit(train_rows)
    ids = written(marks, "fit-ids")
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), *METADATA).join(F.broadcast(ids), "doc_id")  # train_rows ids at most
    one = found.groupBy("doc_id", "bad").agg(F.min(F.struct("text", *METADATA)).alias("x"))
    return written(one.select("doc_id", "bad", "x.*"), "fit-rows")


def labelled(labels: DataFrame) -> DataFrame:
    """``doc_id, bad``: low quality in any row of an id, or toxic in any; rows without an id or a quality are left out."""
    marks = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy("doc_id").agg((F.min("quality") == 0).alias("low"), (F.max(F.coalesce("toxic", F.lit(0))) > 0).alias("toxic"))
    return marks.select("doc_id", (F.col("low") | F.col("toxic")).cast("int").alias("bad"))


def held_out(doc_id: Column) -> Column:
    """Whether a labelled row serves to calibrate, and to nothing else."""
    return F.pmod(F.xxhash64(F.lit("calibrate"), doc_id), F.lit(4)) == 0


def chosen_terms(rows: DataFrame, max_terms: int, least_ratio: float) -> np.ndarray:
    """Terms that bad documents have more often than good ones, the most telling by log-likelihood ratio.

    Terms of good documents are left out: a short text lacks them, which says nothing against it.
    """
    seen = T.StructType([T.StructField("bad", T.IntegerType()), T.StructField("term", T.LongType())])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        bad = np.asarray(batch.column(0))
        data, offsets, _ = K.text_column(batch.column(1))
        for row, _, raw, cuts in K.pieces(data, offsets):
            docs, hashes = terms(raw, cuts)
            pairs = np.unique(np.stack([docs, hashes], axis=1), axis=0) if len(docs) else np.zeros((0, 2), np.int64)
            yield [pa.array(bad[row + pairs[:, 0]].astype(np.int32)), pa.array(pairs[:, 1])]

    total = rows.agg(F.coalesce(F.sum("bad"), F.lit(0)).alias("b"), F.count(F.lit(1)).alias("n")).first()
    b, g = float(total["b"]), float(total["n"] - total["b"])
    if not b or not g:
        return np.zeros(0, np.int64)
    counts = exploded_by_arrow(rows.select("bad", "text"), seen, kernel).groupBy("term").agg(F.sum("bad").cast("double").alias("x"), F.count(F.lit(1)).cast("double").alias("m"))
    part = lambda k, e: F.when(k > 0, k * F.log(k / e)).otherwise(0.0)
    x, m, n = F.col("x"), F.col("m"), b + g
    y = m - x
    ratio = 2 * (part(x, m * b / n) + part(y, m * g / n) + part(b - x, (n - m) * b / n) + part(g - y, (n - m) * g / n))
    best = counts.where((m >= 3) & (x * n > m * b)).withColumn("ratio", ratio).where(F.col("ratio") >= least_ratio).orderBy(F.desc("ratio"), "term").limit(max_terms)
    return np.sort(np.array([r["term"] for r in best.select("term").collect()], np.int64))


def bins(values: np.ndarray, bad: np.ndarray) -> np.ndarray:
    """Bounds of the bins of a figure: half follow all rows, half the bad ones, which would else share the outer bins."""
    half = BINS // 2
    return np.sort(np.concatenate([np.quantile(values, np.arange(1, BINS - half) / (BINS - half)), np.quantile(values[bad], np.arange(1, half + 1) / (half + 1))]))


CELLS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("content", T.ArrayType(T.IntegerType(), False)), T.StructField("metadata", T.ArrayType(T.IntegerType(), False))])


def cells_of(docs: DataFrame, model: CoTrained) -> DataFrame:
    """``doc_id, content, metadata``: the columns that are on in each view of a document, from one pass over the texts."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        own = shipped.value
        data, offsets, _ = K.text_column(batch.column(1))
        for row, end, raw, cuts in K.pieces(data, offsets):
            n = end - row
            found, cells = own.content_cells(raw, cuts)
            _, meta = own.metadata_cells(*(batch.column(i).slice(row, n).to_pylist() for i in (2, 3, 4)))
            yield [batch.column(0).slice(row, n), K.lists(cells.astype(np.int32), np.bincount(found, minlength=n), pa.int32()), K.lists(meta.astype(np.int32), np.full(n, 3), pa.int32())]

    return exploded_by_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *METADATA), CELLS, kernel)


@dataclass
class Rows:
    """Training rows: active columns of each view, and target and weight in each view."""

    columns: list[list[np.ndarray]]
    target: list[np.ndarray]
    weight: list[np.ndarray]

    def active(self, view: int) -> tuple[np.ndarray, np.ndarray]:
        lengths = np.fromiter(map(len, self.columns[view]), np.int64, len(self.columns[view]))
        return np.repeat(np.arange(len(lengths)), lengths), np.concatenate(self.columns[view]) if len(lengths) else np.zeros(0, np.int64)

    def add(self, content: np.ndarray, metadata: np.ndarray, taker: int, label: int) -> None:
        for view, cells in enumerate((content, metadata)):
            self.columns[view].append(cells)
        for view in (0, 1):
            self.target[view] = np.append(self.target[view], label)
            self.weight[view] = np.append(self.weight[view], 0.5 if view == taker else 0.0)


def surest(pool: DataFrame, model: CoTrained, sure: float, exchanged: int, scratch: Scratch, tag: str) -> list:
    """The documents of the pool of which either view is surest, at most ``exchanged`` for each view and class."""
    shipped = pool.sparkSession.sparkContext.broadcast(model)

    def kernel(batch: pa.RecordBatch) -> list[pa.Array]:
        own, out = shipped.value, []
        for i, view in ((1, own.content), (2, own.metadata)):
            column = batch.column(i)
            lengths = np.diff(np.asarray(column.offsets))
            cells = np.asarray(column.flatten())
            out.append(pa.array(sigmoid(view.score(np.repeat(np.arange(len(lengths)), lengths), cells, len(lengths)))))
        return out

    schema = T.StructType([T.StructField(f"p{v}", T.DoubleType()) for v in (0, 1)])
    rated = scratch.keep(with_arrow_columns(pool, schema, kernel).groupBy("doc_id").agg(F.min("p0").alias("p0"), F.min("p1").alias("p1")), f"rated-{tag}")
    picks = None
    for giver in (0, 1):
        for label in (1, 0):
            certain = F.col(f"p{giver}") if label else 1 - F.col(f"p{giver}")
            part = rated.where(certain >= sure).orderBy(F.desc(F.round(certain, 9)), F.xxhash64("doc_id"), "doc_id").limit(exchanged)
            part = part.select("doc_id", F.lit(giver).alias("giver"), F.lit(label).alias("label"))
            picks = part if picks is None else picks.unionByName(part)
    picks = scratch.keep(picks, f"picks-{tag}")
    picked = pool.join(F.broadcast(picks), "doc_id")  # 4 * exchanged ids at most
    one = picked.groupBy("doc_id", "giver", "label").agg(F.min(F.struct("content", "metadata")).alias("x"))
    found = one.select("doc_id", "giver", "label", "x.*").orderBy("giver", "label", "doc_id").collect()
    scratch.drop(f"rated-{tag}", f"picks-{tag}")
    return found


def fit(docs: DataFrame, labels: DataFrame, rounds: int = 3, train_rows: int = TRAIN_ROWS, max_terms: int = MAX_TERMS, least_ratio: float = LEAST_RATIO, exchanged: int = EXCHANGED, sure: float = 0.95) -> CoTrained:
    """Fits both views. Each round hands over at most ``exchanged`` documents for each view and class, and
    only those of which the giving view is at least ``sure``. Without labels of both classes all documents pass."""
    docs = with_metadata(docs)
    scratch = Scratch(docs.sparkSession)
    rows = training_rows(docs, labels, train_rows)
    training = rows.where(~held_out(F.col("doc_id")))
    term_hashes = chosen_terms(training, max_terms, least_ratio)
    shape = T.StructType([T.StructField("bad", T.IntegerType()), T.StructField("n_chars", T.LongType()), T.StructField("figures", T.ArrayType(T.DoubleType(), False))])

    def figures_of(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        data, offsets, _ = K.text_column(batch.column(2))
        for row, end, raw, cuts in K.pieces(data, offsets):
            figures = layout(raw, cuts)
            yield [*(batch.column(i).slice(row, end - row) for i in (0, 1)), K.lists(figures.ravel(), np.full(end - row, figures.shape[1]), pa.float64())]

    seen = exploded_by_arrow(training.select("bad", "n_chars", "text"), shape, figures_of).collect()  # train_rows at most
    bad = np.array([r["bad"] == 1 for r in seen], bool)
    if not bad.any() or bad.all():
        model = CoTrained.blank(term_hashes, np.zeros((len(LAYOUT), BINS - 1)), np.zeros(BINS - 1))
        model.content.weights, model.metadata.weights = np.zeros(model.content.width), np.zeros(model.metadata.width)
        model.threshold = 2.0
        return model
    figures = np.array([r["figures"] for r in seen])
    sizes = np.array([float(r["n_chars"] or 0) for r in seen])
    model = CoTrained.blank(term_hashes, np.stack([bins(figures[:, j], bad) for j in range(figures.shape[1])]), bins(sizes, bad))
    cells = scratch.keep(cells_of(docs.where("doc_id IS NOT NULL"), model), "cells")
    marks = rows.select("doc_id", "bad", held_out(F.col("doc_id")).alias("held"))
    known = cells_of(rows, model).join(F.broadcast(marks), "doc_id").orderBy("doc_id").collect()  # train_rows at most
    pool = cells.join(labelled(labels).select("doc_id"), "doc_id", "left_anti")
    target = np.array([float(r["bad"]) for r in known])
    held = np.array([r["held"] for r in known])
    data = Rows([[np.array(r[v], np.int64) for r in known] for v in ("content", "metadata")], [target.copy(), target.copy()], [(~held).astype(float) for _ in (0, 1)])
    taken: set[tuple[int, int]] = set()
    for turn in range(rounds + 1):
        for view, linear in enumerate((model.content, model.metadata)):
            linear.fit(*data.active(view), data.target[view], data.weight[view])
        if turn == rounds:
            break
        for r in surest(pool, model, sure, exchanged, scratch, str(turn)):
            taker = 1 - r["giver"]
            if (r["doc_id"], taker) not in taken:
                taken.add((r["doc_id"], taker))
                data.add(np.array(r["content"], np.int64), np.array(r["metadata"], np.int64), taker, r["label"])
    scratch.drop("cells")
    at = np.flatnonzero(held) if 0 < target[held].sum() < held.sum() else np.arange(len(target))
    scores = [linear.score(*data.active(v), len(data.target[v]))[at] for v, linear in enumerate((model.content, model.metadata))]
    model.scales = tuple(calibration(z, target[at]) for z in scores)
    model.prior = float((target[at].sum() + 1) / (len(at) + 2))
    return model


SCORES = T.StructType([*[T.StructField(c, T.DoubleType()) for c in ("content_bad", "metadata_bad", "bad_score")], T.StructField("kept", T.BooleanType())])


def scored(docs: DataFrame, model: CoTrained) -> DataFrame:
    """``docs`` plus ``content_bad, metadata_bad, bad_score, kept``.

    A null text is scored as empty; null or missing metadata have a cell of their own; repeated rows score
    alike, and same-named input columns are replaced.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # at most MAX_TERMS terms

    def kernel(batch: pa.RecordBatch) -> list[pa.Array]:
        own = shipped.value
        data, offsets, _ = K.text_column(batch.column(batch.schema.get_field_index("text")))
        at = [batch.schema.get_field_index(c) for c in METADATA]
        meta = [batch.column(i).to_pylist() if i >= 0 else [None] * batch.num_rows for i in at]
        out = [[], [], []]
        for row, end, raw, cuts in K.pieces(data, offsets):
            n = end - row
            by_content = own.content.score(*own.content_cells(raw, cuts), n)
            by_metadata = own.metadata.score(*own.metadata_cells(*(m[row:end] for m in meta)), n)
            for held, p in zip(out, own.combined((by_content, by_metadata))):
                held.append(p)
        a, b, c = (np.concatenate(x) if x else np.zeros(0) for x in out)
        return [pa.array(a), pa.array(b), pa.array(c), pa.array(c < own.threshold)]

    return with_arrow_columns(docs, SCORES, kernel)


def op3_cotrained_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", *METADATA)
    return scored(docs, fit(docs, table(spark, sf_dir, "labels"))).drop("text", *METADATA)
