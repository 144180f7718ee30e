"""Per window: topics that burst there, grouped by the documents they share."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import GroupParams
from ..sources.staging import dealt, staged
from .topics import members_of

#: Tokens that one block of a window's documents is meant to have, and cells of documents times topics in one product.
BLOCK_ROWS, DOT_CELLS = 500_000, 2_000_000
#: Words of bursting topics that are sent to all executors, a row for each window; more are joined by a shuffle.
BROADCAST_CELLS = 1_000_000
DOT_SCHEMA = "win int, t int, u int, dot long"
GROUP_SCHEMA = "win int, group_id int, topics array<int>, k int, ratio double"


def _dots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``win, block, doc_id, topic_id`` sorted in this order -> products of the counts of two topics, added up over the documents of a block."""

    def dots(win: int, doc: np.ndarray, topic: np.ndarray) -> pa.RecordBatch:
        ids, at = np.unique(topic, return_inverse=True)
        number = np.concatenate([[0], np.cumsum(doc[1:] != doc[:-1])])
        width, step = len(ids), max(1, DOT_CELLS // len(ids))
        table = np.zeros((width, width))
        for first in range(0, int(number[-1]) + 1, step):
            part = slice(*np.searchsorted(number, [first, first + step]))
            own = number[part] - first
            counts = np.bincount(own * width + at[part], minlength=(int(own[-1]) + 1) * width).reshape(-1, width).astype(float)
            table += counts.T @ counts  # sums of whole numbers are exact
        i, j = np.nonzero(np.triu(table))
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(i), win, np.int32)), pa.array(ids[i].astype(np.int32)), pa.array(ids[j].astype(np.int32)), pa.array(table[i, j].astype(np.int64))], names=["win", "t", "u", "dot"])

    held: list[list[np.ndarray]] = []  # of one block
    for batch in batches:
        cells = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        if not len(cells[0]):
            continue
        edges = np.flatnonzero((cells[0][1:] != cells[0][:-1]) | (cells[1][1:] != cells[1][:-1])) + 1
        for first, end in zip([0, *edges], [*edges, len(cells[0])]):
            if held and (held[0][0][0] != cells[0][first] or held[0][1][0] != cells[1][first]):
                win, _, doc, topic = (np.concatenate(x) for x in zip(*held))
                yield dots(win[0], doc, topic)
                held = []
            held.append([c[first:end] for c in cells])
    if held:
        win, _, doc, topic = (np.concatenate(x) for x in zip(*held))
        yield dots(win[0], doc, topic)


def topic_gram(topics: DataFrame, tokens: DataFrame, rate: DataFrame) -> DataFrame:
    """``win, t, u, cosine`` with t <= u for all topics that burst in a window and share a document (t = u: 1).

    A topic weighs in a document by the mean count of its words, and as its size cancels out in the cosine, whole counts
    are multiplied. A task adds up the products of the documents of a window, or of one of several
    blocks of a window with many tokens, in one square table, so no row is made for a pair of a document.
    """
    blocks = tokens.groupBy("win").agg(F.ceil(F.count(F.lit(1)) / BLOCK_ROWS).cast("int").alias("blocks"))
    bursting = rate.where("bursty").select("topic_id", "win").join(members_of(topics).drop("size"), "topic_id").join(blocks, "win")
    bursting = staged(bursting, "bursting")
    cells = tokens.join(F.broadcast(bursting) if bursting.count() <= BROADCAST_CELLS else bursting, ["win", "feature"])
    dealt_out = cells.where("doc_id IS NOT NULL").select("win", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int").alias("block"), "doc_id", "topic_id")
    dealt_out = dealt(dealt_out, "win", "block").sortWithinPartitions("win", "block", "doc_id")
    dots = staged(dealt_out.mapInArrow(_dots, DOT_SCHEMA).groupBy("win", "t", "u").agg(F.sum("dot").alias("dot")), "dots")
    # Tokens without a document are one document of the window, which shares nothing but counts in the norms.
    unnamed = cells.where("doc_id IS NULL").groupBy("win", F.col("topic_id").alias("t")).agg(F.count(F.lit(1)).alias("n")).select("win", "t", (F.col("n") * F.col("n")).alias("dot"))
    norms = dots.where("t = u").select("win", "t", "dot").unionByName(unnamed).groupBy("win", "t").agg(F.sqrt(F.sum("dot")).alias("nt"))
    out = dots.join(norms, ["win", "t"]).join(norms.select("win", F.col("t").alias("u"), F.col("nt").alias("nu")), ["win", "u"])
    return out.select("win", "t", "u", (F.col("dot") / (F.col("nt") * F.col("nu"))).alias("cosine"))


def spherical_kmeans(gram: np.ndarray, k: int, rounds: int = 50) -> np.ndarray:
    """Labels by K-means on unit vectors known only by their cosines; farthest-first start, ties to the lowest index."""
    centers = [0]
    while len(centers) < k:
        near = gram[:, centers].max(axis=1)
        near[centers] = np.inf
        centers.append(int(near.argmin()))
    labels = gram[:, centers].argmax(axis=1)
    labels[centers] = np.arange(k)
    for _ in range(rounds):
        onehot = np.eye(k)[labels]
        sums = gram @ onehot
        lengths = np.sqrt(np.maximum(np.einsum("ij,ij->j", onehot, sums), 1e-300))
        new = (sums / lengths).argmax(axis=1)
        for c in np.flatnonzero(np.bincount(new, minlength=k) == 0):  # an empty cluster takes its nearest former member
            new[int(np.flatnonzero(labels == c)[0])] = c
        if (new == labels).all():
            break
        labels = new
    return labels


def cluster_quality(gram: np.ndarray, labels: np.ndarray) -> float:
    """Similarity between clusters over similarity inside them; smaller is better."""
    ids = np.unique(labels)
    n = len(labels)
    sizes = np.array([(labels == c).sum() for c in ids])
    onehot = (labels[:, None] == ids[None, :]).astype(float)
    blocks = onehot.T @ gram @ onehot
    inter = blocks / np.outer(sizes, sizes)
    intra = np.where(sizes > 1, (np.diag(blocks) - (onehot * np.diag(gram)[:, None]).sum(axis=0)) / np.maximum(sizes * (sizes - 1), 1), 1.0)
    np.fill_diagonal(inter, 0.0)
    between = (sizes / np.maximum(n - sizes, 1) * (inter @ sizes)).sum()
    inside = (sizes * intra).sum()
    return float(between / inside) if inside > 0 else float("inf")


def grouping(gram: np.ndarray, params: GroupParams) -> tuple[np.ndarray, int, float]:
    """Labels, number of groups and quality of one window's topics."""
    n = len(gram)
    if n == 1:
        return np.zeros(1, int), 1, 0.0
    if params.method == "threshold":
        labels = np.arange(n)
        for i in range(n):
            for j in np.flatnonzero(gram[i] >= params.cosine):
                labels[labels == labels[j]] = min(labels[i], labels[j])
                labels[labels == labels[i]] = min(labels[i], labels[j])
        labels = np.unique(labels, return_inverse=True)[1]
        k = int(labels.max()) + 1
        return labels, k, cluster_quality(gram, labels) if k > 1 else 0.0
    mean = (gram.sum() - np.trace(gram)) / (n * (n - 1))
    if params.k is None and mean >= params.merge_all_at:
        return np.zeros(n, int), 1, 0.0
    tried = [min(params.k, n)] if params.k else range(2, min(params.max_k or n, n) + 1)
    best = min(((cluster_quality(gram, labels := spherical_kmeans(gram, k)) if k > 1 else 0.0, k, labels if k > 1 else np.zeros(n, int)) for k in tried), key=lambda x: (round(x[0], 12), x[1]))
    return best[2], best[1], best[0]


def group_topics(gram: DataFrame, params: GroupParams = GroupParams()) -> DataFrame:
    """``win, group_id, topics, k, ratio``; a task holds the cosines of one window at a time."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(np.concatenate([pdf.t, pdf.u]))
        at = {t: i for i, t in enumerate(ids)}
        full = np.eye(len(ids))
        a, b = pdf.t.map(at).to_numpy(int), pdf.u.map(at).to_numpy(int)
        full[a, b] = full[b, a] = pdf.cosine
        labels, k, ratio = grouping(full, params)
        members = [sorted(int(t) for t in ids[labels == c]) for c in np.unique(labels)]
        members.sort()
        return pd.DataFrame({"win": int(pdf.win.iloc[0]), "group_id": range(len(members)), "topics": members, "k": k, "ratio": ratio})

    return dealt(gram, "win").groupBy("win").applyInPandas(work, GROUP_SCHEMA)
