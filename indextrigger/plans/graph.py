"""Connected components of small graphs of features or chains, without collecting them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.staging import staged

#: Graphs of up to so many nodes and edges are labelled by one task, which costs less than the rounds of small jobs.
TASK_ROWS = 500_000


def _labelled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``id, other``, a node where ``other`` is null and else an edge -> ``id, component``."""
    held = list(batches)
    if not held:
        return
    id_, other = (np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in held]) for i in (0, 1))
    edge = np.concatenate([b.column(1).is_valid().to_numpy(zero_copy_only=False) for b in held])
    known = np.concatenate([b.column(0).is_valid().to_numpy(zero_copy_only=False) for b in held])
    kind = held[0].schema.field(0).type
    ids = np.unique(id_[~edge & known])
    if not known.all():  # no edge meets a null
        yield pa.RecordBatch.from_arrays([pa.nulls(1, kind)] * 2, names=["id", "component"])
    if not len(ids):
        return
    a, b = (np.searchsorted(ids, x[edge]) for x in (id_, other))
    a, b = np.minimum(a, len(ids) - 1), np.minimum(b, len(ids) - 1)
    inside = (ids[a] == id_[edge]) & (ids[b] == other[edge])  # edges of other nodes lead nowhere
    a, b = a[inside], b[inside]
    labels, seen = np.arange(len(ids)), None
    while seen is None or (labels != seen).any():
        seen, labels = labels, labels.copy()
        least = np.minimum(seen[a], seen[b])
        for x in (a, b, seen[a], seen[b]):
            np.minimum.at(labels, x, least)
        labels = labels[labels]
    yield pa.RecordBatch.from_arrays([pa.array(ids, kind), pa.array(ids[labels], kind)], names=["id", "component"])


def connected(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """``id`` and ``a, b`` -> ``id, component``: the least id that edges reach.

    A small graph is labelled in one task. In a larger one each round takes the least label among the neighbours
    and then the label's own label, so rounds grow with the logarithm of the diameter on chains; each is
    written to the shared folder.
    """
    kind = nodes.schema["id"].dataType
    nodes = nodes.select("id", F.lit(None).cast(kind).alias("other")).distinct()
    pairs = edges.select(F.col("a").cast(kind), F.col("b").cast(kind)).where("a IS NOT NULL AND b IS NOT NULL")
    graph = staged(nodes.union(pairs), "edges")
    if graph.count() <= TASK_ROWS:
        schema = f"id {kind.simpleString()}, component {kind.simpleString()}"
        return staged(graph.coalesce(1).mapInArrow(_labelled, schema), "labels")
    pairs = graph.where("other IS NOT NULL").toDF("a", "b")
    both = staged(pairs.union(pairs.select("b", "a")).distinct(), "edges")
    labels = staged(graph.where("other IS NULL").select("id", F.col("id").alias("component")), "labels")
    while True:
        seen = both.join(labels.select(F.col("id").alias("b"), F.col("component").alias("far")), "b").groupBy("a").agg(F.min("far").alias("far"))
        nearer = labels.join(seen.withColumnRenamed("a", "id"), "id", "left").select("id", F.col("component").alias("old"), F.least("component", F.coalesce("far", "component")).alias("component"))
        hop = nearer.select(F.col("id").alias("component"), F.col("component").alias("root"))
        moved = staged(nearer.join(hop, "component", "left").select("id", "old", F.least("component", F.coalesce("root", "component")).alias("component")), "labels")
        labels = moved.select("id", "component")
        if moved.where("old <> component").isEmpty():
            return labels
