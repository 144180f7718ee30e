"""How much two features share documents (Jaccard) and bursts (cosine of their series)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.staging import staged
from .graph import connected

#: Components of up to so many features are counted in square tables, packed to less than twice as many features each.
DENSE_FEATURES = 1_024
#: Rows and documents that a task turns into one product.
GRAM_ROWS, GRAM_DOCS = 200_000, 4_096
GRAM_SCHEMA = "bundle long, i long, j long, shared long"


def incidence(tokens: DataFrame) -> DataFrame:
    return tokens.select("doc_id", "feature").distinct()


def _ordered_pairs(rows: DataFrame, key: list[str], extra: list[str] = []) -> DataFrame:
    f = rows.select(*key, F.col("feature").alias("f"), *[F.col(c).alias(f"{c}_f") for c in extra])
    g = rows.select(*key, F.col("feature").alias("g"), *[F.col(c).alias(f"{c}_g") for c in extra])
    return f.join(g, key).where("f < g")


def _with_jaccard(shared: DataFrame, sizes: DataFrame) -> DataFrame:
    out = shared.join(sizes.select(F.col("feature").alias("f"), F.col("df").alias("df_f")), "f")
    out = out.join(sizes.select(F.col("feature").alias("g"), F.col("df").alias("df_g")), "g")
    return out.select("f", "g", "shared", "df_f", "df_g", (F.col("shared") / (F.col("df_f") + F.col("df_g") - F.col("shared"))).alias("jaccard"))


def _in_blocks(rows: DataFrame, key: str, extra: list[str], block_rows: int) -> DataFrame:
    """Ordered pairs of the features of each key, dealt by (key, block of f, block of g).

    The number of blocks follows the largest key, so that a key with very many features is
    paired by many tasks; with one block nothing is copied.
    """
    most = rows.groupBy(key).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    blocks = max(1, -(-most // block_rows))
    if blocks == 1:
        return _ordered_pairs(rows, [key], extra)
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    own = F.pmod(F.hash("feature"), F.lit(blocks))
    f = rows.select(key, F.col("feature").alias("f"), *[F.col(c).alias(f"{c}_f") for c in extra], own.alias("bf"), every.alias("bg"))
    g = rows.select(key, F.col("feature").alias("g"), *[F.col(c).alias(f"{c}_g") for c in extra], own.alias("bg"), every.alias("bf"))
    return f.join(g, [key, "bf", "bg"]).where("f < g").drop("bf", "bg")


def jaccard_pairs(tokens: DataFrame, method: str = "exact", hashes: int = 128, sample: int = 16, within: DataFrame | None = None) -> DataFrame:
    """``doc_id, feature`` -> ``f, g, shared, df_f, df_g, jaccard`` with f < g, pairs that share a document.

    ``exact`` pairs the features of each document; ``bitmap`` intersects bitmaps of documents by block
    (also exact, for ids from 0). Approximate, and labelled so by ``method``: ``minhash`` from one
    minimum per seed and feature, ``theta`` from sketches, ``sample`` from one document in ``sample`` by hash.
    ``theta`` estimates the pairs of ``within`` (``f, g``), such as those that burst together, and needs them.
    """
    inc = incidence(tokens)
    if method == "sample":
        inc = inc.where(F.pmod(F.xxhash64("doc_id"), F.lit(sample)) == 0)
    sizes = inc.groupBy("feature").agg(F.count(F.lit(1)).alias("df"))
    if method in ("exact", "sample"):
        shared = _ordered_pairs(inc, ["doc_id"]).groupBy("f", "g").agg(F.count(F.lit(1)).alias("shared"))
        return _with_jaccard(shared, sizes)
    if method == "bitmap":
        blocks = inc.groupBy("feature", F.bitmap_bucket_number("doc_id").alias("block")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("doc_id")).alias("bits"))
        both = _ordered_pairs(blocks, ["block"], ["bits"])
        stacked = both.select("f", "g", "block", F.explode(F.array("bits_f", "bits_g")).alias("bits"))
        met = stacked.groupBy("f", "g", "block").agg(F.bitmap_count(F.bitmap_and_agg("bits")).alias("n"))
        shared = met.groupBy("f", "g").agg(F.sum("n").alias("shared")).where("shared > 0")
        return _with_jaccard(shared, sizes)
    features = sizes
    if method == "minhash":
        seeds = F.array(*[F.lit(i) for i in range(hashes)])
        least = inc.select("feature", F.posexplode(F.transform(seeds, lambda s: F.xxhash64("doc_id", s))).alias("i", "h")).groupBy("feature", "i").agg(F.min("h").alias("h"))
        same = _ordered_pairs(least, ["i", "h"]).groupBy("f", "g").agg((F.count(F.lit(1)) / hashes).alias("jaccard"))
        out = same.join(features.select(F.col("feature").alias("f"), F.col("df").alias("df_f")), "f").join(features.select(F.col("feature").alias("g"), F.col("df").alias("df_g")), "g")
        j = F.col("jaccard")
        return out.select("f", "g", (j / (1 + j) * (F.col("df_f") + F.col("df_g"))).alias("shared"), "df_f", "df_g", "jaccard")
    if method == "theta":
        sketches = inc.groupBy("feature").agg(F.expr("theta_sketch_agg(doc_id)").alias("s"), F.count(F.lit(1)).alias("df"))
        if within is None:
            raise ValueError("theta sketches estimate given pairs; all pairs of features would be a cross join")
        both = within.select("f", "g").join(sketches.select(F.col("feature").alias("f"), F.col("s").alias("s_f"), F.col("df").alias("df_f")), "f")
        both = both.join(sketches.select(F.col("feature").alias("g"), F.col("s").alias("s_g"), F.col("df").alias("df_g")), "g")
        shared = both.withColumn("shared", F.expr("theta_sketch_estimate(theta_intersection(s_f, s_g))")).where("shared > 0")
        return shared.select("f", "g", "shared", "df_f", "df_g", (F.col("shared") / (F.col("df_f") + F.col("df_g") - F.col("shared"))).alias("jaccard"))
    raise ValueError(method)


def temporal_pairs(p: DataFrame, sparsify: bool = True, block_rows: int = 4096) -> DataFrame:
    """``feature, win, p, bursty`` -> ``f, g, rho``, f < g, pairs with a positive cosine.

    Cells that are 0 add nothing, so only cells with p > 0 (burst cells if sparsified) are joined;
    a window of more than ``block_rows`` such cells is paired block by block.
    """
    cells = (p.where("bursty") if sparsify else p).where("p > 0").select("feature", "win", "p")
    norms = cells.groupBy("feature").agg(F.sqrt(F.sum(F.col("p") * F.col("p"))).alias("norm"))
    dots = _in_blocks(cells, "win", ["p"], block_rows).groupBy("f", "g").agg(F.sum(F.col("p_f") * F.col("p_g")).alias("dot"))
    out = dots.join(norms.select(F.col("feature").alias("f"), F.col("norm").alias("nf")), "f").join(norms.select(F.col("feature").alias("g"), F.col("norm").alias("ng")), "g")
    return out.select("f", "g", (F.col("dot") / (F.col("nf") * F.col("ng"))).alias("rho"))


def affinities(tokens: DataFrame, p: DataFrame, sparsify: bool = True, method: str = "exact") -> DataFrame:
    """``f, g, jaccard, rho``; pairs that share documents but never burst together have rho 0."""
    joined = jaccard_pairs(tokens, method).select("f", "g", "jaccard").join(temporal_pairs(p, sparsify), ["f", "g"], "full")
    return joined.fillna(0.0, ["jaccard", "rho"])


def bundled(labels: DataFrame, most: int) -> DataFrame:
    """``feature, component, bundle, at``: the features of components of 2 to ``most``, packed side by side.

    Components follow each other along one line that is cut every ``most`` places; a component belongs to
    the bundle in which it begins.
    """
    sizes = labels.groupBy("component").agg(F.count(F.lit(1)).alias("size")).where(F.col("size").between(2, most))
    line = Window.orderBy("component").rowsBetween(Window.unboundedPreceding, -1)  # one row per component of features
    begun = sizes.withColumn("begin", F.coalesce(F.sum("size").over(line), F.lit(0)))
    rank = F.row_number().over(Window.partitionBy("component").orderBy("feature")) - 1
    placed = labels.join(begun, "component").withColumn("bundle", F.floor(F.col("begin") / most))
    return placed.select("feature", "component", "bundle", (F.col("begin") % most + rank).alias("at"))


def _grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``bundle, doc_id, at`` sorted by bundle and document -> how many documents hold both features, a row for each i <= j met."""

    def rows(bundle: int, table: np.ndarray) -> pa.RecordBatch:
        i, j = np.nonzero(np.triu(table))
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(i), bundle)), pa.array(i), pa.array(j), pa.array(table[i, j])], names=["bundle", "i", "j", "shared"])

    def blocks() -> Iterator[list[np.ndarray]]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
            if sum(len(x[0]) for x in held) < GRAM_ROWS:
                continue
            bundle, doc, at = (np.concatenate(x) for x in zip(*held))
            edge = int(np.flatnonzero((bundle != bundle[-1]) | (doc != doc[-1])).max(initial=-1)) + 1
            if edge:
                yield [bundle[:edge], doc[:edge], at[:edge]]
            last = np.unique(at[edge:])  # the last document may go on
            held = [[np.full(len(last), bundle[-1]), np.full(len(last), doc[-1], doc.dtype), last]]
        if held:
            yield [np.concatenate(x) for x in zip(*held)]

    own, table = None, np.zeros((0, 0), np.int64)
    for bundle, doc, at in blocks():
        for b in np.unique(bundle):
            here = slice(*np.searchsorted(bundle, [b, b + 1]))
            if b != own:
                if own is not None:
                    yield rows(own, table)
                own, table = b, np.zeros((0, 0), np.int64)
            place, docs = at[here], doc[here]
            width = max(len(table), int(place.max()) + 1)
            table = np.pad(table, (0, width - len(table)))
            number = np.concatenate([[0], np.cumsum(docs[1:] != docs[:-1])])
            for first in range(0, int(number[-1]) + 1, GRAM_DOCS):
                part = slice(*np.searchsorted(number, [first, first + GRAM_DOCS]))
                held_by = np.zeros((min(GRAM_DOCS, int(number[-1]) + 1 - first), width), np.float32)  # counts to GRAM_DOCS are exact
                held_by[number[part] - first, place[part]] = 1
                table += (held_by.T @ held_by).astype(np.int64)
    if own is not None:
        yield rows(own, table)


def component_jaccard(tokens: DataFrame, labels: DataFrame, most: int = DENSE_FEATURES) -> DataFrame:
    """The exact Jaccard of the pairs of features of one component (``feature, component``) that share a document.

    A task adds products of its documents' incidence to one square table after the other, so no row is made for a
    pair of a document. Components of more than ``most`` features are paired document by document in a join.
    """
    placed = staged(bundled(labels, most), "placed")
    cells = tokens.join(placed, "feature").where("doc_id IS NOT NULL").select("bundle", "doc_id", "at")
    grams = cells.repartition("doc_id").sortWithinPartitions("bundle", "doc_id").mapInArrow(_grams, GRAM_SCHEMA)
    grams = staged(grams.groupBy("bundle", "i", "j").agg(F.sum("shared").alias("shared")), "grams")
    unnamed = tokens.where("doc_id IS NULL").select("feature").distinct().withColumn("more", F.lit(1))  # one document that shares nothing
    own = grams.where("i = j").select("bundle", F.col("i").alias("at"), "shared")
    held = placed.join(own, ["bundle", "at"]).join(unnamed, "feature", "left")
    held = staged(held.select("feature", "component", "bundle", "at", (F.col("shared") + F.coalesce("more", F.lit(0))).alias("df")), "held")
    f, g = (held.select("bundle", "component", F.col("at").alias(i), F.col("feature").alias(x), F.col("df").alias(f"df_{x}")) for i, x in (("i", "f"), ("j", "g")))
    met = grams.where("i < j").join(f, ["bundle", "i"]).join(g, ["bundle", "j", "component"])
    out = met.select("f", "g", "shared", "df_f", "df_g", (F.col("shared") / (F.col("df_f") + F.col("df_g") - F.col("shared"))).alias("jaccard"))
    wide = labels.join(labels.groupBy("component").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > most).select("component"), "component", "left_semi")
    wide = staged(wide, "wide")
    if wide.isEmpty():
        return out
    inc = incidence(tokens.join(wide.select("feature"), "feature", "left_semi"))
    sizes = inc.groupBy("feature").agg(F.count(F.lit(1)).alias("df"))
    shared = _ordered_pairs(inc.join(wide, "feature"), ["doc_id", "component"]).groupBy("f", "g").agg(F.count(F.lit(1)).alias("shared"))
    return out.unionByName(_with_jaccard(shared, sizes))


def component_affinities(tokens: DataFrame, p: DataFrame, sparsify: bool = True, method: str = "exact") -> DataFrame:
    """The affinities that topics can use: pairs of features that a path of common bursts connects.

    Words of different components never meet in a topic, so the documents' features are paired
    inside components only, which keeps the largest shuffle to the pairs that matter.
    """
    rho = staged(temporal_pairs(p, sparsify), "rho")
    labels = connected(p.select(F.col("feature").alias("id")).distinct(), rho.select(F.col("f").alias("a"), F.col("g").alias("b")))
    labels = labels.withColumnRenamed("id", "feature")
    if method == "exact":
        jaccard = component_jaccard(tokens, labels)
    else:
        jaccard = jaccard_pairs(tokens, method, within=rho)
        of = lambda x: labels.select(F.col("feature").alias(x), F.col("component").alias(f"component_{x}"))
        jaccard = jaccard.join(of("f"), "f").join(of("g"), "g").where("component_f = component_g")
    return jaccard.select("f", "g", "jaccard").join(rho, ["f", "g"], "full").fillna(0.0, ["jaccard", "rho"])
