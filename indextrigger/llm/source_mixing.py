"""Operator 2: mixing sources to target weights.

Sizes are summed for each source (partial sums before the shuffle, so a source with
a third of the rows costs no more than another). The targets come from one small
table with a row for each source: weights by rank, a budget as a share of all sizes,
and for each source a ceiling of ``max_repeat`` times its size, whose excess goes to
the others by weight. That water level has a closed form over the sources ordered
by ceiling divided by weight, so no loop is needed. A document is then emitted
``floor(rate)`` times and once more with a probability of the fraction, drawn from a
hash of its id and a seed: reruns give the same copies.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .storage import fresh, n_spaced_words, table


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, max_repeat: float = 2.0) -> DataFrame:
    """``source, size`` -> ``source, source_size, weight, target``; one row per source.

    Sources are ordered by code point with null last and weighted by ``weights`` in
    turn. The table has one row per source, so ordering it in one place is safe.
    """
    total = F.sum("source_size").over(Window.partitionBy())
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    ranked = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = ranked.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int")))
    ranked = ranked.withColumn("ceiling", F.col("source_size") * F.lit(float(max_repeat))).withColumn("asked", total * F.lit(float(share)))
    upward = Window.orderBy(F.col("ceiling") / F.col("weight"), F.col("source").asc_nulls_last())
    before = upward.rowsBetween(Window.unboundedPreceding, -1)
    ranked = ranked.withColumn("full_before", F.coalesce(F.sum("ceiling").over(before), F.lit(0.0)))
    ranked = ranked.withColumn("weight_left", F.sum("weight").over(upward.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
    # The level if all sources before this one are full; the first source below its ceiling sets the level for the rest.
    ranked = ranked.withColumn("level", F.greatest(F.col("asked") - F.col("full_before"), F.lit(0.0)) / F.col("weight_left"))
    open_level = F.min(F.when(F.col("level") * F.col("weight") <= F.col("ceiling"), F.struct(F.col("ceiling") / F.col("weight"), F.col("source").isNull(), F.col("source"), F.col("level")))).over(Window.partitionBy())
    ranked = ranked.withColumn("water", open_level["level"])
    target = F.coalesce(F.least(F.col("ceiling"), F.col("water") * F.col("weight")), F.col("ceiling"))
    return ranked.select("source", "source_size", "weight", target.alias("target"))


def draw(doc_id: Column, seed: str) -> Column:
    """A number in [0, 1) from 52 bits of a hash of the seed and the id."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("null"))))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))


def mixed_sources(docs: DataFrame, size: Column | None = None, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, max_repeat: float = 2.0, seed: str = "mix", id_col: str = "doc_id", source_col: str = "source") -> DataFrame:
    """All columns of ``docs`` plus ``size, source_size, target, rate, copies``, one row per input row.

    Null text has size 0; a null source is a source of its own, ordered last; a null
    id draws by the word null; repeated rows draw alike. Empty input gives no rows. A
    source of size 0 has target 0 and its rows (all of size 0) no copies. An input
    column with a name of the added ones is replaced.
    """
    added = ["size", "source_size", "target", "rate", "copies"]
    docs = docs.drop(*[c for c in docs.columns if c.lower() in added])
    size = n_spaced_words(F.col("text")) if size is None else size
    key = fresh("source_key", docs)
    sized = docs.withColumn("size", size.cast("long"))
    targets = source_targets(sized.select(F.col(source_col).alias("source"), "size"), weights, share, max_repeat)
    targets = targets.select(F.col("source").alias(key), "source_size", "target")
    out = sized.join(targets, sized[source_col].eqNullSafe(targets[key]), "left").drop(key)
    out = out.withColumn("rate", F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(max_repeat)))).otherwise(0.0))
    whole = F.floor("rate")
    return out.withColumn("copies", (whole + (draw(F.col(id_col), seed) < F.col("rate") - whole).cast("long")).cast("long"))


def repeated(mix: DataFrame) -> DataFrame:
    """The mix itself: every row as often as ``copies`` says, with ``copy`` numbered from 1."""
    return mix.withColumn("copy", F.explode(F.expr("CASE WHEN copies > 0 THEN sequence(1L, copies) END")))


def op2_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    mix = mixed_sources(docs)
    return mix.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


OP2_SQL = r"""
WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
r AS (SELECT *, CAST([5, 2, 1][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS DOUBLE) AS weight,
  source_size * CAST(2 AS DOUBLE) AS ceiling, CAST(sum(source_size) OVER () AS BIGINT) * CAST(1.5 AS DOUBLE) AS asked FROM s),
f AS (SELECT *, coalesce(sum(ceiling) OVER (ORDER BY ceiling / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS full_before,
  sum(weight) OVER (ORDER BY ceiling / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weight_left FROM r),
v AS (SELECT *, greatest(asked - full_before, 0) / weight_left AS level FROM f),
w AS (SELECT (SELECT level FROM v WHERE level * weight <= ceiling ORDER BY ceiling / weight, source NULLS LAST LIMIT 1) AS water),
t AS (SELECT source, source_size, coalesce(least(ceiling, water * weight), ceiling) AS target FROM v, w),
q AS (SELECT d.doc_id, d.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN least(t.target / t.source_size, 2.0) ELSE 0 END AS rate
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, CAST(size * (floor(rate) + CASE WHEN
  CAST(('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 13)) AS BIGINT) / 4503599627370496.0 < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM q
"""
