"""A training corpus from raw documents, in five stages that each use one operator.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and returns the
documents it keeps, which are written as Parquet and read again for the next one. All but
the last return the columns of ``documents``; the last adds the shard and the place in it.

No SQL twin is given: the trained classifier and the checksum order of the shards
are beyond SQL. ``tests/llm/test_pipeline.py`` compares the rows of every stage with a version of its
own in plain Python: kept groups, hit documents, copies and shards exactly, the classifier by its verdicts on
labelled rows that it was not fitted on.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from indextrigger.llm import cotraining, decontamination, hilbert_sharding, ngram_join, source_mixing
from indextrigger.llm.storage import fresh, shared_folder, table

ORACLE_SQL = None


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the co-trained views find bad. Without labels nothing is dropped."""
    model = cotraining.fit(docs, table(spark, sf_dir, "labels"))
    return cotraining.scored(docs, model).where("kept").select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the least id of each group linked by five-word shingles at 0.8 or more.

    Documents without a word, and those without an id, have no links and stay. Rows that share an
    id are documents of their own where their texts differ; of rows alike in id and text one stays,
    the least by its other columns.
    """
    named, key = docs.where("doc_id IS NOT NULL"), "doc_id"
    if ngram_join.ids_repeat(named):
        others = [c for c in docs.columns if c not in ("doc_id", "text")]
        order = F.struct(*[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in others])
        named = named.groupBy("doc_id", "text").agg(*[F.min_by(F.col(c), order).alias(c) for c in others]) if others else named.distinct()
        key = fresh("number", docs)
        named = ngram_join.numbered(named.select(*docs.columns), key)
    groups = ngram_join.jaccard_components(named.select(F.col(key).alias("doc_id"), "text"), width=5, percent=80)
    kept = groups.where("doc_id = component_id").select(F.col("doc_id").alias(key))
    return named.join(kept, key, "left_semi").select(*docs.columns).unionByName(docs.where("doc_id IS NULL"))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold ten or more consecutive words of a benchmark item, or all words of a shorter one."""
    found = decontamination.contamination(docs, table(spark, sf_dir, "benchmark"))
    return found.where("NOT contaminated").select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats documents so that sources approach their shares; repeats are rows of their own."""
    return source_mixing.repeated(source_mixing.mixed_sources(docs)).select(*docs.columns)


def sharding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds ``shard`` and ``slot`` along the curve of language, source and length."""
    return hilbert_sharding.sharded(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_classifier", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("source_mixing", mixing_stage),
    ("sharding", sharding_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written and read again, so a lost executor repeats one stage only."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{shared_folder(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
