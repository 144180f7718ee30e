"""Tables written between steps, in a folder that all executors share."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where that is unset (local tests)."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = held.get() if held.isDefined() else None
    if not folder:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir names no folder, and executors would not see a temporary one of this machine")
        folder = tempfile.mkdtemp(prefix="indextrigger-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def written(df: DataFrame, tag: str) -> DataFrame:
    """Writes the rows as Parquet in the shared folder and reads them back: cuts the lineage,
    keeps a result that is used twice, and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Scratch:
    """Tables written between the steps of one call, by tag; those that no later step reads can be dropped at once."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, {}

    def keep(self, df: DataFrame, tag: str) -> DataFrame:
        path = f"{shared_folder(self.spark)}/{tag}-{uuid.uuid4().hex}"
        df.write.option("compression", "zstd").parquet(path)
        self.paths.setdefault(tag, []).append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *tags: str) -> None:
        context = self.spark.sparkContext
        for tag in tags:
            for path in self.paths.pop(tag, ()):
                held = context._jvm.org.apache.hadoop.fs.Path(path)
                held.getFileSystem(context._jsc.hadoopConfiguration()).delete(held, True)

    def free(self) -> None:
        """Lets Spark delete the shuffle files of steps that are written: it does once the driver's heap is collected."""
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()


def fresh(name: str, *frames: DataFrame) -> str:
    """The name, or one with underscores added, that no column of the frames has."""
    taken = {c.lower() for df in frames for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: The character class of words between white space, for Spark's regular expressions.
SPACED_WORD = r"[^\x20\x09-\x0D]+"


def n_spaced_words(text: Column) -> Column:
    """Number of words between white space; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(SPACED_WORD)), F.lit(0)).cast("long")
