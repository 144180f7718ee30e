"""Stage results written to a folder that all executors share, and readers and sinks."""

from __future__ import annotations

import contextlib
import tempfile
import time
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

from py4j.protocol import Py4JJavaError
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where it is unset (local runs)."""
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


#: While a list is here, every stage notes its tag, seconds and shuffled bytes in it.
_notes: list[list[tuple[str, float, int]]] = []


@contextlib.contextmanager
def metered() -> Iterator[list[tuple[str, float, int]]]:
    """Inside it, stages note ``(tag, seconds, bytes written to shuffles)`` in the list that it gives."""
    _notes.append([])
    try:
        yield _notes[-1]
    finally:
        _notes.pop()


def staged(df: DataFrame, tag: str) -> DataFrame:
    """Writes a stage as Parquet and reads it back: any later stage restarts from here."""
    path = f"{shared_folder(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    if _notes:
        _noted(df, tag, path)
    else:
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _noted(df: DataFrame, tag: str, path: str) -> None:
    context, group = df.sparkSession.sparkContext, uuid.uuid4().hex
    began = time.monotonic()
    context.setJobGroup(group, tag)
    df.write.parquet(path)
    context.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.monotonic() - began
    store, tracker, moved = context._jsc.sc().statusStore(), context.statusTracker(), 0
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            with contextlib.suppress(Py4JJavaError):  # a skipped stage has no attempt
                moved += store.lastStageAttempt(stage).shuffleWriteBytes()
    _notes[-1].append((tag, seconds, moved))


def bounded(rows: DataFrame, key: str, most: int) -> DataFrame:
    """The rows, if no key has more than ``most``; what one task would hold is refused before it starts."""
    over = rows.groupBy(key).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    if over > most:
        raise ValueError(f"one {key} has {over} rows and a task may hold {most}: raise max_local_rows or drop frequent features")
    return rows


def dealt(rows: DataFrame, *keys: str) -> DataFrame:
    """The rows by key over twice as many partitions as there are cores.

    For grouped maps whose work goes beyond the bytes of their rows: a shuffle of few bytes would end in one task.
    """
    return rows.repartition(2 * rows.sparkSession.sparkContext.defaultParallelism, *keys)


def at_once(spark: SparkSession, calls: list[Callable[[], object]]) -> list:
    """What the calls give, in their order; each has a thread, so that small steps of one fill the cores that another leaves idle."""
    shared_folder(spark)  # one for all
    with ThreadPoolExecutor(max(len(calls), 1)) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(f)) for f in calls]]


def read_as(spark: SparkSession, kind: str, path: str, schema: T.StructType) -> DataFrame:
    """CSV (with header), JSON lines, ORC, Parquet or text with a given schema."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def write_as(df: DataFrame, kind: str, path: str) -> None:
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """The rows after a write to and a read from another format, in the shared folder."""
    path = f"{shared_folder(df.sparkSession)}/{kind}-{uuid.uuid4().hex}"
    write_as(df, kind, path)
    return read_as(df.sparkSession, kind, path, df.schema)


def write_by_window(df: DataFrame, path: str) -> None:
    """Parquet partitioned by window; only the windows that ``df`` holds are replaced."""
    df.repartition("win").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("win").parquet(path)


def read_windows(df: DataFrame) -> DataFrame:
    """The rows after a write partitioned by window and a second one that replaces the even windows alone."""
    path = f"{shared_folder(df.sparkSession)}/windows-{uuid.uuid4().hex}"
    write_by_window(df, path)
    write_by_window(df.where("win % 2 = 0"), path)
    return df.sparkSession.read.parquet(path).select(*df.columns)


def write_bucketed(df: DataFrame, name: str, key: str = "feature", buckets: int = 16) -> None:
    """A table bucketed and sorted by a key, so that later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def read_bucketed(df: DataFrame, key: str = "feature") -> DataFrame:
    """The rows after a write to and a read from a bucketed table, which is dropped once they are staged."""
    name = f"bucketed_{uuid.uuid4().hex}"
    write_bucketed(df, name, key)
    out = staged(df.sparkSession.table(name), "bucketed")
    df.sparkSession.sql(f"DROP TABLE {name}")
    return out
