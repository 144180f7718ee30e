"""What users call from SQL and in aggregations: registered functions, a grouped-aggregate function and a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import bursts as B
from ..functions import volatility as VOL
from ..functions.text import stem
from ..sources import views as V
from ..sources.staging import staged


def register(spark: SparkSession) -> None:
    """Makes ``burst_tail(n, total, pe)``, ``stem(word)`` and ``runs_of(TABLE (...))`` known to SQL."""
    spark.udf.register("burst_tail", B.tail_function("strict"))
    spark.udf.register("stem", stem)
    spark.udtf.register("runs_of", RunsOf)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def logistic_mle(vi: pd.Series) -> list[float]:
    """Location and scale of the logistic curve of greatest likelihood of a group's values, as an aggregate."""
    return list(VOL.logistic_mle(np.sort(vi.dropna().to_numpy(float))))


@F.arrow_udtf(returnType=T.StructType([T.StructField("feature", T.StringType()), T.StructField("start_win", T.IntegerType()), T.StructField("end_win", T.IntegerType()), T.StructField("length", T.LongType())]))
class RunsOf:
    """Runs of consecutive windows, from rows ``feature, win`` that come feature by feature in order of windows."""

    def __init__(self) -> None:
        self.feature, self.start, self.last = None, None, None

    def _run(self) -> pa.Table:
        return pa.table({"feature": [self.feature], "start_win": pa.array([self.start], pa.int32()), "end_win": pa.array([self.last], pa.int32()), "length": [self.last - self.start + 1]})

    def eval(self, rows: pa.RecordBatch) -> Iterator[pa.Table]:
        for feature, win in zip(rows.column("feature").to_pylist(), rows.column("win").to_pylist()):
            if feature == self.feature and win == self.last + 1:
                self.last = win
                continue
            if self.start is not None:
                yield self._run()
            self.feature, self.start, self.last = feature, win, win

    def terminate(self) -> Iterator[pa.Table]:
        if self.start is not None:
            yield self._run()


def order_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``feature, win, n, total, pe`` of the order stream."""
    counts = staged(B.window_counts(V.order_stream(spark, sf_dir)), "counts")
    totals = B.window_totals(counts)
    return counts.join(totals, "win").join(B.expected_rate(counts, totals), "feature")


def sql_burst_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    return spark.sql("SELECT feature, win, n, round(burst_tail(double(n), double(total), pe), 6) + 0.0D AS p FROM {cells}", cells=order_cells(spark, sf_dir))


def aggregated_mle(spark: SparkSession, sf_dir: str) -> DataFrame:
    vi = VOL.volatility(VOL.log_returns(V.order_index(spark, sf_dir)))
    fit = vi.where("vi IS NOT NULL").agg(logistic_mle("vi").alias("fit"))
    return fit.select(F.round(F.col("fit")[0], 6).alias("mu"), F.round(F.col("fit")[1], 6).alias("s"))


def table_function_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    cells = order_cells(spark, sf_dir)
    counts, totals, rates = cells.select("feature", "win", "n"), cells.select("win", "total").distinct(), cells.select("feature", "pe").distinct()
    bursty = staged(B.burst_windows(B.burst_probability(counts, totals, rates)), "bursty")
    return spark.sql("SELECT * FROM runs_of(TABLE(SELECT feature, win FROM {bursty}) PARTITION BY feature ORDER BY win)", bursty=bursty)


#: The SQL twins are in the registry, beside those of the functions that these call.
QUERIES = {"sql_burst_tail": sql_burst_tail, "aggregated_logistic_mle": aggregated_mle, "table_function_runs": table_function_runs}
SQL: dict[str, str] = {}
