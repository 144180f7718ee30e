"""Applying a kernel to the Arrow batches of a DataFrame."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema


def with_arrow_columns(df: DataFrame, added: T.StructType, kernel: Callable[[pa.RecordBatch], list[pa.Array]]) -> DataFrame:
    """``df`` plus the columns that ``kernel`` gives for each batch, row for row; no shuffle.

    Input columns with a name of the added ones are replaced.
    """
    names = {f.name.lower() for f in added}
    kept = [c for c in df.columns if c.lower() not in names]
    schema = T.StructType([*[f for f in df.schema if f.name in kept], *added])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        target = to_arrow_schema(added)
        for batch in batches:
            made = [a.cast(f.type) if a.type != f.type else a for a, f in zip(kernel(batch), target, strict=True)]
            held = [batch.column(batch.schema.get_field_index(c)) for c in kept]
            yield pa.RecordBatch.from_arrays([*held, *made], names=[f.name for f in schema])

    return df.mapInArrow(run, schema)


def exploded_by_arrow(df: DataFrame, schema: T.StructType, kernel: Callable[[pa.RecordBatch], Iterator[list[pa.Array]]]) -> DataFrame:
    """Rows that ``kernel`` makes from each batch, in as many parts as it likes; no shuffle."""
    names = [f.name for f in schema]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        target = to_arrow_schema(schema)
        for batch in batches:
            for columns in kernel(batch):
                yield pa.RecordBatch.from_arrays([a.cast(f.type) if a.type != f.type else a for a, f in zip(columns, target, strict=True)], names=names)

    return df.mapInArrow(run, schema)
