"""Operator 10 [native]: sharding along a Hilbert curve.

Three metadata dimensions (language, source, length) are quantised to ``BITS`` bits
each and folded into one Hilbert index, so that a run of the order covers a compact
box of all three and a reader can skip shards by any of them. Rows are ordered by
(index, checksum, text hash, id), equal texts side by side, and the order is cut into
runs whose row counts differ by one at most. The global rank is taken in two steps: a
range partitioning, sorted and numbered inside each part, is written to the shared
folder, and a small table of counts for each part gives the offsets; rows move once
and no step brings all of them to one task.
"""

from __future__ import annotations

from functools import lru_cache, reduce
from itertools import accumulate
from operator import xor

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .storage import fresh, table, written

#: Bits of each quantised dimension: a curve of 2 ** (3 * BITS) cells.
BITS = 8


def length_cell(n: Column, bits: int = BITS) -> Column:
    """Classes of a length by its logarithm, from 0 up; with five bits half an octave each, with more bits finer."""
    top = (1 << bits) - 1
    return F.least(F.floor(2.0 ** (bits - 4) * F.log2(F.greatest(F.coalesce(n, F.lit(0)).cast("double"), F.lit(0.0)) + 1)), F.lit(top)).cast("int")


def name_cell(name: Column, bits: int = BITS) -> Column:
    """A cell for a name, null included, from a hash."""
    return F.pmod(F.xxhash64(F.coalesce(name.cast("string"), F.lit("\0null"))), F.lit(1 << bits)).cast("int")


@lru_cache
def curve_steps(n: int) -> tuple[list[int], list[int]]:
    """Digits and next states of the curve in n dimensions, at ``state * 2 ** n + cell``.

    A level reads one bit of every coordinate (the cell) as a digit in Gray code and then
    reflects and swaps all bits below. A state is what the levels above have done to the bits of
    the next: which coordinate stands where, which are inverted, and whether the digit is.
    """
    start = (tuple(range(n)), (0,) * n, 0)
    states, order, digits, after = {start: 0}, [start], [], []
    for axes, inverted, twist in order:
        for cell in range(1 << n):
            bits = [(cell >> (n - 1 - axis)) & 1 ^ turn for axis, turn in zip(axes, inverted)]
            below = list(zip(axes, inverted))
            for i, on in enumerate(bits):
                if on:
                    below[0] = (below[0][0], 1 - below[0][1])
                else:
                    below[0], below[i] = below[i], below[0]
            gray = list(accumulate(bits, xor))
            state = (tuple(axis for axis, _ in below), tuple(turn for _, turn in below), twist ^ gray[-1])
            if state not in states:
                states[state] = len(states)
                order.append(state)
            digits.append(sum((g ^ twist) << (n - 1 - i) for i, g in enumerate(gray)))
            after.append(states[state])
    return digits, after


def hilbert_index(axes: list[Column], bits: int = BITS) -> Column:
    """The index along the Hilbert curve of a cell given by its coordinates.

    From the highest bit down, each level looks up its digit and the state of the next in a
    table; the fold holds the index so far above the state, in one integer.
    """
    n = len(axes)
    digits, after = curve_steps(n)
    width = max(after).bit_length()
    steps = F.expr(f"array({', '.join(f'{d << width | s}L' for d, s in zip(digits, after))})")
    point = F.struct(*[a.cast("int").alias(f"x{i}") for i, a in enumerate(axes)])

    def index(at: Column) -> Column:
        def cell(level: int) -> Column:
            parts = [F.shiftright(at[f"x{i}"], level).bitwiseAND(F.lit(1)) * F.lit(1 << (n - 1 - i)) for i in range(n)]
            return reduce(Column.__add__, parts)

        def step(held: Column, here: Column) -> Column:
            state = held.bitwiseAND(F.lit((1 << width) - 1))
            return F.shiftleft(held - state, n) + F.get(steps, (state * F.lit(1 << n)).cast("int") + here)

        return F.aggregate(F.array(*[cell(level) for level in range(bits - 1, -1, -1)]), F.lit(0).cast("long"), step)

    return F.shiftright(F.transform(F.array(point), index)[0], width)


def with_curve(docs: DataFrame, dims: list[Column] | None = None) -> DataFrame:
    """``docs`` plus ``size`` (UTF-8 bytes of the text, none for null, plus 8), ``text_crc32`` (of the
    empty text for null), ``text_hash`` and ``curve``; same-named columns of the input are replaced."""
    added = ["size", "text_crc32", "text_hash", "curve"]
    docs = docs.drop(*[c for c in docs.columns if c.lower() in added])
    text = F.coalesce(F.col("text"), F.lit(""))
    if dims is None:
        dims = [name_cell(F.col("lang")), name_cell(F.col("source")), length_cell(F.octet_length(text))]
    keyed = docs.withColumn("size", (F.octet_length(text) + 8).cast("long")).withColumn("text_crc32", F.crc32(text.cast("binary")))
    return keyed.withColumn("text_hash", F.xxhash64("text")).withColumn("curve", hilbert_index(dims))


def cut_runs(keyed: DataFrame, n_shards: int = 24, parts: int | None = None) -> DataFrame:
    """Rows of :func:`with_curve`, with or without the text, plus ``shard, slot``.

    Row counts of shards differ by one at most; slots run from 0 without gaps in curve
    order. Ties fall to the checksum, the hash of the text and then every other column,
    so only rows alike in all of them change places. Empty input gives no rows; with
    fewer rows than shards the last shards stay empty.
    """
    spark = keyed.sparkSession
    keyed = keyed.drop(*[c for c in keyed.columns if c.lower() in ("shard", "slot")])
    part, rank, before, count = (fresh(x, keyed) for x in ("part", "rank", "before", "count"))
    first = ["curve", "text_crc32", "text_hash"]
    rest = [c for c, kind in keyed.dtypes if c not in {*first, "text"} and not kind.startswith(("map", "variant"))]
    order = [F.col(c) for c in first] + [F.col(c).asc_nulls_first() for c in rest]
    parts = parts or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    laid = keyed.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn(part, F.spark_partition_id())
    # The lower 33 bits number the rows of a part in its order; written once, so a repeated step reads the same numbers.
    laid = written(laid.withColumn(rank, F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))), "shards")
    counts = laid.groupBy(part).agg(F.count(F.lit(1)).alias(count))
    through = Window.orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(part, F.coalesce(F.sum(count).over(through), F.lit(0)).alias(before), F.sum(count).over(Window.partitionBy()).alias(count))
    ranked = laid.join(F.broadcast(offsets), part)  # one row for each part: as many as shuffle partitions
    ranked = ranked.withColumn(rank, F.col(before) + F.col(rank))
    base, extra = F.floor(F.col(count) / n_shards), F.col(count) % n_shards
    long_rows, short = extra * (base + 1), F.greatest(base, F.lit(1))
    early = F.col(rank) < long_rows
    shard = F.when(early, F.floor(F.col(rank) / (base + 1))).otherwise(extra + F.floor((F.col(rank) - long_rows) / short))
    slot = F.when(early, F.col(rank) % (base + 1)).otherwise((F.col(rank) - long_rows) % short)
    return ranked.withColumn("shard", shard.cast("int")).withColumn("slot", slot.cast("long")).drop(part, rank, before, count)


def sharded(docs: DataFrame, n_shards: int = 24, dims: list[Column] | None = None) -> DataFrame:
    """Whole documents with ``size, text_crc32, curve, shard, slot``: ready to be written by shard."""
    return cut_runs(with_curve(docs, dims), n_shards).drop("text_hash")


def op10_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The plan of the shards; the texts themselves need not move for it."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    out = cut_runs(with_curve(docs).drop("text"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")
