"""Operator 4: chat formatting with offset-aligned loss masks.

A conversation is rendered as one string, encoded once with offsets, and the sorted
spans of the assistant texts are intersected with the token spans by binary search.
The marks of the template are added to the tokenizer as tokens of their own, so no
token runs over the border of a span; inside texts a backslash escapes itself and the
start of every mark, so no text can close a turn or open one, and reading back is exact.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow_rows import exploded_by_arrow
from .prefix_tokens import vocabulary_path
from .storage import table

TURN, SAYS, END = "<|turn|>", "<|says|>", "<|end|>"
_tokenizers: dict = {}

FORMATTED = T.StructType(
    [
        T.StructField("conv_id", T.LongType()),
        T.StructField("n_turns", T.LongType()),
        T.StructField("formatted", T.StringType()),
        T.StructField("input_ids", T.ArrayType(T.IntegerType(), False)),
        T.StructField("loss_mask", T.ArrayType(T.BooleanType(), False)),
    ]
)


def escaped(text: str) -> str:
    return text.replace("\\", "\\\\").replace("<|", "<\\|")


def unescaped(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.DOTALL)


def tokenizer(path: str):
    if path not in _tokenizers:
        from tokenizers import AddedToken, Tokenizer

        own = Tokenizer.from_file(path)
        own.add_special_tokens([AddedToken(m, normalized=False, special=True) for m in (TURN, SAYS, END)])
        _tokenizers[path] = own
    return _tokenizers[path]


def rendered(turns: list[tuple[str, str]], loss_role: str) -> tuple[str, list[tuple[int, int]]]:
    """The string of a conversation and the sorted character spans of the texts to be learnt."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{TURN}{escaped(role)}{SAYS}", escaped(text)
        if role == loss_role and body:
            spans.append((at + len(head), at + len(head) + len(body)))
        parts += [head, body, END]
        at += len(head) + len(body) + len(END)
    return "".join(parts), spans


def span_mask(offsets: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """True for tokens inside a span; spans are sorted and disjoint, so one binary search finds the only candidate."""
    if not spans or not len(offsets):
        return np.zeros(len(offsets), bool)
    starts, ends = np.array(spans).T
    at = np.searchsorted(starts, offsets[:, 0], "right") - 1
    return (at >= 0) & (offsets[:, 1] <= ends[np.maximum(at, 0)])


def formatted(conversations: DataFrame, path: str | None = None, loss_role: str = "assistant", group: int = 64) -> DataFrame:
    """``conv_id, turn, role, text`` -> one row per conversation: ``conv_id, n_turns, formatted, input_ids, loss_mask``.

    Turns go by ``turn``, then role and text, nulls first; repeated rows are turns of
    their own. A null role or text counts as empty; an empty text has no tokens to
    learn. Rows with a null id form one conversation. Other columns are not used. Rows of a
    conversation are sorted into one stream and never gathered into one value, so a task holds
    one conversation and ``group`` finished ones at a time.
    """
    path = path or vocabulary_path()
    rows = conversations.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")
    names = [f.name for f in FORMATTED]

    def encoded(convs: list[tuple[int | None, list[tuple[str, str]]]]) -> pa.RecordBatch:
        texts, spans = zip(*[rendered(turns, loss_role) for _, turns in convs])
        found = tokenizer(path).encode_batch(list(texts), add_special_tokens=False)
        masks = [span_mask(np.array(e.offsets, np.int64).reshape(-1, 2), s) for e, s in zip(found, spans)]
        columns = [
            pa.array([c for c, _ in convs], pa.int64()),
            pa.array([len(t) for _, t in convs], pa.int64()),
            pa.array(texts, pa.string()),
            pa.array([e.ids for e in found], pa.list_(pa.int32())),
            pa.array([m.tolist() for m in masks], pa.list_(pa.bool_())),
        ]
        return pa.RecordBatch.from_arrays(columns, names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: list[tuple[int | None, list[tuple[str, str]]]] = []
        for batch in batches:
            for conv, role, text in zip(*(c.to_pylist() for c in batch.columns)):
                if not done or done[-1][0] != conv:
                    if len(done) >= group:
                        yield encoded(done)
                        done = []
                    done.append((conv, []))
                done[-1][1].append((role, text))
        if done:
            yield encoded(done)

    return rows.mapInArrow(run, FORMATTED)


def read_back(ids: list[int], mask: list[bool], path: str) -> tuple[list[tuple[str, str]], str, str]:
    """Turns, learnt text and formatted string of one conversation, from its tokens and mask alone."""
    own = tokenizer(path)
    text = own.decode(ids, skip_special_tokens=False)
    turns = []
    for turn in text.split(TURN)[1:]:
        role, _, body = turn.removesuffix(END).partition(SAYS)
        turns.append((unescaped(role), unescaped(body)))
    learnt, run = [], []
    for i, on in zip([*ids, -1], [*mask, False]):
        if on:
            run.append(i)
        elif run:
            learnt.append(unescaped(own.decode(run, skip_special_tokens=False)))
            run = []
    return turns, "".join(learnt), text


def digests(rows: DataFrame, path: str | None = None) -> DataFrame:
    """Rows of :func:`formatted` -> counts and digests of what their tokens and masks say."""
    path = path or vocabulary_path()
    schema = T.StructType([T.StructField(n, T.StringType() if n.endswith("sha256") else T.LongType()) for n in ("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars")])

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        out = []
        for conv, ids, mask in zip(*(batch.column(batch.schema.get_field_index(c)) for c in ("conv_id", "input_ids", "loss_mask"))):
            turns, learnt, text = read_back(ids.as_py(), mask.as_py(), path)
            all_turns = hashlib.sha256("".join(f"{role}\n{said}\n" for role, said in turns).encode())
            out.append((conv.as_py(), len(turns), all_turns.hexdigest(), len(learnt), hashlib.sha256(learnt.encode()).hexdigest(), len(text)))
        if out:
            yield [pa.array(c, pa.string() if isinstance(c[0], str) else pa.int64()) for c in zip(*out)]

    return exploded_by_arrow(rows, schema, kernel)


def op4_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = table(spark, sf_dir, "conversations").select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text")
    said = F.lit("\\### Assistant: </turn> ok")
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), said.alias("text"))
    return digests(formatted(own.unionByName(extra)))
