"""Operator 6: token counts by prefix dynamic programming.

A byte-pair encoding of a piece is the only chain of tokens in which every two
neighbours would also stay apart when encoded alone. So the last token of the encoding of
each prefix follows from those of shorter prefixes: among the tokens that end there, it
is the one that its predecessor tolerates. Texts are first split into the pieces that merges
never cross; the counts of a piece are kept in a bounded memo, as most pieces recur. A
:class:`PrefixTable` strings the counts at all prefixes of the pieces together to those at every
prefix of the text, from which truncations and budgets are read off.
"""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from .arrow_rows import with_arrow_columns
from .storage import table

#: Fixed values of the byte-level vocabulary: how text is split before merges.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Pieces whose counts a worker remembers before it starts its memo anew.
MEMO_PIECES = 1_000_000
_counters: dict[str, "PrefixCounter"] = {}


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_of_symbol() -> dict[str, int]:
    """The byte that each printable symbol of a byte-level vocabulary stands for."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


#: Finds a character for which the classes of Python's own patterns may differ from letters and numbers.
NOT_LATIN = re.compile("[^\x00-\x1b\x20-\x84\x86-\xb1\xb4-\xb8\xba\xbb\xbf-\u024f]").search


class PieceMemo(dict):
    """Counts of pieces, worked out when first asked for; starts anew when full."""

    def __init__(self, owner: "PrefixCounter"):
        self.owner = owner

    def __missing__(self, piece: str) -> int:
        if len(self) >= MEMO_PIECES:
            self.clear()
        data = piece.encode()
        n = self[piece] = 1 if data in self.owner.good else self.owner.prefixes(data)[-1]
        return n


class PrefixCounter:
    """Exact token counts of the texts of one byte-level BPE vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            held = json.load(f)
        symbols = byte_of_symbol()
        as_bytes = lambda t: bytes(symbols[c] for c in t)
        self.special = [t["content"] for t in held["added_tokens"]]
        self.specials = frozenset(self.special)
        self.ids = {as_bytes(t): i for t, i in held["model"]["vocab"].items() if t not in set(self.special)}
        pairs = (m if isinstance(m, list) else m.split(" ") for m in held["model"]["merges"])
        self.rank = {(as_bytes(a), as_bytes(b)): i for i, (a, b) in enumerate(pairs)}
        self.longest = max(map(len, self.ids))
        #: Tokens that are the encoding of their own bytes; no other can end a prefix.
        self.good = {t: i for t, i in self.ids.items() if len(t) == 1 or self.merged(t) == [t]}
        self.by_id = {i: t for t, i in self.good.items()}
        self.apart: dict[int, bool] = {}
        self.memo = PieceMemo(self)
        self.prefix_memo: dict[str, list[int]] = {}
        self.split_any = regex.compile(SPLIT).findall
        self.split_latin = re.compile(SPLIT.replace(r"[^\s\p{L}\p{N}]", r"(?:[^\s\w]|_)").replace(r"\p{L}", r"[^\W\d_]").replace(r"\p{N}", r"\d")).findall
        self.special_split = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None

    def split(self, text: str) -> list[str]:
        return self.split_latin(text) if NOT_LATIN(text) is None else self.split_any(text)

    def merged(self, data: bytes) -> list[bytes]:
        """The encoding by merges in order of rank; used on one or two tokens only."""
        rank, never = self.rank, 1 << 60
        parts = [data[i : i + 1] for i in range(len(data))]
        ranks = [rank.get(p, never) for p in zip(parts, parts[1:])]
        while ranks and (best := min(ranks)) != never:
            i = ranks.index(best)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del ranks[i]
            if i:
                ranks[i - 1] = rank.get((parts[i - 1], parts[i]), never)
            if i < len(ranks):
                ranks[i] = rank.get((parts[i], parts[i + 1]), never)
        return parts

    def tolerates(self, left: int, right: int) -> bool:
        """Whether the two tokens, encoded together, stay as they are."""
        if len(self.apart) > MEMO_PIECES:
            self.apart.clear()
        a, b = self.by_id[left], self.by_id[right]
        known = self.apart[left << 32 | right] = self.merged(a + b) == [a, b]
        return known

    def prefixes(self, piece: bytes) -> list[int]:
        """Token counts of the prefixes of 0, 1, ... bytes of a piece."""
        good, apart, longest = self.good.get, self.apart.get, self.longest
        counts, last = [0], [-1]
        for end in range(1, len(piece) + 1):
            for start in range(end - longest if end > longest else 0, end):
                token = good(piece[start:end])
                if token is None:
                    continue
                if start:
                    fits = apart(last[start] << 32 | token)
                    if fits is None:
                        fits = self.tolerates(last[start], token)
                    if not fits:
                        continue
                counts.append(counts[start] + 1)
                last.append(token)
                break
        return counts

    def char_prefixes(self, piece: str) -> list[int]:
        """Token counts of the prefixes of 1, 2, ... characters of a piece."""
        found = self.prefix_memo.get(piece)
        if found is None:
            counts = self.prefixes(piece.encode())
            found = counts[1:] if piece.isascii() else [counts[b] for b in accumulate(len(c.encode()) for c in piece)]
            if len(piece) <= 64:
                if len(self.prefix_memo) >= MEMO_PIECES // 10:
                    self.prefix_memo.clear()
                self.prefix_memo[piece] = found
        return found

    def runs(self, text: str) -> Iterator[tuple[bool, str]]:
        """The text cut at special strings: whether a run is special, and the run."""
        at = 0
        for m in self.special_split.finditer(text) if self.special_split else ():
            if m.start() > at:
                yield False, text[at : m.start()]
            yield True, m[0]
            at = m.end()
        if at < len(text):
            yield False, text[at:]

    def pieces(self, text: str) -> Iterator[tuple[str, int]]:
        """Pieces of the text with their token counts."""
        for special, run in self.runs(text):
            if special:
                yield run, 1
            else:
                for piece in self.split(run):
                    yield piece, self.memo[piece]

    def count(self, text: str) -> int:
        if self.special and any(s in text for s in self.special):
            return sum(n for _, n in self.pieces(text))
        return sum(map(self.memo.__getitem__, self.split(text)))

    def table(self, text: str) -> "PrefixTable":
        return PrefixTable(self, text)


#: Pieces that are another split when they are cut short: an apostrophe and the letters after it.
BLANK = regex.compile(r"\s+").fullmatch
CONTRACTIONS = frozenset(("'s", "'t", "'re", "'ve", "'m", "'ll", "'d"))


class PrefixTable:
    """Token counts of all prefixes of one text, each as if the prefix were encoded alone.

    A prefix that ends inside a piece takes the count at that place of the piece. One that ends in
    white space has its last run of it as one piece, and one that ends inside a contraction
    has the apostrophe and the letters apart; both are prefixes of pieces as well. Only inside a special
    string, where the characters before may join it, is the last line of pieces split anew.
    """

    def __init__(self, counter: PrefixCounter, text: str):
        self.text = text
        self.at = at = array("l", [0])
        ends, totals = [0], [0]  # borders of pieces, and the tokens of the pieces before them
        run = None  # where the white space before the border starts, and the tokens before it
        for piece, whole in counter.pieces(text):
            border, total = ends[-1], totals[-1]
            special = piece in counter.specials
            lead = 0 if special else len(piece) if BLANK(piece) else int(piece[0] == " ")
            if lead:
                run = run or (border, total)
                at.extend(run[1] + n for n in counter.char_prefixes(text[run[0] : border + lead])[border - run[0] :])
            if special:
                k = max(0, len(ends) - 4)
                while k and (text[ends[k] - 1].isspace() or text[ends[k]].isspace()):
                    k -= 1
                at.extend(totals[k] + counter.count(text[ends[k] : border + n]) for n in range(1, len(piece)))
                at.append(total + whole)
            elif piece in CONTRACTIONS:
                mark = counter.char_prefixes("'")[0]
                at.extend([total + mark, *(total + mark + n for n in counter.char_prefixes(piece[1:])[:-1]), total + whole])
            elif lead < len(piece):
                at.extend(total + n for n in counter.char_prefixes(piece)[lead:])
            if lead < len(piece):
                run = None
            ends.append(border + len(piece))
            totals.append(total + whole)

    def tokens(self, n_chars: int) -> int:
        """Tokens of the first ``n_chars`` characters encoded alone."""
        return self.at[max(0, min(n_chars, len(self.text)))]

    def longest_within(self, budget: int) -> int:
        """The greatest number of characters whose encoding has at most ``budget`` tokens."""
        return int(np.flatnonzero(np.asarray(self.at) <= budget)[-1]) if budget >= 0 else 0


def counter(path: str) -> PrefixCounter:
    """One counter for each vocabulary file and worker process."""
    if path not in _counters:
        _counters[path] = PrefixCounter(path)
    return _counters[path]


def token_counts(docs: DataFrame, path: str | None = None, limit: int = 1024, budget: int | None = None, prefixes: bool = False, text_col: str = "text") -> DataFrame:
    """``docs`` plus ``n_bytes, n_tokens, over_limit``; with a budget, ``budget_chars``; with ``prefixes``, ``tokens_at``.

    ``budget_chars`` is the greatest number of characters that encode to at most so many tokens, and
    ``tokens_at`` an array with the count of every prefix of 1, 2, ... characters, which later steps
    can ask for any truncation or budget.

    Counts equal those of the vocabulary's own library for the whole text without added
    tokens; a special string inside a text is one token, as is that library's default. A
    null text counts as empty: no bytes, no tokens, not over the limit. Rows are independent,
    so repeated rows, extra columns and empty tables need no care; same-named columns are
    replaced. ``path`` is a byte-level BPE file that every worker can open.
    """
    path = path or vocabulary_path()
    added = [T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())]
    added += [T.StructField("budget_chars", T.LongType())] if budget is not None else []
    added += [T.StructField("tokens_at", T.ArrayType(T.IntegerType(), False))] if prefixes else []

    def kernel(batch: pa.RecordBatch) -> list[pa.Array]:
        own = counter(path)
        n_bytes, n_tokens, fit, tables = [], [], [], []
        for value in batch.column(batch.schema.get_field_index(text_col)):
            text = value.as_py() or ""
            n_bytes.append(len(text.encode()))
            if budget is None and not prefixes:
                n_tokens.append(own.count(text))
            else:
                held = own.table(text)
                n_tokens.append(held.at[-1])
                if budget is not None:
                    fit.append(held.longest_within(budget))
                if prefixes:
                    tables.append(np.asarray(held.at[1:], np.int32))
        tokens = np.array(n_tokens, np.int64)
        out = [pa.array(n_bytes, pa.int64()), pa.array(tokens), pa.array(tokens > limit)]
        out += [pa.array(fit, pa.int64())] if budget is not None else []
        return out + ([pa.array(tables, pa.list_(pa.int32()))] if prefixes else [])

    return with_arrow_columns(docs, T.StructType(added), kernel)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts(docs).select("doc_id", "n_bytes", "n_tokens", "over_limit")
