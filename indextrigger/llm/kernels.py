"""Vectorised byte kernels shared by the text operators.

Every kernel works on one *piece*: the UTF-8 bytes of several whole documents laid
end to end, with the offsets of the documents. Pieces hold about ``PIECE_BYTES``
bytes (one document is never cut), so the memory of a task is bounded by that size
plus its longest document, whatever the size of the Arrow batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

#: Bytes of text that one vectorised step handles; a longer document makes a piece alone.
PIECE_BYTES = 1 << 19

_ODD = np.uint64(0x9E3779B97F4A7C15)
_HALF = np.uint64(32)
#: Words beyond this many bytes are hashed one by one.
LONG_WORD = 256
_LANE_MASKS = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words, so that all bits depend on all bits."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(32))


def text_column(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes, offsets (one more than rows) and null mask of an Arrow string column."""
    nulls = np.asarray(column.is_null())
    column = column.cast(pa.large_string()).cast(pa.large_binary())
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64), nulls
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    if nulls.any():  # the slot of a null may hold bytes
        lengths = np.where(nulls, 0, np.diff(offsets))
        if lengths.sum() != offsets[-1] - offsets[0]:
            data = np.concatenate([data[offsets[i] : offsets[i] + lengths[i]] for i in range(n)])
            offsets = np.concatenate([[0], np.cumsum(lengths)])
    return data[offsets[0] : offsets[-1]], (offsets - offsets[0]).astype(np.int64), nulls


def pieces(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Cuts a batch at document borders: first row, last row + 1, bytes, offsets from 0."""
    n, row = len(offsets) - 1, 0
    while row < n:
        end = int(np.searchsorted(offsets, offsets[row] + PIECE_BYTES, "right")) - 1
        end = min(n, max(end, row + 1))
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def byte_table(kept: np.ndarray, lower: bool) -> np.ndarray:
    """A table from bytes to codes: 0 for bytes outside words, else byte + 1; A-Z lowered on request."""
    codes = np.arange(1, 257, dtype=np.uint16)
    if lower:
        codes[65:91] += 32
    codes[~kept] = 0
    return codes


_all = np.arange(256)
#: Words are runs of anything but the space and the five control characters from tab to CR.
SPACED = (_all != 0x20) & ~((_all >= 0x09) & (_all <= 0x0D))
#: Words are runs of digits, letters and everything beyond ASCII.
ALNUM = ((_all >= 0x30) & (_all <= 0x39)) | ((_all >= 0x41) & (_all <= 0x5A)) | ((_all >= 0x61) & (_all <= 0x7A)) | (_all >= 0x80)


def words(data: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and 64-bit hash of every word, and the word range of every document.

    The fourth array has one entry more than documents: words of document d are
    ``bounds[d]:bounds[d + 1]``. Words never run over the border of two documents.
    """
    n = len(data)
    if n == 0:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    codes = table[data]
    inside = np.zeros(n + 2, bool)
    inside[1:-1] = codes != 0
    first = inside[1:-1] & ~inside[:-2]
    last = inside[1:-1] & ~inside[2:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < n)]
    joined = cuts[inside[cuts + 1] & inside[cuts]]
    first[joined] = True
    last[joined - 1] = True
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    spelled = (codes - 1).astype(np.uint8)
    return starts, ends, slice_hashes(spelled, starts, ends), np.searchsorted(starts, offsets).astype(np.int64)


def lanes(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every place on as one number; zeros follow the end."""
    padded = np.zeros(len(data) + 8, np.uint8)
    padded[: len(data)] = data
    return np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))


def slice_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each slice, mixed eight at a time after the length.

    No sum over bytes is taken, so no choice of letters cancels out; slices of more than
    ``LONG_WORD`` bytes go through xxh3.
    """
    sizes = ends - starts
    hashes = mixed(sizes.astype(np.uint64) * _ODD)
    eight, left, at, rows = lanes(data), sizes, starts, np.flatnonzero((sizes > 0) & (sizes <= LONG_WORD))
    left, at = left[rows], at[rows]
    while len(rows):
        hashes[rows] = mixed((hashes[rows] ^ (eight[at] & _LANE_MASKS[np.minimum(left, 8)])) * _ODD)
        more = left > 8
        rows, left, at = rows[more], left[more] - 8, at[more] + 8
    raw = memoryview(np.ascontiguousarray(data))
    for i in np.flatnonzero(sizes > LONG_WORD).tolist():
        hashes[i] = xxhash.xxh3_64_intdigest(raw[int(starts[i]) : int(ends[i])])
    return hashes


def digests(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """xxh3 of each slice, for slices of some dozens of bytes and more."""
    raw, one = memoryview(np.ascontiguousarray(data)), xxhash.xxh3_64_intdigest
    return np.fromiter((one(raw[a:b]) for a, b in zip(starts.tolist(), ends.tolist())), np.uint64, len(starts))


def followed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """One number for two in this order; the first goes through a bijection that is not linear."""
    return (a ^ (a >> _HALF)) * _ODD + b


def grams(hashes: np.ndarray, k: int) -> np.ndarray:
    """A hash for every run of k consecutive words, borders of documents ignored."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.full(n, np.uint64(k), np.uint64)
    for j in range(k):
        total = followed(total, hashes[j : j + n])
    return mixed(total)


def window_hashes(data: np.ndarray, width: int) -> np.ndarray:
    """A hash of every string of ``width`` bytes, eight at least, from hashes of its halves; the last two may overlap."""
    n = len(data) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    found, span = mixed(lanes(data)[: len(data) - 7]), 8
    while span < width:
        step = min(span, width - span)
        found, span = followed(found[: len(found) - step], found[step:]), span + step
    return mixed(found)


def lists(values: np.ndarray, lengths: np.ndarray, kind: pa.DataType) -> pa.Array:
    """An Arrow list column from flat values and the length of every row."""
    ends = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(values, kind))


def sliding_least(x: np.ndarray, w: int, greatest: bool = False) -> np.ndarray:
    """The minimum (or maximum) of every w consecutive values, in three passes."""
    n = len(x)
    if n < w:
        return x[:0]
    best = np.maximum if greatest else np.minimum
    fill = np.iinfo(x.dtype).min if greatest else np.iinfo(x.dtype).max
    blocks = np.full(-(-n // w) * w, fill, x.dtype)
    blocks[:n] = x
    blocks = blocks.reshape(-1, w)
    ahead = best.accumulate(blocks, axis=1).ravel()
    behind = best.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return best(behind[: n - w + 1], ahead[w - 1 : n])
