"""Words, lines and hashes of whole Arrow string columns as numpy arrays.

Spark hands over batches of texts; everything here works on the UTF-8 bytes of a batch at once, without a Python
step per word. Nulls count as empty texts. A single text of any length is handled whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

CHUNK_BYTES = 1 << 20

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column, and where each text begins (one more entry than texts)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] > at[0] else np.zeros(0, np.uint8)
    return raw, at - at[0]


def chunks(batch: pa.RecordBatch, column: str = "text", size: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about `size` bytes of text, at least one row each."""
    n = batch.num_rows
    if not n:
        return
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < n:
        done = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, done + size, "right")))
        yield batch.slice(at, to - at)
        at = to


def words(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of runs of non-space bytes, and the index of each text's first word (one more entry than texts)."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(at), np.int64)
    ink = ~SPACE[data]
    first, last = ink.copy(), ink.copy()
    first[1:] &= ~ink[:-1]
    last[:-1] &= ~ink[1:]
    own = at[:-1][at[:-1] < at[1:]]
    first[own] = ink[own]
    own = at[1:][at[:-1] < at[1:]] - 1
    last[own] = ink[own]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, at)


def lines(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the lines of each text split at \\n, and the index of each text's first line. An empty text has one empty line."""
    breaks = np.flatnonzero(data == 10)
    starts = np.concatenate([at[:-1], breaks + 1])
    ends = np.concatenate([at[1:], breaks])
    # a break ends a line of the text that holds it; the starts sort into the same order as the ends
    text_of_break = np.searchsorted(at, breaks, "right") - 1
    text = np.concatenate([np.arange(len(at) - 1), text_of_break])
    by_start = np.lexsort((starts, text))
    by_end = np.lexsort((ends, text))
    count = np.bincount(text, minlength=len(at) - 1) if len(at) > 1 else np.zeros(0, np.int64)
    return starts[by_start], ends[by_end], np.concatenate([[0], np.cumsum(count)]).astype(np.int64)


def mixed(h: np.ndarray) -> np.ndarray:
    """Spreads 64-bit values over all bits."""
    h = h ^ (h >> np.uint64(30))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def distinct_slices(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, pa.Array]:
    """The number of each slice's bytes among the distinct ones, in the order they first appear, and those as binaries. Slices follow each other, don't overlap and
    are compared byte by byte, so different ones never share a number."""
    inside = np.zeros(len(data) + 1, np.int8)
    full = ends > starts
    inside[starts[full]] += 1
    inside[ends[full]] -= 1
    raw = data[np.cumsum(inside[:-1], dtype=np.int8).view(bool)]
    at = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(ends - starts, out=at[1:])
    kind, offsets = (pa.binary(), at.astype(np.int32)) if at[-1] < 1 << 31 else (pa.large_binary(), at)
    coded = pa.Array.from_buffers(kind, len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(raw)]).dictionary_encode()
    return coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), coded.dictionary


def slice_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
    """XXH3's 64 bits of each slice, the same for the same bytes anywhere. Slices as in `distinct_slices`."""
    code, distinct = distinct_slices(LOWER[data] if lower else data, starts, ends)
    digest = xxhash.xxh3_64_intdigest
    return np.fromiter((digest(x) for x in distinct.to_pylist()), np.uint64, len(distinct))[code]


def sums(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sums of slices, empty ones 0. A slice of floats sums alike wherever it stands."""
    if values.dtype.kind == "f":
        out = np.zeros(len(starts))
        full = np.flatnonzero(ends > starts)
        if len(full):
            both = np.column_stack([starts[full], ends[full]]).ravel()
            out[full] = np.add.reduceat(np.append(values, 0.0), both)[::2]
        return out
    total = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, dtype=np.int64, out=total[1:])
    return total[ends] - total[starts]


#: Kinds of bytes: letters, digits, others. 0xC3 and the byte after it are a letter, but for two signs.
_KIND = np.full(256, 3, np.uint8)
_KIND[[*range(65, 91), *range(97, 123), *range(0x80, 0x100)]] = 1
_KIND[48:58] = 2


def kind_cuts(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, single_digits: bool, never: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """For each byte whether a tokenizer's pattern cuts before it, inside a simple word, and whether it is in a simple word at all. Simple words have ASCII and
    precomposed Latin-1 letters only, no apostrophe, and no byte marked in `never`; they fall into runs of letters, of digits (or single ones) and of other signs."""
    high = np.flatnonzero(data >= 0x80)
    after = (data[high - 1] == 0xC3) & (high > 0)
    known = (data[high] == 0xC3) | (after & (data[high] != 0x97) & (data[high] != 0xB7))
    at = np.concatenate([high[~known], np.flatnonzero(data == 0x27), np.flatnonzero(never) if never is not None else high[:0]])
    of = np.searchsorted(starts, at, "right") - 1
    simple = np.ones(len(starts), bool)
    simple[of[(of >= 0) & (at < ends[of])]] = False
    inside = np.zeros(len(data) + 1, np.int8)
    inside[starts[simple]] += 1
    inside[ends[simple]] -= 1
    inside = np.cumsum(inside[:-1], dtype=np.int8).view(bool)
    kind = _KIND[data]
    cut = np.zeros(len(data), bool)
    cut[1:] = kind[1:] != kind[:-1]
    if single_digits:
        cut[1:] |= kind[1:] == 2
    cut &= inside
    cut[starts] = False
    return cut, inside


def owners(bounds: np.ndarray) -> np.ndarray:
    """The text of each item, from the index of each text's first item."""
    return np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


def take_slices(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes (or ids) of many slices one after another, and where each begins."""
    at = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(lengths, out=at[1:])
    index = np.ones(at[-1], np.int64)
    keep = lengths > 0
    first = at[:-1][keep]
    if len(first):
        index[first[0]] = starts[keep][0]
        index[first[1:]] = starts[keep][1:] - (starts[keep][:-1] + lengths[keep][:-1]) + 1
        np.cumsum(index, out=index)
    return data[index] if len(first) else data[:0], at
