"""Blocks of documents with a dictionary of their distinct words.

A block is up to some 48 MB of texts of one task (or what a caller asks for, or one longer text). Its row holds the documents' words as positions in the block's own dictionary, so
work on words is done once per distinct word and block: the dictionaries are joined with a corpus-wide word table by an ordinary
shuffle, and what that gives returns to the block, whose size bounds the memory. The corpus-wide table is never broadcast.

Words are told apart by their bytes, within a block and across blocks.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.llm.text_arrays import chunks, distinct_slices
from wingcount.shared import bucketed

BLOCK_BYTES = 48 << 20
#: (bytes, starts, ends, index of each text's first word) of a string column
Split = Callable[[pa.Array], tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]


def packed(codes: np.ndarray) -> bytes:
    """Dictionary positions as three planes of bytes, compressed; frequent words have small positions, so the upper planes are nearly empty."""
    planes = np.ascontiguousarray(codes.astype("<u4").view(np.uint8).reshape(-1, 4).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unpacked(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(4, -1)
    return np.ascontiguousarray(planes.T).view("<u4").ravel()


def shut(x: np.ndarray) -> bytes:
    """Numbers of the least width that holds them, as planes of bytes, compressed."""
    top = int(x.max()) if len(x) else 0
    width = next(k for k in (1, 2, 4, 8) if top < 1 << (8 * k))
    raw = np.ascontiguousarray(x.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T)
    return bytes([width]) + zstandard.ZstdCompressor(level=1).compress(raw)


def opened(raw: bytes) -> np.ndarray:
    width = raw[0]
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw[1:]), np.uint8).reshape(width, -1)
    return np.ascontiguousarray(planes.T).view(f"<u{width}").ravel().astype(np.uint64)


def in_order(hashes: np.ndarray) -> np.ndarray:
    """The order of 64-bit hashes, equal ones by place. Their upper bits are sorted with the place in the lower ones, which is much faster than to sort places by hashes;
    where that can't tell two apart, the full order is taken."""
    bits = np.uint64(max(1, len(hashes) - 1).bit_length())
    key = hashes >> bits
    key <<= bits
    key |= np.arange(len(hashes), dtype=np.uint64)
    key.sort()
    key &= np.uint64((1 << int(bits)) - 1)
    by = key.view(np.int64)
    full = hashes[by]
    return by if (full[1:] >= full[:-1]).all() else np.argsort(hashes, kind="stable")


def digests(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Both halves of the words' 128-bit BLAKE2 digests."""
    halves = np.frombuffer(b"".join([hashlib.blake2b(w, digest_size=16).digest() for w in words]), "<u8").reshape(-1, 2)
    return np.ascontiguousarray(halves[:, 0]), np.ascontiguousarray(halves[:, 1])


def block_table(docs: DataFrame, split: Split, text: str = "text", doc_id: str = "doc_id", flag=None, size_of_block: int = BLOCK_BYTES, keyed: bool = False) -> DataFrame:
    """block, ids (of its documents), flags, counts (words of each document), codes (packed), words, ks and ns (a dictionary in the order of its
    words, each word's position, and how often it occurs in documents with a flag). Written to the shared folder in buckets of the block. With `keyed` words are their digests
(high: steps from one to the next in their order, low: as they are), and all columns of the dictionary are `shut`."""
    rows = docs.select(F.col(doc_id).cast("long").alias("id"), (F.lit(True) if flag is None else flag).alias("flag"), F.col(text).alias("_text"))

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, n = TaskContext.get().partitionId(), 0
        held, size = [], 0
        for batch in batches:
            for piece in chunks(batch, "_text"):
                data, starts, ends, bounds = split(piece.column("_text"))
                code, own = distinct_slices(data, starts, ends)
                flags = piece.column("flag").fill_null(False).to_numpy(zero_copy_only=False)
                marked = np.repeat(flags, np.diff(bounds))
                held.append((piece.column("id"), flags, np.diff(bounds), code.astype(np.uint32), own, np.bincount(code[marked], minlength=len(own)), np.bincount(code, minlength=len(own))))
                size += len(data)
                if size >= size_of_block:
                    yield block((part << 32) + n, held)
                    held, size, n = [], 0, n + 1
                    pa.default_memory_pool().release_unused()
        if held:
            yield block((part << 32) + n, held)

    def block(key: int, held: list) -> pa.RecordBatch:
        ids, flags, counts, codes, own, ns, alls = zip(*held, strict=True)
        coded = pa.concat_arrays([x.cast(pa.binary()) for x in own]).dictionary_encode()
        words, back = coded.dictionary, coded.indices.to_numpy(zero_copy_only=False)
        total = np.bincount(back, np.concatenate(alls), len(words))
        by = np.argsort(-total, kind="stable")
        rank = np.empty(len(words), np.uint32)
        rank[by] = np.arange(len(words), dtype=np.uint32)
        shift = np.cumsum([0, *(len(x) for x in own)])
        own_rank = rank[back]
        code = np.concatenate([own_rank[shift[k] + codes[k]] for k in range(len(codes))])
        n = np.bincount(back, np.concatenate(ns), len(words)).astype(np.int64)
        first = [
            pa.array([key]),
            pa.array([pa.concat_arrays(ids).to_pylist()], pa.list_(pa.int64())),
            pa.array([np.concatenate(flags).astype(np.uint8).tobytes()], pa.binary()),
            pa.array([np.concatenate(counts).astype("<i8").tobytes()], pa.binary()),
            pa.array([packed(code)], pa.binary()),
        ]
        if keyed:
            high, low = digests(words.to_pylist())
            by = np.lexsort((low, high))
            own = (shut(np.diff(high[by], prepend=np.uint64(0))), low[by].tobytes(), shut(rank[by]), shut(n[by]), int(n.sum()))
            return pa.RecordBatch.from_arrays(first + [pa.array([x], t) for x, t in zip(own, [pa.binary()] * 4 + [pa.int64()], strict=True)], [*named, "high", "low", "ks", "ns", "n"])
        alike = pc.sort_indices(words).to_numpy()  # neighbours share their beginnings, which shrinks the shuffle
        words, place, n = words.take(pa.array(alike)), rank[alike].astype(np.int32), n[alike]
        return pa.RecordBatch.from_arrays(
            [
                *first,
                pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), words),
                pa.ListArray.from_arrays(pa.array([0, len(n)], pa.int32()), pa.array(place)),
                pa.ListArray.from_arrays(pa.array([0, len(n)], pa.int32()), pa.array(n)),
            ],
            [*named, "words", "ks", "ns"],
        )

    named = ["block", "ids", "flags", "counts", "codes"]
    schema = "block long, ids array<long>, flags binary, counts binary, codes binary, "
    schema += "high binary, low binary, ks binary, ns binary, n long" if keyed else "words array<binary>, ks array<int>, ns array<long>"
    return bucketed(rows.mapInArrow(blocks, schema), "blocks", "block")


def dictionary(blocks: DataFrame) -> DataFrame:
    """(block, k, word, n): a row for each distinct word of each block."""
    return blocks.select("block", F.explode(F.arrays_zip("words", "ks", "ns")).alias("w")).select("block", F.col("w.ks").alias("k"), F.col("w.words").alias("word"), F.col("w.ns").alias("n"))
