"""Byte-pair encoding and decoding through a table of distinct words.

Texts are cut where the tokenizer's own pre-tokenization always cuts, into words with the space before them and runs of white space. Each distinct word
is encoded once in the whole corpus: the words of all blocks are shuffled and sorted by their bytes, so equal words stand together.
Their ids return to the blocks and are joined to the positions. Ids are decoded by a join with the table of pieces (as many rows as the vocabulary).

Where a special token's string or white space beyond ASCII stands, nothing is cut at it nor at the white space next to it: the words on both sides and what is between
them are one word, so the library decides on it.
Null texts encode as empty ones: no ids, decoded empty. Repeated rows encode each on its own; doc_id may be null. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import itertools
import json
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.llm.blocks import block_table, dictionary, unpacked
from wingcount.llm.merges import Merges, byte_characters
from wingcount.llm.text_arrays import SPACE, kind_cuts, owners, sums, take_slices, text_bytes, words

#: White space that the pre-tokenization knows and a split at ASCII white space doesn't, and separators that some engines count as such.
ODD_SPACE = "[\x1c-\x1f\u0085\u00a0\u1680\u180e\u2000-\u200b\u2028\u2029\u202f\u205f\u3000\ufeff]"
_ODD_BYTES = rb"[\x1c-\x1f]|\xc2[\x85\xa0]|\xe1(?:\x9a\x80|\xa0\x8e)|\xe2(?:\x80[\x80-\x8b\xa8\xa9\xaf]|\x81\x9f)|\xe3\x80\x80|\xef\xbb\xbf"


def specials(path: str) -> list[str]:
    with open(path, encoding="utf-8") as f:
        return [x["content"] for x in json.load(f)["added_tokens"]]


def spaced_words(column: pa.Array, whole: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Cuts each text into words with one space before them and what white space remains, and simple words where the pattern cuts; not at `whole` nor at odd white space."""
    data, at = text_bytes(column)
    starts, ends, bounds = words(data, at)
    mark = np.zeros(len(data) + 1, bool)
    mark[at[:-1]] = True
    inner = starts[starts > at[owners(bounds)]] if len(starts) else starts
    mark[inner - 1] = True
    mark[inner[data[inner - 1] != 32]] = True
    mark[ends] = True
    mark[:-1] |= kind_cuts(data, starts, ends, single_digits=False)[0]
    odd = pc.match_substring_regex(column, "|".join([ODD_SPACE, *map(re.escape, whole)]))
    _glue(mark, data, at, np.flatnonzero(pc.fill_null(odd, False).to_numpy(zero_copy_only=False)), whole)
    mark[len(data)] = False
    cut = np.flatnonzero(mark)
    return data, cut, np.append(cut[1:], len(data)) if len(cut) else cut, np.searchsorted(cut, at)


def _glue(mark: np.ndarray, data: np.ndarray, at: np.ndarray, texts: np.ndarray, whole: list[str]) -> None:
    """Takes out the marks in and around odd stretches of the given texts, as far as ASCII white space goes on on both sides; texts still begin with a mark."""
    pattern = re.compile(b"|".join([_ODD_BYTES, *(re.escape(x.encode()) for x in whole)]))
    for k in texts.tolist():
        low, high = int(at[k]), int(at[k + 1])
        own = data[low:high]
        spans = np.array([m.span() for m in pattern.finditer(own.tobytes())])
        if not len(spans):
            continue
        ink = np.flatnonzero(~SPACE[own])  # every odd stretch has some
        left = ink[np.searchsorted(ink, spans[:, 0]) - 1] + 1
        left[spans[:, 0] <= ink[0]] = 0
        right = np.append(ink, len(own))[np.searchsorted(ink, spans[:, 1])]
        shut = np.zeros(len(own) + 2, np.int32)
        np.add.at(shut, left, 1)
        np.add.at(shut, right + 1, -1)
        inside = np.cumsum(shut[:-2]) > 0
        inside[0] = False
        mark[low:high][inside] = False


class WordEncoder:
    """Encodes many words in one call: simple ones by `Merges`, others by the library."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        # what becomes of a space and of capitals tells which words are left as one piece
        left = [x for x, _ in self.tokenizer.pre_tokenizer.pre_tokenize_str(" ab")]
        lowers = self.tokenizer.normalizer is not None and self.tokenizer.normalizer.normalize_str("Ab") == "ab"
        self.spaced = left == ["\u0120ab"]
        self.merges = Merges(path) if self.spaced or left == ["ab"] else None
        self.letter, self.second = np.zeros(256, bool), np.zeros(256, bool)  # bytes in words, and after 0xC3 in words
        self.letter[97:123] = True
        self.letter[65:91] = not lowers
        self.second[0x9F if lowers else 0x80 : 0xC0] = True
        self.second[[0x97, 0xB7]] = False

    def encode(self, texts: pa.Array, most: int = 10_000) -> tuple[np.ndarray, np.ndarray]:
        """All ids one after another, and where those of each word begin, of an array of distinct binaries."""
        data, at = text_bytes(texts)
        size = np.diff(at)
        simple = np.zeros(len(size), bool)
        if self.merges is not None and self.merges.usable and len(data):
            fits = self.letter[data]
            lead = np.flatnonzero(data[:-1] == 0xC3)
            lead = lead[self.second[data[lead + 1]]]
            fits[lead] = fits[lead + 1] = True
            if self.spaced:
                lead = at[:-1][size > 1]
                fits[lead] |= data[lead] == 32
            simple = (size > 0) & (sums(~fits, at[:-1], at[1:]) == 0)
        ids, counts = [], np.zeros(len(size), np.int64)
        own = np.flatnonzero(simple)
        if len(own):
            got, begin = self.merges.encode(*take_slices(data, at[own], size[own]))
            ids.append(got)
            counts[own] = np.diff(begin)
        other = np.flatnonzero(~simple)
        words_ = [x.decode() for x in texts.take(pa.array(other)).to_pylist()]
        for k in range(0, len(words_), most):
            got = [x.ids for x in self.tokenizer.encode_batch_fast(words_[k : k + most], add_special_tokens=False)]
            counts[other[k : k + most]] = np.fromiter(map(len, got), np.int64, len(got))
            ids.append(np.fromiter(itertools.chain.from_iterable(got), np.int64, sum(map(len, got))))
        order = np.concatenate([own, other])
        begin = np.empty(len(size), np.int64)
        begin[order] = np.cumsum(counts[order]) - counts[order]
        return take_slices(np.concatenate(ids) if ids else np.zeros(0, np.int64), begin, counts)


def encoded_words(pairs: DataFrame, path: str) -> DataFrame:
    """(block, ks, ns, ids): for each block the positions, numbers of ids and ids (16-bit little-endian, 32-bit where the vocabulary needs them) of some of its
    words. Words are dealt by their bytes and sorted, and each is encoded when it first appears; a batch's words go back in one row a block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = WordEncoder(path)
        kind = id_kind(encoder.tokenizer.get_vocab_size(with_added_tokens=True))
        held, size = [], 0

        def sent() -> pa.RecordBatch:
            table = pa.Table.from_batches(held).combine_chunks()
            column = table.column("word").combine_chunks().dictionary_encode()
            column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
            ids, at = encoder.encode(column.dictionary)
            of = column.indices.to_numpy(zero_copy_only=False)
            block, k = table.column("block").to_numpy(), table.column("k").to_numpy()
            by = np.lexsort((k, block))
            of, block, k = of[by], block[by], k[by]
            n = np.diff(at)[of]
            own, out = take_slices(ids.astype(kind), at[:-1][of], n)
            cuts = [*np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]])).tolist(), len(block)]
            spans = list(zip(cuts, cuts[1:], strict=False))
            columns = [pa.array(block[cuts[:-1]])]
            for values in (lambda a, b: k[a:b].astype("<u4"), lambda a, b: n[a:b].astype("<u4"), lambda a, b: own[out[a] : out[b]]):
                columns.append(pa.array([zstandard.compress(values(a, b).tobytes(), 1) for a, b in spans], pa.binary()))
            return pa.RecordBatch.from_arrays(columns, ["block", "ks", "ns", "ids"])

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= 200_000:
                yield sent()
                held, size = [], 0
        if size:
            yield sent()

    n = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = pairs.select("block", "k", "word").repartition(n, "word").sortWithinPartitions("word")
    return dealt.mapInArrow(run, "block long, ks binary, ns binary, ids binary")


def id_kind(vocabulary: int) -> str:
    return "<u2" if vocabulary <= 1 << 16 else "<u4"


def pieces(path: str) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of every piece of a byte-level vocabulary one after another, and where each begins, in the order of ids."""
    with open(path, encoding="utf-8") as f:
        stored = json.load(f)
    byte_of = {c: b for b, c in enumerate(byte_characters())}
    by_id = {i: x for x, i in stored["model"]["vocab"].items()} | {x["id"]: x["content"] for x in stored["added_tokens"]}
    raw = [bytes(byte_of[c] for c in by_id[i]) if i in by_id and all(c in byte_of for c in by_id[i]) else by_id.get(i, "").encode() for i in range(max(by_id) + 1)]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in raw])])


def decoded(ids: np.ndarray, table: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of the pieces of all ids, and where each id's begin."""
    data, at = table
    return take_slices(data, at[ids], at[ids + 1] - at[ids])


def word_ids(words: pa.Table, path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """All ids of a block's words, where those of word k begin and how many they are, and the vocabulary's size."""
    with open(path, encoding="utf-8") as f:
        stored = json.load(f)
    size = 1 + max(*stored["model"]["vocab"].values(), *(x["id"] for x in stored["added_tokens"]))
    kind = id_kind(size)
    read = lambda name, kind: [np.frombuffer(zstandard.decompress(x), kind) for x in words.column(name).to_pylist()]
    joined = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
    k, n = joined(read("ks", "<u4"), "<u4"), joined(read("ns", "<u4"), "<u4").astype(np.int64)
    word_at, word_n = np.zeros(len(k), np.int64), np.zeros(len(k), np.int64)
    word_at[k], word_n[k] = np.cumsum(n) - n, n
    return joined(read("ids", kind), kind), word_at, word_n, size


def encode_decode(docs: DataFrame, path: str, text: str = "text", tokens: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of each document; with `tokens` also its ids and the decoded text."""
    whole = specials(path)
    blocks = block_table(docs, lambda column: spaced_words(column, whole), text)
    ids = encoded_words(dictionary(blocks), path)
    more = ", ids array<int>, decoded string" if tokens else ""
    schema = f"doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string{more}"

    def joined(block: pa.Table, words: pa.Table) -> pa.Table:
        table = pieces(path)
        every, word_at, word_n, _ = word_ids(words, path)
        out = {"doc_id": [], "n_tokens": [], "ids_sha256": [], "decoded_sha256": []} | ({"ids": [], "decoded": []} if tokens else {})
        for row in block.to_pylist():
            counts, codes = np.frombuffer(row["counts"], "<i8"), unpacked(row["codes"])
            bounds = np.concatenate([[0], np.cumsum(counts)])
            done = 0
            while done < len(counts):
                to = max(done + 1, int(np.searchsorted(bounds, bounds[done] + 500_000, "right")) - 1)
                code = codes[bounds[done] : bounds[to]]
                own, token_at = take_slices(every, word_at[code], word_n[code])
                cut = token_at[bounds[done : to + 1] - bounds[done]]
                text_, byte_at = decoded(own.astype(np.int64), table)
                wide, byte_cut = own.astype("<u4").tobytes(), byte_at[cut]
                text_ = text_.tobytes()
                for i in range(to - done):
                    raw_text = text_[byte_cut[i] : byte_cut[i + 1]]
                    lossy = raw_text.decode("utf-8", "replace")
                    out["doc_id"].append(row["ids"][done + i])
                    out["n_tokens"].append(int(cut[i + 1] - cut[i]))
                    out["ids_sha256"].append(hashlib.sha256(wide[4 * cut[i] : 4 * cut[i + 1]]).hexdigest())
                    out["decoded_sha256"].append(hashlib.sha256(lossy.encode()).hexdigest())
                    if tokens:
                        out["ids"].append(own[cut[i] : cut[i + 1]].astype(np.int32).tolist())
                        out["decoded"].append(lossy)
                done = to
        fields = [("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
        fields += [("ids", pa.list_(pa.int32())), ("decoded", pa.string())] if tokens else []
        return pa.table({c: pa.array(out[c], t) for c, t in fields})

    return blocks.select("block", "ids", "counts", "codes").groupBy("block").cogroup(ids.groupBy("block")).applyInArrow(joined, schema)
