"""Token-id files compressed by a grammar of repeated pairs, with random access.

Documents are dealt by ranges of doc_id and written in that order. A block of some documents' ids is rewritten in rounds: the most frequent pairs of neighbouring
symbols each become a new symbol, whose rule is the pair, until no pair of neighbours is left that stands in the block `least` times. No rule crosses the end of a document.
A block's row holds its rules, the length of each rule's expansion, the symbols left, and how many ids each document has; so any run of ids can be read
by expanding only the symbols that cover it. Blocks are rows of a Parquet table that Spark writes, so a lost task is simply written anew.

Null texts count as empty: only the end id. doc_id null sorts first; rows that repeat a doc_id are each written, in the order of their texts' hashes. An
empty table gives an empty file. Extra columns are ignored.
"""

from __future__ import annotations

import functools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wingcount.llm.blocks import block_table, dictionary, unpacked
from wingcount.llm.byte_pairs import encoded_words, specials, word_ids
from wingcount.llm.text_arrays import kind_cuts, take_slices, text_bytes, words
from wingcount.shared import size_of

END_ID = 2
BLOCK_IDS = 1 << 20
MOST_SENT = 1_000_000
PART_BYTES = 16 << 20
SCHEMA = "part long, block long, seq int, ids array<long>, counts binary, base int, rules binary, lengths binary, symbols binary, before long, n long"
ARROW = pa.schema(
    [("part", pa.int64()), ("block", pa.int64()), ("seq", pa.int32()), ("ids", pa.list_(pa.int64())), ("counts", pa.binary()), ("base", pa.int32())]
    + [(c, pa.binary()) for c in ("rules", "lengths", "symbols")]
    + [("before", pa.int64()), ("n", pa.int64())]
)
_CELLS = 20


def letter_runs(column: pa.Array, whole: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Cuts texts at white space, and simple words also where the tokenizer's pattern cuts. Simple words are lower-cased, as the tokenizer does; others, and all words of a text with one of `whole`, stay as they are."""
    data, at = text_bytes(column)
    starts, ends, bounds = words(data, at)
    special = pc.fill_null(functools.reduce(pc.or_, (pc.match_substring(column, x) for x in whole)), False).to_numpy(zero_copy_only=False)
    cut, inside = kind_cuts(data, starts, ends, single_digits=True, never=np.repeat(special, np.diff(at)) if special.any() else None)
    low = data + (((data - np.uint8(65)) < 26) & inside).view(np.uint8) * np.uint8(32)
    latin = np.flatnonzero((data == 0xC3) & inside) + 1
    low[latin[(data[latin] >= 0x80) & (data[latin] <= 0x9E)]] += 32
    first = cut.copy()
    first[starts] = True
    last = np.zeros(len(data) + 1, bool)
    last[ends] = True
    last[:-1] |= cut
    first = np.flatnonzero(first)
    return low, first, np.flatnonzero(last), np.searchsorted(first, at)


def grammar(ids: np.ndarray, bounds: np.ndarray, base: int, least: int = 32) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rules, lengths, symbols) of a block of ids, whose documents begin at `bounds`. Symbols from `base` on are rules, each of two earlier symbols. Goes on until no
    two neighbours stand together `least` times. A pair of old symbols only ever gets rarer, so after the first round only places next to a new symbol, or where a pair
    had to give way, are looked at; symbols are a chain, from which the second one of a pair drops out."""
    n = len(ids)
    s = np.append(ids.astype(np.int64), 0)
    after, ahead = np.arange(1, n + 2), np.arange(-1, n)  # place n is past the end
    last = np.zeros(n + 1, bool)
    last[bounds[1:][np.diff(bounds) > 0] - 1] = True
    last[n] = True
    dead = np.zeros(n + 1, bool)
    dead[n] = True
    rules, n_rules = [], 0
    at = np.flatnonzero(~last)
    key = (s[:-1] << 32 | s[1:])[at]
    while len(at):
        if len(at) > 1 << 16:  # many pairs are rare: those that share no cell of a table with others are left out before sorting
            cell = _cell(key)
            heavy = (np.bincount(cell, minlength=1 << _CELLS) >= least)[cell]
            at, key = at[heavy], key[heavy]
        pairs, counts = np.unique(key, return_counts=True)
        own = np.flatnonzero(counts >= least)
        own = own[np.argsort(-counts[own], kind="stable")]
        if not len(own):
            break
        pairs = pairs[own]
        of_cell = np.full(1 << _CELLS, -1, np.int32)
        of_cell[_cell(pairs[::-1])] = np.arange(len(pairs), dtype=np.int32)[::-1]  # the more frequent of two in a cell, the other one next time
        rank = of_cell[_cell(key)]
        open_ = rank >= 0
        at, key, rank = at[open_], key[open_], rank[open_]
        hit = pairs[rank] == key
        put, rank = at[hit], rank[hit]
        taken = _apart(put, rank, after)
        put, rank = put[taken], rank[taken]
        used = np.flatnonzero(np.bincount(rank, minlength=len(pairs)))
        number = np.zeros(len(pairs), np.int64)
        number[used] = base + n_rules + np.arange(len(used))
        rules.append(pairs[used])
        n_rules += len(used)
        gone = after[put]
        s[put], last[put], after[put] = number[rank], last[gone], after[gone]
        ahead[after[gone]] = put
        dead[gone] = True
        at = np.sort(np.concatenate([at, put, ahead[put]]))
        at = at[np.append(at[1:] != at[:-1], True) & ~dead[at] & ~last[at]]
        key = s[at] << 32 | s[after[at]]
    flat = np.concatenate(rules) if rules else np.zeros(0, np.int64)
    rule = np.column_stack([flat >> 32, flat & 0xFFFFFFFF]).astype(np.int32)
    lengths, done = np.ones(len(rule), np.int64), 0
    for group in rules:  # a round's rules stand on earlier rounds' only
        own = rule[done : done + len(group)]
        lengths[done : done + len(group)] = sum(np.where(own[:, k] >= base, lengths[np.maximum(own[:, k] - base, 0)], 1) for k in (0, 1))
        done += len(group)
    return rule, lengths, s[~dead].astype(np.int32)


def _cell(key: np.ndarray) -> np.ndarray:
    return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - _CELLS)).view(np.int64)


def _apart(at: np.ndarray, rank: np.ndarray, after: np.ndarray) -> np.ndarray:
    """Which of the pairs at these places are taken, so that none overlap: every second one where a pair follows itself, then the more frequent of two that touch.
    One of the most frequent pair always is."""
    taken = np.ones(len(at), bool)
    touch = at[1:] == after[at[:-1]]
    again = np.flatnonzero(touch & (rank[1:] == rank[:-1])) + 1
    if len(again):
        place = np.arange(len(again))
        begins = np.concatenate([[True], again[1:] != again[:-1] + 1])
        taken[again[(place - np.maximum.accumulate(np.where(begins, place, 0))) % 2 == 0]] = False
        touch &= taken[1:] & taken[:-1]
    left_first = rank[:-1] < rank[1:]
    taken[1:] &= ~(touch & left_first)
    taken[:-1] &= ~touch | left_first
    return taken


def expanded(symbols: np.ndarray, rule: np.ndarray, base: int) -> np.ndarray:
    """All ids that the symbols stand for."""
    s = symbols.astype(np.int64)
    while len(open_ := np.flatnonzero(s >= base)):
        size = np.ones(len(s), np.int64)
        size[open_] = 2
        at = np.cumsum(size) - size
        out = np.empty(at[-1] + size[-1], np.int64)
        out[at] = s
        pair = rule[s[open_] - base]
        out[at[open_]], out[at[open_] + 1] = pair[:, 0], pair[:, 1]
        s = out
    return s


def all_ids(symbols: np.ndarray, rule: np.ndarray, lengths: np.ndarray, base: int) -> np.ndarray:
    """The same for a whole block: each rule is expanded once (some thousand ids in all, as a rule stands for far fewer ids than its block has), each symbol is copied."""
    made = symbols >= base
    of = np.where(made, symbols - base, 0)
    if not len(rule) or lengths.sum() > 4 * max(len(symbols), lengths[of][made].sum()):
        return expanded(symbols, rule, base)
    flat = np.concatenate([expanded(np.arange(base, base + len(rule)), rule, base), symbols])
    begins = np.cumsum(lengths) - lengths
    start = np.where(made, begins[of], len(flat) - len(symbols) + np.arange(len(symbols)))
    return take_slices(flat, start, np.where(made, lengths[of], 1))[0]


def ids_between(row: dict, start: int, stop: int) -> np.ndarray:
    """Ids start to stop of a block, expanding no symbol that lies outside."""
    base, rule, lengths, symbols = row["base"], _rules(row["rules"]), _back(row["lengths"], "<i4"), _back(row["symbols"], "<i4")
    size = np.ones(len(symbols), np.int64)
    made = symbols >= base
    size[made] = lengths[symbols[made] - base]
    ends = np.cumsum(size)
    first, last = np.searchsorted(ends, start, "right"), np.searchsorted(ends, stop, "left") + 1
    before = ends[first - 1] if first else 0
    return expanded(symbols[first:last], rule, base)[start - before : stop - before]


def _squeezed(values: np.ndarray) -> bytes:
    planes = np.ascontiguousarray(values.astype("<i4").view(np.uint8).reshape(-1, 4).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _back(raw: bytes, kind: str) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8).reshape(4, -1)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


def _rules(raw: bytes) -> np.ndarray:
    return _back(raw, "<i4").reshape(2, -1).T


def write_ids(docs: DataFrame, path: str, tokenizer: str, text: str = "text", doc_id: str = "doc_id", parts: int | None = None) -> None:
    """Encodes all texts and writes their ids to `path` in ascending order of doc_id. Blocks are cut from the ordered documents, so their numbers ascend too;
    each distinct word of the corpus is encoded once and returns to the blocks."""
    parts = parts or max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), size_of(docs) // PART_BYTES)
    order = [F.col(doc_id).cast("long").asc_nulls_first(), F.col("_tie")]
    # rows of one id (or none) may be many, so their texts' hashes deal them too
    dealt = docs.select(doc_id, text, F.xxhash64(text).alias("_tie")).repartitionByRange(parts, *order).sortWithinPartitions(*order)
    whole = specials(tokenizer)
    blocks = block_table(dealt, lambda column: letter_runs(column, whole), text, doc_id)
    words_ = encoded_words(dictionary(blocks), tokenizer)

    def written_rows(block: pa.Table, own: pa.Table) -> pa.Table:
        every, word_at, word_n, base = word_ids(own, tokenizer)
        out = []
        for row in block.to_pylist():
            counts, codes = np.frombuffer(row["counts"], "<i8"), unpacked(row["codes"])
            bounds = np.concatenate([[0], np.cumsum(counts)])
            tokens = np.concatenate([[0], np.cumsum(word_n[codes])])[bounds] + np.arange(len(bounds))  # with an end id for each text
            done = seq = before = 0
            while done < len(counts):
                to = max(done + 1, int(np.searchsorted(tokens, tokens[done] + BLOCK_IDS, "right")) - 1)
                code, n = codes[bounds[done] : bounds[to]], counts[done:to]
                place = np.arange(len(code)) + np.repeat(np.arange(len(n)), n)
                start, size = np.full(len(code) + len(n), len(every)), np.ones(len(code) + len(n), np.int64)
                start[place], size[place] = word_at[code], word_n[code]
                ids, _ = take_slices(np.append(every, every.dtype.type(END_ID)), start, size)
                at = tokens[done : to + 1] - tokens[done]
                rule, lengths, symbols = grammar(ids, at, base)
                out.append({"part": row["block"] >> 32, "block": row["block"], "seq": seq, "ids": row["ids"][done:to], "counts": np.diff(at).astype("<i8").tobytes(), "base": base})
                out[-1] |= {"rules": _squeezed(rule.T.ravel()), "lengths": _squeezed(lengths), "symbols": _squeezed(symbols), "before": before, "n": len(ids)}
                before, seq, done = before + len(ids), seq + 1, to
        return pa.Table.from_pylist(out, ARROW)

    left = blocks.select("block", "ids", "counts", "codes")
    left.groupBy("block").cogroup(words_.groupBy("block")).applyInArrow(written_rows, SCHEMA).write.option("compression", "none").parquet(path)


def read_ids(spark, path: str, tokens: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document of the files, and with `tokens` its ids."""
    stored = spark.read.schema(SCHEMA).parquet(path)
    earlier = lambda by: F.coalesce(F.sum("n").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    totals = stored.groupBy("part", "block").agg(F.sum("n").alias("n"))  # blocks of some 24 MB of text
    parts = totals.groupBy("part").agg(F.sum("n").alias("n")).select("part", earlier(Window.orderBy("part")).alias("ahead"))  # a row a task
    inner = totals.select("part", "block", earlier(Window.partitionBy("part").orderBy("block")).alias("within"))
    offset = inner.join(parts, "part").select("block", (F.col("ahead") + F.col("within")).alias("offset"))
    more = ", tokens array<int>" if tokens else ""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids = all_ids(_back(row["symbols"], "<i4"), _rules(row["rules"]), _back(row["lengths"], "<i4").astype(np.int64), row["base"])
                counts = np.frombuffer(row["counts"], "<i8")
                at = np.concatenate([[0], np.cumsum(counts)])
                raw = ids.astype("<u4").tobytes()
                crc = [zlib.crc32(raw[4 * at[i] : 4 * at[i + 1]]) for i in range(len(counts))]
                columns = [pa.array(row["ids"], pa.int64()), pa.array(row["offset"] + row["before"] + at[:-1]), pa.array(counts), pa.array(crc, pa.int64())]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if tokens:
                    columns.append(pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(ids.astype(np.int32))))
                    names.append("tokens")
                yield pa.RecordBatch.from_arrays(columns, names)

    # a row for some 48 MB of text: to all tasks up to a million of them, which are 16 MB, by a shuffle beyond
    few = stored.select("block").distinct().limit(MOST_SENT + 1).count() <= MOST_SENT
    placed = stored.join(F.broadcast(offset) if few else offset, "block")
    return placed.mapInArrow(read, f"doc_id long, start long, n_tokens long, ids_crc32 long{more}")
