"""Benchmark decontamination: rare n-gram seeds, then local alignment.

Both sides are lower-cased and cut into runs of letters and digits. The corpus is read once to count the benchmark's words, so that each n-gram of an item has an
expected share among the corpus's n-grams (the product of its words' shares). N-grams under `rare_share`, and always an item's three rarest, are
seeds. A second pass finds every seed in every document; around its hits a window of the document is aligned with the item (Smith-Waterman over words:
match +2, mismatch -1, gap -1). A window whose best local score is at least `least_score` of the item's own, over at least `least_words` of its words, is a leak.

Tasks get the benchmark in slices of `slice_words` words at most, a pass over the corpus for each slice; benchmarks of usual size are one slice.

Null and empty texts and items match nothing, nor do items with fewer words than a seed. Items of equal text match alike. Rows that repeat a doc_id are looked
at one by one. Empty tables give empty results. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from wingcount.llm.text_arrays import chunks, mixed, owners, slice_hashes, text_bytes

MATCH, MISMATCH, GAP = 2, -1, -1
_INK = np.zeros(256, bool)
_INK[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True


def folded_words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the runs of letters and digits of each lower-cased text, and the index of each text's first one."""
    data, at = text_bytes(pc.utf8_lower(pc.fill_null(column, "")))
    ink = _INK[data]
    first, last = ink.copy(), ink.copy()
    first[1:] &= ~ink[:-1]
    last[:-1] &= ~ink[1:]
    full = at[:-1] < at[1:]
    first[at[:-1][full]] = ink[at[:-1][full]]
    last[at[1:][full] - 1] = ink[at[1:][full] - 1]
    starts = np.flatnonzero(first)
    return slice_hashes(data, starts, np.flatnonzero(last) + 1), np.searchsorted(starts, at)


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of n words from each word on, and whether all n are of one text."""
    if len(words) < n:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    h = np.zeros(len(words) - n + 1, np.uint64)
    for k in range(n):
        h = mixed(h * np.uint64(0x9E3779B97F4A7C15) + words[k : len(words) - n + 1 + k])
    of = owners(bounds)
    return h, of[: len(h)] == of[n - 1 :]


@dataclass(frozen=True)
class Items:
    """A slice of the benchmark: words of all items one after another, and its seeds by hash, each with an item and a place in it."""

    ids: tuple
    words: np.ndarray
    bounds: np.ndarray
    seeds: np.ndarray
    seed_item: np.ndarray
    seed_at: np.ndarray


def word_shares(docs: DataFrame, wanted: np.ndarray, text: str = "text") -> np.ndarray:
    """The share of each wanted word hash among all words of the corpus, add-one."""
    sent = docs.sparkSession.sparkContext.broadcast(np.unique(wanted))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent.value
        n, total = np.zeros(len(held), np.int64), 0
        for batch in batches:
            for part in chunks(batch, "text"):
                words, _ = folded_words(part.column("text"))
                near = np.minimum(np.searchsorted(held, words), len(held) - 1)
                n += np.bincount(near[held[near] == words], minlength=len(held))
                total += len(words)
        found = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(found, -1)), pa.array(np.append(n[found], total))], ["k", "n"])

    rows = docs.select(F.col(text).alias("text")).mapInArrow(counted, "k long, n long").groupBy("k").agg(F.sum("n").alias("n"))
    table = rows.toArrow()  # a row for each word of the slice
    k, n = table.column("k").to_numpy(), table.column("n").to_numpy()
    counts = np.zeros(len(sent.value), np.int64)
    counts[k[k >= 0]] = n[k >= 0]
    total = int(n[k < 0].sum())
    return ((counts + 1) / (total + len(counts) + 1))[np.searchsorted(sent.value, wanted)]


def seeded(docs: DataFrame, ids: list, texts: list, text: str, n: int, rare_share: float) -> Items:
    words, bounds = folded_words(pa.array(texts, pa.string()))
    h, whole = shingle_hashes(words, bounds, n)
    at = np.flatnonzero(whole)
    if not len(at):
        return Items(tuple(ids), words, bounds, np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64))
    share = np.log(word_shares(docs, words, text))
    expected = sum(share[at + k] for k in range(n))
    of = owners(bounds)[at]
    by = np.lexsort((at, expected, of))
    place = np.arange(len(by)) - np.searchsorted(of[by], of[by])
    chosen = np.zeros(len(at), bool)
    chosen[by[place < 3]] = True
    chosen |= expected <= np.log(rare_share)
    at = at[chosen]
    seeds = h[at]
    order = np.argsort(seeds, kind="stable")
    return Items(tuple(ids), words, bounds, seeds[order], owners(bounds)[at][order], (at - bounds[:-1][owners(bounds)[at]])[order])


def aligned(items: np.ndarray, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best local scores of rows of items (padded with 0) in rows of windows (padded with 1), and where they end in the window."""
    k, width = windows.shape
    h = np.zeros((k, width + 1), np.int32)
    slope = np.arange(width, dtype=np.int32) * -GAP
    best, end = np.zeros(k, np.int32), np.zeros(k, np.int64)
    rows = np.arange(k)
    for i in range(items.shape[1]):
        t = h[:, :-1] + np.where(windows == items[:, i : i + 1], MATCH, MISMATCH).astype(np.int32)
        np.maximum(t, h[:, 1:] + GAP, out=t)
        np.maximum(t, 0, out=t)
        t += slope
        np.maximum.accumulate(t, axis=1, out=t)
        t -= slope
        h[:, 1:] = t
        j = t.argmax(1)
        better = t[rows, j] > best
        best[better], end[better] = t[rows, j][better], j[better]
    return best, end


def _windows(hit_doc: np.ndarray, hit_at: np.ndarray, item: np.ndarray, item_at: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, ...]:
    """(doc, item, from, to) of stretches of words that hits point to, those that overlap joined."""
    slack = length // 4 + 4
    low, high = hit_at - item_at - slack, hit_at - item_at + length + slack
    by = np.lexsort((low, item, hit_doc))
    doc, item, low, high = hit_doc[by], item[by], low[by], high[by]
    pair = np.concatenate([[0], np.cumsum((doc[1:] != doc[:-1]) | (item[1:] != item[:-1]))])
    span = int(high.max() - low.min()) + 1
    reach = np.maximum.accumulate(high - low.min() + pair * span) + low.min() - pair * span
    new = np.concatenate([[True], (pair[1:] != pair[:-1]) | (low[1:] > reach[:-1])])
    first = np.flatnonzero(new)
    return doc[first], item[first], low[first], np.maximum.reduceat(high, first)


def leaks_of(held: Items, column: pa.Array, n: int, least_score: float, least_words: int, table: np.ndarray) -> dict[str, np.ndarray]:
    words, bounds = folded_words(column)
    h, whole = shingle_hashes(words, bounds, n)
    none = {c: np.zeros(0, np.int64) for c in ("doc", "item", "score", "first", "last")}
    at = np.flatnonzero(whole & table[(h & np.uint64(len(table) - 1)).astype(np.int64)]) if len(h) else np.zeros(0, np.int64)
    if not len(at):
        return none
    left, right = np.searchsorted(held.seeds, h[at], "left"), np.searchsorted(held.seeds, h[at], "right")
    found = right > left
    at, left, n_hits = at[found], left[found], (right - left)[found]
    if not len(at):
        return none
    seed = np.arange(n_hits.sum()) - np.repeat(np.cumsum(n_hits) - n_hits, n_hits) + np.repeat(left, n_hits)
    at = np.repeat(at, n_hits)
    doc = owners(bounds)[at]
    item = held.seed_item[seed]
    length = np.diff(held.bounds)
    doc, item, low, high = _windows(doc, at - bounds[doc], item, held.seed_at[seed], length[item])
    low, high = np.maximum(low, 0), np.minimum(high, np.diff(bounds)[doc])
    out = []
    order = np.lexsort((high - low, length[item]))
    done = 0
    while done < len(order):
        # a batch of like sizes, some 2 million cells a step
        to = done + 1
        wide = high[order[done]] - low[order[done]]
        while to < len(order) and to - done < 4096 and (to - done + 1) * max(wide, high[order[to]] - low[order[to]]) <= 2_000_000:
            wide = max(wide, high[order[to]] - low[order[to]])
            to += 1
        own = order[done:to]
        done = to
        tall = int(length[item[own]].max())
        i = np.arange(tall)
        rows = np.where(i < length[item[own]][:, None], held.words[np.minimum(held.bounds[item[own]][:, None] + i, len(held.words) - 1)], np.uint64(0))
        j = np.arange(int(wide))
        size = (high - low)[own][:, None]
        seen = np.where(j < size, words[np.minimum((bounds[doc[own]] + low[own])[:, None] + j, len(words) - 1)], np.uint64(1))
        best, end = aligned(rows, seen)
        good = np.flatnonzero((best >= np.maximum(MATCH * least_score * length[item[own]], MATCH * np.minimum(least_words, length[item[own]]))))
        if not len(good):
            continue
        # the same alignment from the other end finds where it starts
        back = np.where(j[None, ::-1] <= end[good][:, None], seen[good][:, ::-1], np.uint64(1))
        item_back = np.take_along_axis(rows[good], np.maximum(length[item[own[good]]][:, None] - 1 - i, 0), 1)
        item_back = np.where(i < length[item[own[good]]][:, None], item_back, np.uint64(0))
        _, start = aligned(item_back, back)
        out.append((doc[own[good]], item[own[good]], best[good] / (MATCH * length[item[own[good]]]), low[own[good]] + int(wide) - 1 - start, low[own[good]] + end[good]))
    if not out:
        return none
    return dict(zip(("doc", "item", "score", "first", "last"), (np.concatenate(x) for x in zip(*out, strict=True)), strict=True))


def seed_table(held: Items) -> np.ndarray:
    """Which low bits of a hash any seed has."""
    table = np.zeros(1 << 20, bool)
    table[(held.seeds & np.uint64(len(table) - 1)).astype(np.int64)] = True
    return table


def slices(docs: DataFrame, benchmark: DataFrame, text: str = "text", n: int = 3, rare_share: float = 1e-8, slice_words: int = 2_000_000) -> Iterator[Items]:
    """The benchmark's items with their seeds, in slices of a bounded number of words."""
    items = benchmark.where("item_id is not null and text is not null").select("item_id", "text")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    count = max(1, -(-int(total) // (2 * slice_words)))  # a word and its space have two bytes at least
    for k in range(count):
        own = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(count)) == k).orderBy("item_id", "text").collect()
        yield seeded(docs, [r[0] for r in own], [r[1] for r in own], text, n, rare_share)


def leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), n: int = 3, least_score: float = 0.5, least_words: int = 8, **how) -> DataFrame:
    """`keep` columns, item_id, score (share of the item's own score), first_word and last_word (of the document's folded words) of every leak."""
    rows = docs.select(*keep, F.col(text).alias("_text"))
    schema = T.StructType([rows.schema[c] for c in keep] + [benchmark.schema["item_id"]] + [T.StructField(c, t) for c, t in (("score", T.DoubleType()), ("first_word", T.LongType()), ("last_word", T.LongType()))])
    out = None
    for items in slices(docs, benchmark, text, n, **how):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            held = sent.value
            table = seed_table(held)
            names = pa.array(held.ids, to_arrow_type(schema["item_id"].dataType))
            for batch in batches:
                for part in chunks(batch, "_text"):
                    got = leaks_of(held, part.column("_text"), n, least_score, least_words, table)
                    which = pa.array(got["doc"])
                    yield pa.RecordBatch.from_arrays([*(part.column(c).take(which) for c in keep), names.take(pa.array(got["item"])), pa.array(got["score"].astype(float)), pa.array(got["first"]), pa.array(got["last"])], schema.fieldNames())

        found = rows.mapInArrow(run, schema)
        out = found if out is None else out.union(found)
    return out
