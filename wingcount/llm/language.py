"""Language identification with bit-sliced Bloom filters over byte n-grams.

One bit array per language is stored crosswise: row r holds a bitmask of the languages whose filter has bit r set, so
one lookup of an n-gram's few rows and an AND of their masks gives every language that contains it. A text's n-grams
are counted per language from those masks, the counts are corrected for each filter's false-positive rate, and the
largest corrected share decides.

A language has the n-grams whose share of it is at least a quarter of their largest share of any language, however rare they are. Tasks set the filters' bits, and the driver gets the rows
of the table: their number follows from `log2_rows` (or the languages, 64 to a number), not from the corpus or its n-grams.

Nulls and texts without a letter are `und` with score 0. Training rows with null text or null language are left out;
without any training row every text is `und`. Equal shares go to the language that sorts first. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.llm.text_arrays import chunks, mixed, sums, text_bytes
from wingcount.shared import written

UNDETERMINED = "und"
#: Letters and non-ASCII bytes stay; everything else is one boundary.
_FOLD = np.zeros(256, np.uint8)
_FOLD[list(range(97, 123)) + list(range(128, 256))] = list(range(97, 123)) + list(range(128, 256))


@dataclass(frozen=True)
class LanguageFilters:
    """`rows[r]` is the mask of languages with bit r, in slices of 64 languages; `false_rate` and `learned` (n-grams read) are per language."""

    names: tuple[str, ...]
    rows: np.ndarray
    probes: int
    false_rate: np.ndarray
    learned: np.ndarray = field(default_factory=lambda: np.zeros(0))


def _ngrams(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes of the 4-grams of folded bytes of each text between boundaries, and each text's slice of them."""
    data, at = text_bytes(pc.utf8_lower(pc.fill_null(column, "")))
    n = len(at) - 1
    lengths = np.diff(at)
    base = at[:-1] + 4 * np.arange(n)
    padded = np.zeros(len(data) + 4 * n, np.uint32)
    padded[np.arange(len(data)) + np.repeat(4 * np.arange(n) + 2, lengths)] = _FOLD[data]
    codes = (padded[:-3] << 24) | (padded[1:-2] << 16) | (padded[2:-1] << 8) | padded[3:] if len(padded) > 3 else np.zeros(0, np.uint32)
    return codes, base, base + lengths + 1


def _bits(codes: np.ndarray, size: int, probes: int) -> Iterator[np.ndarray]:
    h = mixed(codes.astype(np.uint64) + np.uint64(0x51ED270B))
    step = (h >> np.uint64(32)) | np.uint64(1)
    for i in range(probes):
        yield ((h + np.uint64(i) * step) & np.uint64(size - 1)).astype(np.int64)


def _informative(codes: np.ndarray) -> np.ndarray:
    """An n-gram of boundaries alone, or with one letter only, says nothing."""
    return ((codes & 0xFFFF) != 0) & ((codes & 0xFFFFFF00) != 0)


def count_ngrams(train: DataFrame, text: str = "text", lang: str = "lang") -> DataFrame:
    """(lang, code, n): how often each language has each n-gram, over all training rows; summed per task before the shuffle."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {}

        def folded(name: str) -> None:
            codes, n = (np.concatenate(x) for x in zip(*held[name], strict=True))
            unique, back = np.unique(codes, return_inverse=True)
            held[name] = [(unique, np.bincount(back, n, len(unique)).astype(np.int64))]

        for batch in batches:
            for part in chunks(batch, "text"):
                codes, starts, ends = _ngrams(part.column("text"))
                names = part.column("lang").dictionary_encode()
                of = names.indices.to_numpy(zero_copy_only=False)
                for k, name in enumerate(names.dictionary.to_pylist()):
                    mark = np.zeros(len(codes) + 1, np.int8)
                    np.add.at(mark, starts[of == k], 1)
                    np.add.at(mark, ends[of == k], -1)
                    own = codes[np.cumsum(mark[:-1]).astype(bool)]
                    held.setdefault(name, []).append(np.unique(own[_informative(own)], return_counts=True))
                    if len(held[name]) > 16:
                        folded(name)
        for name in list(held):
            folded(name)
            unique, n = held[name][0]
            for at in range(0, len(unique), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(unique[at : at + (1 << 18)]), pa.string()), pa.array(unique[at : at + (1 << 18)].astype(np.int64)), pa.array(n[at : at + (1 << 18)])], ["lang", "code", "n"])

    rows = train.select(F.col(text).alias("text"), F.col(lang).alias("lang")).where("text is not null and lang is not null")
    return rows.mapInArrow(counted, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n"))


def fit_filters(train: DataFrame, text: str = "text", lang: str = "lang", of_best: float = 0.25, log2_rows: int = 22, probes: int = 3, most_languages: int = 1024) -> LanguageFilters:
    """Filters of the n-grams that have at least `of_best` of their largest share. More than `most_languages` names are refused."""
    counts = written(count_ngrams(train, text, lang), "ngrams")
    totals = counts.groupBy("lang").agg(F.sum("n").alias("total"))
    read = totals.orderBy("lang").limit(most_languages + 1).collect()
    names = tuple(r["lang"] for r in read)
    if len(names) > most_languages:
        raise ValueError(f"more than {most_languages} languages")
    slices, size = max(1, -(-len(names) // 64)), 1 << log2_rows
    kind = np.uint8 if len(names) <= 8 else np.uint64
    rows = np.zeros((size, slices), kind)
    share = counts.join(F.broadcast(totals), "lang").select("lang", "code", (F.col("n") / F.col("total")).alias("share"))
    best = share.groupBy("code").agg(F.max("share").alias("best"), F.collect_list(F.struct("lang", "share")).alias("held"))  # at most a row a language
    kept = best.select("code", F.transform(F.filter("held", lambda x: x["share"] >= of_best * F.col("best")), lambda x: x["lang"]).alias("langs"))

    def bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = pa.array(names, pa.string())
        for batch in batches:
            langs = batch.column("langs")
            of = np.repeat(np.arange(batch.num_rows), pc.list_value_length(langs).to_numpy())
            code = batch.column("code").to_numpy().astype(np.uint32)[of]
            lang_ = pc.index_in(langs.flatten(), number).to_numpy(zero_copy_only=False).astype(np.int64)
            at = np.concatenate([x * slices + lang_ // 64 for x in _bits(code, size, probes)] or [np.zeros(0, np.int64)])
            mask = np.tile(np.uint64(1) << (lang_ % 64).astype(np.uint64), probes)
            by = np.argsort(at)
            first = np.flatnonzero(np.concatenate([[True], at[by[1:]] != at[by[:-1]]])) if len(by) else by
            both = np.bitwise_or.reduceat(mask[by], first) if len(by) else mask
            yield pa.RecordBatch.from_arrays([pa.array(at[by[first]]), pa.array(both.view(np.int64))], ["at", "mask"])

    if names:
        table = kept.mapInArrow(bits, "at long, mask long").groupBy("at").agg(F.bit_or("mask").alias("mask")).toArrow()  # 2^log2_rows rows at most for 64 languages
        rows.reshape(-1)[table.column("at").to_numpy()] = table.column("mask").to_numpy().view(np.uint64).astype(kind)
    fill = np.array([float(((rows[:, k // 64] >> kind(k % 64)) & kind(1)).mean()) for k in range(len(names))])
    return LanguageFilters(names, rows, probes, fill**probes, np.array([r["total"] for r in read], np.int64))


def shares(filters: LanguageFilters, column: pa.Array) -> np.ndarray:
    """Per text and language, the share of the text's n-grams that are the language's, corrected for false positives."""
    codes, starts, ends = _ngrams(column)
    telling = _informative(codes)
    n = np.maximum(sums(telling, starts, ends), 1)
    out = np.zeros((len(starts), len(filters.names)))
    masks = None
    for at in _bits(codes, len(filters.rows), filters.probes):
        masks = filters.rows[at] if masks is None else masks & filters.rows[at]
    for k in range(len(filters.names)):
        kind = masks.dtype.type
        hits = sums(((masks[:, k // 64] >> kind(k % 64)) & kind(1)).astype(bool) & telling, starts, ends)
        out[:, k] = np.clip((hits / n - filters.false_rate[k]) / max(1e-9, 1 - filters.false_rate[k]), 0, 1)
    return out


def predict(docs: DataFrame, filters: LanguageFilters, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """`keep` columns with lang_pred and score: the best language's share of n-grams, weighed by its lead over the next."""
    sent = docs.sparkSession.sparkContext.broadcast(filters)
    rows = docs.select(*keep, F.col(text).alias("_text"), F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False)).alias("_letters"))
    from pyspark.sql import types as T

    schema = T.StructType([rows.schema[c] for c in keep] + [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def predicted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent.value
        names = np.array([*held.names, UNDETERMINED], object)
        for batch in batches:
            for part in chunks(batch, "_text"):
                lettered = part.column("_letters").to_numpy(zero_copy_only=False)
                got = shares(held, part.column("_text")) if held.names else np.zeros((part.num_rows, 1))
                best = got.argmax(1) if held.names else np.zeros(part.num_rows, int)
                top = got.max(1)
                total = got.sum(1)
                score = np.where(lettered & (total > 0), top * top / np.maximum(total, 1e-12), 0.0)
                label = names[np.where(lettered & bool(held.names), best, len(names) - 1)]
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(label, pa.string()), pa.array(score)], [*keep, "lang_pred", "score"])

    return rows.mapInArrow(predicted, schema)
