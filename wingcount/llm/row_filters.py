"""Filters that look at a whole text in Python and keep or drop its row, whatever other columns the row has."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.llm import decontaminate, language, perplexity
from wingcount.llm.text_arrays import chunks, sums
from wingcount.shared import written


def keep_rows(docs: DataFrame, verdict: Callable[[pa.RecordBatch], np.ndarray], text: str = "text") -> DataFrame:
    """The rows for which `verdict` is true, all columns as they were. A null text is an empty one; equal rows fare alike; no row is made twice; an empty table stays empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, text):
                yield part.filter(pa.array(verdict(part), pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def passing_quality(docs: DataFrame, text: str = "text", lang: str = "lang", below: float = 4.2, above: float = 4.0, floor: float = 0.004) -> DataFrame:
    """Documents that pass the base rules and lie within their language's perplexity band; the rules are those of `perplexity.judged`."""
    spark = docs.sparkSession
    model = perplexity.fit(docs, text)
    plain = docs.select(F.col(lang).alias("lang"), F.col(text).alias("text"))
    band = perplexity.bands(written(perplexity.scored(plain, model, ("lang",), statistics=False), "perplexity"))
    sent = spark.sparkContext.broadcast((model, band))

    def verdict(part: pa.RecordBatch) -> np.ndarray:
        model, band = sent.value
        stats = perplexity.text_statistics(part.column(text))
        good = ~((stats["n_words"] < 10) | (100 * stats["n_repeat_words"] > 20 * stats["n_words"]))
        if not band:
            return good
        codes, starts, ends = perplexity._codes(part.column(text))
        unique, back = np.unique(codes, return_inverse=True)
        n = np.maximum(ends - starts, 1)
        entropy = -sums(model.log_prob(unique).astype(np.float32).astype(np.float64)[back], starts, ends) / n
        centre, noise = np.array([band.get(f"={x}", band[""]) if x is not None else band[""] for x in part.column(lang).to_pylist()]).T
        allowed = np.sqrt(floor * floor + noise * noise / n)
        return good & (entropy >= centre - below * allowed) & (entropy <= centre + above * allowed)

    return keep_rows(docs, verdict, text)


def in_known_language(docs: DataFrame, text: str = "text", lang: str = "lang", least_share: float = 0.4, least_learned: int = 50_000) -> DataFrame:
    """Documents with a letter, `least_share` of whose n-grams one language has. Filters are learned from the rows that name a language, in two halves by the texts' hashes, and each half
    is judged by what the other one holds: no text vouches for itself or its copies. (Held-out clean texts have 0.55 at least, languages that were not learned 0.25 at most.) A row that
    names a language of which the other half has under `least_learned` n-grams stays, as there is nothing to judge it by; so do all rows if no row names a language."""
    half = F.pmod(F.xxhash64(text), F.lit(2))
    named = docs.where(F.col(lang).isNotNull())
    learned = [language.fit_filters(named.where(half == k), text, lang) for k in (1, 0)]  # for texts of half 0 and of half 1
    sent = docs.sparkSession.sparkContext.broadcast(learned)
    known = max((int(x.learned.sum()) for x in learned), default=0)

    def verdict(part: pa.RecordBatch) -> np.ndarray:
        good = np.ones(part.num_rows, bool)
        for k, held in enumerate(sent.value):
            own = np.flatnonzero(part.column("_half").to_numpy() == k)
            if not len(own) or not len(held.names):
                continue
            taught = {x for x, n in zip(held.names, held.learned.tolist(), strict=True) if n >= least_learned}
            at = pa.array(own)
            best = language.shares(held, part.column(text).take(at)).max(1) if taught else np.ones(len(own))
            unjudged = np.array([x is not None and x not in taught for x in part.column(lang).take(at).to_pylist()], bool)
            good[own] = (best >= least_share) | unjudged
        return good

    lettered = docs.where(F.col(text).rlike(r"\p{L}"))
    return keep_rows(lettered.withColumn("_half", half), verdict, text).drop("_half") if known else lettered


def without_leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", n: int = 3, least_score: float = 0.5, least_words: int = 8, **how) -> DataFrame:
    """Documents in which no benchmark item is found; the same search as `decontaminate.leaks`."""
    for items in decontaminate.slices(docs, benchmark, text, n, **how):
        sent = docs.sparkSession.sparkContext.broadcast(items)

        def verdict(part: pa.RecordBatch, sent=sent) -> np.ndarray:
            found = decontaminate.leaks_of(sent.value, part.column(text), n, least_score, least_words, decontaminate.seed_table(sent.value))
            good = np.ones(part.num_rows, bool)
            good[found["doc"]] = False
            return good

        docs = keep_rows(docs, verdict, text)
    return docs
