"""Document quality from a linear-chain conditional random field over lines.

Every line has features of its own (kinds of characters, lengths, repeats) and those of the lines before and after it. The chain labels each line good or bad;
forward-backward marginals, weighed by the lines' lengths, make a document's share of good text, which a logistic step turns into the score.

Training labels are documents' only. A bounded sample of labelled documents (`most_docs` of at most `most_bytes`, those with the lowest hash of their text) is fitted: first lines take
their document's label, then the chain is fitted, lines of bad documents that look like lines of good ones are relabelled, and the chain is fitted again.

Null and empty texts have one empty line and get a score like any other. Documents without a label are scored, not learned from. Without labels of both kinds the
score is 0.5 for all. Rows repeating a doc_id are scored each. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wingcount.llm.text_arrays import chunks, lines, mixed, owners, slice_hashes, sums, text_bytes, words

_GROUPS = {"upper": range(65, 91), "lower": range(97, 123), "digit": range(48, 58), "high": range(128, 192), "stop": b".,;:?'\"-", "sign": b"#$%&*@+=~^<>", "bar": b"|/\\_", "bang": b"!"}


def _table(group) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(group)] = True
    return out


_TABLES = {k: _table(v) for k, v in _GROUPS.items()}


def line_features(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of each line (its own, then the previous and the next line's), the index of each text's first line, and each line's weight."""
    data, at = text_bytes(column)
    starts, ends, bounds = lines(data, at)
    ws, we, _ = words(data, at)
    first, last = np.searchsorted(ws, starts), np.searchsorted(ws, ends)
    n_words = last - first
    size = ends - starts
    per = 1.0 / np.maximum(size, 1)
    own = [sums(_TABLES[k][data], starts, ends) * per for k in _TABLES]
    lengths = we - ws
    h = slice_hashes(data, ws, we, lower=True)
    word_line = np.searchsorted(starts, ws, "right") - 1 if len(starts) else np.zeros(0, np.int64)
    word_text = np.searchsorted(at, ws, "right") - 1
    short = sums(lengths <= 3, first, last) / np.maximum(n_words, 1)
    repeat = np.zeros(len(ws), bool)
    repeat[1:] = (h[1:] == h[:-1]) & (word_text[1:] == word_text[:-1])
    # words of three-word windows that the text has had before
    again = np.zeros(len(ws), bool)
    if len(ws) >= 3:
        window = mixed(mixed(mixed(word_text[:-2].astype(np.uint64) + np.uint64(77)) + h[:-2]) * np.uint64(0x9E3779B97F4A7C15) + h[1:-1]) * np.uint64(0xD6E8FEB86659FD93) + h[2:]
        _, unique = np.unique(window, return_index=True)
        seen = np.ones(len(window), bool)
        seen[unique] = False
        seen &= word_text[:-2] == word_text[2:]
        for k in range(3):
            again[k : len(ws) - 2 + k] |= seen
    per_word = 1.0 / np.maximum(n_words, 1)
    capital = _TABLES["upper"][data[ws]] if len(ws) else np.zeros(0, bool)
    line_key = mixed(slice_hashes(data, starts, ends) + owners(bounds).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    _, unique = np.unique(line_key, return_index=True)
    copy = np.ones(len(starts), bool)
    copy[unique] = False
    own += [
        short,
        sums(repeat, first, last) * per_word,
        sums(again, first, last) * per_word,
        sums(capital, first, last) * per_word,
        np.minimum(sums(lengths.astype(np.int64), first, last) * per_word, 30) / 10,
        np.log1p(n_words) / 5,
        (n_words == 0).astype(float),
        (copy & (n_words > 0)).astype(float),
    ]
    del word_line
    one = np.column_stack(own)
    inner = owners(bounds)
    before, after = np.zeros_like(one), np.zeros_like(one)
    if len(one) > 1:
        same = (inner[1:] == inner[:-1])[:, None]
        before[1:] = one[:-1] * same
        after[:-1] = one[1:] * same
    return np.hstack([one, before, after, np.ones((len(one), 1))]), bounds, size.astype(float) + 1


@dataclass(frozen=True)
class Chain:
    """Standardisation of features, the weight of `good` over `bad` per feature, the 2x2 transition weights, and the document step."""

    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray
    move: np.ndarray
    step: tuple[float, float]


def _passes(score: np.ndarray, bounds: np.ndarray, move: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Marginals of good per line, expected transitions, and log Z per text. score: of good over bad per line. All texts move a line at a time."""
    n = np.diff(bounds)
    order = np.argsort(-n, kind="stable")
    live = np.searchsorted(-n[order], -np.arange(1, (n.max() if len(n) else 0) + 1), "right")  # texts with over t lines
    start = bounds[:-1][order]
    forward, backward = np.zeros((len(score), 2)), np.zeros((len(score), 2))
    for t, m in enumerate(live):
        at = start[:m] + t
        if t:
            before = forward[at - 1]
            forward[at] = np.logaddexp(before[:, :1] + move[0], before[:, 1:] + move[1])
        forward[at, 1] += score[at]
    z = np.zeros(len(n))
    own = np.flatnonzero(n > 0)
    z[own] = np.logaddexp(*forward[bounds[1:][own] - 1].T)
    for t in range(len(live) - 2, -1, -1):
        at = start[: live[t + 1]] + t
        ahead = backward[at + 1] + np.column_stack([np.zeros(len(at)), score[at + 1]])
        backward[at] = np.logaddexp(ahead[:, :1] + move[:, 0], ahead[:, 1:] + move[:, 1])
    of = np.repeat(np.arange(len(n)), n)
    good = np.exp(np.minimum(forward[:, 1] + backward[:, 1] - z[of], 0))
    pairs = np.zeros((2, 2))
    inner = np.flatnonzero(of[1:] == of[:-1]) if len(of) > 1 else np.zeros(0, np.int64)
    for a in (0, 1):
        for b in (0, 1):
            pairs[a, b] = np.exp(forward[inner, a] + move[a, b] + b * score[inner + 1] + backward[inner + 1, b] - z[of[inner]]).sum()
    return good, pairs, z


def _fitted(x: np.ndarray, bounds: np.ndarray, y: np.ndarray, rounds: int, ridge: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Maximum conditional likelihood of the line labels y by gradient steps with running moments."""
    theta = np.zeros(x.shape[1] + 4)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    of = owners(bounds)
    inner = np.flatnonzero(of[1:] == of[:-1])
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[inner], y[inner + 1]), 1)
    wanted = np.concatenate([x.T @ y, seen.ravel()])
    for k in range(1, rounds + 1):
        good, pairs, _ = _passes(x @ theta[:-4], bounds, theta[-4:].reshape(2, 2))
        slope = (wanted - np.concatenate([x.T @ good, pairs.ravel()])) / max(1, len(y)) - ridge * theta
        m, v = 0.9 * m + 0.1 * slope, 0.99 * v + 0.01 * slope * slope
        theta = theta + 0.1 * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-8)
    return theta[:-4], theta[-4:].reshape(2, 2)


def fit_chain(texts: list[str | None], labels: list[int], rounds: int = 120) -> Chain | None:
    label = np.array(labels)
    if len(set(labels)) < 2:
        return None
    x, bounds, weight = line_features(pa.array(texts, pa.string()))
    mean, scale = x.mean(0), x.std(0)
    scale[scale < 1e-6] = 1
    mean[-1], scale[-1] = 0, 1
    x = (x - mean) / scale
    of = owners(bounds)
    y = label[of]
    # documents count alike by kind, so that the rarer label isn't drowned
    w, move = _fitted(x, bounds, y, rounds)
    for _ in range(2):
        good, _, _ = _passes(x @ w, bounds, move)
        usual = np.quantile(good[y == 1], 0.05) if (label[of] == 1).any() else 0.5
        y = np.where(label[of] == 1, 1, (good >= max(0.5, usual)).astype(int))
        w, move = _fitted(x, bounds, y, rounds)
    good, _, _ = _passes(x @ w, bounds, move)
    share = _shares(good, bounds, weight)
    a, b = 4.0, 0.0
    odds = _spread(share)
    for _ in range(200):  # Newton steps of a logistic regression on one number
        p = 1 / (1 + np.exp(-(a * odds + b)))
        slope = np.array([((label - p) * odds).sum() - 0.01 * a, (label - p).sum()])
        q = p * (1 - p) + 1e-9
        curve = np.array([[(q * odds * odds).sum() + 0.01, (q * odds).sum()], [(q * odds).sum(), q.sum() + 1e-6]])
        move_ = np.linalg.solve(curve, slope)
        a, b = a + np.clip(move_[0], -1, 1), b + np.clip(move_[1], -1, 1)
    return Chain(mean, scale, w, move, (float(a), float(b)))


def _shares(good: np.ndarray, bounds: np.ndarray, weight: np.ndarray) -> np.ndarray:
    return sums(good * weight, bounds[:-1], bounds[1:]) / np.maximum(sums(weight, bounds[:-1], bounds[1:]), 1e-9)


def _spread(share: np.ndarray) -> np.ndarray:
    s = np.clip(share, 0.005, 0.995)
    return np.log(s / (1 - s)) / 4


def document_scores(chain: Chain, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Score of each text, and per line its probability of being good, with each text's first line."""
    x, bounds, weight = line_features(column)
    good, _, _ = _passes(((x - chain.mean) / chain.scale) @ chain.weight, bounds, chain.move)
    return 1 / (1 + np.exp(-(chain.step[0] * _spread(_shares(good, bounds, weight)) + chain.step[1]))), good, bounds


def fit(docs: DataFrame, labels: DataFrame, train: Column, text: str = "text", most_docs: int = 1600, most_bytes: int = 1 << 16) -> Chain | None:
    """Fits the chain on at most `most_docs` labelled training documents of at most `most_bytes` each, half of them of either label where there are as many. Of equal texts
    with one label the row of the smallest doc_id stands for all, so that a large group of copies is one text of the sample."""
    known = labels.where(F.col("quality").isin(0, 1)).groupBy("doc_id").agg(F.max("quality").alias("quality"))
    own = docs.where(train & (F.coalesce(F.octet_length(text), F.lit(0)) <= most_bytes)).select("doc_id", F.col(text).alias("_text"), F.xxhash64(text).alias("_h"))
    # ids and hashes alone are joined and ordered; texts are read for the chosen ones
    hashed = own.select("doc_id", "_h").join(known, "doc_id").groupBy("_h", "quality").agg(F.min("doc_id").alias("doc_id"))
    chosen = [r for value in (0, 1) for r in hashed.where(F.col("quality") == value).orderBy("_h", "doc_id").limit(most_docs // 2).collect()]
    if not chosen:
        return None
    picks = docs.sparkSession.createDataFrame(chosen, hashed.schema)  # most_docs rows at most
    rows = own.join(F.broadcast(picks), ["doc_id", "_h"]).select("_h", "doc_id", "_text", "quality").distinct().collect()
    rows.sort(key=lambda r: (r["quality"], r["_h"], r["doc_id"]))
    return fit_chain([r["_text"] for r in rows], [r["quality"] for r in rows])


def score(docs: DataFrame, chain: Chain | None, text: str = "text", keep: tuple[str, ...] = ("doc_id",), lines_too: bool = False) -> DataFrame:
    """`keep` columns and score; with `lines_too` also line_scores, the probability of each line of being good."""
    sent = docs.sparkSession.sparkContext.broadcast(chain)
    rows = docs.select(*keep, F.col(text).alias("_text"))
    more = [T.StructField("line_scores", T.ArrayType(T.DoubleType()))] if lines_too else []
    schema = T.StructType([rows.schema[c] for c in keep] + [T.StructField("score", T.DoubleType()), *more])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent.value
        for batch in batches:
            for part in chunks(batch, "_text"):
                if held is None:
                    n = np.diff(lines(*text_bytes(part.column("_text")))[2])
                    got, good, bounds = np.full(part.num_rows, 0.5), np.full(n.sum(), 0.5), np.concatenate([[0], np.cumsum(n)])
                else:
                    got, good, bounds = document_scores(held, part.column("_text"))
                columns = [*(part.column(c) for c in keep), pa.array(got)]
                if lines_too:
                    columns.append(pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(good)))
                yield pa.RecordBatch.from_arrays(columns, schema.fieldNames())

    return rows.mapInArrow(run, schema)
