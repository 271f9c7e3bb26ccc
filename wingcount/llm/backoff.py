"""Language-model scoring with a weighted backoff automaton over words.

States are contexts: the empty one, a word, or two words. An arc reads a word and has a log-probability; where a state has no arc for the word, its failure arc
leads to the state without its first word, at the cost of the state's backoff weight. What state follows depends only on the last words read, so one pass over a text
from left to right needs no more than its current state. `Automaton.walk` reads so, token by token; `score` makes the same moves for all texts of a block at once.

Smoothing is absolute discounting: n-grams of two and three words that training texts have twice or more become arcs, with (n - cut) / (count of the context)
and what the failure arc would give besides; the weight of a failure arc is what the arcs of its state leave. Each order's cut follows from how many n-grams occur once
and twice. Counts cover all training texts, and no arc is left out at any size of the corpus.

No table of words or n-grams is sent to each task or to the driver. A block of documents asks for what it holds: its distinct words, then pairs of words that occur twice,
then triples whose both pairs occur twice, each with its count in the block's training texts, cut into ranges of hashes. A task adds up one range over all blocks
and answers each block in the order of its questions (`_answered`); so a block's memory is its own, and a hot word is one question a block like any other.
Words are counted under a 128-bit BLAKE2 digest. N-grams are known by 64 bits: of 1e9, some 0.03 pairs clash.

Null texts count as empty: one end token. Repeated rows count each. doc_id may be null. Without training texts all words are unknown. Extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wingcount.llm.blocks import block_table, digests, in_order, opened, shut, unpacked
from wingcount.llm.text_arrays import LOWER, mixed, sums, text_bytes, words
from wingcount.shared import bucketed

LEAST = 2
BLOCK_BYTES = 8 << 20
PART_TOKENS = 4_000_000
END, BEGIN = "\n", "\t"


def lowered_words(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    data, at = text_bytes(column)
    return LOWER[data], *words(data, at)


def cut_of(once: float, twice: float) -> float:
    """What is taken from each count, by how many n-grams occur once and twice."""
    return once / (once + 2 * twice) if once > 0 and twice else 0.5


def word_probability(c, cut: float, total: int, known: int):
    """The empty state's arcs: unknown words share what the cut leaves of `known` words."""
    free = cut * known if total else 1.0
    return np.where(np.asarray(c) > 0, np.maximum(c - cut, 1e-12), max(free, 1e-12)) / max(total, 1)


@dataclass(frozen=True)
class Automaton:
    """Arcs and failure weights of one small corpus as dictionaries: `counts` of words, `arcs` of (context, word) with log10 probabilities, `fails` by context."""

    counts: dict
    word: Callable
    arcs: dict
    fails: dict

    @classmethod
    def of(cls, texts: list[list[str]], order: int = 3) -> Automaton:
        """From the training texts' words. For tests and texts that fit the driver."""
        read = [[BEGIN, *x, END] for x in texts]
        grams = {k: Counter(tuple(x[i : i + k]) for x in read for i in range(len(x) - k + 1)) for k in range(1, order + 1)}
        counts = Counter({w[0]: n for w, n in grams[1].items() if w[0] != BEGIN})
        few = Counter(counts.values())
        total, of_words = sum(counts.values()), cut_of(few[1] - (len(texts) == 1), few[2] - (len(texts) == 2))  # the end is no word
        word = lambda w: float(word_probability(counts[w], of_words, total, len(counts)))
        below, arcs, fails = word, {}, {}
        for k in range(2, order + 1):
            few = Counter(grams[k].values())
            cut, kept = cut_of(few[1], few[2]), {g: n for g, n in grams[k].items() if n >= LEAST}
            left = Counter({g[:-1]: 0 for g in kept})
            for g, n in kept.items():
                left[g[:-1]] += n - cut
            own = {h: 1 - x / grams[k - 1][h] for h, x in left.items()}
            shorter, state = (lambda g, b=below: b(g[-1])) if k == 2 else (lambda g, b=below: b(g[1:])), dict(own)
            arc = {g: (n - cut) / grams[k - 1][g[:-1]] + state[g[:-1]] * shorter(g) for g, n in kept.items()}
            below = lambda g, a=arc, s=state, b=shorter: a[g] if g in a else s.get(g[:-1], 1.0) * b(g)
            arcs |= {g: np.log10(p) for g, p in arc.items()}
            fails |= {h: np.log10(max(x, 1e-300)) for h, x in own.items()}
        return cls(counts, word, arcs, fails)

    def step(self, state: list[str], w: str, order: int = 3) -> float:
        """log10 probability of the next word, over failure arcs down to a state that has an arc for it."""
        total, at = 0.0, tuple(state[-(order - 1) :]) if order > 1 else ()
        while at and (*at, w) not in self.arcs:
            total += self.fails.get(at, 0.0)
            at = at[1:]
        return total + float(self.arcs[(*at, w)] if at else np.log10(self.word(w)))

    def walk(self, text: list[str], order: int = 3) -> float:
        """log10 probability of a text's words and its end, in one pass whose state is at most the last `order` - 1 words."""
        total, state = 0.0, [BEGIN]
        for w in [*text, END]:
            total += self.step(state, w, order)
            state = [*state, w][-(order - 1) :]
        return total


@dataclass(frozen=True)
class Question:
    """Distinct keys in ascending order (with a second word of 64 bits in `more`, where 64 don't do), and numbers for each key that are to be added up over all blocks."""

    keys: np.ndarray
    values: tuple[np.ndarray, ...]
    more: np.ndarray | None = None


def _answered(blocks: DataFrame, name: str, parts: int, asked: Callable[[dict], list[Question]], least: tuple[int, ...]) -> DataFrame:
    """(block, got, facts). `asked` gives a block's questions; `got` has, by question and part of the keys, the answers in the order of the keys: where the question's
    `least` is 0 all sums, else twice the first sum plus whether this block is the first one to ask for the key, or 0 for sums under `least`. `facts` adds up over
    blocks to, for questions with a `least`: how many keys have a sum, how many one of 1, how many one of 2, and the sums of `least` or more."""
    bounds = np.array([(((p << 32) + parts - 1) // parts) << 32 for p in range(1, parts)], np.uint64)
    fields = [("block", pa.int64()), ("kind", pa.int32()), ("part", pa.int64()), ("keys", pa.binary()), ("more", pa.binary()), ("sums", pa.list_(pa.binary()))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                for kind, q in enumerate(asked(row)):
                    edges = [0, *np.searchsorted(q.keys, bounds).tolist(), len(q.keys)]
                    out: dict[str, list] = {c: [] for c, _ in fields}
                    for part, (a, b) in enumerate(zip(edges, edges[1:])):
                        if a < b:
                            gaps = np.diff(q.keys[a:b], prepend=np.uint64(0))
                            one = (row["block"], kind, part, shut(gaps), None if q.more is None else q.more[a:b].tobytes(), [shut(x[a:b]) for x in q.values])
                            for (c, _), v in zip(fields, one, strict=True):
                                out[c].append(v)
                    yield pa.RecordBatch.from_arrays([pa.array(out[c], t) for c, t in fields], [c for c, _ in fields])
                    pa.default_memory_pool().release_unused()

    def summed(table: pa.Table) -> pa.Table:
        table = table.sort_by("block")
        pieces = [np.cumsum(opened(x), dtype=np.uint64) for x in table.column("keys").to_pylist()]
        keys, at = np.concatenate(pieces), np.cumsum([0, *map(len, pieces)])
        by = in_order(keys)
        new = np.concatenate([[True], keys[by[1:]] != keys[by[:-1]]])
        if not table.column("more").null_count:
            more = np.frombuffer(b"".join(table.column("more").to_pylist()), np.uint64)
            differ = more[by[1:]] != more[by[:-1]]
            if (differ & ~new[1:]).any():  # half a digest is not enough
                by = np.lexsort((more, keys))
                new, differ = np.concatenate([[True], keys[by[1:]] != keys[by[:-1]]]), more[by[1:]] != more[by[:-1]]
            new[1:] |= differ
        group = np.empty(len(keys), np.int64)
        group[by] = np.cumsum(new) - 1
        values = [np.concatenate([opened(x) for x in own]) for own in zip(*table.column("sums").to_pylist(), strict=True)]
        totals = [np.bincount(group, x).astype(np.uint64) for x in values]
        facts, answers = [0, 0, 0, 0], [x[group] for x in totals]
        if low := least[table.column("kind")[0].as_py()]:
            n, first = totals[0], np.zeros(len(keys), np.uint64)
            first[by[new]] = 1
            facts = [int(np.count_nonzero(n)), int(np.count_nonzero(n == 1)), int(np.count_nonzero(n == 2)), int(n[n >= low].sum())]
            answers = [np.where(n[group] >= low, 2 * n[group] + first, 0)]
        got = [[shut(x[a:b]) for x in answers] for a, b in zip(at, at[1:])]
        told = [facts if k == 0 else [0, 0, 0, 0] for k in range(len(got))]
        return table.select(["block", "kind", "part"]).append_column("got", pa.array(got, pa.list_(pa.binary()))).append_column("facts", pa.array(told, pa.list_(pa.int64())))

    rows = blocks.mapInArrow(run, "block long, kind int, part long, keys binary, more binary, sums array<binary>")
    answers = rows.groupBy("kind", "part").applyInArrow(summed, "block long, kind int, part long, got array<binary>, facts array<long>")
    facts = F.array(*(F.sum(F.col("facts")[k]) for k in range(4)))
    return bucketed(answers.groupBy("block").agg(F.sort_array(F.collect_list(F.struct("kind", "part", "got"))).alias(name), facts.alias("facts")), name, "block")


def _facts(answers: DataFrame) -> list[int]:
    row = answers.agg(*(F.sum(F.col("facts")[k]) for k in range(4))).first()
    return [int(x or 0) for x in row]


def _got(pieces: list[dict] | None, kind: int, k: int = 0) -> np.ndarray:
    """One question's answers for all its keys."""
    own = [opened(p["got"][k]) for p in pieces or [] if p["kind"] == kind]
    return np.concatenate(own) if own else np.zeros(0, np.uint64)


def _asked_words(row: dict) -> list[Question]:
    return [Question(np.cumsum(opened(row["high"]), dtype=np.uint64), (opened(row["ns"]),), np.frombuffer(row["low"], np.uint64))]


class Grams:
    """Distinct n-grams of a block in the order of their hashes: `keys`, for each of `at` (the places that have one) its number, and the first of these places for each."""

    def __init__(self, hashes: np.ndarray, at: np.ndarray):
        by = in_order(hashes)
        sorted_ = hashes[by]
        new = np.concatenate([[True], sorted_[1:] != sorted_[:-1]]) if len(by) else np.zeros(0, bool)
        self.at, self.keys, self.first = at, sorted_[new], at[by[new]]
        self.number = np.empty(len(by), np.int64)
        self.number[by] = np.cumsum(new) - 1

    def question(self, trained: np.ndarray) -> Question:
        return Question(self.keys, (np.bincount(self.number[trained[self.at]], minlength=len(self.keys)).astype(np.uint64),))


class Block:
    """A block's tokens with an end after each text. Words have the numbers of the block's dictionary, then come the end and the beginning."""

    def __init__(self, row: dict, texts: int):
        place, told = opened(row["ks"]).view(np.int64), _got(row["counted"], 0)
        n_words = len(place)
        self.c, self.hash = np.full(n_words + 2, texts, np.int64), np.empty(n_words + 2, np.uint64)
        self.c[place] = told >> np.uint64(1)
        self.hash[place] = np.cumsum(opened(row["high"]), dtype=np.uint64)
        self.hash[n_words:] = digests([END.encode(), BEGIN.encode()])[0]  # white space, so no word's
        counts, codes = np.frombuffer(row["counts"], "<i8"), unpacked(row["codes"])
        self.bounds = np.concatenate([[0], np.cumsum(counts + 1)])
        self.token = np.full(self.bounds[-1], n_words, np.int32)
        self.token[np.arange(len(codes)) + np.repeat(np.arange(len(counts)), counts)] = codes
        self.before = np.empty_like(self.token)
        self.before[1:] = self.token[:-1]
        self.before[self.bounds[:-1]] = n_words + 1
        self.trained = np.repeat(np.frombuffer(row["flags"], np.uint8).astype(bool), counts + 1)
        self.often = self.c >= LEAST

    def pairs(self) -> Grams:
        at = np.flatnonzero(self.often[self.before] & self.often[self.token])
        h = mixed(self.hash[self.before[at]])
        h += self.hash[self.token[at]]
        return Grams(mixed(h), at)

    def kept(self, pairs: Grams, told: np.ndarray) -> np.ndarray:
        """The number of the pair that ends at each place, -1 where it isn't frequent."""
        out = np.full(len(self.token), -1, np.int64)
        out[pairs.at] = np.where((told > 0)[pairs.number], pairs.number, -1)
        return out

    def triples(self, pairs: Grams, kept: np.ndarray) -> Grams:
        both = (kept >= 0) & (np.roll(kept, 1) >= 0)
        both[self.bounds[:-1]] = False
        at = np.flatnonzero(both)
        h = mixed(pairs.keys[kept[at - 1]] ^ np.uint64(0x51ED270B))
        h += self.hash[self.token[at]]
        return Grams(mixed(h), at)

    def contexts(self) -> np.ndarray:
        """Words (and the beginning) that may have arcs, in the order of their hashes."""
        own = np.flatnonzero(self.often)
        own = own[own != len(self.c) - 2]
        return own[np.argsort(self.hash[own])]


def _sums(of: np.ndarray, told: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """By context number: the sum and the number of the frequent n-grams that this block speaks for."""
    own = np.flatnonzero(told & np.uint64(1))
    return np.bincount(of[own], (told[own] >> np.uint64(1)).astype(float), n).astype(np.uint64), np.bincount(of[own], minlength=n).astype(np.uint64)


def _left(sums_: np.ndarray, arcs: np.ndarray, cut: float, of: np.ndarray) -> np.ndarray:
    """Weights of failure arcs: what the arcs leave."""
    return np.maximum(1 - (sums_.astype(float) - cut * arcs.astype(float)) / np.maximum(of, 1), 1e-300)


def score(docs: DataFrame, train: Column, text: str = "text") -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score and score (log10) of every document; learns from those where `train` holds."""
    blocks = block_table(docs, lowered_words, text, flag=train, size_of_block=BLOCK_BYTES, keyed=True)
    seen = blocks.agg(F.sum("n").alias("n"), F.sum(F.length(F.translate(F.hex("flags"), "0", ""))).alias("texts")).first()
    texts = int(seen["texts"] or 0)
    total = int(seen["n"] or 0) + texts
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-total // PART_TOKENS))

    counted = _answered(blocks.select("block", "high", "low", "ns"), "counted", parts, _asked_words, (1,))
    distinct, once, twice, _ = _facts(counted)
    known = distinct + (texts > 0)
    cut = cut_of(once, twice)
    blocks = blocks.select("block", "ids", "flags", "counts", "codes", "high", "ks").join(counted.drop("facts").hint("merge"), "block", "left")

    paired = _answered(blocks, "paired", parts, lambda row: [(b := Block(row, texts)).pairs().question(b.trained)], (LEAST,))
    _, _, twice, often = _facts(paired)
    pair_cut = cut_of(total - often, twice)  # every token ends a pair; those that are not frequent occur once
    blocks = blocks.join(paired.drop("facts").hint("merge"), "block", "left")

    def triples(row: dict) -> list[Question]:
        b, told = Block(row, texts), _got(row["paired"], 0)
        pairs = b.pairs()
        own = b.contexts()
        of = np.zeros(len(b.c), np.int64)
        of[own] = np.arange(len(own))
        return [b.triples(pairs, b.kept(pairs, told)).question(b.trained), Question(b.hash[own], _sums(of[b.before[pairs.first]], told, len(own)))]

    tripled = _answered(blocks, "tripled", parts, triples, (LEAST, 0))
    _, _, twice, often = _facts(tripled)
    triple_cut = cut_of(total - texts - often, twice)  # every token but a text's first ends a triple
    blocks = blocks.join(tripled.drop("facts").hint("merge"), "block", "left")

    def states(row: dict) -> list[Question]:
        b, told = Block(row, texts), _got(row["paired"], 0)
        pairs = b.pairs()
        kept = b.kept(pairs, told)
        found = b.triples(pairs, kept)
        sums_ = _sums(kept[found.first - 1], _got(row["tripled"], 0), len(pairs.keys))
        own = np.flatnonzero(told)
        return [Question(pairs.keys[own], tuple(x[own] for x in sums_))]

    left = _answered(blocks, "states", parts, states, (0,))

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                yield answer(batch.slice(k, 1).to_pylist()[0])
                pa.default_memory_pool().release_unused()

    def answer(row: dict) -> pa.RecordBatch:
        b, told = Block(row, texts), _got(row["paired"], 0)
        own = b.contexts()
        fail = np.ones(len(b.c))
        fail[own] = _left(_got(row["tripled"], 1, 0), _got(row["tripled"], 1, 1), pair_cut, b.c[own])
        one = word_probability(b.c, cut, total, known)
        p = fail[b.before] * one[b.token]
        pairs = b.pairs()
        n = (told >> np.uint64(1)).astype(float)
        kept = b.kept(pairs, told)
        at = np.flatnonzero(kept >= 0)
        p[at] += (n[kept[at]] - pair_cut) / b.c[b.before[at]]
        found, often = b.triples(pairs, kept), (_got(row["tripled"], 0) >> np.uint64(1)).astype(float)
        weight = np.ones(len(pairs.keys))
        weight[told > 0] = _left(_got(row["states"], 0, 0), _got(row["states"], 0, 1), triple_cut, n[told > 0])
        in_state = np.roll(kept, 1) >= 0
        in_state[b.bounds[:-1]] = False
        at = np.flatnonzero(in_state)
        p[at] *= weight[kept[at - 1]]
        hit = often[found.number] > 0
        at, m = found.at[hit], often[found.number[hit]]
        p[at] += (m - triple_cut) / n[kept[at - 1]]
        starts, stops = b.bounds[:-1], b.bounds[1:]
        size = stops - starts
        base = sums(np.log10(b.c + 1.0)[b.token], starts, stops) - size * np.log10(float(total + known + 1))
        known_ = sums((b.c > 0)[b.token], starts, stops)
        columns = [pa.array(row["ids"], pa.int64()), pa.array(size), pa.array(known_), pa.array(np.full(len(size), total)), pa.array(base), pa.array(sums(np.log10(p), starts, stops))]
        return pa.RecordBatch.from_arrays(columns, ["doc_id", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return blocks.join(left.drop("facts").hint("merge"), "block", "left").mapInArrow(scored, "doc_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double")
