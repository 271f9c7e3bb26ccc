"""Byte-pair merges of many simple words at once.

A simple word is a run of ASCII and precomposed Latin-1 letters (lower-case ones where the tokenizer lower-cases, after one space where the tokenizer keeps it with the
word): normalization and pre-tokenization leave it as one piece, in which bytes stand as characters. In every round each word's lowest-ranked pair of neighbours is merged wherever it stands in the word, left to right, until
no word has a pair in the table. A merge's result is first used by later merges, so this gives what merging one pair at a time gives. The tests hold it against the library.
"""

from __future__ import annotations

import json

import numpy as np

_NONE = np.int32((1 << 31) - 1)
_FACTORS = [0x9E3779B97F4A7C15 + 2 * 0x51ED270B * k for k in range(400)]


def _cell(key: np.ndarray, factor: int, bits: int) -> np.ndarray:
    return ((key * np.uint64(factor)) >> np.uint64(64 - bits)).view(np.int64)


def byte_characters() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: printable ones for themselves, the others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = {b: chr(256 + k) for k, b in enumerate(sorted(set(range(256)) - set(plain)))}
    return [other.get(b, chr(b)) for b in range(256)]


class Merges:
    """The table of a tokenizer file's byte-pair model; `usable` is False for models with options that change how merges run, or that lack a byte."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, pairs = model["vocab"], [tuple(x.split(" ")) if isinstance(x, str) else tuple(x) for x in model["merges"]]
        characters, suffix = byte_characters(), model.get("end_of_word_suffix") or ""
        self.usable = not (model.get("ignore_merges") or model.get("dropout") or model.get("continuing_subword_prefix"))
        self.usable = self.usable and all(c in vocab and c + suffix in vocab for c in characters)
        if not self.usable:
            return
        self.first, self.last = (np.array([vocab[c + end] for c in characters], np.int32) for end in ("", suffix))
        left, right, self.made = (np.array([vocab[x] for x in own], np.int64) for own in ([a for a, _ in pairs], [b for _, b in pairs], [a + b for a, b in pairs]))
        self.made = self.made.astype(np.int32)
        self.keys = (left << 32 | right).view(np.uint64)
        ranks = np.arange(len(pairs), dtype=np.int32)
        # two tables: the second one, without clashes, has the pairs that clash in the first
        self.one = np.full(1 << 20, -1, np.int32)
        at = _cell(self.keys, _FACTORS[0], 20)
        self.one[at[::-1]] = ranks[::-1]
        rest = ranks[self.one[at] != ranks]
        self.factor = next(f for f in _FACTORS[1:] if len(np.unique(_cell(self.keys[rest], f, 18))) == len(rest))
        self.two = np.full(1 << 18, -1, np.int32)
        self.two[_cell(self.keys[rest], self.factor, 18)] = rest

    def ranks(self, key: np.ndarray) -> np.ndarray:
        out = np.full(len(key), _NONE, np.int32)
        for table, factor, bits in ((self.one, _FACTORS[0], 20), (self.two, self.factor, 18)):
            rank = table[_cell(key, factor, bits)]
            hit = self.keys[rank] == key
            hit &= rank >= 0
            out[hit] = rank[hit]
        return out

    def encode(self, data: np.ndarray, at: np.ndarray, most: int = 16_384) -> tuple[np.ndarray, np.ndarray]:
        """All ids of simple words one after another, and where those of each word begin. Words are the bytes between the places `at`, none is empty."""
        done = [self._some(data[at[k] : at[min(k + most, len(at) - 1)]], at[k : k + most + 1] - at[k]) for k in range(0, len(at) - 1, most)]
        counts = np.concatenate([np.zeros(0, np.int64), *(c for _, c in done)])
        return np.concatenate([np.zeros(0, np.int64), *(x for x, _ in done)]), np.concatenate([[0], np.cumsum(counts)])

    def _some(self, data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(at) - 1
        s = self.first[data]
        s[at[1:] - 1] = self.last[data[at[1:] - 1]]
        word, begin = np.arange(n), at.astype(np.int64)
        rank = np.full(len(s), _NONE, np.int32)
        rank[:-1] = self.ranks((s[:-1].astype(np.int64) << 32 | s[1:]).view(np.uint64))
        rank[begin[1:] - 1] = _NONE
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(word):
            least = np.minimum.reduceat(rank, begin[:-1])
            size = np.diff(begin)
            busy = least < _NONE
            if not busy.all():
                mine = np.repeat(busy, size)
                done.append((word[~busy], size[~busy], s[~mine]))
                s, rank, word, size, least = s[mine], rank[mine], word[busy], size[busy], least[busy]
                begin = np.concatenate([[0], np.cumsum(size)])
                if not len(word):
                    break
            hit = np.flatnonzero(rank == np.repeat(least, size))
            if (again := hit[1:] == hit[:-1] + 1).any():  # a pair of equal symbols that overlaps itself: every second one from the left
                run = np.flatnonzero(np.concatenate([[True], ~again]))
                odd = (np.arange(len(hit)) - np.repeat(run, np.diff(np.append(run, len(hit))))) & 1
                hit = hit[odd == 0]
            s[hit] = self.made[rank[hit]]
            keep = np.ones(len(s), bool)
            keep[hit + 1] = False
            ends = np.zeros(len(s), bool)
            ends[begin[1:] - 1] = True
            ends[hit] = ends[hit + 1]
            place = np.cumsum(keep)
            new, begin = place[hit] - 1, np.concatenate([[0], place[begin[1:] - 1]])
            s, rank, ends = s[keep], rank[keep], ends[keep]
            new = np.concatenate([new, new[new > 0] - 1])
            rank[new] = _NONE
            new = new[~ends[new]]
            rank[new] = self.ranks((s[new].astype(np.int64) << 32 | s[new + 1]).view(np.uint64))
        count = np.zeros(n, np.int64)
        for own, size, _ in done:
            count[own] = size
        start = np.cumsum(count) - count
        out = np.empty(count.sum(), np.int64)
        for own, size, ids in done:
            out[np.arange(len(ids)) + np.repeat(start[own] - (np.cumsum(size) - size), size)] = ids
        return out, count
