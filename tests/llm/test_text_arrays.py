import re

import numpy as np
import pyarrow as pa
from hypothesis import given, settings
from hypothesis import strategies as st

from wingcount.llm.text_arrays import lines, slice_hashes, sums, take_slices, text_bytes, words

TEXTS = st.lists(st.one_of(st.none(), st.text(alphabet="ab é\n\t\x1c字", max_size=12)), max_size=6)


@settings(max_examples=150, deadline=None)
@given(TEXTS)
def test_words_and_lines(texts):
    data, at = text_bytes(pa.array(texts, pa.string()))
    raw = data.tobytes()
    starts, ends, bounds = words(data, at)
    got = [[raw[a:b].decode() for a, b in zip(starts[i:j], ends[i:j])] for i, j in zip(bounds, bounds[1:])]
    assert got == [re.findall(r"[^\x20\x09-\x0D]+", t or "") for t in texts]
    starts, ends, bounds = lines(data, at)
    got = [[raw[a:b].decode() for a, b in zip(starts[i:j], ends[i:j])] for i, j in zip(bounds, bounds[1:])]
    assert got == [(t or "").split("\n") for t in texts]


@settings(max_examples=50, deadline=None)
@given(st.binary(max_size=40))
def test_hashes_depend_on_bytes_alone(raw):
    data = np.frombuffer(b"xyz" + raw + b"--" + raw, np.uint8)
    h = slice_hashes(data, np.array([3, 5 + len(raw)]), np.array([3 + len(raw), 5 + 2 * len(raw)]))
    assert h[0] == h[1]


def test_slices():
    data = np.arange(10)
    got, at = take_slices(data, np.array([4, 0, 7, 2]), np.array([2, 0, 3, 1]))
    assert got.tolist() == [4, 5, 7, 8, 9, 2] and at.tolist() == [0, 2, 2, 5, 6]
    assert sums(data, np.array([0, 3, 3]), np.array([3, 3, 10])).tolist() == [3, 0, 42]
    assert sums(data.astype(float), np.array([0, 3, 3]), np.array([3, 3, 10])).tolist() == [3.0, 0.0, 42.0]
