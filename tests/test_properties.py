"""Properties that hold for any input."""

from __future__ import annotations

from fractions import Fraction

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from litspark.functions.text import split_sentences, split_tokens
from litspark.functions.vectors import maxsim, unit
from litspark.operators import chunk, parse
from litspark.operators.index import quantise

TEXT = st.text(alphabet="ab .!?\n<p>&;é", max_size=80)


@settings(max_examples=200, deadline=None)
@given(TEXT, st.integers(1, 20))
def test_chunks_partition_the_sentences(text, tenth):
    said = split_sentences(text)
    spans = chunk.cut(said, Fraction(tenth, 20))
    assert [i for a, b, _ in spans for i in range(a, b + 1)] == list(range(len(said)))
    assert sum(n for *_, n in spans) == sum(len(split_tokens(s)) for s in said)
    assert len(chunk.cut(said, Fraction(2))) == len(said)
    assert len(chunk.cut(said, Fraction(-1))) == min(1, len(said))


@settings(max_examples=200, deadline=None)
@given(TEXT)
def test_any_markup_is_read(page):
    found = parse.regions(page)
    assert [r[0] for r in found] == list(range(len(found)))
    assert all(r[1] in parse.KINDS and 0 <= r[4] <= r[5] <= len(page) for r in found)
    parse.end_to_end_text(page)
    parse.scanline_text(page)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.lists(st.floats(-5, 5), min_size=3, max_size=3), min_size=1, max_size=5))
def test_similarities_are_bounded(rows):
    m = np.array(rows)
    u = unit(m)
    assert np.all(np.abs(u @ u.T) <= 1 + 1e-9)
    assert maxsim(m, m) <= len(m) + 1e-9
    codes, scale = quantise(m)
    assert np.all(np.abs(codes * scale[:, None] - m) <= scale[:, None] / 2 + 1e-9)
