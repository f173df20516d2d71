"""Words of a block numbered at once, and the rarest places of its windows."""

import random

import numpy as np
import pyarrow as pa
import pytest

from kdforest.llm import substring


@pytest.mark.parametrize("known", [[], [b"the", b"of", b"\xff\x00"]])
def test_numbers_are_those_of_a_word_by_word_coder(known):
    rng = random.Random(2)
    words = [rng.choice([b"the", b"of", b"\xff\x00", b"a", b"\xc3\xa4", b"w%d" % rng.randrange(40)]) for _ in range(500)]
    coder = substring.Coder(known)
    want = [coder[w] for w in words]
    for n in (500, 0):
        got, more = substring.numbered(pa.array(words[:n], pa.large_binary()), pa.array(known, pa.large_binary()))
        assert got.tolist() == want[:n] and more.to_pylist() == (coder.more if n else [])


@pytest.mark.parametrize("width", [1, 2, 3, 7, 11, 300])
def test_rarest_place_is_the_first_of_the_least(monkeypatch, width):
    monkeypatch.setattr(substring, "SLICE", 16)
    rng = random.Random(width)
    key = np.array([rng.randrange(6) for _ in range(700)], dtype=np.uint64) << np.uint64(60)
    at = np.array(sorted(rng.sample(range(700 - width + 1), 90)))
    assert substring.rarest(key, at, width).tolist() == [i + int(np.argmin(key[i : i + width])) for i in at.tolist()]
