"""Blocks of words are looked at in slices."""

import tracemalloc

import numpy as np

from kdforest.llm import substring


def test_a_block_of_slices_tells_what_one_slice_tells(monkeypatch):
    rng = np.random.default_rng(3)
    codes = rng.integers(0, 3, 400)
    starts, doc = np.arange(380), np.repeat(np.arange(4), 95)
    whole = substring.later_windows(codes, starts, doc, 5)
    monkeypatch.setattr(substring, "SLICE", 7)
    assert whole.any() and (substring.later_windows(codes, starts, doc, 5) == whole).all()
    words = [tuple(codes[s : s + 5]) for s in starts]
    least = {}
    for w, d in zip(words, doc.tolist(), strict=True):
        least[w] = min(d, least.get(w, d))
    assert [d > least[w] for w, d in zip(words, doc.tolist(), strict=True)] == whole.tolist()


def test_a_block_takes_little_memory_beside_its_words():
    """Windows are looked at in slices, so a block holds few numbers per word at a time."""
    codes = np.random.default_rng(4).integers(0, 1 << 20, 400_000).astype(np.int32)
    starts = np.arange(len(codes) - 12)
    tracemalloc.start()
    substring.digests(codes, starts, 13)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 30 * len(codes)
