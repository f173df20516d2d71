"""The near-dedup stage takes fingerprints' links: without any band of minimum hashes near copies are found by them."""

import random

import numpy as np

from kdforest.llm import simhash


def test_fingerprints_link_candidates(spark, monkeypatch):
    rng = random.Random(12)
    words = [f"w{rng.randrange(9000)}" for _ in range(2500)]
    near = [*words[:1200], "other", *words[1201:]]
    far = [f"v{rng.randrange(9000)}" for _ in range(2500)]
    rows = [(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(far)), (4, "short text"), (5, "")]
    assert (simhash.fingerprint(rows[0][1]) ^ simhash.fingerprint(rows[1][1])).bit_count() <= 4
    monkeypatch.setattr(simhash, "band_keys", lambda s: np.array([hash(s.tobytes()) & 0xFFFF], dtype=np.uint64) + (np.arange(1, dtype=np.uint64)))
    kept = {r.doc_id for r in simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert kept == {1, 3, 4, 5}
