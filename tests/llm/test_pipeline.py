"""Each stage of the pipeline against a plain computation on the stage's own input; the fusion of language evidence."""

import math
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from kdforest.llm import langid

from .conftest import SF
from .test_text_operators import windows_removed


@pytest.fixture(scope="module")
def stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for _, stage in corpus_pipeline.STAGES:
        out.append(corpus_pipeline.written(stage(spark, out[-1], SF), "stage"))
    return out


def test_columns_stay(stages):
    assert all(s.columns == stages[0].columns for s in stages[:-1])


def test_language_stage(spark, stages):
    """The posterior by hand: tempered likelihoods, priors of sources smoothed towards all rows, declared languages."""
    model = langid.trained(stages[0])
    n = len(model.languages)
    rows = [(r.doc_id, r.source or "", (r.lang or "").lower(), *model.of(r.text)) for r in stages[0].collect() if r.text]
    counts, world = defaultdict(lambda: np.zeros(n + 1)), np.zeros(n + 1)
    for _, source, _, ll, grams in rows:
        if grams:
            counts[source][int(np.argmax(ll))] += 1
            world[int(np.argmax(ll))] += 1
    world = (world + 1) / (world + 1).sum()
    everywhere = sum(counts.values())
    suffix = (everywhere + langid.SMOOTHING * world) / (everywhere.sum() + langid.SMOOTHING)
    kept = set()
    for d, source, lang, ll, grams in rows:
        prior = np.log((counts[source] + langid.SMOOTHING * suffix) / (counts[source].sum() + langid.SMOOTHING)) if source in counts else np.full(n + 1, -math.log(n + 1))
        said = np.zeros(n + 1)
        if lang in model.languages:
            said[:] = math.log((1 - langid.DECLARED_RIGHT) / max(1, n - 1))
            said[model.languages.index(lang)] = math.log(langid.DECLARED_RIGHT)
            said[n] = -math.log(n)
        if grams and int(np.argmax(np.array(ll) + prior + said)) < n:
            kept.add(d)
    assert {r.doc_id for r in stages[1].select("doc_id").collect()} == kept


def test_near_dedup_stage(stages):
    rows = [(r.doc_id, r.text) for r in stages[1].collect()]
    sets = {}
    for d, t in rows:
        w = re.sub("[A-Z]", lambda m: m[0].lower(), t or "").encode().split()
        sets[d] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if 9 * len(sets[a] & sets[b]) >= 4 * (len(sets[a]) + len(sets[b])):
                low, high = sorted((find(a), find(b)))
                root[high] = low
    assert {r.doc_id for r in stages[2].select("doc_id").collect()} == {d for d in ids if find(d) == d}


def test_substring_stage(stages):
    before = {r.doc_id: r.text for r in stages[2].collect()}
    import hashlib

    want = {d: (gone, digest) for d, _, gone, digest in windows_removed(list(before.items()))}
    for r in stages[3].collect():
        gone, digest = want[r.doc_id]
        assert (hashlib.sha256(r.text.encode()).hexdigest() == digest) if gone else r.text == before[r.doc_id]
        assert r.n_chars == len(r.text)
    assert stages[3].count() == len(before)


def test_decontamination_stage(spark, stages):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    wins = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = split(r.text)
        wins |= {tuple(w[i : i + 13]) for i in range(max(1, len(w) - 12) if w else 0)}
    kept = set()
    for r in stages[3].collect():
        w, hit = split(r.text), set()
        for k in {len(x) for x in wins}:
            for i in range(len(w) - k + 1):
                if tuple(w[i : i + k]) in wins:
                    hit |= set(range(i, i + k))
        if not hit or 20 * len(hit) < len(w):
            kept.add(r.doc_id)
    assert {r.doc_id for r in stages[4].select("doc_id").collect()} == kept


def test_packing_stage(stages):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path(corpus_pipeline.TOKENIZER))
    want = {r.doc_id: len(tok.encode(r.text, add_special_tokens=False).ids) + 1 for r in stages[4].collect()}
    got, fill = Counter(), Counter()
    for r in stages[5].collect():
        assert r.doc_tokens == want[r.doc_id]
        got[r.doc_id] += r.length
        fill[r.sequence_id] += r.length
    assert got == want and all(n == 1024 or n & (n - 1) == 0 for n in fill.values())


def test_empty_input(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns and out.count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() == 0


def test_clashing_columns(spark):
    """Names that the stages use for themselves."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id < 40")
    for name in ("_d", "_m", "_bucket", "_none", "_id", "_mark", "mark", "fp", "told_doc", "rejected_id", "bad_mark"):
        docs = docs.selectExpr("*", f"'x' AS {name}")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns and {r.x for r in out.selectExpr("concat(_d, _m, _bucket, _none, _id, _mark, mark, fp) AS x").collect()} == {"x" * 8}
