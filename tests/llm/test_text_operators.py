"""Brute-force checks of the text operators on the smallest tables and on odd rows."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from kdforest.llm import decontaminate, fingerprint, html_text, langid, packing, quality, sharding, simhash, substring, warc

from .conftest import SF


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def windows_removed(rows, n=13):
    words = [(d, (t or "").encode().split()) for d, t in rows]
    least = {}
    for d, w in words:
        for i in range(len(w) - n + 1):
            if d is not None:
                k = tuple(w[i : i + n])
                least[k] = min(least.get(k, d), d)
    out = []
    for d, w in words:
        gone = {i + j for i in range(len(w) - n + 1) for j in range(n) if d is not None and least[tuple(w[i : i + n])] < d}
        kept = b" ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return out


def test_suffix_dedup(docs, odd, monkeypatch):
    for table, bits in ((docs, 0), (docs, 3), (odd, 6)):
        rows = [(r.doc_id, r.text) for r in table.select("doc_id", "text").collect()]
        got = substring.remove_repeats(table, prefix_bits=bits).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256)).collect()
        assert Counter(map(tuple, got)) == Counter(windows_removed(rows))


def test_suffixes_by_words_alone(spark, docs, monkeypatch):
    """Every digest collides, blocks are small and the dictionary has few words: words decide."""
    rows = [(r.doc_id, r.text) for r in docs.where("doc_id < 60").select("doc_id", "text").collect()]
    from kdforest.llm.substring import Coder, later_windows

    monkeypatch.setattr(substring, "digests", lambda codes, starts, length: np.zeros(len(starts), dtype=np.uint64))
    coder = Coder([b"the", b"of"])
    words = [(d, (t or "").encode().split()) for d, t in rows]
    codes = np.concatenate([np.array([coder[w] for w in ws], dtype=np.int64) for _, ws in words])
    owner = np.repeat(np.arange(len(words)), [len(ws) for _, ws in words])
    starts = np.array([i for i in range(len(codes) - 12) if owner[i] == owner[i + 12]])
    ids = np.array([d for d, _ in words])
    later = later_windows(codes, starts, ids[owner[starts]], 13)
    gone = Counter()
    for s in starts[later].tolist():
        gone.update({(owner[s], p) for p in range(s, s + 13)})
    per = Counter(ids[o] for o, _ in gone)
    assert {d: per[d] for d, *_ in windows_removed(rows)} == {d: n for d, _, n, _ in windows_removed(rows)}


def test_suffix_blocks(docs, odd, monkeypatch):
    monkeypatch.setattr(substring, "BLOCK", 300)
    monkeypatch.setattr(substring, "DICTIONARY", 50)
    clash = docs.withColumnsRenamed({"source": "told_bucket", "lang": "_bucket", "n_chars": "told_doc"})
    for table, bits in ((clash, 4), (odd, 2)):
        rows = [(r.doc_id, r.text) for r in table.select("doc_id", "text").collect()]
        out = substring.remove_repeats(table, prefix_bits=bits)
        assert out.columns[: len(table.columns)] == table.columns
        got = out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256)).collect()
        assert Counter(map(tuple, got)) == Counter(windows_removed(rows))


def plain_simhash(text):
    import xxhash

    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    grams = [" ".join(words[i : i + 4]) for i in range(len(words) - 3)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g.encode(), seed=42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def linked_brute(rows, fps, distance):
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= distance:
                parent[root(i)] = root(j)
    groups = defaultdict(list)
    for i, d in enumerate(rows):
        groups[root(i)].append(d)
    return {i: min((x for x in groups[root(i)] if x is not None), default=None) for i in range(len(rows))}


@pytest.mark.parametrize("parts", [2, 3])
def test_simhash(spark, docs, odd, parts, monkeypatch):
    monkeypatch.setattr(simhash, "TWO_SEGMENTS_FROM", 0 if parts == 2 else 1 << 25)
    for table in (docs, odd):
        rows = [(r.doc_id, r.text) for r in table.select("doc_id", "text").collect()]
        fps = [plain_simhash(t) for _, t in rows]
        root = linked_brute([d for d, _ in rows], fps, 4)
        got = simhash.linked(simhash.fingerprints(table)).collect()
        want = Counter((d, fps[i], root[i]) for i, (d, _) in enumerate(rows))
        assert Counter((r.doc_id, r.fp & (2**64 - 1), r.component_id) for r in got) == want


def test_dense_bucket(spark):
    rng = np.random.default_rng(1)
    centre = 0x123456789ABCDEF0
    values = {centre ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 6), replace=False)) for _ in range(400)} | {int(x) for x in rng.integers(0, 2**63, 300)}
    signed = [int(np.uint64(v).view(np.int64)) for v in values]
    links = simhash.near_links(spark.createDataFrame([(v,) for v in signed], "fp long"))
    assert links.count() < 67 * len(values) / 4  # each bucket keeps a tree of its members
    roots = {r.node: r.root for r in simhash.components(links).collect()}
    brute = linked_brute(signed, [v & (2**64 - 1) for v in signed], 4)
    groups, want = defaultdict(set), defaultdict(set)
    for i, v in enumerate(signed):
        groups[roots.get(v, v)].add(v)
        want[brute[i]].add(v)
    assert {frozenset(g) for g in groups.values()} == {frozenset(g) for g in want.values()}


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 60)] + [(100, 90), (90, 95)], "a long, b long")
    got = {r.node: r.root for r in simhash.components(edges).collect()}
    assert got == {i: 0 for i in range(61)} | {100: 90, 90: 90, 95: 90}


def test_one_of_each(docs, odd):
    kept = [r.doc_id for r in simhash.one_of_each(docs).collect()]
    assert len(kept) == len(set(kept)) < docs.count()
    assert {r.doc_id for r in simhash.one_of_each(odd).collect()} >= {1, 3, 7, 9}


def test_near_copies_go(spark):
    rng = np.random.default_rng(4)
    rows = []
    for i in range(60):
        words = [f"w{x}" for x in rng.integers(0, 3000, 200)]
        rows.append((10 * i, " ".join(words)))
        for k in (2, 3):  # shingles in common: about 0.9 and 0.86
            other = list(words)
            for at in rng.choice(200, k, replace=False):
                other[at] = "changed"
            rows.append((10 * i + k, " ".join(other)))
    kept = {r.doc_id for r in simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {10 * i for i in range(60)} <= kept and len(kept) <= 64


def test_near_copies_against_all_pairs(spark):
    rng = np.random.default_rng(8)
    rows = []
    for i in range(150):  # similarities of 0.7 to 0.9, some at 0.8; sets of 12 to 400 shingles
        n = int(rng.integers(12, 400))
        words = [f"v{x}" for x in rng.integers(0, 50_000, n + 4)]
        more = round(n / int(rng.integers(3, 8)))
        rows += [(10 * i + 1, " ".join(words)), (10 * i, " ".join(words + [f"u{x}" for x in rng.integers(0, 50_000, more)]))]
    for i in range(40):  # 80 equal shingles of 100, of 90 each and of 101 in all
        words = [f"x{i}y{x}" for x in range(104)]
        rows += [(5000 + 10 * i, " ".join(words)), (5001 + 10 * i, " ".join(words[:84]))]
        rows += [(6000 + 10 * i, " ".join("q" + w for w in words)), (6001 + 10 * i, " ".join("q" + w for w in words[:83]))]
    sets = {d: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} for d, w in ((d, t.split()) for d, t in rows)}
    root = {d: d for d in sets}
    ids = sorted(sets)
    by = defaultdict(set)
    for d, s in sets.items():
        for x in s:
            by[x].add(d)
    for a, b in {(a, b) for v in by.values() for a in v for b in v if a < b}:
        if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            low, high = sorted((root[a], root[b]))
            root = {d: low if r == high else r for d, r in root.items()}
    want = {d for d in ids if root[d] == d}
    got = {r.doc_id for r in simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == want and all(5001 + 10 * i not in got and 6001 + 10 * i in got for i in range(40))


def test_different_texts_stay_under_one_id_and_none(spark):
    text = lambda i: " ".join(f"t{i}w{j}" for j in range(30))
    rows = [(None, text(i)) for i in range(5)] + [(4, text(i)) for i in range(5, 9)] + [(4, text(5)), (None, text(1)), (9, text(6)), (3, text(7)), (None, text(8))]
    kept = simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    want = [(None, text(i)) for i in range(5)] + [(4, text(5)), (4, text(6)), (3, text(7)), (4, text(8))]
    assert Counter((r.doc_id, r.text) for r in kept) == Counter(want)


def test_packing(docs, odd):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    named = odd.unionByName(odd.limit(1).selectExpr("700L AS doc_id", "'a <|endoftext|> b<|endoftext|>' AS text", "lang", "source", "n_chars", "_extra"))
    for table in (docs, named):
        texts = Counter()
        ids = {}
        for r in table.collect():
            texts[r.doc_id, r.text] += 1
            ids[r.doc_id, r.text] = [*tok.encode(r.text or "", add_special_tokens=False).ids, 0]
        got = packing.pack(table, path).collect()
        by_doc, by_seq = defaultdict(list), defaultdict(list)
        for r in got:
            by_doc[r.doc_id].append(r)
            by_seq[r.sequence_id].append(r)
        for d in by_doc:
            if sum(n for (k, _), n in texts.items() if k == d) == 1:
                own = next(v for k, v in ids.items() if k[0] == d)
                at = 0
                for r in sorted(by_doc[d], key=lambda r: r.start):
                    part = own[at : at + r.length]
                    assert (r.start, r.doc_tokens, r.ids_crc32) == (at, len(own), zlib.crc32(np.array(part, "<u4").tobytes()))
                    at += r.length
                assert at == len(own)
        assert sum(r.length for r in got) == sum(len(ids[k]) * n for k, n in texts.items())
        for seq in by_seq.values():
            at = 0
            for r in sorted(seq, key=lambda r: r.offset):
                assert r.offset == at
                at += r.length
            assert at <= 1024
        assert packing.padding(packing.pack(table, path)).first().padding == 0


def test_special_names_are_tokens():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    text = "a <|endoftext|> b"
    ids = Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids
    assert packing.text_encoder(path)(text) == ids and 50256 in ids


def test_levels_by_brute_force():
    """Each piece goes where the sum of squared counts is smallest; windows of the rule stay at the end."""
    rng = np.random.default_rng(3)
    packer, size, opened = packing.LevelPacker(16), 16, Counter()
    for i in range(600):
        n = int(rng.integers(1, 16))
        square = lambda counts: sum(c * c for c in counts.values())
        options = {}
        for level in [0, *[v for v, c in opened.items() if c and v + n <= size]]:
            after = Counter(opened)
            after[level] -= level > 0
            after[level + n] += level + n < size
            options[level] = square(after) - square(opened)
        level = packer.level_for(n)
        assert options[level] == min(options.values())
        packer.add(("d", i), np.arange(n, dtype="<u4"))
        opened[level] -= level > 0
        opened[level + n] += level + n < size
        assert all(packer.count[v] == c for v, c in opened.items() if 0 < v < size)
    total, windows = sum(v * c for v, c in opened.items() if v & (v - 1)), sum(c for v, c in opened.items() if v & (v - 1))
    closed = packer.finish()
    assert packer.kept == total // size and packer.kept + packer.parted == windows
    assert all((k := sum(len(x) for *_, x in w)) == size or k & (k - 1) == 0 for w in closed)


def test_levels():
    p = packing.LevelPacker(16)
    closed = p.add("a", np.arange(10, dtype="<u4")) + p.add("b", np.arange(6, dtype="<u4"))
    assert [[(d, s, len(x)) for d, s, x in w] for w in closed] == [[("a", 0, 10), ("b", 0, 6)]] and not p.count.any()
    p.add("c", np.arange(35, dtype="<u4"))
    assert p.count[3] == 1
    assert sorted(sum(len(x) for *_, x in w) for w in p.finish()) == [1, 2]


def test_fingerprints(docs, odd):
    for table in (docs, odd):
        rows = sorted(((r.doc_id, r.text or "") for r in table.collect()), key=lambda r: (r[0] is None, -(r[0] or 0), r[1]))
        got = fingerprint.edit_report(table, parts=5).collect()
        want = Counter()
        for i, (d, t) in enumerate(rows):
            nxt, k = rows[(i + 1) % len(rows)][1], len(t) // 3
            want[d, len(t), hashlib.sha256((t[: len(t) - k] + nxt[:k]).encode()).hexdigest()] += 1
        assert Counter((r.doc_id, r.n_chars, r.edited_sha256) for r in got) == want
        text_of = dict(rows)
        seen = defaultdict(set)
        for r in got:
            if Counter(d for d, _ in rows)[r.doc_id] == 1:
                seen[text_of[r.doc_id]].add(r.fingerprint)
            assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        assert all(len(v) == 1 for v in seen.values())
    full = fingerprint.edit_report(docs).collect()
    long = [r for r in full if r.n_chars > 500]
    assert np.mean([r.near_edited for r in long]) > 0.4 > 0.25 > np.mean([r.near_next for r in long])


def test_likeness_against_sets(spark, docs):
    rows = docs.orderBy(F.desc("doc_id")).collect()
    cut = [set(x for x in re.split(r"\n+|(?<=[.!?])[ ]+", r.text or "") if x) for r in rows]
    got = {r.doc_id: r for r in fingerprint.edit_report(docs, parts=3).collect()}
    exact = 0
    for i, r in enumerate(rows):
        a, b = cut[i], cut[(i + 1) % len(rows)]
        want = 1 - len(a ^ b) / max(1, len(a) + len(b))
        if len(a ^ b) <= 12:
            exact += 1
            assert got[r.doc_id].near_next == pytest.approx(want, abs=0.35)
        assert got[r.doc_id].near_next == pytest.approx(want if a or b else 1.0, abs=1e-9)
    assert exact


def test_likeness_is_exact_for_large_differences(spark):
    sizes = [3, 40, 90, 300, 60, 200]
    rows = [(i, "\n".join(f"line {j if j % 3 else (i, j)}" for j in range(n))) for i, n in enumerate(sizes)]
    cut = lambda t: {x for x in re.split(r"\n+|(?<=[.!?])[ ]+", t) if x}
    got = {r.doc_id: r for r in fingerprint.edit_report(spark.createDataFrame(rows, "doc_id long, text string"), parts=2).collect()}
    for i, text in rows:
        other = rows[i - 1][1]  # the next by descending id, the last one's is the first
        third = len(text) // 3
        edited = text[: len(text) - third] + other[:third]
        for near, b in ((got[i].near_next, cut(other)), (got[i].near_edited, cut(edited))):
            assert near == pytest.approx(1 - len(cut(text) ^ b) / (len(cut(text)) + len(b)), abs=1e-9)


def test_recovered_digests(spark):
    old = spark.createDataFrame([(1, "a.\nb.\nc."), (2, "\n".join(f"line {i}" for i in range(300))), (3, "same")], "doc_id long, text string")
    new = spark.createDataFrame([(1, "a.\nx.\nc."), (2, "\n".join(f"other {i}" for i in range(280))), (3, "same"), (4, "new one")], "doc_id long, text string")
    got = fingerprint.recovered(old, new)
    n = {(r.doc_id, r.side): r.n for r in got.groupBy("doc_id", "side").agg(F.count("*").alias("n")).collect()}
    assert n == {(1, 1): 1, (1, -1): 1, (2, 1): 300, (2, -1): 280, (4, -1): 1}
    small = {(r.doc_id, r.side): r.n for r in fingerprint.recovered(old, new, retries=1).groupBy("doc_id", "side").agg(F.count("*").alias("n")).collect()}
    assert small == n


def test_decontamination(spark, docs, odd):
    bench = spark.read.parquet(f"{SF}/benchmark.parquet").unionByName(spark.createDataFrame([(900, "word3 Word4, word5"), (901, None), (902, "  "), (903, "word3 word4 word5"), (None, "word7 word8")], "item_id long, text string"))
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    wins = defaultdict(set)
    for r in bench.collect():
        w = split(r.text)
        for i in range(max(1, len(w) - 12) if w else 0):
            wins[tuple(w[i : i + 13])].add(None if r.item_id is None else str(r.item_id))
    for table in (docs, odd):
        want = Counter()
        for r in table.collect():
            w, hit, items = split(r.text), set(), set()
            for k in {len(x) for x in wins}:
                for i in range(len(w) - k + 1):
                    if (g := tuple(w[i : i + k])) in wins:
                        hit |= set(range(i, i + k))
                        items |= wins[g] - {None}
            want[r.doc_id, len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)] += 1
        got = decontaminate.contamination(table, bench).drop("mark").collect()
        assert Counter(map(tuple, got)) == want
        assert any(k[-1] for k in want)
        assert decontaminate.decontaminated(table, bench).count() == sum(n for k, n in want.items() if not k[-1])


def test_sharding(docs, odd, spark):
    for table in (docs, odd):
        got = sharding.sharded(table).collect()
        rows = table.count()
        assert len(got) == rows
        want = Counter((r.doc_id, len((r.text or "").encode()) + 16, zlib.crc32((r.text or "").encode())) for r in table.collect())
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == want
        by = defaultdict(list)
        for r in got:
            by[r.shard].append(r.slot)
        assert all(sorted(v) == list(range(len(v))) for v in by.values()) and set(by) <= set(range(40))
        counts = [len(by.get(s, ())) for s in range(40)]
        assert max(counts) - min(counts) <= 1
    many = spark.range(4000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("hot")).otherwise(F.concat(F.lit("text "), (F.col("id") / 4).cast("int"))).alias("text"))
    rows = sharding.described(many)
    cells, cut = sharding.propagated(rows)
    assert cut[-1] < cut[0]
    loads = {r.shard: r.n for r in sharding.sharded(many).groupBy("shard").agg(F.count("*").alias("n")).collect()}
    assert set(loads.values()) == {100}
    apart = sharding.sharded(many).where("text_crc32 <> " + str(zlib.crc32(b"hot"))).groupBy("text_crc32").agg(F.countDistinct("shard").alias("k")).where("k > 1").count()
    assert apart < 200
    assert apart <= 50  # of 1000 groups


def test_sharding_over_links(spark):
    """Twelve planted clusters, a hub, and links that count for nothing."""
    links = [(c * 100 + i, c * 100 + (i + s) % 60) for c in range(12) for i in range(60) for s in (1, 2, 5, 7)] + [(i, 999) for i in range(0, 1200, 7)]
    ids = sorted({x for p in links for x in p})
    nodes = spark.createDataFrame([(i,) for i in ids + ids[:5]] + [(None,)], "id long")
    edges = spark.createDataFrame([*links, *links[:50], (3, 3), (5, 77777), (None, 4)], "a long, b long")
    state, cut = sharding.propagated_links(nodes, edges, shards=4, rounds=8, slack=0.1)
    got = {r.id: r.label for r in state.collect()}
    assert sorted(got) == ids and set(got.values()) <= set(range(4))
    real = {tuple(sorted(p)) for p in links if p[0] != p[1]}
    assert cut[-1] == sum(got[a] != got[b] for a, b in real) < 0.7 * cut[0]
    assert max(Counter(got.values()).values()) <= len(ids) / 4 * 1.25


def test_warc(spark, tmp_path):
    html = "<p>" + "x\r\n\r\nWARC/1.1\r\n" * 20
    rows = [(5, "http://a/\r\nb", html), (3, "u", html), (9, None, html), (1, "u", "short"), (2, "u", "short"), (4, "u", None), (6, "ü", "é" * 60), (3, "v", html)]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, other int")
    path = f"file://{tmp_path}/warc"
    warc.write_warc(pages, path)
    back = warc.read_warc(spark, path)
    got = {(r.page_id, r.url): r for r in back.collect()}
    assert set(got) == {(p, u) for p, u, _ in rows}
    assert {k: (r.record_type, r.refers_to) for k, r in got.items() if r.payload_bytes >= 100} == {
        (5, "http://a/\r\nb"): ("revisit", 3), (3, "u"): ("response", None), (9, None): ("revisit", 3), (6, "ü"): ("response", None), (3, "v"): ("response", None),
    }
    for p, u, h in rows:
        r = got[p, u]
        assert r.payload_digest == hashlib.sha256((h or "").encode()).hexdigest() and r.payload_bytes == len((h or "").encode())
        if r.record_type == "response":
            assert r.payload == (h or "") and r.computed_digest == r.payload_digest
    some = back.where("record_type = 'revisit' AND page_id IN (5, 6)")
    assert [r.page_id for r in some.select("page_id").collect()] == [5]
    assert warc.read_warc(spark, path, ["page_id"]).count() == len(rows)
    warc.write_warc(pages.limit(0), f"file://{tmp_path}/none")
    assert warc.read_warc(spark, f"file://{tmp_path}/none").count() == 0


def test_html(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    odd = spark.createDataFrame([(1, None, None), (2, "u", ""), (3, "u", "<p>broken <b>text"), (4, "u", "no markup &amp; more words here")], "page_id long, url string, html string")
    assert {r.page_id: r.text for r in html_text.extract(odd).collect()}[1] == ""
    for r in html_text.extract(pages).limit(40).collect():
        body = re.search(r"<article>(.*?)(?:</article>|<footer>)", r.html, re.S)[1]
        import html

        want = [" ".join(html.unescape(re.sub("<[^>]*>", " ", x)).split()) for x in re.split(r"</?(?:p|h1)>", body)]
        assert r.text == "\n".join(x for x in want if x)
    page = "<div class=cookie-notice>We use cookies</div><main><article><h1>T &lt;x</h1><p>One&nbsp;<a href=x>two</a>\n three.<aside>related</aside><form><p>mail</p></form><div id=comments><p>so nice</p></div><p>End.</article></main><footer>f</footer>"
    assert html_text.main_text(page) == "T <x\nOne two three.\nEnd."


def test_html_keeps_all_of_an_article():
    page = "<article><h1>Title</h1><p>One two.</p><figure><img src=x><figcaption>A caption here.</figcaption></figure><address>Written at home</address><p>End.</p></article>"
    whole = "Title\nOne two.\nA caption here.\nWritten at home\nEnd."
    assert html_text.main_text(page) == whole
    for named in ("content-sidebar-wrap", "layout with-sidebar", "page header-fixed"):
        assert html_text.main_text(f"<body><div class='{named}'><nav>menu</nav>{page}<aside>side</aside></div><footer>f</footer></body>") == whole
    for part in ("<aside>{}</aside>", "<div class=related-posts>{}</div>", "<div id=comments>{}</div>", "<section class='teaser box'>{}</section>", "<div hidden>{}</div>"):
        assert html_text.main_text(page + part.format("<article><h2>Other</h2><p>text of another one</p></article>")) == whole


def test_quality(spark, docs, odd):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality.trained(docs, labels.where(~quality.held_out()))
    rows = quality.scored(docs.join(labels, "doc_id"), model, ["doc_id", "quality"]).where(quality.held_out()).collect()
    assert np.mean([r.predicted == r.quality for r in rows]) > 0.9
    assert all(0 <= r.score <= 1 for r in quality.scored(odd, model, ["doc_id"]).collect())
    empty = quality.trained(docs, labels.limit(0))
    assert {r.score for r in quality.scored(odd, empty, ["doc_id"]).collect()} == {0.5}


def test_language(spark, docs, odd):
    model = langid.trained(docs)
    assert model.languages == ["de", "en", "es", "fr"]
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    got = langid.page_languages(pages, model).collect()
    assert np.mean([r.language == r.declared for r in got]) > 0.97
    kept = langid.accepted_documents(docs, model)
    assert kept.columns == docs.columns and kept.count() >= 0.99 * docs.where("text rlike '[A-Za-z]{3}'").count()
    assert {r.doc_id for r in langid.accepted_documents(odd, model).collect()}.isdisjoint({1, 2, 10})
    assert langid.accepted_documents(docs, langid.trained(docs.limit(0))).count() == 0


def test_language_is_decided_by_the_posterior(spark):
    clean, odd, junk = "the clear words of a known tongue", "odd brief note", "zzqx vvkj wqqz xkcd"
    log = np.full((2, langid.BUCKETS), langid.OTHER - 3)
    log[1, langid.trigrams(clean)] = -4.0
    log[1, langid.trigrams(odd)] = langid.OTHER - 0.1  # just below no known language
    model = langid.Likelihood(["de", "en"], log)
    rows = [(i, clean, "en", "good") for i in range(60)] + [(i, junk, "", "bad") for i in range(100, 160)] + [(200, odd, "en", "good"), (201, odd, "", "bad"), (202, junk, "en", "good")]
    kept = {r.doc_id for r in langid.accepted_documents(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string"), model).collect()}
    assert kept == {*range(60), 200}


def test_a_small_language_has_no_high_floor(spark):
    rows = [(i, f"the usual words of sentence {i} are here", "en") for i in range(50)] + [(99, "una lingua rara", "xx")]
    model = langid.trained(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert model.languages == ["en", "xx"] and (model.log.min(axis=1) < langid.OTHER).all()
    assert np.exp(model.log).sum(axis=1) == pytest.approx(1)


@pytest.mark.parametrize("name", ["edit_report", "remove_repeats", "linked", "sharded", "contamination", "pack"])
def test_empty_tables(spark, docs, name):
    none = docs.limit(0)
    out = {
        "edit_report": lambda: fingerprint.edit_report(none), "remove_repeats": lambda: substring.remove_repeats(none), "linked": lambda: simhash.linked(simhash.fingerprints(none)), "sharded": lambda: sharding.sharded(none),
        "contamination": lambda: decontaminate.contamination(none, spark.read.parquet(f"{SF}/benchmark.parquet").limit(0)), "pack": lambda: packing.pack(none, __import__("public_tokenizers").path("byte_bpe_50k.json")),
    }[name]()
    assert out.count() == 0


def test_packed_runs_come_back():
    rng = np.random.default_rng(3)
    for n, most in ((0, 0), (1, 0), (40, 3), (900, 500)):
        count = rng.integers(1, 9, n)
        words = rng.integers(0, 60_000, int(count.sum()) + 12 * n)
        rare = rng.random(len(words)) < (0.3 if most else 0)
        spelled = np.unique(rng.integers(0, max(1, most), int(rare.sum())), return_inverse=True)[1]
        words[rare] = substring.SPELLED
        names = [b"w%d" % i for i in rng.permutation(int(spelled.max(initial=-1)) + 1)]
        docs, marks = np.sort(rng.integers(-(1 << 62), 1 << 62, n)), rng.integers(0, 1 << 32, n)
        given = [docs, marks, np.arange(n), rng.integers(0, 1 << 20, n), count, words]
        back = substring.unpacked(substring.packed(*given, spelled, names))
        assert all(np.array_equal(a, b) for a, b in zip(given, back[:6], strict=True))
        assert [back[7][i] for i in back[6].tolist()] == [names[i] for i in spelled.tolist()]
