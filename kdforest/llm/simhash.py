"""SimHash fingerprints, linked at a few differing bits through multi-index hashing.

Fingerprints are computed where the texts are read; only (id, fingerprint) rows travel. Equal fingerprints are one
from then on. A fingerprint is cut into segments so few that of two fingerprints within the distance one segment
differs in at most ``radius`` bits. Each distinct fingerprint is entered once per segment and looked up under all
values in the small Hamming ball around each segment; a bucket is the entries and lookups of one segment value.
Inside a bucket complete distances are verified in blocks, and only the links that join what the bucket has not
joined yet are kept, so a dense group of near copies gives a tree and not all its pairs. Components follow from
rounds of joins over those links.

``one_of_each`` drops near copies: linked fingerprints are its first candidates, bands of minimum hashes add those that so
few bits can't tell, and the Jaccard similarity of word shingles decides.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import given_back, maybe_broadcast, table, unused, written

#: A-Z to a-z, nothing else.
LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
#: Distinct fingerprints from which on two segments are cheaper than three.
TWO_SEGMENTS_FROM = 1 << 25


def fingerprint(text: str | None, shingle: int = 4) -> int:
    """64-bit SimHash of a text's word shingles; a bit is 1 if set in over half the shingle hashes."""
    words = (text or "").encode().translate(LOWER).split()
    if not words:
        return 0
    if len(words) < shingle:
        grams = [b" ".join(words)]
    else:
        grams = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
    h = np.array([xxhash.xxh64_intdigest(g, 42) for g in grams], dtype=">u8")
    ones = np.zeros(64, dtype=np.int64)
    for i in range(0, len(h), 1 << 16):
        ones += np.unpackbits(h[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(h)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long. Null texts have no words."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t.as_py(), shingle) for t in b.column(1)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(work, "doc_id long, fp long")


def segments(distance: int, parts: int) -> list[tuple[int, int, list[int]]]:
    """(shift, width, masks of the Hamming ball) of each segment: of two fingerprints within ``distance`` one
    segment differs in at most ``distance // parts`` bits."""
    cuts = [64 * i // parts for i in range(parts + 1)]
    out = []
    for lo, hi in zip(cuts, cuts[1:], strict=False):
        ball = [sum(1 << b for b in bits) for r in range(distance // parts + 1) for bits in combinations(range(hi - lo), r)]
        out.append((lo, hi - lo, ball))
    return out


def near_links(fps: DataFrame, distance: int = 4, parts: int | None = None) -> DataFrame:
    """(a, b), a < b: links between distinct fingerprints (column ``fp``) within ``distance`` bits, enough of them
    to join all that are joined by any: inside a bucket a link that closes a circle is left out."""
    parts = parts or (3 if fps.count() < TWO_SEGMENTS_FROM else 2)
    cut = segments(distance, parts)

    def looked_up(i: int, part: Column) -> Callable[[Column], Column]:
        return lambda m: F.struct(F.lit(i).alias("seg"), part.bitwiseXOR(m).alias("value"), (m == 0).alias("entry"))

    rows = []
    for i, (lo, width, ball) in enumerate(cut):
        part = F.shiftrightunsigned("fp", lo).bitwiseAND(F.lit((1 << width) - 1))
        masks = F.array(*[F.lit(m).cast("long") for m in ball])
        rows.append(F.transform(masks, looked_up(i, part)))
    keyed = fps.select("fp", F.explode(F.concat(*rows)).alias("k")).select("k.seg", "k.value", "k.entry", "fp")

    def bucket_links(entries: np.ndarray, lookups: np.ndarray) -> list[tuple[int, int]]:
        """Links of one bucket, each of which joins two of its groups."""
        values = np.unique(lookups)  # the entries are looked up too
        group = np.arange(len(values))
        rows, cols, out = values, np.searchsorted(values, np.unique(entries)), []
        for i in range(0, len(rows), 2048):
            for j in range(0, len(cols), 2048):
                there = cols[j : j + 2048]
                near = np.bitwise_count(rows[i : i + 2048, None] ^ values[there][None, :]) <= distance
                while True:  # each round joins some group of every row that has a near one outside its own
                    apart = near & (group[i : i + 2048, None] != group[there][None, :])
                    some = np.flatnonzero(apart.any(axis=1))
                    if not len(some):
                        break
                    parent: dict[int, int] = {}

                    def root(x: int, parent: dict[int, int] = parent) -> int:
                        while (up := parent.get(x, x)) != x:
                            parent[x] = x = parent.get(up, up)
                        return x

                    for r, c in zip(some.tolist(), there[apart[some].argmax(axis=1)].tolist(), strict=True):
                        a, b = root(int(group[i + r])), root(int(group[c]))
                        if a != b:
                            parent[max(a, b)] = min(a, b)
                            out.append((int(rows[i + r]), int(values[c])))
                    moved = np.arange(len(values))
                    moved[list(parent)] = [root(x) for x in parent]
                    group = moved[group]
        return out

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by bucket; the bucket that a batch breaks off is carried on."""
        held: list[np.ndarray] = []

        def solve(block: np.ndarray, last: bool) -> tuple[list[tuple[int, int]], np.ndarray]:
            keys = block["seg"].astype(np.int64), block["value"]
            edge = np.flatnonzero((np.diff(keys[0]) != 0) | (np.diff(keys[1]) != 0)) + 1
            starts = np.concatenate([[0], edge])
            ends = np.concatenate([edge, [len(block)]])
            if not last:
                keep = starts[-1]
                starts, ends = starts[:-1], ends[:-1]
            else:
                keep = len(block)
            entries = np.add.reduceat(block["entry"].astype(np.int64), starts) if len(starts) else np.zeros(0, np.int64)
            out = []
            for k in np.flatnonzero((entries > 0) & (ends - starts > 1)):
                part = block[starts[k] : ends[k]]
                out += bucket_links(part["fp"][part["entry"]], part["fp"])
            return out, block[keep:]

        def sent(links: list[tuple[int, int]]) -> pa.RecordBatch:
            ab = np.array(links, dtype=np.uint64).reshape(-1, 2).view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(ab.min(axis=1), pa.int64()), pa.array(ab.max(axis=1), pa.int64())], ["a", "b"])

        for b in batches:
            block = np.empty(b.num_rows, dtype=[("seg", "i4"), ("value", "i8"), ("entry", "?"), ("fp", "u8")])
            for name in ("seg", "value", "entry"):
                block[name] = b.column(name).to_numpy(zero_copy_only=False)
            block["fp"] = b.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
            held.append(block)
            first = held[0][0]
            if len(block) and (first["seg"], first["value"]) == (block[-1]["seg"], block[-1]["value"]):
                continue  # still one bucket
            links, rest = solve(np.concatenate(held), last=False)
            held = [rest]
            yield sent(links)
        if held and sum(map(len, held)):
            yield sent(solve(np.concatenate(held), last=True)[0])

    found = keyed.repartition("seg", "value").sortWithinPartitions("seg", "value").mapInArrow(work, "a long, b long")
    return found.where("a <> b").distinct()


def components(links: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """(node, root): the smallest node that is reachable over ``links`` (a, b), for each node in a link.

    Rounds of two steps, each a grouped minimum and a join: every node's larger neighbours, then its smaller
    ones, are linked to its smallest neighbour. Rounds end when nothing changes; their number grows with the
    logarithm of the longest path. Work tables go to the shared folder.
    """
    edges = written(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "links")

    def mark(e: DataFrame) -> tuple:
        return e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()

    before = mark(edges)
    while True:
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = written(small.unionByName(least.select("u", F.col("m").alias("v"))).where("u > v").distinct(), "links")
        after = mark(edges)
        if after == before:
            break
        before = after
    roots = edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def linked(fps: DataFrame, distance: int = 4) -> DataFrame:
    """(doc_id, fp, component_id) for all rows (doc_id, fp).

    Component ids are the smallest doc_id of those reachable. Null ids are carried, but name a component only if it
    has no others; repeated rows stay. An empty table gives none.
    """
    reps = written(fps.groupBy("fp").agg(F.min("doc_id").alias("first")), "fingerprints")
    found = components(near_links(reps.select("fp"), distance))
    named = reps.join(found.select(F.col("node").alias("fp"), "root"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    ids = named.groupBy("root").agg(F.min("first").alias("component_id"))
    labels = named.join(ids, "root").select("fp", "component_id")
    return fps.join(labels, "fp", "left")


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fingerprint of every document and the smallest id that is linked to it at 4 bits; see ``linked``."""
    fps = written(fingerprints(table(spark, sf_dir, "documents")), "simhash")
    return linked(fps).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def by_row(docs: DataFrame) -> tuple[DataFrame, list[str]]:
    """``docs`` with three columns, and their names, which are equal only in rows with equal ids (or none) and equal texts."""
    key = F.col("doc_id").cast("long")
    none, own, mark = (unused(docs, n) for n in ("_none", "_id", "_mark"))
    return docs.withColumns({none: key.isNull(), own: F.coalesce(key, F.lit(0).cast("long")), mark: F.xxhash64("text")}), [none, own, mark]


#: Bands and their minimum hashes: texts with a Jaccard similarity j share a band with a chance of 1 - (1 - j**6)**32,
#: 0.99994 at 0.8 and more above it.
BANDS, BAND_ROWS = 32, 6
_MULTIPLIERS = np.random.default_rng(46).integers(0, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SEEDS = np.random.default_rng(47).integers(0, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64)


def shingle_set(text: str | None, shingle: int = 5) -> np.ndarray:
    """Sorted 64-bit hashes of a text's distinct word shingles; a shorter text is one shingle, one without words none."""
    words = (text or "").encode().translate(LOWER).split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    grams = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False)) if len(words) >= shingle else [b" ".join(words)]
    return np.unique(np.fromiter((xxhash.xxh3_64_intdigest(g, 5) for g in grams), dtype=np.uint64))


def band_keys(own: np.ndarray) -> np.ndarray:
    """One key per band, of the set's minimum hashes in it."""
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for i in range(0, len(own), 1 << 12):
        h = (own[i : i + (1 << 12), None] ^ _SEEDS) * _MULTIPLIERS
        h ^= h >> np.uint64(32)
        h *= np.uint64(0x9E3779B97F4A7C15)
        least = np.minimum(least, h.min(axis=0))
    return np.array([xxhash.xxh3_64_intdigest(row.tobytes(), i) for i, row in enumerate(least.reshape(BANDS, BAND_ROWS))], dtype=np.uint64)


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether the Jaccard similarity of two sets is 0.8 or more."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 9 * both >= 4 * (len(a) + len(b))


def similar_groups(sets: list[np.ndarray]) -> np.ndarray:
    """The group of each set: sets are in one if links between similar ones join them.

    All such links are found: similar sets share an element among the first of each, in one order, up to a fifth.
    Elements are in order of their number of sets, so shared passages come last. Pairs in one group already are not compared.
    """
    order = np.array(sorted(range(len(sets)), key=lambda i: len(sets[i])), dtype=np.int64)
    sizes = np.array([len(sets[i]) for i in order], dtype=np.int64)
    _, code, count = np.unique(np.concatenate([sets[i] for i in order]), return_inverse=True, return_counts=True)
    rank = np.empty(len(count), dtype=np.int64)
    rank[np.argsort(count, kind="stable")] = np.arange(len(count))
    ends = np.cumsum(sizes)
    first = [np.sort(rank[code[e - n : e]])[: n - (4 * n + 4) // 5 + 1] for e, n in zip(ends, sizes, strict=True)]
    entry, owner = np.concatenate(first), np.repeat(np.arange(len(order)), [len(f) for f in first])
    by = np.lexsort((owner, entry))
    entry, owner = entry[by], owner[by]
    group = np.arange(len(order))
    for x, own in enumerate(first):
        lo, hi = np.searchsorted(entry, own), np.searchsorted(entry, own, side="right")
        some = [o[: np.searchsorted(o, x)] for o in (owner[i:j] for i, j in zip(lo, hi, strict=True)) if o[0] < x]
        if not some:
            continue
        cand = np.unique(np.concatenate(some))
        cand = cand[5 * sizes[cand] >= 4 * sizes[x]][::-1]
        while len(cand := cand[group[cand] != group[x]]):
            if similar(sets[order[x]], sets[order[cand[0]]]):
                a, b = sorted((group[x], group[cand[0]]))
                group[group == b] = a
            cand = cand[1:]
    out = np.empty(len(order), dtype=np.int64)
    out[order] = group
    return out


def fingerprint_links(reps: DataFrame, distance: int = 4) -> DataFrame:
    """(a, b): links between the nodes of ``reps`` (node, sims) by fingerprints that are equal or within ``distance`` bits."""
    sims = written(reps.select("node", F.explode("sims").alias("fp")), "sims")
    firsts = written(sims.groupBy("fp").agg(F.min("node").alias("first")), "fingerprints")
    same = sims.join(firsts, "fp").select(F.col("first").alias("a"), F.col("node").alias("b"))
    near = near_links(firsts.select("fp"), distance)
    a, b = (firsts.select(F.col("fp").alias(n), F.col("first").alias(f"{n}_first")) for n in ("a", "b"))
    apart = near.join(a, "a").join(b, "b").select(F.col("a_first").alias("a"), F.col("b_first").alias("b"))
    return same.unionByName(apart).where("a <> b")


def one_of_each(docs: DataFrame, shingle: int = 5, distance: int = 4) -> DataFrame:
    """``docs`` with one document of each group of near duplicates, that with the smallest id; null ids come last.

    Near duplicates are texts whose sets of five-word shingles have a Jaccard similarity of 0.8 or more, and those
    that such texts join. Candidates have fingerprints within ``distance`` bits, or share a band of minimum hashes, with the same
    bands at every size; those that candidates join meet in one task, which compares their sets exactly. Different texts under one id are different
    documents, and so are those without an id. Texts without words are one; other columns stay as they are.
    """
    marked, row = by_row(docs)
    keys = f"`{row[0]}` boolean, `{row[1]}` long, `{row[2]}` long"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [shingle_set(t.as_py(), shingle) for t in b.column(3)]
            digests = pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary())
            bands = pa.array([band_keys(s).view(np.int64) if len(s) else [] for s in sets], pa.list_(pa.int64()))
            sims = pa.array(np.array([fingerprint(t.as_py()) for t in b.column(3)], dtype=np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(3)), digests, bands, sims], [*row, "fp", "bands", "sim"])

    def starred(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by band and node; each is linked to its band's first."""
        key = first = None
        for b in batches:
            band, node = b.column(0).to_numpy(), b.column(1).to_numpy()
            if not len(band):
                continue
            start = np.concatenate([[band[0] != key], band[1:] != band[:-1]])
            at = np.maximum.accumulate(np.where(start, np.arange(len(band)), -1))
            to = np.where(at >= 0, node[at], first if first is not None else 0)
            key, first = band[-1], to[-1]
            apart = to != node
            yield pa.RecordBatch.from_arrays([pa.array(to[apart]), pa.array(node[apart])], ["a", "b"])

    def solved(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows (root, _none, _id, _mark, text) come sorted by root; those that a row before them replaces."""
        key, held = None, []

        def lost() -> pa.RecordBatch:
            rows = sorted(held, key=lambda r: r[:3])
            group = similar_groups([r[3] for r in rows]) if len(rows) > 1 else np.arange(len(rows))
            first = set(np.unique(group, return_index=True)[1].tolist())
            gone = [r[:3] for i, r in enumerate(rows) if i not in first]
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array([g[i] for g in gone], t) for i, t in enumerate((pa.bool_(), pa.int64(), pa.int64()))], row)

        for b in batches:
            for root, *own, text in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if root != key:
                    yield lost()
                    key = root
                held.append((*own, shingle_set(text, shingle)))
        yield lost()

    fps = marked.select(*row, "text").mapInArrow(lambda it: given_back(work(it)), f"{keys}, fp binary, bands array<long>, sim long")
    each = fps.groupBy("fp").agg(F.min(F.struct(*row)).alias("r"), F.first("bands").alias("bands"), F.collect_set("sim").alias("sims"))
    least = each.select(F.xxhash64("fp").alias("node"), "r.*", "bands", "sims")
    reps = written(least, "fingerprints")
    keyed = reps.select(F.explode("bands").alias("band"), "node")
    banded = keyed.repartition("band").sortWithinPartitions("band", "node").mapInArrow(lambda it: given_back(starred(it)), "a long, b long")
    links = fingerprint_links(reps, distance).unionByName(banded).distinct()
    met = written(reps.join(components(links), "node").select("root", *row), "candidates")
    texts = marked.select(*row, "text").join(maybe_broadcast(met), row).dropDuplicates(["root", *row]).select("root", *row, "text")
    gone = written(texts.repartition("root").sortWithinPartitions("root").mapInArrow(lambda it: given_back(solved(it)), keys), "replaced")
    keep = reps.select(*row).join(gone, row, "left_anti")
    return marked.join(keep, row, "left_semi").dropDuplicates(row).drop(*row)
