"""Removal of long word passages that an earlier document has too, by prefix-partitioned suffix trees.

Words are integers: a bounded dictionary of frequent words goes along with each task, other words are spelled out once
a block. Each window of ``length`` words belongs to one suffix of its document, that which starts at the window's rarest
place (by the dictionary, then by hash) of three words, its anchor; equal windows have equal anchors, so only anchors
need suffixes. Suffixes are dealt by prefixes of their words, three where a rare word leads and all words of a window
where only common words do, to groups that fit in memory; neighbouring windows of one anchor travel as one run of words.

Inside a group, and before that inside each block of documents of a task, suffixes are sorted by their words; neighbours'
common prefixes of ``length`` words make the deep internal nodes of the subtree, the repeats. Digests only keep suffixes
without a twin out of the sort, so words alone decide. Each but a node's smallest document is told where its windows
start. What a block settles is not sent, so a passage of a third of all documents costs a group one entry per block.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import given_back, hash_sample, table, unused

#: Words that a task sorts and settles at once.
BLOCK = 2_000_000
#: Windows of a block that are looked at side by side.
SLICE = 1 << 17
#: Windows meant for a group: some 3 MB packed.
GROUP = 250_000
#: Words of an anchor, and frequent words with a number of their own; the first COMMON of these lead long prefixes.
ANCHOR, DICTIONARY, COMMON = 3, 60_000, 1024
#: Documents whose words the dictionary is made of; it decides sizes, never results.
DICTIONARY_ROWS = 10_000
SPELLED = 0xFFFF
_M1, _M2, _M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().split()


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M2
    x = (x ^ (x >> np.uint64(27))) * _M3
    return x ^ (x >> np.uint64(31))


def digests(codes: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """64-bit digests of the windows at ``starts``; different windows may share one."""
    h = mixed(codes.astype(np.uint64) * _M1 + _M1)
    out = np.zeros(len(starts), dtype=np.uint64)
    for i in range(0, len(starts), SLICE):
        own, at = out[i : i + SLICE], starts[i : i + SLICE]
        for j in range(length):
            own ^= h[at + j]
            own *= _M1
            own ^= own >> np.uint64(29)
    return out


def deep_nodes(codes: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(leaves, node): the windows that have an equal one, sorted by their words, and a number for each internal node of depth ``length``."""
    digest = digests(codes, starts, length)
    order = np.argsort(digest)
    digest = digest[order]
    same = digest[1:] == digest[:-1]
    del digest
    twin = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(order) else np.zeros(0, dtype=bool)
    leaves = order[twin]
    del order, twin, same
    per = 3 if not len(codes) or int(codes.max()) < 1 << 21 else 2
    bits = np.uint64(64 // per if per == 2 else 21)
    keys = []
    for j in range(0, length, per):  # several words in one integer
        key = np.zeros(len(leaves), dtype=np.uint64)
        for i in range(j, min(j + per, length)):
            key = (key << bits) | codes[starts[leaves] + i].astype(np.uint64)
        keys.append(key)
    by = np.lexsort(keys[::-1])
    leaves, keys = leaves[by], [k[by] for k in keys]
    apart = np.zeros(max(0, len(leaves) - 1), dtype=bool)  # neighbours whose common prefix is shorter
    for k in keys:
        apart |= k[1:] != k[:-1]
    node = np.concatenate([[0], np.cumsum(apart)]) if len(leaves) else np.zeros(0, dtype=np.int64)
    return leaves, node


def later_windows(codes: np.ndarray, starts: np.ndarray, doc: np.ndarray, length: int) -> np.ndarray:
    """Which windows also start in a smaller document."""
    leaves, node = deep_nodes(codes, starts, length)
    later = np.zeros(len(starts), dtype=bool)
    if len(leaves):
        first = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
        least = np.minimum.reduceat(doc[leaves], first)
        later[leaves] = doc[leaves] > least[node]
    return later


class Coder(dict):
    """Words to integers one by one: those of the dictionary have theirs, others get the next. ``numbered`` does the same for many."""

    def __init__(self, words: list[bytes]):
        super().__init__(zip(words, range(len(words)), strict=True))
        self.own = len(words)
        self.more: list[bytes] = []

    def __missing__(self, word: bytes) -> int:
        self[word] = n = self.own + len(self.more)
        self.more.append(word)
        return n

    def forget(self) -> None:
        for w in self.more:
            del self[w]
        self.more = []


def numbered(words: pa.Array, known: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """(numbers, more): words of ``known`` have their place there, others the next in the order of first use; ``more`` are these."""
    place = pc.index_in(words, value_set=known)
    new = place.is_null().to_numpy(zero_copy_only=False)
    out = place.fill_null(0).to_numpy().astype(np.int32)
    more = words.filter(pa.array(new)).dictionary_encode()
    out[new] = more.indices.to_numpy() + len(known)
    return out, more.dictionary


def rarest(key: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """The first place with the least key of the ``width`` from each of ``at``, which rise."""
    out = np.empty_like(at)
    for i in range(0, len(at), SLICE):
        own = at[i : i + SLICE]
        low = int(own[0])
        best = key[low : int(own[-1]) + width].copy()
        step = np.zeros(len(best), dtype=np.uint8 if width < 256 else np.int32)
        span = 1
        while span < width:  # least of twice as many places from those of as many
            by = min(span, width - span)
            left, right = best[:-by], best[by:]
            less = right < left
            step = np.where(less, step[by:] + step.dtype.type(by), step[:-by])
            best = np.where(less, right, left)
            span += by
        out[i : i + SLICE] = own + step[own - low]
    return out


def _spans(lengths: np.ndarray) -> np.ndarray:
    """0 to n - 1 for each of ``lengths``, joined."""
    return np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)


def frequent_words(docs: DataFrame, rows: int = DICTIONARY_ROWS, most: int = DICTIONARY) -> list[bytes]:
    """The most frequent words of at most about ``rows`` documents, most frequent first."""
    some = hash_sample(docs.where("doc_id IS NOT NULL"), "doc_id", rows).select(F.explode(F.split("text", r"[ \t-\r]+")).alias("w")).where("w <> ''")
    top = some.groupBy("w").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").limit(most)
    return [r.w.encode() for r in top.collect()]  # ``most`` rows


def bucket_column(doc: Column, buckets: int) -> Column:
    return F.pmod(F.xxhash64(doc), F.lit(buckets))


TOLD = pa.schema([("doc", pa.int64()), ("mark", pa.int64()), ("start", pa.list_(pa.int64())), ("count", pa.list_(pa.int64()))])
PACKED = pa.schema([("prefix", pa.int64()), ("blob", pa.binary()), ("doc", pa.int64()), ("mark", pa.int64()), ("runs", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int64()))])
PACKED_DDL = "prefix long, blob binary, doc long, mark long, runs array<long>, sizes array<long>"


def _planes(x: np.ndarray) -> bytes:
    """First bytes of all numbers, then second ones and so on: likes together, which packs better."""
    return x.view(np.uint8).reshape(len(x), x.itemsize).T.tobytes() if len(x) else b""


def _unplaned(raw: bytes, kind: str) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.frombuffer(raw, np.uint8).reshape(size, -1).T.copy().view(kind).ravel() if raw else np.zeros(0, dtype=kind)


_KINDS = ("<i8", "<u4", "<u4", "<i4", "<u1", "<u2", "<u4")
#: First bytes of words whose second bytes are packed together: 0, the next few, others, spelled words.
_LEADS = (0, 1, 4, SPELLED >> 8, 256)


def _word_streams(words: np.ndarray) -> list[bytes]:
    """First bytes, then second ones by the class of the first: frequent words differ in the second byte in another way than rare ones."""
    high, low = (words >> 8).astype(np.uint8), (words & 255).astype(np.uint8)
    return [high.tobytes(), *(low[(high >= i) & (high < j)].tobytes() for i, j in zip(_LEADS, _LEADS[1:], strict=False))]


def _words_of_streams(raw: bytes) -> np.ndarray:
    n = len(raw) // 2
    high, low = np.frombuffer(raw, np.uint8, n), np.frombuffer(raw, np.uint8, n, n)
    out, at = high.astype(np.int64) << 8, 0
    for i, j in zip(_LEADS, _LEADS[1:], strict=False):
        own = np.flatnonzero((high >= i) & (high < j))
        out[own] |= low[at : at + len(own)]
        at += len(own)
    return out


def _steps_back(spelled: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(steps, by): for each use of a spelled word 0 if it is new, else how many new words ago it was; and the words in the order of first use."""
    first = np.unique(spelled, return_index=True)[1]
    by = np.argsort(first)
    number = np.empty(len(by), dtype=np.int64)
    number[by] = np.arange(len(by))
    new = np.zeros(len(spelled), dtype=np.int64)
    new[first] = 1
    return np.cumsum(new) - new - number[spelled], by


def packed(docs: np.ndarray, marks: np.ndarray, owner: np.ndarray, start: np.ndarray, count: np.ndarray, words: np.ndarray, spelled: np.ndarray, vocabulary: list[bytes]) -> bytes:
    """Runs of one group and block, compressed, each kind of number in blocks of its own; documents and owners rise."""
    steps, by = _steps_back(spelled)
    rising = np.diff(docs, prepend=np.int64(0)), marks, np.diff(owner, prepend=0), np.diff(start, prepend=0), count, words, steps
    streams = [[_planes(np.ascontiguousarray(x.astype(k)))] for x, k in zip(rising, _KINDS, strict=True)] + [[b" ".join([vocabulary[i] for i in by.tolist()])]]
    streams[5] = _word_streams(words)
    head = np.array([sum(map(len, x)) for x in streams], dtype="<u8").tobytes()
    flat = [head, *(x for part in streams for x in part if x)]
    maker = zstandard.ZstdCompressor(level=3).compressobj(size=sum(map(len, flat)))
    out = []
    for x in flat:
        out += [maker.compress(x), maker.flush(zstandard.COMPRESSOBJ_FLUSH_BLOCK)]
    return b"".join([*out, maker.flush()])


def unpacked(blob: bytes) -> list:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    ends = np.cumsum(np.frombuffer(raw, "<u8", 8).astype(np.int64)) + 64
    parts = [raw[i:j] for i, j in zip([64, *ends[:-1].tolist()], ends.tolist(), strict=True)]
    x = [_words_of_streams(r) if i == 5 else _unplaned(r, k).astype(np.int64) for i, (r, k) in enumerate(zip(parts[:7], _KINDS, strict=True))]
    new = (x[6] == 0).astype(np.int64)
    spelled = np.cumsum(new) - new - x[6]
    return [np.cumsum(x[0]), x[1], np.cumsum(x[2]), np.cumsum(x[3]), x[4], x[5], spelled, parts[7].split(b" ") if parts[7] else []]


def mark_of(raw: bytes) -> int:
    """32 bits that tell texts of one id apart."""
    return xxhash.xxh3_64_intdigest(raw) & 0xFFFFFFFF


def _told_rows(doc: np.ndarray, mark: np.ndarray, start: np.ndarray) -> Iterator[tuple]:
    """(doc, mark, starts, counts): the told windows of each document as runs."""
    if not len(doc):
        return
    order = np.lexsort((start, mark, doc))
    doc, mark, start = doc[order], mark[order], start[order]
    own = np.concatenate([[True], (doc[1:] != doc[:-1]) | (mark[1:] != mark[:-1])])
    first = np.flatnonzero(own | np.concatenate([[True], start[1:] != start[:-1] + 1]))
    count = np.diff(np.append(first, len(doc)))
    edge = np.append(np.flatnonzero(own[first]), len(first))
    for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        yield int(doc[first[i]]), int(mark[first[i]]), start[first[i:j]], count[i:j]


def _batches(rows: Iterator[dict], schema: pa.Schema, size: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    held, held_bytes = [], 0

    def batch() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r.get(f.name) for r in held], f.type) for f in schema], schema=schema)

    for row in rows:
        held.append(row)
        held_bytes += 64 + sum(getattr(x, "nbytes", len(x) if isinstance(x, bytes) else 0) for x in row.values())
        if held_bytes > size:
            yield batch()
            held, held_bytes = [], 0
    yield batch()


def repeated_windows(docs: DataFrame, length: int, prefix_bits: int, words: list[bytes]) -> DataFrame:
    """(doc, mark, start, count): runs of windows that also start in a smaller document, by document and digest of its text; may have several rows each."""
    groups = 1 << prefix_bits
    anchor = min(ANCHOR, length)
    known = np.array([xxhash.xxh3_64_intdigest(w) for w in words], dtype=np.uint64)
    dictionary = pa.array(words, pa.large_binary())

    def settled(codes: np.ndarray, size: np.ndarray, docs_of: np.ndarray, marks: np.ndarray, more: list[bytes]) -> Iterator[dict]:
        """Told windows of a block, and its other windows as packed runs by group."""
        owner = np.repeat(np.arange(len(size), dtype=np.int32), size)
        at = _spans(size).astype(np.int32)
        starts = np.flatnonzero(at + length <= size[owner])
        if not len(starts):
            return
        gone = later_windows(codes, starts, docs_of[owner[starts]], length)
        for d, m, s, n in _told_rows(docs_of[owner[starts[gone]]], marks[owner[starts[gone]]], at[starts[gone]]):
            yield {"doc": d, "mark": m, "runs": s, "sizes": n}
        starts = starts[~gone]
        if not len(starts):
            return
        own = np.concatenate([known, np.array([xxhash.xxh3_64_intdigest(w) for w in more], dtype=np.uint64)])[codes]
        n = len(codes) - anchor + 1
        gram, rank = np.zeros(n, dtype=np.uint64), np.zeros(n, dtype=np.int32)
        for j in range(anchor):
            gram = mixed((gram ^ own[j : j + n]) * _M1 + np.uint64(j + 1))
            rank = np.maximum(rank, codes[j : j + n])
        common = rank < COMMON
        # rarest first: sixteen classes of rank, then by hash
        rarity = np.minimum(15, np.where(rank >= len(words), 16, np.log2(rank + 1.0))).astype(np.uint8)
        del rank
        order_key = gram >> np.uint64(4)
        order_key |= (15 - rarity).astype(np.uint64) << np.uint64(60)
        del rarity
        place = rarest(order_key, starts, length - anchor + 1)
        del order_key
        alone = common[place]
        deal = gram[place]
        del gram, common
        if alone.any():
            whole = own[starts[alone]].copy()
            for j in range(1, length):
                whole = mixed((whole ^ own[starts[alone] + j]) * _M1)
            deal[alone] = whole
        new = np.concatenate([[True], (starts[1:] != starts[:-1] + 1) | (place[1:] != place[:-1]) | alone[1:] | (owner[starts[1:]] != owner[starts[:-1]])])
        first = np.flatnonzero(new)
        count = np.diff(np.append(first, len(starts)))
        group = (deal[first] >> np.uint64(64 - prefix_bits)).astype(np.int64) if prefix_bits else np.zeros(len(first), dtype=np.int64)
        by = np.argsort(group.astype(np.uint16) if prefix_bits <= 16 else group, kind="stable")
        first, count, group = first[by], count[by], group[by]
        edge = np.append(np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])), len(group))
        for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            s, c = starts[first[i:j]], count[i:j]
            flat = codes[np.repeat(s, c + length - 1) + _spans(c + length - 1)]
            rare = flat >= len(words)
            names, spelled = np.unique(flat[rare], return_inverse=True)
            held, mine = np.unique(owner[s], return_inverse=True)
            by_doc = np.argsort(docs_of[held], kind="stable")
            place = np.empty(len(held), dtype=np.int64)
            place[by_doc] = np.arange(len(held))
            mine = place[mine]
            if (np.diff(mine) < 0).any():  # documents of a block in another order than that of their ids
                runs = np.argsort(mine, kind="stable")
                lengths = c + length - 1
                begin = np.cumsum(lengths) - lengths
                moved = np.repeat(begin[runs], lengths[runs]) + _spans(lengths[runs])
                flat, s, c, mine = flat[moved], s[runs], c[runs], mine[runs]
                rare = flat >= len(words)
                names, spelled = np.unique(flat[rare], return_inverse=True)
            words16 = np.where(rare, SPELLED, flat)
            yield {"prefix": int(group[i]), "blob": packed(docs_of[held][by_doc], marks[held][by_doc], mine, at[s], c, words16, spelled, [more[x - len(words)] for x in names.tolist()])}

    def leaves(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        found, size, owners, marks, held = [], [], [], [], 0

        def block() -> Iterator[dict]:
            codes, more = numbered(pa.concat_arrays(found), dictionary)
            found.clear()
            pa.default_memory_pool().release_unused()
            yield from settled(codes, np.array(size), np.array(owners, dtype=np.int64), np.array(marks, dtype=np.int64), more.to_pylist())

        for b in batches:
            for d, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                raw = (text.as_py() or "").encode()
                own = raw.split()
                if len(own) < length:
                    continue
                found.append(pa.array(own, pa.large_binary()))
                size.append(len(own))
                owners.append(d)
                marks.append(mark_of(raw))
                held += len(own)
                if held >= BLOCK:
                    yield from block()
                    size.clear(), owners.clear(), marks.clear()
                    held = 0
        if held:
            yield from block()

    def subtree(blobs: list[bytes]) -> Iterator[dict]:
        """Told windows of one group."""
        parts, docs_of, marks, owner, start, count, vocabularies = [], [], [], [], [], [], []
        seen = names = 0
        for blob in blobs:
            own_docs, own_marks, own, at, n, flat, spelled, vocabulary = unpacked(blob)
            flat[flat == SPELLED] = SPELLED + names + spelled
            vocabularies.append(pa.array(vocabulary, pa.large_binary()))
            names += len(vocabulary)
            parts.append(flat)
            docs_of.append(own_docs)
            marks.append(own_marks)
            owner.append(own + seen)
            start.append(at)
            count.append(n)
            seen += len(own_docs)
        spelt = pa.concat_arrays(vocabularies).dictionary_encode().indices.to_numpy().astype(np.int64) + SPELLED  # one number a word in all blobs
        for flat in parts:
            rare = flat >= SPELLED
            flat[rare] = spelt[flat[rare] - SPELLED]
        codes, owner, start, count = (np.concatenate(x) for x in (parts, owner, start, count))
        docs_of, marks = np.concatenate(docs_of).astype(np.int64), np.concatenate(marks).astype(np.int64)
        span = count + length - 1
        begin = np.cumsum(span) - span
        starts = np.repeat(begin, count) + _spans(count)
        own, at = np.repeat(owner, count), np.repeat(start, count) + _spans(count)
        gone = later_windows(codes, starts, docs_of[own], length)
        for d, m, s, n in _told_rows(docs_of[own[gone]], marks[own[gone]], at[gone]):
            yield {"doc": d, "mark": m, "start": s, "count": n}

    def subtrees(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        """Rows come sorted by prefix; told windows of blocks have none and pass through."""
        group, held = None, []
        for b in batches:
            for i in range(b.num_rows):
                prefix = b.column("prefix")[i].as_py()
                if prefix is None:
                    yield {"doc": b.column("doc")[i].as_py(), "mark": b.column("mark")[i].as_py(), "start": b.column("runs")[i].values.to_numpy(), "count": b.column("sizes")[i].values.to_numpy()}
                    continue
                if prefix != group and held:
                    yield from subtree(held)
                    held = []
                group = prefix
                held.append(b.column("blob")[i].as_py())
        if held:
            yield from subtree(held)

    made = docs.where("doc_id IS NOT NULL").mapInArrow(lambda it: given_back(_batches(leaves(it), PACKED, 8 << 20)), PACKED_DDL)
    dealt = made.repartition(F.coalesce("prefix", -1 - F.pmod(F.xxhash64("doc"), F.lit(groups)))).sortWithinPartitions("prefix")
    return dealt.mapInArrow(lambda it: given_back(_batches(subtrees(it), TOLD, 8 << 20)), "doc long, mark long, start array<long>, count array<long>")


def remove_repeats(docs: DataFrame, length: int = 13, id_col: str = "doc_id", text_col: str = "text", prefix_bits: int | None = None) -> DataFrame:
    """``docs`` with n_words, n_removed and kept_text: its words but those in a window of ``length`` words that a smaller id has too.

    Words are runs without ASCII white space. Windows are judged on the input. Kept words are joined by one space.
    A null or empty text has no words and kept_text "". Rows of one id judge each other never; a row whose id is
    null neither loses words nor makes others lose any. Columns named n_words, n_removed or kept_text are replaced.
    ``prefix_bits`` (default: from the table's size) sets the number of groups.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    if prefix_bits is None:
        windows = (slim.agg(F.sum(F.octet_length("text"))).first()[0] or 0) / 6
        prefix_bits = max(8, int(np.ceil(np.log2(max(1.0, windows / GROUP)))))
    told = repeated_windows(slim, length, prefix_bits, frequent_words(slim))
    rest = docs.drop("n_words", "n_removed", "kept_text")
    names = rest.columns
    schema = rest.select("*", F.lit(0).cast("long").alias("n_words"), F.lit(0).cast("long").alias("n_removed"), F.lit("").alias("kept_text")).schema
    own = [unused(rest, n) for n in ("told_doc", "told_mark", "told_start", "told_count", "told_bucket")]
    buckets = max(1, 1 << prefix_bits)
    heard = told.toDF(*own[:4]).withColumn(own[4], bucket_column(F.col(own[0]), buckets))
    key = F.col(id_col).cast("long")
    placed = rest.where(key.isNotNull()).withColumn(own[4], bucket_column(key, buckets))
    both = heard.unionByName(placed, allowMissingColumns=True).select(*names, *own)
    both = both.repartition(own[4]).sortWithinPartitions(F.col(own[4]), F.col(own[0]).asc_nulls_last())

    def kept(texts: pa.Array, ids: list, cut: dict) -> list[pa.Array]:
        n, gone, left = [], [], []
        for d, text in zip(ids, texts, strict=True):
            raw = (text.as_py() or "").encode()
            words = raw.split()
            n.append(len(words))
            found = cut.get((int(d), mark_of(raw))) if cut and d is not None else None
            if found:
                change = np.zeros(len(words) + 1, dtype=np.int64)
                for start, count in found:
                    np.add.at(change, start, 1)
                    np.add.at(change, start + count + length - 1, -1)
                words = list(compress(words, (np.cumsum(change[:-1]) == 0).tolist()))
            gone.append(n[-1] - len(words))
            left.append(b" ".join(words).decode())
        return [pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(left, pa.string())]

    out_names = [*names, "n_words", "n_removed", "kept_text"]
    at_id, at_text = names.index(id_col), names.index(text_col)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by bucket, what a bucket is told before its documents, which pass one by one."""
        bucket, cut = None, {}
        for b in batches:
            at = b.column(own[4]).to_numpy()
            is_doc = b.column(own[0]).is_null().to_numpy(zero_copy_only=False)
            edge = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])) if len(at) else np.zeros(0, dtype=np.int64)
            columns: list[list[pa.Array]] = []
            for i, j in zip(edge.tolist(), [*edge[1:].tolist(), len(at)], strict=True):
                if at[i] != bucket:
                    bucket, cut = at[i], {}
                mid = i + int((~is_doc[i:j]).sum())
                for r in range(i, mid):
                    cut.setdefault((b.column(own[0])[r].as_py(), b.column(own[1])[r].as_py()), []).append((b.column(own[2])[r].values.to_numpy(), b.column(own[3])[r].values.to_numpy()))
                part = b.slice(mid, j - mid)
                columns.append([*part.columns[: len(names)], *kept(part.column(at_text), part.column(at_id).to_pylist(), cut)])
            for c in columns:
                if len(c[0]):
                    yield pa.RecordBatch.from_arrays(c, out_names)

    def alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, *kept(b.column(at_text), [None] * b.num_rows, {})], out_names)

    return both.mapInArrow(lambda it: given_back(work(it)), schema).unionByName(rest.where(key.isNull()).mapInArrow(alone, schema))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document the words it has, those removed and a digest of those kept; see ``remove_repeats``."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return remove_repeats(docs).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))

OP3_SQL = r"""
WITH w AS (SELECT doc_id, row_number() OVER () AS rid, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents),
win AS (SELECT rid, doc_id, i, array_to_string(words[i:i + 12], ' ') AS gram FROM w, unnest(range(1, len(words) - 11)) AS t(i)),
least_doc AS (SELECT gram, min(doc_id) AS d FROM win GROUP BY gram),
gone AS (SELECT DISTINCT rid, i + k AS p FROM win JOIN least_doc USING (gram), unnest(range(0, 13)) AS u(k) WHERE d < doc_id),
per AS (SELECT rid, list(p) AS ps FROM gone GROUP BY rid)
SELECT doc_id, len(words)::BIGINT AS n_words, coalesce(len(ps), 0)::BIGINT AS n_removed,
  sha256(array_to_string(CASE WHEN ps IS NULL THEN words ELSE list_filter(words, lambda x, i: NOT list_contains(ps, i)) END, ' ')) AS kept_sha256
FROM w LEFT JOIN per USING (rid)
"""
