"""Packing of tokenised documents into fixed windows by the sum-of-squares rule.

Each task tokenises its documents as it reads them and packs them online, so no rows are shuffled and a task
holds only its partly filled windows. A document is its token ids and a closing id. Whole windows of it are
filled at once; the rest goes to the fill level for which the sum of squared counts of partly filled windows,
kept in a level array, becomes smallest. When a task ends, its fullest windows stay as they are and are topped up with
pieces cut from the emptiest ones; what is left of those goes to a few windows whose lengths are powers of two, which
take no padding.
"""

from __future__ import annotations

import functools
import json
import zlib
from array import array
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import table

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Pieces of a byte-level tokeniser: fixed pattern of the public vocabulary format.
PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: The id that ends each document.
CLOSING = array("I", [0]).tobytes()


def text_encoder(path: str) -> Callable[[str], list[int]]:
    """Token ids of a text as the tokeniser file says.

    A plain byte-level file whose ids follow its merges is run by a faster library with the same merges (tests
    compare the two), any other by the tokeniser itself. The name of a special token in a text is that token, as the
    tokeniser has it.
    """
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    spec = json.loads(tokenizer.to_str())
    pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
    plain = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not spec.get("normalizer") and model["type"] == "BPE"
    added = spec["added_tokens"]
    plain = plain and all(t["special"] and not (t["lstrip"] or t["rstrip"] or t["single_word"]) for t in added)
    if plain and (ranks := byte_ranks(model["vocab"], model["merges"], {t["content"] for t in added})):
        import tiktoken

        names = {t["content"]: t["id"] for t in added}
        fast = tiktoken.Encoding("bytes", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=names)
        return lambda text: fast.encode(text, allowed_special="all") if any(n in text for n in names) else fast.encode_ordinary(text)
    return lambda text: tokenizer.encode(text, add_special_tokens=False).ids


def byte_ranks(vocab: dict[str, int], merges: list, added: set[str]) -> dict[bytes, int]:
    """Ranks by byte string of a byte-level vocabulary; empty if its ids don't rise with its merges."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]  # bytes shown as themselves; the others follow from 256 on
    to_byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(shown))}
    pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
    made = [vocab[a + b] for a, b in pairs]
    single = {c: vocab[c] for c in to_byte if c in vocab}
    if made != sorted(made) or len(single) < 256 or len(single) + len(set(made)) + len(added & vocab.keys()) != len(vocab):
        return {}
    return {bytes(to_byte[c] for c in t): i for t, i in vocab.items() if t not in added}


@functools.cache
def encoder(path: str) -> Callable[[str], list[int]]:
    """One for each worker process, kept from task to task."""
    return text_encoder(path)


class LevelPacker:
    """Windows of ``size`` ids. ``add`` and ``finish`` return closed windows: lists of (document, start, ids)."""

    def __init__(self, size: int = 1024):
        self.size = size
        self.count = np.zeros(size + 1, dtype=np.int64)  # partly filled windows at each level; level 0 and full count none
        self.open: dict[int, list[list[tuple]]] = {}
        self.kept = self.parted = 0  # open windows at the end that stayed, and that were cut up

    def level_for(self, n: int) -> int:
        """The level whose windows take ``n`` more ids with the smallest sum of squared counts; 0 opens a window."""
        top = self.size - n
        levels = np.flatnonzero(self.count[: top + 1])  # level 0 is always empty
        after = 2 * self.count + 1
        after[self.size] = 0
        fresh = after[n]
        if not len(levels):
            return 0
        change = after[levels + n] - (2 * self.count[levels] - 1)
        best = len(change) - 1 - int(np.argmin(change[::-1]))  # of equal changes the fullest
        return int(levels[best]) if change[best] <= fresh else 0

    def add(self, doc: tuple, ids: np.ndarray) -> list[list[tuple]]:
        whole = len(ids) // self.size * self.size
        closed = [[(doc, i, ids[i : i + self.size])] for i in range(0, whole, self.size)]
        if n := len(ids) - whole:
            level = self.level_for(n)
            window = self.open[level].pop() if level else []
            if level:
                self.count[level] -= 1
            window.append((doc, whole, ids[whole:].copy()))
            if level + n == self.size:
                closed.append(window)
            else:
                self.open.setdefault(level + n, []).append(window)
                self.count[level + n] += 1
        return closed

    def finish(self) -> list[list[tuple]]:
        """Windows of a power of two stay; of the others the fullest are topped up from the emptiest, whose last ids go to powers of two."""
        closed, partly = [], []
        for level in sorted(self.open, reverse=True):
            for window in self.open[level]:
                if level & (level - 1) == 0:
                    closed.append(window)
                else:
                    partly.append((level, window))
        total = sum(level for level, _ in partly)
        stay = total // self.size
        self.kept, self.parted = stay, len(partly) - stay
        rest = [piece for _, window in partly[stay:] for piece in window]
        rest.reverse()

        def take(room: int) -> list[tuple]:
            out = []
            while room:
                doc, start, ids = rest.pop()
                k = min(room, len(ids))
                out.append((doc, start, ids[:k]))
                if k < len(ids):
                    rest.append((doc, start + k, ids[k:]))
                room -= k
            return out

        closed += [window + take(self.size - level) for level, window in partly[:stay]]
        left = total - stay * self.size
        while left:
            room = 1 << (left.bit_length() - 1)
            closed.append(take(room))
            left -= room
        self.open, self.count = {}, np.zeros_like(self.count)
        return closed


def pack(docs: DataFrame, tokenizer_path: str, size: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece of a document in a window of ``size`` ids.

    A null text is empty: its document is the closing id alone. Null and repeated ids are packed like any other
    row. An empty table gives no rows; columns besides the two are ignored. Windows are those of one task;
    ``sequence_id`` is the task's partition and a running number, so a task that runs again gives the same ids.
    ``size`` is a power of two of 2 to 65536.
    """
    if size < 2 or size & (size - 1) or size > 65536:
        raise ValueError("size is a power of two of 2 to 65536")

    def tasks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, packer = encoder(tokenizer_path), LevelPacker(size)
        part, n = TaskContext.get().partitionId(), 0
        rows: list[tuple] = []

        def take(windows: list) -> None:
            nonlocal n
            for window in windows:
                at = 0
                for (doc, total), start, ids in window:
                    rows.append((doc, start, len(ids), zlib.crc32(ids.tobytes()), total, (part << 36) + n, at))
                    at += len(ids)
                n += 1

        def flush() -> pa.RecordBatch:
            cols = list(zip(*rows, strict=True)) if rows else [()] * 7
            out = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], [c.split()[0] for c in SCHEMA.split(", ")])
            rows.clear()
            return out

        for batch in batches:
            known: dict[str | None, bytes] = {}  # copies inside a batch are encoded once
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if text not in known:
                    known[text] = array("I", encode(text or "")).tobytes() + CLOSING
                ids = np.frombuffer(known[text], dtype="<u4")
                take(packer.add((doc, len(ids)), ids))
                if len(rows) >= 20_000:
                    yield flush()
        take(packer.finish())
        yield flush()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tasks, SCHEMA)


def padding(pieces: DataFrame, size: int = 1024) -> DataFrame:
    """One row: windows, ids in them and padding ids (none in a window whose length is a power of two)."""
    used = pieces.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    pad = F.when(F.col("used").bitwiseAND(F.col("used") - 1) == 0, 0).otherwise(F.lit(size) - F.col("used"))
    return used.agg(F.count("*").alias("sequences"), F.sum("used").alias("ids"), F.sum(pad).alias("padding"))


def op10_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pieces of all documents in windows of 1024 ids; see ``pack``."""
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
