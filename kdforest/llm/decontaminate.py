"""Benchmark decontamination: a prefix-filtered join of item windows with document words, on DataFrame functions only.

A window of an item occurs in a document only if all its words do, so its prefix is one word: the rarest, by
counts over all documents of the words that items use. Documents are searched for these words alone (a bit table
of fixed size drops most others before rows are made); a found word gives its position and the words around it.
Joined with the windows of that word, a candidate passes the length and positional bounds and is verified word
by word.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kdforest.llm.common import maybe_broadcast, table, unused, written

WINDOW = 13
#: Everything but ASCII digits, letters in lower case and non-ASCII.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Bits of the table that words pass before rows are made of them, at most.
MOST_BITS = 1 << 20


def words_of(text: Column) -> Column:
    low = F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.array_remove(F.split(F.coalesce(low, F.lit("")), BETWEEN), "")


def bit_test(words: DataFrame, name: str) -> Callable[[Column], Column]:
    """A test whether a word may be in column ``name`` of ``words``: a bit table of at most MOST_BITS, no false negatives."""
    bits = min(MOST_BITS, max(1 << 10, 1 << (256 * words.count()).bit_length()))
    at = F.pmod(F.xxhash64(name), F.lit(bits))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (at % 64).cast("int"))
    cells = words.groupBy(F.floor(at / 64).cast("int").alias("cell")).agg(F.bit_or(bit).alias("v")).collect()  # MOST_BITS / 64 rows at most
    held = {r.cell: r.v for r in cells}
    ones = F.expr(f"array({', '.join(f'{held.get(i, 0)}L' for i in range(bits // 64))})")

    def test(word: Column) -> Column:
        h = F.xxhash64(word).bitwiseAND(F.lit(bits - 1).cast("long"))
        return F.getbit(F.get(ones, F.shiftright(h, 6).cast("int")), h.bitwiseAND(F.lit(63).cast("long")).cast("int")) == 1

    return test


def item_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(toks, items): each distinct window with the ids of its items; an item of fewer words is one window, of none none."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item"), words_of(F.col("text")).alias("w")).where(F.size("w") > 0)
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.size("w") - F.lit(window - 1), F.lit(1))))
    cut = items.select("item", "w", at.alias("at")).select("item", F.slice("w", F.col("at"), window).alias("toks"))
    return cut.groupBy("toks").agg(F.collect_set("item").alias("items"))


def occurrences(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, mark, first, last, items): places of item windows in documents; positions count words from 0.

    ``mark`` is a digest of the text, which tells rows of one id apart.
    """
    windows = written(item_windows(benchmark, window), "windows")
    used = windows.select(F.explode("toks").alias("tok")).distinct()
    slim = docs.select(F.col("doc_id"), F.xxhash64("text").alias("mark"), words_of(F.col("text")).alias("words"))
    seen = slim.select(F.explode("words").alias("tok"))
    counts = seen.where(bit_test(used, "tok")(F.col("tok"))).groupBy("tok").agg(F.count("*").alias("df"))
    placed = windows.select("toks", "items", F.posexplode("toks").alias("off", "tok")).join(counts, "tok", "left")
    rare = Window.partitionBy("toks").orderBy(F.coalesce("df", F.lit(0)), "tok", "off")
    prefix = placed.withColumn("r", F.row_number().over(rare)).where("r = 1 AND df > 0").select("tok", "off", "toks", "items")
    prefix = written(prefix, "prefix")
    may = bit_test(prefix.select("tok").distinct(), "tok")
    placed_words = F.transform("words", lambda w, i: F.when(may(w), F.struct(i.alias("pos"), w.alias("tok"))))
    hits = slim.select("doc_id", "mark", "words", F.explode(F.filter(placed_words, lambda x: x.isNotNull())).alias("h"))
    begin = F.greatest(F.col("h.pos") - F.lit(window - 1), F.lit(0))
    around = hits.select("doc_id", "mark", F.col("h.tok").alias("tok"), F.col("h.pos").alias("pos"), F.size("words").alias("n"), begin.alias("begin"), F.slice("words", begin + 1, 2 * window - 1).alias("ctx"))
    both = around.join(maybe_broadcast(prefix), "tok")
    first, length = F.col("pos") - F.col("off"), F.size("toks")
    bounded = both.where((first >= 0) & (first + length <= F.col("n")))
    real = bounded.where(F.slice("ctx", first - F.col("begin") + 1, length) == F.col("toks"))
    return real.select("doc_id", "mark", first.alias("first"), (first + length - 1).alias("last"), "items")


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20) -> DataFrame:
    """Per row of ``docs``: doc_id, n_words, n_hit, n_items, items_sha256, contaminated and the text's mark.

    A word inside any occurrence of an item's window is hit; a row is contaminated if at least one word in
    ``share`` is. A null or empty text has no words and is clean, items without words have no windows; items
    with a null id hit words but are not listed. Repeated rows get equal results. Other columns are ignored.
    """
    places = occurrences(docs, benchmark, window)
    spans = places.groupBy("doc_id", "mark").agg(F.array_sort(F.collect_set(F.struct("first", "last"))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    zero = F.struct(F.lit(-1).alias("to"), F.lit(0).alias("n"))

    def cover(acc: Column, s: Column) -> Column:
        new = F.greatest(s["last"] - F.greatest(s["first"] - 1, acc["to"]), F.lit(0))
        return F.struct(F.greatest(acc["to"], s["last"]).alias("to"), (acc["n"] + new).alias("n"))

    hit = spans.select("doc_id", "mark", F.aggregate("spans", zero, cover, lambda acc: acc["n"]).cast("long").alias("hit"), F.size("items").cast("long").alias("listed"), F.sha2(F.concat_ws(",", "items"), 256).alias("digest"))
    base = docs.select(F.col("doc_id"), F.xxhash64("text").alias("mark"), F.size(words_of(F.col("text"))).cast("long").alias("n_words"))
    joined = base.join(hit.withColumnsRenamed({"doc_id": "_d", "mark": "_m"}), F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("mark") == F.col("_m")), "left")
    n_hit = F.coalesce("hit", F.lit(0).cast("long"))
    return joined.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.coalesce("listed", F.lit(0).cast("long")).alias("n_items"), F.coalesce("digest", F.sha2(F.lit(""), 256)).alias("items_sha256"),
        ((n_hit > 0) & (F.lit(share) * n_hit >= F.col("n_words"))).alias("contaminated"), "mark",
    )


def decontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20) -> DataFrame:
    """``docs`` without contaminated rows; every column stays."""
    d, m = unused(docs, "bad_id"), unused(docs, "bad_mark")
    bad = contamination(docs, benchmark, window, share).where("contaminated").select(F.col("doc_id").alias(d), F.col("mark").alias(m)).distinct()
    return docs.join(bad, F.col("doc_id").eqNullSafe(F.col(d)) & F.xxhash64("text").eqNullSafe(F.col(m)), "left_anti")


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far each document repeats windows of benchmark items; see ``contamination``."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return contamination(docs, table(spark, sf_dir, "benchmark")).drop("mark")


OP9_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, least(len(w), 13) AS k, array_to_string(w[i:i + least(len(w), 13) - 1], ' ') AS gram FROM b, unnest(range(1, greatest(len(w) - 11, 2))) AS t(i) WHERE len(w) > 0),
ks AS (SELECT DISTINCT k FROM win),
occ AS (SELECT rid, i, ks.k, array_to_string(w[i:i + ks.k - 1], ' ') AS gram FROM d, ks, unnest(range(1, len(w) - ks.k + 2)) AS t(i)),
hit AS (SELECT rid, i, k, item_id FROM occ JOIN win USING (k, gram)),
words_hit AS (SELECT rid, count(DISTINCT i + j) AS n FROM hit, unnest(range(0, k)) AS u(j) GROUP BY rid),
items AS (SELECT rid, count(*) AS n, string_agg(item, ',' ORDER BY item) AS s FROM (SELECT DISTINCT rid, item_id::VARCHAR AS item FROM hit) GROUP BY rid)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(h.n, 0)::BIGINT AS n_hit, coalesce(x.n, 0)::BIGINT AS n_items, sha256(coalesce(s, '')) AS items_sha256,
  coalesce(h.n, 0) > 0 AND 20 * coalesce(h.n, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words_hit h USING (rid) LEFT JOIN items x USING (rid)
"""
