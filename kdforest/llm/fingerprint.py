"""Document fingerprints as invertible Bloom lookup sketches, on DataFrame functions only.

A text is the set of its paragraphs, cut further at sentence ends. Each has a 32-bit digest, entered into one cell
of each of three subtables: the cell holds a signed count, the XOR of digests and the XOR of 16-bit checks. The
difference of two sketches holds only the digests that one side has; peeling takes a cell with a single digest,
removes it from its other cells, and goes on. A pair is peeled in a small folded table first, then in the full
one; pairs that stay hidden are sketched again from their digests with larger tables, and so on, until every differing digest
is known. A larger table is dealt in parts by another hash of the digest, so that each part is peeled by itself. Sketches are
made in their rows; texts travel once, to meet the next.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kdforest.llm.common import table, written

TABLES = 3
CELLS = 16  # of a subtable
FOLDED = 4
PART_CELLS, PART_DIGESTS, MOST_PARTS = 4, 5, 64  # of a larger table: cells of a part's subtable, digests of both texts meant for it, parts that one is dealt into at a time
RETRIES = 8
#: Pieces end with a line or a sentence.
PIECE_ENDS = r"\n+|(?<=[.!?])[ ]+"


def digests(text: Column) -> Column:
    """The distinct digests of a text's pieces, as signed integers."""
    return F.array_distinct(F.transform(F.array_remove(F.split(text, PIECE_ENDS), ""), lambda p: signed(F.xxhash64(p).bitwiseAND(F.lit(0xFFFFFFFF)))))


def signed(key: Column) -> Column:
    return (key.bitwiseXOR(F.lit(0x80000000)) - F.lit(0x80000000).cast("long")).cast("int")


def unsigned(digest: Column) -> Column:
    return digest.cast("long").bitwiseAND(F.lit(0xFFFFFFFF))


def mixed(key: Column) -> Column:
    """Decides a digest's sign (bit 60), its check (bits 32 on) and its cells: bits 0, 8 and 16 on in tables of up to 256 cells."""
    return F.xxhash64(F.lit(7), key)


def cell_of(h: Column, t: int, cells: int) -> Column:
    """The cell in subtable ``t``; that of a table with fewer cells has its low bits. Larger tables hash once more."""
    source = F.shiftright(h, 8 * t) if cells <= 256 else F.xxhash64(F.lit(t), h)
    return source.bitwiseAND(F.lit(cells - 1).cast("long")) + t * cells


def sign_of(h: Column) -> Column:
    return F.lit(1).cast("long") - 2 * F.shiftright(h, 60).bitwiseAND(F.lit(1).cast("long"))


def check_of(h: Column) -> Column:
    return F.shiftright(h, 32).bitwiseAND(F.lit(0xFFFF).cast("long"))


def hashed(keys: Column, cells: int = CELLS) -> Column:
    """Each digest with its count, check and cells."""

    def one(key: Column) -> Column:
        k = unsigned(key)
        h = mixed(k)
        return F.struct(k.alias("k"), sign_of(h).alias("c"), check_of(h).alias("x"), F.array(*[cell_of(h, t, cells) for t in range(TABLES)]).alias("at"))

    return F.transform(keys, one)


def sketch(entries: Column, cells: int = CELLS) -> Column:
    """The cells (c, k, x) of ``hashed`` digests, made in their row."""
    zero = F.lit(0).cast("long")
    empty = F.struct(zero.alias("c"), zero.alias("k"), zero.alias("x"))
    every = F.sequence(F.lit(0).cast("long"), F.lit(TABLES * cells - 1).cast("long"))

    def merged(acc: Column, e: Column) -> Column:
        return F.struct((acc["c"] + e["c"]).alias("c"), acc["k"].bitwiseXOR(e["k"]).alias("k"), acc["x"].bitwiseXOR(e["x"]).alias("x"))

    def cells_of(own: Column) -> Column:
        return F.transform(every, lambda i: F.aggregate(F.filter(own, lambda e: F.array_contains(e["at"], i)), empty, merged))

    return F.get(F.transform(F.array(entries), cells_of), F.lit(0))  # entries are computed once, not once a cell


def as_text(cells: Column, n: Column) -> Column:
    """The number of pieces and each cell's count, digests and checks in hexadecimal digits."""

    def cell(z: Column) -> Column:  # 16 bits of count, 32 of digests, 16 of checks
        whole = F.shiftleft(z["c"], 48).bitwiseOR(F.shiftleft(z["k"], 16)).bitwiseOR(z["x"])
        return F.lpad(F.hex(whole), 16, "0")

    return F.lower(F.concat(F.lpad(F.hex(n.cast("long")), 8, "0"), F.array_join(F.transform(cells, cell), "")))


def subtracted(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda p, q: F.struct((p["c"] - q["c"]).alias("c"), p["k"].bitwiseXOR(q["k"]).alias("k"), p["x"].bitwiseXOR(q["x"]).alias("x")))


def folded(cells: Column, size: int, to: int) -> Column:
    """Subtables of ``size`` cells as such of ``to``: cells are chosen by the low bits of a hash."""
    parts = []
    for t in range(TABLES):
        for i in range(to):
            same = [F.get(cells, F.lit(t * size + j)) for j in range(i, size, to)]
            c, k, x = same[0]["c"], same[0]["k"], same[0]["x"]
            for z in same[1:]:
                c, k, x = c + z["c"], k.bitwiseXOR(z["k"]), x.bitwiseXOR(z["x"])
            parts.append(F.struct(c.alias("c"), k.alias("k"), x.alias("x")))
    return F.array(*parts)


def peeled(cells: Column, size: int, rounds: int = 16) -> Column:
    """The digests (key, side) in a difference, side 1 for the first sketch and -1 for the second; null if some stay hidden."""

    def pure(z: Column, i: Column) -> Column:
        h = mixed(z["k"])
        at = [cell_of(h, t, size) for t in range(TABLES)]
        right = (F.abs(z["c"]) == 1) & (check_of(h) == z["x"]) & (at[0].eqNullSafe(i) | at[1].eqNullSafe(i) | at[2].eqNullSafe(i))
        return F.when(right, F.struct(z["k"].alias("key"), (z["c"] * sign_of(h)).alias("side"), z["c"].alias("c"), z["x"].alias("x"), at[0].alias("p"), at[1].alias("q"), at[2].alias("r")))

    def pures(cells: Column) -> Column:
        return F.array_distinct(F.filter(F.transform(cells, pure), lambda p: p.isNotNull()))

    def one_round(state: Column, _: Column) -> Column:
        def without(z: Column, i: Column) -> Column:
            mine = F.filter(state["new"], lambda p: (p["p"] == i) | (p["q"] == i) | (p["r"] == i))
            return F.aggregate(mine, z, lambda acc, p: F.struct((acc["c"] - p["c"]).alias("c"), acc["k"].bitwiseXOR(p["key"]).alias("k"), acc["x"].bitwiseXOR(p["x"]).alias("x")))

        cleared = F.transform(state["cells"], without)
        found = F.concat(state["found"], F.transform(state["new"], lambda p: F.struct(p["key"].alias("key"), p["side"].alias("side"))))
        return F.when(F.size(state["new"]) == 0, state).otherwise(F.struct(cleared.alias("cells"), pures(cleared).alias("new"), found.alias("found")))

    none = F.expr("cast(array() as array<struct<key:bigint,side:bigint>>)")
    start = F.struct(cells.alias("cells"), pures(cells).alias("new"), none.alias("found"))
    empty = lambda s: ~F.exists(s["cells"], lambda z: (z["c"] != 0) | (z["k"] != 0) | (z["x"] != 0))
    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), start, one_round, lambda s: F.when(empty(s), s["found"]))


def with_likeness(df: DataFrame, name: str, a: str, a_n: str, b: str, b_n: str, cells: int = CELLS) -> DataFrame:
    """``df`` and column ``name``: 1 less the differing pieces' share of the pieces of both sketches, 0 to 1; 1 for two empty texts.

    Null where the difference can't be peeled; the estimate only saves attempts.
    """
    diff, est, small, full = (f"_{name}_{x}" for x in ("diff", "est", "small", "full"))
    df = df.withColumn(diff, subtracted(F.col(a), F.col(b)))
    df = df.withColumn(est, F.aggregate(diff, F.lit(0).cast("long"), lambda acc, z: acc + z["c"] * z["c"]) / F.lit(float(TABLES)))
    df = df.withColumn(small, F.when(F.col(est) <= TABLES * FOLDED // 2, F.size(peeled(folded(F.col(diff), cells, FOLDED), FOLDED, 6))))
    df = df.withColumn(full, F.when(F.coalesce(small, F.lit(-1)).isin(-1) & (F.col(est) <= TABLES * cells * 3 // 4), F.size(peeled(F.col(diff), cells, 10))))
    small_n, full_n = (F.when(F.col(x) >= 0, F.col(x)) for x in (small, full))  # size of null is -1 in some modes
    differing = F.coalesce(small_n, full_n).cast("double")
    both = F.col(a_n) + F.col(b_n)
    value = F.when(both == 0, F.lit(1.0)).when(differing.isNotNull(), F.greatest(F.lit(0.0), F.least(F.lit(1.0), 1 - differing / both)))
    return df.withColumn(name, value).drop(diff, est, small, full)


def with_next(docs: DataFrame, parts: int) -> DataFrame:
    """(part, pos, doc_id, text, next_text, extra): each row of (doc_id, text) and the next row's text by descending id.

    Equal ids are in the order of their texts, null ids come last; after the last row comes the first. Ids are cut
    into ``parts`` ranges by quantiles, which are dealt out; each range also gets, as an extra row, the first one of
    the range below it.
    """
    cuts = sorted(set(docs.approxQuantile("doc_id", [i / parts for i in range(1, parts)], 0.2 / parts))) if parts > 1 else []
    bounds = F.array(*[F.lit(int(c)).cast("long") for c in cuts]) if cuts else F.expr("cast(array() as array<bigint>)")
    part = F.coalesce(F.size(F.filter(bounds, lambda b: b <= F.col("doc_id"))), F.lit(-1))
    dealt = docs.select(F.when(F.col("doc_id").isNull(), F.lit(-1)).otherwise(part).alias("part"), "doc_id", "text")
    tops = {r.part: r.top for r in dealt.groupBy("part").agg(F.max("doc_id").alias("top")).collect()}  # one row per range
    order = sorted(tops)
    marks = F.array(*[F.struct(F.lit(order[(i + 1) % len(order)]).alias("to"), F.lit(tops[p]).cast("long").alias("top")) for i, p in enumerate(order)]) if order else F.expr("cast(array() as array<struct<to:int,top:bigint>>)")
    extra = docs.sparkSession.range(1).select(F.inline(marks))
    firsts = docs.join(F.broadcast(extra), F.col("doc_id").eqNullSafe(F.col("top"))).select(F.col("to").alias("part"), "doc_id", "text", F.lit(True).alias("extra"))
    rows = dealt.select("*", F.lit(False).alias("extra")).unionByName(firsts)
    down = Window.partitionBy("part").orderBy("extra", F.col("doc_id").desc_nulls_last(), "text")
    return rows.select("part", F.row_number().over(down).alias("pos"), "doc_id", "text", F.lead(F.struct("text")).over(down)["text"].alias("next_text"), "extra")


def edited(text: Column, other: Column) -> Column:
    """``text`` with its last third replaced by as many first code points of ``other``, or all."""
    third = F.floor(F.char_length(text) / 3).cast("int")
    return F.concat(F.substring(text, F.lit(1), F.char_length(text) - third), F.substring(other, F.lit(1), third))


def edit_report(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Fingerprints of each text and of its edited version, with the likeness of it to that and to the next text.

    A null text is empty. Repeated rows follow each other; a single row is its own next. An empty table gives none.
    Other columns are ignored. ``parts`` (default: twice the shuffle partitions, and so many that a range has some 64 MB of texts) cuts the ids.
    """
    spark = docs.sparkSession
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    if parts is None:
        total = slim.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        parts = max(2 * int(spark.conf.get("spark.sql.shuffle.partitions")), total >> 26)
    rows = with_next(slim, parts)
    changed = F.when(~F.col("extra"), edited(F.col("text"), F.col("next_text")))
    rows = rows.select("part", "pos", "doc_id", "extra", "text", changed.alias("edited"))
    rows = rows.select("part", "pos", "doc_id", "extra", F.char_length("text").cast("long").alias("n_chars"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), digests(F.col("text")).alias("own"), digests(F.coalesce("edited", F.lit(""))).alias("other"))
    rows = rows.select("*", hashed(F.col("own")).alias("own_h"), hashed(F.col("other")).alias("other_h"))
    rows = rows.select("part", "pos", "doc_id", "extra", "n_chars", "edited_sha256", "own", "other", F.size("own").alias("n"), F.size("other").alias("edited_n"), sketch(F.col("own_h")).alias("a"), sketch(F.col("other_h")).alias("b"))
    down = Window.partitionBy("part").orderBy("pos")
    both = rows.withColumn("f", F.lead(F.struct("a", "n", "own")).over(down)).where(~F.col("extra"))
    both = both.select("*", F.col("f.a").alias("next_a"), F.col("f.n").alias("next_n"), F.col("f.own").alias("next")).drop("f", "extra")
    out = with_likeness(both, "near_edited", "a", "n", "b", "edited_n")
    out = with_likeness(out, "near_next", "a", "n", "next_a", "next_n")
    # texts without a piece in common differ in all of them, which needs no table
    for name, other in (("near_edited", "other"), ("near_next", "next")):
        out = out.withColumn(name, F.coalesce(name, F.when(~F.arrays_overlap("own", other), F.lit(0.0))))
    hidden = F.array(F.when(F.col("near_edited").isNull(), F.struct(F.lit(0).alias("to"), F.col("other").alias("p"))), F.when(F.col("near_next").isNull(), F.struct(F.lit(1).alias("to"), F.col("next").alias("p"))))
    out = out.withColumn("hidden", F.filter(hidden, lambda z: z.isNotNull())).withColumn("own", F.when(F.size("hidden") > 0, F.col("own")))
    packed = [F.unhex(as_text(F.col(c), F.col(n))).alias(name) for c, n, name in (("a", "n", "fingerprint"), ("b", "edited_n", "edited_fingerprint"))]
    out = written(out.select("part", "pos", "doc_id", "n_chars", "edited_sha256", *packed, "near_edited", "near_next", "n", "edited_n", "next_n", "own", "hidden"), "likeness")
    pairs = out.where(F.size("hidden") > 0).select("part", "pos", "own", F.explode("hidden").alias("z")).select("part", "pos", F.col("z.to").alias("to"), "own", F.col("z.p").alias("other"))
    known = differing(pairs, ["part", "pos", "to"]).groupBy("part", "pos", "to").agg(F.count("*").alias("d"))
    known = known.groupBy("part", "pos").agg(*[F.max(F.when(F.col("to") == i, F.col("d"))).alias(f"d{i}") for i in (0, 1)])
    out = out.drop("own", "hidden").join(known, ["part", "pos"], "left")
    for name, i, other_n in (("near_edited", 0, "edited_n"), ("near_next", 1, "next_n")):
        out = out.withColumn(name, F.coalesce(name, 1 - F.coalesce(f"d{i}", F.lit(0)) / (F.col("n") + F.col(other_n))))
    return out.select("doc_id", "n_chars", "edited_sha256", F.lower(F.hex("fingerprint")).alias("fingerprint"), F.lower(F.hex("edited_fingerprint")).alias("edited_fingerprint"), "near_edited", "near_next")


def recovered(old: DataFrame, new: DataFrame, key: str = "doc_id", retries: int = RETRIES) -> DataFrame:
    """(key, digest, side): digests of the pieces that only the old (1) or the new (-1) version of a text has.

    Versions are joined by ``key``; a missing one is empty. What a table can't tell is tried again with larger ones, up to
    ``retries`` times; for what is left, digests are compared one by one. Rows with a null key are left out, rows of one key
    are one set of pieces; no difference gives no row.
    """

    def slim(df: DataFrame, name: str) -> DataFrame:
        return df.where(F.col(key).isNotNull()).groupBy(key).agg(F.array_distinct(F.flatten(F.collect_list(digests(F.coalesce("text", F.lit("")))))).alias(name))

    none = F.expr("cast(array() as array<int>)")
    pairs = slim(old, "own").join(slim(new, "other"), key, "full_outer").select(key, F.coalesce("own", none).alias("own"), F.coalesce("other", none).alias("other"))
    return differing(pairs, [key], retries)


def differing(pairs: DataFrame, by: list[str], retries: int = RETRIES) -> DataFrame:
    """(*by, digest, side): what ``recovered`` gives, of rows (*by, own, other) of digests. Nothing is dealt anew."""
    left, found = pairs, []
    for k in range(retries):
        size = F.size("own") + F.size("other")
        parts = F.least(F.lit(MOST_PARTS), F.greatest(F.lit(2 if k else 1), F.ceil(size / PART_DIGESTS).cast("int")))
        dealt = left.select(*by, "own", "other", parts.alias("parts")).select("*", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("at"))

        def mine(c: str, k: int = k) -> Column:
            return F.filter(c, lambda d: F.pmod(F.xxhash64(F.lit(101 + k), d), F.col("parts")) == F.col("at")).alias(c)

        dealt = dealt.select(*by, mine("own"), mine("other"))
        cells = [sketch(hashed(F.col(c), PART_CELLS), PART_CELLS) for c in ("own", "other")]
        diff = dealt.select(*by, "own", "other", subtracted(*cells).alias("d"))
        about = F.aggregate("d", F.lit(0).cast("long"), lambda acc, z: acc + z["c"] * z["c"]) / F.lit(float(TABLES))
        tried = diff.select(*by, "own", "other", F.when(about <= TABLES * PART_CELLS * 3 // 4, peeled(F.col("d"), PART_CELLS, 10)).alias("got"))
        hidden = F.col("got").isNull()
        done = written(tried.select(*by, *[F.when(hidden, F.col(c)).alias(c) for c in ("own", "other")], "got"), "peeled")  # a filter before the write would be pushed down and peel twice
        found.append(done.where("got IS NOT NULL").select(*by, F.explode("got").alias("g")).select(*by, F.col("g.key").alias("digest"), F.col("g.side").cast("int").alias("side")))
        left = done.where("got IS NULL").select(*by, "own", "other")
        if left.isEmpty():
            break
    else:
        for one_side, other, side in (("own", "other", 1), ("other", "own", -1)):
            only = left.select(*by, F.explode(F.array_except(one_side, other)).alias("digest"))
            found.append(only.select(*by, unsigned(F.col("digest")).alias("digest"), F.lit(side).alias("side")))
    out = found[0] if found else None
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def op2_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints and likenesses of every document; see ``edit_report``."""
    return edit_report(table(spark, sf_dir, "documents"))
