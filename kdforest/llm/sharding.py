"""Sharding by balanced label propagation, on DataFrame functions only.

Documents with equal texts are linked. Labels (shards) start from a hash of the id and spread in rounds of joins:
a group's members move to the shard that most of them have (a group larger than a shard: to as many as it needs), as
far as the quota of room there lets them. The
state is one row per group and first label, never one per link, so a group of a third of all rows is a few rows.
In the end each group that a shard can hold settles on one label, documents are ranked by label, and shards are cut from that
rank, so counts differ by at most one (law "rows"). Rows that may be parted, those without a link and those of larger groups, lie at
both ends of a label, where the cuts fall.

``propagated_links`` does the same rounds over any table of links.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kdforest.llm.common import table, written

SHARDS = 40
ROUNDS = 4
#: Documents in a bin of the final ranking; groups beyond it are ranked in parts of about as many.
BIN = 1000
GROUP = ["h", "text_crc32", "size"]


def described(docs: DataFrame) -> DataFrame:
    """doc_id, size (UTF-8 bytes and 16), text_crc32 and h, a digest of the text. A null text is empty in all of them."""
    text = F.coalesce("text", F.lit("")).cast("binary")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.xxhash64(text).alias("h"))


def first_label(shards: int) -> Column:
    return F.pmod(F.xxhash64(F.col("doc_id"), F.lit(1)), F.lit(shards)).cast("int")


def shares_admitted(moves: list[tuple[int, int, bool, int]], load: dict[int, int], capacity: int, shards: int) -> tuple[list[float], list[float]]:
    """Shares of whole groups and of parts of hot ones that each shard lets in. ``moves`` has (label, goal, whole, n), at most two per pair of shards.

    Whole groups come first, parts get the room left. Room that leavers make counts as far as they are let in elsewhere.
    """
    moves = [m for m in moves if m[0] != m[1]]
    demand = {w: [sum(n for _, goal, is_whole, n in moves if goal == s and is_whole is w) for s in range(shards)] for w in (True, False)}
    share = {True: [1.0] * shards, False: [1.0] * shards}
    for _ in range(20):
        room = [float(capacity - load.get(s, 0)) for s in range(shards)]
        for label, goal, is_whole, n in moves:
            room[label] += n * share[is_whole][goal]
        whole = [min(1.0, max(0.0, room[s]) / demand[True][s]) if demand[True][s] else 1.0 for s in range(shards)]
        part = [min(1.0, max(0.0, room[s] - whole[s] * demand[True][s]) / demand[False][s]) if demand[False][s] else 1.0 for s in range(shards)]
        share = {True: whole, False: part}
    return share[True], share[False]


def label_array(values: list[float], at: str) -> Column:
    return F.get(F.array(*[F.lit(x) for x in values]), F.col(at))


def propagated(rows: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS, slack: float = 0.02) -> tuple[DataFrame, list[int]]:
    """Cells of linked documents (group, first, n, group_n, label) after ``rounds``, and the links cut before and after each.

    Any two documents of a group are linked; a link is cut if their labels differ. A group's goals are the shards with most of its
    members, as many as its size needs. Ties go by a hash of group and shard, so that wishes spread evenly.
    A shard takes movers up to its capacity, the mean and ``slack``: whole groups first, then single cells of groups
    larger than a quarter of that, while a hash of theirs is below the share that has room. Rounds end early when no cell wishes to move.
    """
    total = rows.count()
    capacity = int(total / shards * (1 + slack)) + 1
    cells = rows.groupBy(*GROUP, first_label(shards).alias("first")).agg(F.count("*").alias("n"))
    sizes = Window.partitionBy(*GROUP)
    cells = cells.withColumn("group_n", F.sum("n").over(sizes)).withColumn("label", F.col("first"))
    cells = written(cells.where("group_n > 1"), "cells")
    single = {r["first"]: r.n for r in rows.groupBy(first_label(shards).alias("first")).agg(F.count("*").alias("n")).collect()}
    for r in cells.groupBy("first").agg(F.sum("n").alias("n")).collect():
        single[r["first"]] -= r.n
    is_whole = F.col("group_n") <= capacity // 4
    cut: list[int] = []
    for k in range(rounds + 1):
        votes = cells.groupBy(*GROUP, "group_n", "label").agg(F.sum("n").alias("votes"))
        cut.append(cut_links(votes))
        if k == rounds:
            break
        ordered = F.sort_array(F.collect_list(F.struct("votes", F.xxhash64(*GROUP, "label").alias("tie"), "label")), asc=False)
        tops = votes.groupBy(*GROUP).agg(F.transform(ordered, lambda x: x["label"]).alias("tops"))  # an entry per shard at most
        needed = F.least(F.ceil(F.col("group_n") / capacity), F.size("tops")).cast("int")
        goals = F.slice("tops", 1, needed)
        goal = F.when(F.array_contains(goals, F.col("label")), F.col("label")).otherwise(F.get("tops", F.pmod(F.xxhash64(*GROUP, "first"), needed).cast("int")))
        wish = cells.join(tops, GROUP).withColumn("goal", goal)
        moves = [(r.label, r.goal, r.whole, r.n) for r in wish.groupBy("label", "goal", is_whole.alias("whole")).agg(F.sum("n").alias("n")).collect()]
        if not any(label != to for label, to, _, _ in moves):
            break
        load = dict(single)
        for label, _, _, n in moves:
            load[label] = load.get(label, 0) + n
        whole, part = (label_array(share, "goal") for share in shares_admitted(moves, load, capacity, shards))
        lot = F.when(is_whole, F.xxhash64(*GROUP, F.lit(k))).otherwise(F.xxhash64(*GROUP, "first", F.lit(k)))
        admitted = F.pmod(lot, F.lit(1 << 20)) < F.when(is_whole, whole).otherwise(part) * (1 << 20)
        cells = written(wish.select(*GROUP, "first", "n", "group_n", F.when(admitted, F.col("goal")).otherwise(F.col("label")).alias("label")), "cells")
    return cells, cut


def cut_links(votes: DataFrame) -> int:
    """Links between documents of one group with different labels, from rows (group, group_n, votes) per group and label."""
    own = votes.groupBy(*GROUP, "group_n").agg(F.sum(F.col("votes").cast("decimal(20,0)") * F.col("votes")).alias("inside"))
    total = own.agg(F.sum((F.col("group_n").cast("decimal(20,0)") * F.col("group_n") - F.col("inside")) / 2)).first()[0]
    return int(total or 0)


def propagated_links(nodes: DataFrame, links: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS, slack: float = 0.02) -> tuple[DataFrame, list[int]]:
    """(id, label) of ``nodes`` (id) after rounds over ``links`` (a, b), and the links cut before and after each round.

    A node wishes to move where most of its neighbours are, if that is more than are with it; a shard admits as many as it has
    room for, by a hash of node and round. Votes are counted per node and label before they are dealt, so a node with many
    links costs no task more than a row per shard and source. Links to unknown or null ids, to oneself and repeated ones
    don't count; nodes without links keep their first label, null ids are left out.
    """
    state = written(nodes.where("id IS NOT NULL").select("id").distinct().select("id", F.pmod(F.xxhash64("id", F.lit(1)), F.lit(shards)).cast("int").alias("label")), "labels")
    capacity = int(state.count() / shards * (1 + slack)) + 1
    pairs = links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    both = written(both.join(state.select(F.col("id").alias("a")), "a", "left_semi").join(state.select(F.col("id").alias("b")), "b", "left_semi"), "links")
    cut: list[int] = []
    for k in range(rounds + 1):
        met = both.join(state.select(F.col("id").alias("b"), F.col("label").alias("to")), "b").groupBy("a", "to").agg(F.count("*").alias("votes"))
        seen = written(met.join(state.select(F.col("id").alias("a"), "label"), "a"), "votes")
        cut.append((seen.where("to <> label").agg(F.sum("votes")).first()[0] or 0) // 2)
        if k == rounds:
            break
        best = seen.groupBy("a", "label").agg(F.max(F.struct("votes", F.xxhash64("a", "to").alias("tie"), "to")).alias("top"), F.max(F.when(F.col("to") == F.col("label"), F.col("votes"))).alias("here"))
        wish = best.where(F.col("top.votes") > F.coalesce("here", F.lit(0))).select(F.col("a").alias("id"), F.col("top.to").alias("goal"))
        moves = [(r.label, r.goal, False, r.n) for r in state.join(wish, "id").groupBy("label", "goal").agg(F.count("*").alias("n")).collect()]  # a row per pair of shards at most
        if not moves:
            break
        load = {r.label: r.n for r in state.groupBy("label").agg(F.count("*").alias("n")).collect()}
        # half of the wishes a round, so that neighbours don't swap places for ever
        share = [x / 2 for x in shares_admitted(moves, load, capacity, shards)[1]]
        admitted = F.pmod(F.xxhash64("id", F.lit(k)), F.lit(1 << 20)) < label_array(share, "goal") * (1 << 20)
        moved = wish.where(admitted)
        state = written(state.join(moved, "id", "left").select("id", F.coalesce("goal", "label").alias("label")), "labels")
    return state, cut


def sharded(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, size, text_crc32, law ("rows"), shard, slot (gapless from 0 in each shard) and grown_shard (null).

    All rows are placed, also those with null ids or texts and repeated ones; equal rows may swap slots. An empty
    table gives none; other columns are ignored.
    """
    rows = written(described(docs), "rows")
    total = rows.count()
    cells, _ = propagated(rows, shards, rounds)
    room = max(1, total // shards)
    votes = cells.groupBy(*GROUP, "group_n", "label").agg(F.sum("n").alias("votes"))
    home = votes.where(F.col("group_n") <= room // 2).groupBy(*GROUP).agg(F.max_by("label", F.struct("votes", F.xxhash64(*GROUP, "label"))).alias("home"))
    known = cells.join(home, GROUP, "left").select(*GROUP, "first", F.coalesce("home", "label").alias("label"), "group_n", F.col("home").isNotNull().alias("whole"))
    labelled = rows.withColumn("first", first_label(shards)).join(known, [*GROUP, "first"], "left")
    bins = max(1, total // (shards * BIN), min(64, total // (shards * 32)))
    part = F.when(F.col("group_n") > BIN, F.pmod(F.xxhash64("doc_id", F.lit(2)), F.ceil(F.col("group_n") / BIN))).otherwise(0).cast("long")
    # rows that may be parted lie before (bin < 0) and after the groups of a label
    inner = F.pmod("h", F.lit(bins))
    loose = F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(2 * bins))
    bin_of = F.when(F.coalesce("whole", F.lit(False)), inner).when(loose < bins, loose - bins).otherwise(loose)
    placed = labelled.select("doc_id", *GROUP, F.coalesce("label", "first").alias("label"), bin_of.alias("bin"), part.alias("part"))
    placed = written(placed, "placed")
    counts = placed.groupBy("label", "bin", "part").agg(F.count("*").alias("n"))
    before = Window.partitionBy("label").orderBy("bin", "part").rowsBetween(Window.unboundedPreceding, -1)
    labels = {r.label: r.n for r in counts.groupBy("label").agg(F.sum("n").alias("n")).collect()}  # one row per shard
    start = [sum(n for k, n in labels.items() if k < s) for s in range(shards)]
    offsets = counts.select("label", "bin", "part", (F.coalesce(F.sum("n").over(before), F.lit(0)) + F.get(F.array(*[F.lit(x) for x in start]), F.col("label"))).alias("offset"))
    inside = Window.partitionBy("label", "bin", "part").orderBy("h", "text_crc32", "size", "doc_id")
    ranked = placed.withColumn("k", F.row_number().over(inside) - 1).join(offsets, ["label", "bin", "part"]).withColumn("rank", F.col("offset") + F.col("k"))
    cut = ranked.withColumn("shard", F.expr(f"(rank * {shards}L) div {max(1, total)}L"))
    slot = F.expr(f"rank - (shard * {total}L + {shards - 1}L) div {shards}L")
    return cut.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), slot.cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op8_shard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shard and slot of every document; see ``sharded``."""
    return sharded(table(spark, sf_dir, "documents"))
