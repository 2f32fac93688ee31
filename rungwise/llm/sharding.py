"""Balanced label propagation: linked documents move towards their neighbours' shards under capacity quotas.

DataFrame functions only.  A link group is a set of documents that belong together (here: equal texts).  A group
is split beforehand only if it is larger than a shard, into parts of a shard's size.  Every round counts each
group's members by shard, proposes to move the others to the group's best shard, and grants moves between two
shards up to what flows the other way plus the room that linked rows have in the target.  At last rows level the
shards, those without links first: row counts differ by one at most.  Rows of large groups are dealt to the counting and ranking tasks by
document, those of small groups by group, so that no task takes all of a large one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, drop_cut, keyed_join

SHARDS = 24
ROUNDS = 5
#: Rows that one window task ranks, about; salts grow with the table so that this holds.
ROWS_PER_RANK = 50_000


def _ranked(rows: DataFrame, keys: list[str], order: list, salts: int, salt_of) -> DataFrame:
    """``rank``: gapless position from 0 within ``keys``, by salt and then ``order``; no task ranks a whole key."""
    salted = rows.withColumn("salt", F.pmod(salt_of, F.lit(salts)).cast("int"))
    sums = salted.groupBy(*keys, "salt").agg(F.count("*").alias("n"))
    before = Window.partitionBy(*keys).orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("start", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    within = Window.partitionBy(*keys, "salt").orderBy(*order)
    placed = salted.withColumn("nth", F.row_number().over(within) - 1)
    return placed.join(starts, [*keys, "salt"]).withColumn("rank", (F.col("start") + F.col("nth")).cast("long")).drop("salt", "start", "nth")


def _sizes(rows: DataFrame, shards: int) -> list[int]:
    """Rows by shard: as many numbers as there are shards."""
    found = {r.shard: r.n for r in rows.groupBy("shard").agg(F.count("*").alias("n")).collect()}
    return [found.get(s, 0) for s in range(shards)]


def _quotas(asked: dict[tuple[int, int], int], room: list[int]) -> dict[tuple[int, int], int]:
    """Granted moves by (from, to): matched two-way flow, then the target's free room in order of demand."""
    granted = {(a, b): min(n, asked.get((b, a), 0)) for (a, b), n in asked.items()}
    for (a, b), n in sorted(asked.items(), key=lambda x: (-x[1], x[0])):
        more = min(n - granted[a, b], max(room[b], 0))
        granted[a, b] += more
        room[b] -= more
        room[a] += more
    return granted


def propagate(nodes: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """``nodes(doc_id, link, ...)`` -> the same rows with ``shard`` and ``slot``.

    ``link`` is any hashable group key; rows with a null link have no neighbours.  Row counts of the shards end at
    most one apart, and slots are gapless from 0 in each shard.  Repeated rows are rows of their own, ties are
    broken by hashes, an empty table gives an empty result, other columns are kept.
    """
    total = nodes.count()
    tied = nodes.groupBy("link").agg(F.count("*").alias("__n")).where("link is not null and __n > 1").withColumn("members", F.col("__n"))
    part = max(2, total // shards)
    salts = max(1, -(-total // (ROWS_PER_RANK * shards)) * 4)
    piece = F.floor(F.pmod(F.xxhash64("doc_id", F.lit("part")), F.lit(1 << 20)) * F.col("members") / (part << 20))  # full parts, then the rest
    start = F.pmod(F.xxhash64("doc_id", "crc"), F.lit(shards)).cast("int")
    # a key of its own for every row without a link, so that such rows aren't dealt to one task
    alone = F.concat(F.lit("-"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("-"), F.col("crc").cast("string")).cast("binary")
    keyed = nodes.withColumn("own", F.col("link").isNull()).withColumn("link", F.coalesce("link", alone))
    grouped = keyed_join(keyed.where("not own"), tied, "link", total)
    grouped = grouped.withColumn("grp", F.xxhash64("link", piece)).withColumn("deal", F.when(F.least(F.col("members"), F.lit(part)) > max(1, total // 500), F.xxhash64("doc_id", "grp")).otherwise(F.col("grp")))
    single = nodes.groupBy("link").agg(F.count("*").alias("__n")).where("link is not null and __n = 1").select("link")
    unlinked = keyed.where("own").unionByName(keyed.where("not own").join(single.hint("merge"), "link", "left_semi"))
    unlinked = unlinked.withColumn("grp", F.lit(None).cast("long")).withColumn("deal", F.xxhash64("doc_id", F.lit("level")))
    columns = [*(F.when(F.col("own"), None).otherwise(F.col("link")).alias("link") if c == "link" else F.col(c) for c in nodes.columns), "grp", "deal"]
    state = cut(grouped.select(*columns).unionByName(unlinked.select(*columns)).withColumn("shard", start))
    capacity = -(-total // shards)
    for _ in range(rounds if total else 0):
        state, moved = _round(state, shards, capacity, salts, total)
        if not moved:
            break
    sizes = _sizes(state, shards)
    goal = [total // shards + (s < total % shards) for s in range(shards)]
    over = [max(0, n - g) for n, g in zip(sizes, goal, strict=True)]
    under = [max(0, g - n) for n, g in zip(sizes, goal, strict=True)]
    take, leave = _running(over), _running(under)
    # rows without links go first, then whole small groups side by side
    first = F.when(F.col("grp").isNull(), 0).otherwise(1)
    ordered = _ranked(state.withColumn("tied", first), ["shard", "tied"], ["grp", "doc_id", "crc"], salts, F.col("deal"))
    loose = {r.shard: r.n for r in state.where("grp is null").groupBy("shard").agg(F.count("*").alias("n")).collect()}
    offsets = _pick(F.col("shard"), [loose.get(s, 0) for s in range(shards)])
    ordered = ordered.withColumn("rank", F.col("rank") + F.when(F.col("tied") == 1, offsets).otherwise(0))
    number = _pick(F.col("shard"), take) + F.col("rank")
    target = F.coalesce(F.array_position(F.transform(F.array(*[F.lit(x + n).cast("long") for x, n in zip(leave, under, strict=True)]), lambda end: end > number), True).cast("int") - 1, F.col("shard"))
    levelled = cut(ordered.withColumn("shard", F.when(F.col("rank") < _pick(F.col("shard"), over), target).otherwise(F.col("shard"))).drop("rank", "tied"))
    drop_cut(state)
    placed = _ranked(levelled, ["shard"], ["doc_id", "crc"], salts * 2, F.xxhash64("doc_id", F.lit("slot")))
    return placed.withColumnRenamed("rank", "slot").drop("grp", "deal")


def _running(values: list[int]) -> list[int]:
    out, at = [], 0
    for v in values:
        out.append(at)
        at += v
    return out


def _pick(index, values: list[int]):
    return F.element_at(F.array(*[F.lit(v).cast("long") for v in values]), (index + 1).cast("int"))


def _round(state: DataFrame, shards: int, capacity: int, salts: int, total: int) -> tuple[DataFrame, int]:
    """One round of propagation; the new state and the number of rows that moved."""
    linked = state.where("grp is not null")
    held = linked.groupBy("grp", "shard").agg(F.count("*").alias("n"))
    best = held.groupBy("grp").agg(F.max(F.struct("n", F.xxhash64("grp", "shard").alias("tie"), F.col("shard").alias("best"))).alias("b"), F.sum("n").alias("__n")).select("grp", F.col("b.best").alias("best"), F.col("b.n").alias("pull"), "__n")
    wishes = cut(keyed_join(linked, best, "grp", total).where("best <> shard").select("doc_id", "crc", "grp", "deal", "shard", "best", "pull"))
    asked = {(r.shard, r.best): r.n for r in wishes.groupBy("shard", "best").agg(F.count("*").alias("n")).collect()}
    if not asked:
        drop_cut(wishes)
        return state, 0
    # rows without links make room at last, so only linked rows count against a shard's capacity
    sizes = _sizes(linked, shards)
    granted = _quotas(asked, [capacity - n for n in sizes])
    table = F.array(*[F.lit(granted.get((a, b), 0)).cast("long") for a in range(shards) for b in range(shards)])
    ranked = _ranked(wishes, ["shard", "best"], ["grp", "doc_id", "crc"], salts, F.col("deal"))
    moves = ranked.where(F.col("rank") < F.element_at(table, (F.col("shard") * shards + F.col("best") + 1).cast("int"))).groupBy("doc_id", "crc", "grp", "shard").agg(F.first("best").alias("to"))
    after = cut(state.join(moves, ["doc_id", "crc", "grp", "shard"], "left").withColumn("shard", F.coalesce("to", "shard")).drop("to").select(*state.columns))
    drop_cut(wishes)
    drop_cut(state)
    return after, sum(granted.values())


def shard_documents(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """One row per row of ``docs``: doc_id, size, text_crc32, law, shard, slot, grown_shard.

    The law is ``rows``: the shards' row counts differ by one at most, so ``grown_shard`` is null.  Equal texts are
    linked; a null text is linked to nothing, has 8 bytes and the checksum of an empty text.  Repeated rows are
    rows of their own, each with a slot; ties between shards and between rows are broken by hashes; an empty table
    gives an empty result; other columns are ignored.
    """
    text = F.col("text").cast("string")
    nodes = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.coalesce(F.octet_length(text), F.lit(0)) + 8).cast("long").alias("size"), F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("crc"), F.unhex(F.md5(text.cast("binary"))).alias("link"))
    placed = propagate(cut(nodes), shards, rounds)
    return placed.select("doc_id", "size", F.col("crc").alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def cut_links(placed: DataFrame) -> DataFrame:
    """``(groups, rows, cut)``: linked groups, their rows, and rows away from their group's largest shard."""
    held = placed.groupBy("link", "shard").agg(F.count("*").alias("n"))
    groups = held.groupBy("link").agg(F.sum("n").alias("all"), F.max("n").alias("most")).where("all > 1 and link is not null")
    return groups.agg(F.count("*").alias("groups"), F.coalesce(F.sum("all"), F.lit(0)).alias("rows"), F.coalesce(F.sum(F.col("all") - F.col("most")), F.lit(0)).alias("cut"))
