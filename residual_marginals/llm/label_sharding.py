"""Sharding by balanced label propagation.

Documents that share a group are linked. Every document starts in a shard by rank, so that
shard counts differ by one at most. In each round a linked document asks for the shard in
which most of its group lives; a group that no shard can hold (there are fewer of those than shards) asks for as many of its fullest shards as it needs, in proportion to the room that is left for it there. Moves are granted only in exchange: a move against an opposite
request, or against an unlinked document that leaves the wanted shard. So counts never change.
Which requests are granted goes by rank inside each (from, to) pair. The request counts have at
most shards x shards entries; everything else is joins. Rounds go on until all linked documents are together or ``PATIENCE`` rounds
bring no more of them together.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.llm.common import empty, materialise, table, with_rank

FREE = -1
#: Rounds in a row that may bring nothing; ties fall differently in each.
PATIENCE = 3


def exchange(asked: dict[tuple[int, int], int], free: dict[int, int]) -> list[tuple[int, int, int, int, int]]:
    """(from, want, low rank, high rank, new shard) rows that keep every shard's count.

    ``asked``: requests by (from, to); ``free``: unlinked documents by shard.
    """
    moves, spare, used = [], dict(free), defaultdict(int)
    for (a, b), n in sorted(asked.items(), key=lambda x: (-x[1], x[0])):
        granted = min(n, asked.get((b, a), 0))
        extra = min(n - granted, spare.get(b, 0))
        if extra:
            spare[b] -= extra
            moves.append((b, FREE, used[b], used[b] + extra, a))
            used[b] += extra
        if granted + extra:
            moves.append((a, b, 0, granted + extra, b))
    return moves


def quotas(held: dict[int, int], room: int) -> list[tuple[int, int, int]]:
    """(low, high, shard): shares of the requests of a group too large for one shard, for the fullest shards that it needs; ``held`` are its members by shard."""
    order = sorted(held, key=lambda s: (-held[s], s))
    need, out, at = -(-sum(held.values()) // room), [], 0
    for s in order[:need]:
        left = max(0, room - held[s])
        if left:
            out.append((at, at + left, s))
            at += left
    return out


def cut_links(placed: DataFrame, room: int | None = None) -> DataFrame:
    """One row: linked documents, and those outside the main shard of their group (with ``room``: outside as many of its fullest shards as it needs)."""
    sizes = placed.groupBy("grp", "shard").agg(F.count(F.lit(1)).alias("n")).groupBy("grp").agg(F.sum("n").alias("n"), F.sort_array(F.collect_list("n"), asc=False).alias("by"))
    need = F.ceil(F.col("n") / room).cast("int") if room else F.lit(1)
    home = F.aggregate(F.slice("by", F.lit(1), need), F.lit(0).cast("long"), lambda a, x: a + x)
    return sizes.where("n > 1").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("linked"), F.coalesce(F.sum(F.col("n") - home), F.lit(0)).alias("cut"))


def assign(rows: DataFrame, shards: int = 24, rounds: int | None = None, spread: int | None = None) -> DataFrame:
    """Adds ``shard`` (0 to shards - 1, counts at most one apart) to rows (doc_id, grp, and others not named shard, linked, want, or from t_ or s_ on).

    A null ``grp`` links to nothing. Rows that repeat are placed one by one. ``rounds``: at most so many (by default until it has settled).
    """
    spark = rows.sparkSession
    order, scatter = [F.col("doc_id"), F.col("grp")], F.xxhash64("doc_id", "grp")
    sizes = rows.where("grp is not null").groupBy("grp").agg(F.count(F.lit(1)).alias("members")).where("members > 1")
    linked = materialise(sizes.select("grp", F.lit(True).alias("linked")))
    ranked = with_rank(rows.withColumn("_all", F.lit(0)), ["_all"], order, scatter, "_rank", spread).drop("_all")
    now = ranked.withColumn("shard", (F.col("_rank") % shards).cast("int")).drop("_rank")
    now = materialise(now.join(linked, "grp", "left").withColumn("linked", F.coalesce("linked", F.lit(False))))
    room = max(1, now.count() // shards)
    cut, turn = cut_links(now.where("linked"), room).first()["cut"], 0
    stale = 0
    while cut and stale < PATIENCE and (rounds is None or turn < rounds):
        turn += 1
        held = now.where("linked").groupBy("grp", "shard").agg(F.count(F.lit(1)).alias("n"))
        # the fullest shard of the group; ties by a mix of group, shard and round
        best = F.max_by("shard", F.struct("n", F.xxhash64("grp", "shard", F.lit(turn)))).alias("want")
        wanted = materialise(held.groupBy("grp").agg(best, F.sum("n").alias("members")))
        # at most ``shards`` groups are larger than a shard
        large = wanted.where(F.col("members") > room).select("grp")
        by_group: dict[int, dict[int, int]] = defaultdict(dict)
        for r in held.join(F.broadcast(large), "grp").collect():
            by_group[r["grp"]][r["shard"]] = r["n"]
        shares = {g: quotas(own, room) for g, own in by_group.items()}
        told = [(g, low, high, s, parts[-1][1]) for g, parts in shares.items() for low, high, s in parts]
        targets = spark.createDataFrame(told, "t_grp long, t_low long, t_high long, t_want int, t_all long") if told else empty(spark, "t_grp long, t_low long, t_high long, t_want int, t_all long")
        homes = {g: {s for s in sorted(own, key=lambda s: (-own[s], s))[: -(-sum(own.values()) // room)]} for g, own in by_group.items()}
        stay = [(g, s) for g, own in homes.items() for s in own]
        settled = spark.createDataFrame(stay, "s_grp long, s_shard int") if stay else empty(spark, "s_grp long, s_shard int")
        spot = F.pmod(F.xxhash64("doc_id", F.lit(turn)), F.col("t_all"))
        asked = now.join(wanted.select("grp", "want"), "grp", "left")
        asked = asked.join(F.broadcast(targets), (F.col("grp") == F.col("t_grp")) & (spot >= F.col("t_low")) & (spot < F.col("t_high")), "left")
        asked = asked.join(F.broadcast(settled), (F.col("grp") == F.col("s_grp")) & (F.col("shard") == F.col("s_shard")), "left")
        want = F.when(~F.col("linked"), F.lit(FREE)).when(F.col("s_grp").isNotNull(), F.lit(None)).otherwise(F.coalesce("t_want", "want"))
        asking = materialise(asked.withColumn("want", F.when(want != F.col("shard"), want)).drop("t_grp", "t_low", "t_high", "t_want", "t_all", "s_grp", "s_shard"))
        tally = {(int(r["shard"]), int(r["want"])): int(r["n"]) for r in asking.where("want is not null").groupBy("shard", "want").agg(F.count(F.lit(1)).alias("n")).collect()}
        moves = exchange({k: n for k, n in tally.items() if k[1] != FREE}, {k[0]: n for k, n in tally.items() if k[1] == FREE})
        if not moves:
            stale += 1
            continue
        granted = spark.createDataFrame(moves, "m_from int, m_want int, m_low long, m_high long, m_to int")
        numbered = with_rank(asking.where("want is not null"), ["shard", "want"], order, scatter, "_rank", spread)
        fits = (F.col("shard") == F.col("m_from")) & (F.col("want") == F.col("m_want")) & (F.col("_rank") >= F.col("m_low")) & (F.col("_rank") < F.col("m_high"))
        # at most two rows per pair of shards
        moved = numbered.join(F.broadcast(granted), fits, "left").withColumn("shard", F.coalesce("m_to", "shard"))
        later = materialise(moved.select(*now.columns).unionByName(asking.where("want is null").select(*now.columns)))
        before, cut = cut, cut_links(later.where("linked"), room).first()["cut"]
        if cut > before:
            stale, cut = stale + 1, before
            continue
        stale, now = stale + 1 if cut == before else 0, later
    return now.drop("linked")


def shard_documents(docs: DataFrame, shards: int = 24, rounds: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of (doc_id, text).

    Size is the text's UTF-8 bytes plus 8, null texts count as empty; equal texts are linked.
    The law is ``rows``: shard counts are at most one apart; ``slot`` is gapless from 0 inside a shard.
    Extra columns are ignored; an empty table gives an empty result.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    narrow = docs.select(
        F.col("doc_id").cast("long"),
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.xxhash64(text, F.octet_length(text), F.crc32(text)).alias("grp"),
    )
    placed = assign(materialise(narrow), shards, rounds)
    slotted = with_rank(placed, ["shard"], [F.col("doc_id"), F.col("grp")], F.xxhash64("doc_id", "grp"), "slot")
    return slotted.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op9_label_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards."""
    return shard_documents(table(spark, sf_dir, "documents"))
