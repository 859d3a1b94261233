"""Best-fit packing of token sequences in bulk-synchronous rounds.

Documents are cut into pieces; sequences start as empty gaps, as many as the ids fill at least. A round takes
the longest pieces left (a window of lengths) and all gaps that hold any of them, range-sorts both by size over
the cluster, and sweeps each range for successors: a piece takes the smallest gap that holds it and has a slot left. What a range
leaves over is resolved by rank: its pieces go, in order, to the nearest gaps that ranges of larger sizes left over, for which the driver
only sees two counts a range. Then gaps are updated, and the next round begins, until no piece is left; new
sequences are opened only when a piece fits no gap at all. When the pieces and gaps left are no more than one task's share of a sweep, that task goes on
alone, one piece a round.
"""

from __future__ import annotations

import math
import zlib
from array import array
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from residual_marginals.llm.common import empty, local_threads, materialise, small_batches, table, unused, vocabulary

#: A round takes lengths down to this share of the longest piece left; all at once when that is at most SMALL.
WINDOW, SMALL = 0.8, 16
#: Pieces and gaps that one task sweeps.
SWEEP_ROWS = 1 << 16


class TextEncoder:
    """Encodes whole texts with the ids of the given tokenizer file.

    Texts go through the faster ``tiktoken`` with the merges and the pattern of the same file, if it gives the
    same ids on a fixed trial, and through ``tokenizers`` otherwise. Texts that spell a special token always go through
    ``tokenizers``, which knows those. Tests compare both on every code point.
    """

    TRIAL = " The quick-brown föx's 1234 été;\n\tx=3.14!! 日本語 we'll aaaaaaa  \n\n <b>\u3000\x85\x1c"

    def __init__(self, path: str):
        local_threads()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        fast = self._fast(path, self.special)
        self.fast = fast if fast and fast(self.TRIAL) == self._whole(self.TRIAL) else self._whole

    def _whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    @staticmethod
    def _fast(path: str, special: list[str]):
        try:
            import json

            import public_tokenizers
            import tiktoken
        except ImportError:
            return None
        # the usual printable stand-ins for bytes in byte-level vocabularies
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in shown]
        byte_of = {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(hidden)}
        with open(path, encoding="utf-8") as file:
            words = json.load(file)["model"]["vocab"]
        ranks = {bytes(byte_of[c] for c in word): k for word, k in words.items() if word not in special}
        return tiktoken.Encoding("texts", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        """Little-endian unsigned 32-bit ids of each text (executors are little-endian machines)."""
        for text in texts:
            known = any(s in text for s in self.special)
            yield array("I", self._whole(text) if known else self.fast(text)).tobytes() if text else b""


def pieces(docs: DataFrame, capacity: int = 2048, tokenizer: str | None = None, end_id: int = 0, keep_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32[, ids]): every document as pieces of at most ``capacity`` ids.

    A document is its ids followed by ``end_id``; null texts count as empty. Longer ones are cut
    from the end into full pieces, so only the first piece may be shorter. Rows that repeat are cut one by one, a null doc_id stays
    null, extra columns are ignored, an empty table gives no piece.
    """
    small_batches(docs.sparkSession, 1000)
    path = tokenizer or vocabulary("byte_bpe_50k.json")
    tail = np.array([end_id], "<u4").tobytes()

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        encoder = TextEncoder(path)
        for batch in batches:
            rows = []
            ids_of = encoder.encode([t or "" for t in batch["text"]])
            for doc_id, ids in zip(batch["doc_id"].tolist(), ids_of):
                ids += tail
                total = len(ids) // 4
                first = total % capacity or capacity
                bounds = [0, *range(first, total + 1, capacity)]
                for k, (a, b) in enumerate(zip(bounds, bounds[1:])):
                    part = ids[4 * a : 4 * b]
                    rows.append((doc_id, k, a, b - a, zlib.crc32(part), np.frombuffer(part, "<u4").astype(np.int32) if keep_ids else None))
            out = pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32", "ids"])
            out["doc_id"] = out["doc_id"].astype("Int64")
            yield out if keep_ids else out.drop(columns="ids")

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if keep_ids else "")
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInPandas(cut, schema)


def sweep(sizes: np.ndarray, slots: np.ndarray, who: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Successor sweep over pieces (``slots`` 0) and gaps by falling size, gaps before pieces of their size.

    Each piece takes the smallest gap seen so far that has a slot left. Returns (pieces, gaps) that met, as positions, the positions of
    the pieces without a gap in sweep order, and of the gaps with slots left in sweep order, with the number of those.
    """
    order = np.lexsort((who, slots == 0, -sizes))
    many = np.maximum(slots[order], 1)
    spot = np.repeat(order, many)
    is_gap = slots[spot] > 0
    # like brackets: a piece closes the last open slot, which stands on its level
    depth = np.cumsum(np.where(is_gap, 1, -1))
    level = np.where(is_gap, depth, depth + 1)
    by_level = np.argsort(level, kind="stable")
    a, b = by_level[:-1], by_level[1:]
    met = (level[a] == level[b]) & is_gap[a] & ~is_gap[b]
    free = np.ones(len(spot), bool)
    free[a[met]] = free[b[met]] = False
    left = spot[free & is_gap]
    first = np.nonzero(np.r_[True, left[1:] != left[:-1]])[0] if len(left) else np.zeros(0, np.int64)
    return spot[b[met]], spot[a[met]], spot[free & ~is_gap], left[first], np.diff(np.r_[first, len(left)])


def _swept(rows: DataFrame) -> DataFrame:
    """(part, state, piece, size, seq, at, many): each part's own matches (state 0), pieces left (1) and gaps left (2) with their rank among those of the part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        sizes, slots, who = (whole.column(c).to_numpy() for c in ("size", "slots", "who"))
        piece, gap, alone, spare, many = sweep(sizes, slots, who)
        rank = np.cumsum(many) - many
        none = lambda n: np.zeros(n, np.int64)
        columns = {
            "state": np.repeat(np.arange(3), [len(piece), len(alone), len(spare)]),
            "piece": np.r_[who[piece], who[alone], none(len(spare))],
            "size": np.r_[sizes[piece], sizes[alone], sizes[spare]],
            "seq": np.r_[who[gap], none(len(alone)), who[spare]],
            "at": np.r_[none(len(piece)), np.arange(len(alone)), rank],
            "many": np.r_[none(len(piece)), none(len(alone)) + 1, many],
        }
        part = np.full(len(columns["at"]), TaskContext.get().partitionId())
        yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (part, *columns.values())], names=["part", *columns])

    return rows.mapInArrow(run, "part long, state long, piece long, size long, seq long, at long, many long")


def conflicts(left: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int, int, int]]:
    """Which pieces left in one part get which gaps left in the parts before it: (piece part, first piece rank, pairs, gap part, end gap rank, first pair).

    ``left``: (part, pieces left, slots left) of the parts in order. Pieces come by rank and take the nearest slots first. At most two
    rows a part come out.
    """
    stack, out, pair = [], [], 0
    for part, pieces, slots in sorted(left):
        rank = 0
        while rank < pieces and stack:
            there, end = stack.pop()
            n = min(pieces - rank, end)
            out.append((part, rank, n, there, end, pair))
            rank, pair = rank + n, pair + n
            if end > n:
                stack.append((there, end - n))
        if slots:
            stack.append((part, slots))
    return out


def _finished(rows: DataFrame, capacity: int, opened: int) -> DataFrame:
    """(piece, size, seq): the last rows, one piece after the other, each to the smallest gap that holds it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        sizes, slots, who = (whole.column(c).to_numpy() for c in ("size", "slots", "who"))
        gaps = sorted(zip(sizes[slots > 0].tolist(), who[slots > 0].tolist()))
        fresh, out = opened, []
        pieces = np.nonzero(slots == 0)[0]
        for k in pieces[np.lexsort((who[pieces], -sizes[pieces]))].tolist():
            size = int(sizes[k])
            at = bisect_left(gaps, (size, -1))
            if at < len(gaps):
                gap, seq = gaps.pop(at)
            else:
                gap, seq, fresh = capacity, fresh, fresh + 1
            out.append((int(who[k]), size, seq))
            insort(gaps, (gap - size, seq))
        columns = np.array(out, np.int64).reshape(-1, 3).T
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(c)) for c in columns], names=["piece", "size", "seq"])

    return rows.coalesce(1).mapInArrow(run, "piece long, size long, seq long")


def _resolved(swept: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(matches (piece, size, seq), pieces that found no gap (piece, size)) of a sweep over several parts."""
    spark = swept.sparkSession
    tally = swept.where("state > 0").groupBy("part").agg(F.sum(F.when(F.col("state") == 1, 1).otherwise(0)).alias("p"), F.sum(F.when(F.col("state") == 2, F.col("many")).otherwise(0)).alias("g"))
    deals = conflicts([(r["part"], r["p"], r["g"]) for r in tally.collect()])
    schema = "p_part long, p_low long, n long, g_part long, g_end long, pair0 long"
    # a row or two for each part of the sweep
    deals = F.broadcast(spark.createDataFrame(deals, schema) if deals else empty(spark, schema))
    alone = swept.where("state = 1").join(deals, (F.col("part") == F.col("p_part")) & (F.col("at") >= F.col("p_low")) & (F.col("at") < F.col("p_low") + F.col("n")), "left")
    given = alone.where("p_part is not null").select("piece", "size", (F.col("pair0") + F.col("at") - F.col("p_low")).alias("pair"))
    low, high = F.greatest("at", F.col("g_end") - F.col("n")), F.least(F.col("at") + F.col("many"), F.col("g_end")) - 1
    spare = swept.where("state = 2").join(deals, F.col("part") == F.col("g_part")).where(low <= high)
    slots = spare.select("seq", "g_end", "pair0", F.explode(F.sequence(low, high)).alias("slot")).select("seq", (F.col("pair0") + F.col("g_end") - 1 - F.col("slot")).alias("pair"))
    matches = swept.where("state = 0").select("piece", "size", "seq").unionByName(given.join(slots, "pair").select("piece", "size", "seq"))
    return matches, alone.where("p_part is null").select("piece", "size")


def pack(cut: DataFrame, capacity: int = 2048, window: float = WINDOW, sweep_rows: int = SWEEP_ROWS) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to a table of pieces (length, from 1 to ``capacity``, and any other columns except those two).

    Every row keeps its place in the result, rows that repeat are pieces of their own; an empty table gives an empty result. Pieces of
    one length are placed in the order in which they are stored.
    """
    spark, key = cut.sparkSession, unused(cut, "_row")
    stored = materialise(cut.withColumn(key, F.monotonically_increasing_id()))
    base = stored.select(F.col(key).alias("piece"), F.col("length").cast("long").alias("size"))
    facts = base.agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("total"), F.min("size").alias("least"), F.max("size").alias("most"), F.count("size").alias("known")).first()
    if facts["n"] and (facts["known"] < facts["n"] or facts["least"] < 1 or facts["most"] > capacity):
        raise ValueError(f"pieces must have 1 to {capacity} ids")
    placed = [empty(spark, "piece long, size long, seq long, turn int")]
    opened = -(-(facts["total"] or 0) // capacity)
    gaps = spark.range(opened).select(F.col("id").alias("seq"), F.lit(capacity).cast("long").alias("gap"))
    waiting, below, turn, top = empty(spark, "piece long, size long"), capacity + 1, 0, facts["most"]
    while top:
        slots = F.greatest(F.floor(F.col("gap") / top), F.lit(1)).cast("long")
        offered = gaps.select(F.col("gap").alias("size"), slots.alias("slots"), F.col("seq").alias("who"))
        asking = lambda rows: rows.select("size", F.lit(0).cast("long").alias("slots"), F.col("piece").alias("who"))
        rest = offered.unionByName(asking(base.where(F.col("size") < below).unionByName(waiting)))
        if rest.count() <= sweep_rows:
            placed.append(materialise(_finished(rest, capacity, opened)).withColumn("turn", F.lit(turn + 1)))
            break
        widest = gaps.agg(F.max("gap")).first()[0] or 0
        floor = max(1, min(top, math.ceil(top * window))) if top > SMALL else 1
        # lengths come into play by falling windows; what found no gap goes on to the next sweep
        active = base.where((F.col("size") < below) & (F.col("size") >= floor)).unionByName(waiting)
        if top > widest:
            big = active.where(F.col("size") > widest).agg(F.sum("size")).first()[0]
            fresh = -(-big // capacity)
            gaps = gaps.unionByName(spark.range(opened, opened + fresh).select(F.col("id").alias("seq"), F.lit(capacity).cast("long").alias("gap")))
            opened += fresh
            offered = gaps.select(F.col("gap").alias("size"), slots.alias("slots"), F.col("seq").alias("who"))
        # a gap has as many slots as pieces of the greatest length surely fit, so it is filled before a wider one is touched
        union = offered.where(F.col("size") >= floor).unionByName(asking(active))
        parts = max(1, -(-union.count() // sweep_rows))
        ranged = union.repartitionByRange(parts, F.col("size").desc(), (F.col("slots") == 0), "who") if parts > 1 else union.coalesce(1)
        swept = materialise(_swept(ranged))
        if parts > 1:
            matches, alone = _resolved(swept)
            matches = materialise(matches)
        else:
            matches, alone = swept.where("state = 0").select("piece", "size", "seq"), swept.where("state = 1").select("piece", "size")
        turn += 1
        placed.append(matches.withColumn("turn", F.lit(turn)))
        taken = matches.groupBy("seq").agg(F.sum("size").alias("taken"))
        gaps = materialise(gaps.join(taken, "seq", "left").select("seq", (F.col("gap") - F.coalesce("taken", F.lit(0))).alias("gap")).where(F.col("gap") >= facts["least"]))
        waiting = materialise(alone) if parts > 1 else alone
        below = floor
        top = base.where(F.col("size") < below).unionByName(waiting).agg(F.max("size")).first()[0]
    every = reduce(DataFrame.unionByName, placed)
    # a sequence holds at most ``capacity`` pieces
    before = Window.partitionBy("seq").orderBy("turn", F.desc("size"), "piece").rowsBetween(Window.unboundedPreceding, -1)
    offset = F.coalesce(F.sum("size").over(before), F.lit(0)).alias("offset")
    found = every.select(F.col("piece").alias(key), F.col("seq").alias("sequence_id"), offset)
    return stored.join(found, key).select(*cut.columns, "sequence_id", "offset")


def op8_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 2048 ids. Rows that repeat are packed as often as they come, null texts are one end id."""
    return pack(pieces(table(spark, sf_dir, "documents"))).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
