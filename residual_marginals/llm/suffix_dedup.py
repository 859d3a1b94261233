"""Repeated passages by a hash-compared suffix sort.

A byte goes when a string of ``length`` bytes around it also starts anywhere else. Every such
string holds an anchor: the gram of ``gram`` bytes with the least mixed hash in it (the last of
equals), so equal strings have equal anchors at equal places. Only suffixes at anchors whose gram occurs
again are compared. First whole neighbourhoods of an anchor (all strings that have it) are compared by a 128-bit BLAKE2
digest of their bytes; neighbourhoods that occur again are settled. For the rest, the text to the right and to the
left of each anchor becomes a suffix, and both sets are sorted by a mergesort whose comparisons
find the common extension by binary search over prefix polynomial hashes. Sorted neighbours are
verified byte by byte; a hash collision sends the block to a plain sort. In sorted order the suffixes that share a
given extension stand together, so a string of the anchor repeats exactly if another suffix
shares its run on both sides. An anchor with more distinct neighbourhoods than ``GROUP_LIMIT`` is not gathered: its strings
are counted one by one by their 128-bit digest instead. Grams and neighbourhoods that a large share of all rows has are told to every
task instead of being dealt to one.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.llm.common import materialise, small_batches, table

LENGTH, GRAM = 200, 50
GROUP_LIMIT = 2000
#: Keys that may be broadcast because each holds a larger share of the rows than one of these.
HOT_KEYS = 5000
#: Suffixes sorted at once, and bytes of a text hashed at once.
BLOCK, STRIDE = 8192, 1 << 20

BASE = np.uint64(0x9E3779B97F4A7C15)
INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_LETTERS = np.random.default_rng(20240501).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[str, np.ndarray] = {}


def powers(base: np.uint64, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1), modulo 2 ** 64."""
    known = _POWERS.get(str(base))
    if known is None or len(known) < n:
        steps = np.full(max(n, 1 << 12), base, np.uint64)
        steps[0] = 1
        known = _POWERS[str(base)] = np.multiply.accumulate(steps)
    return known[:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xFF51AFD7ED558CCD)
    return h ^ (h >> np.uint64(29))


def prefix_hashes(data: np.ndarray) -> np.ndarray:
    """Hash sums of every prefix of a byte array (one more entry than bytes)."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_LETTERS[data] * powers(BASE, len(data)), out=out[1:])
    return out


def range_hashes(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Mixed hashes of byte ranges, the same wherever the range stands."""
    return mix((prefix[ends] - prefix[starts]) * powers(INVERSE, len(prefix))[starts])


def sliding_minimum(values: np.ndarray, width: int) -> np.ndarray:
    """Least value of every window, from running minima inside blocks of the window's width."""
    n = len(values)
    padded = np.full(-(-n // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[:n] = values
    blocks = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def anchors(data: np.ndarray, length: int = LENGTH, gram: int = GRAM):
    """(position, first start, last start, gram hash) of a text's anchors, by position.

    Starts are those of the strings that have the anchor; its neighbourhood reaches from the first start to
    the end of the last string.
    """
    n, parts = len(data), []
    low = np.uint64((1 << 24) - 1)
    for at in range(0, n - length + 1, STRIDE):
        own = data[at : at + STRIDE + length - 1]
        prefix = prefix_hashes(own)
        spots = np.arange(len(own) - gram + 1)
        hashes = range_hashes(prefix, spots, spots + gram)
        ranked = (hashes & ~low) | (low - spots.astype(np.uint64))
        best = (low - (sliding_minimum(ranked, length - gram + 1) & low)).astype(np.int64)
        cut = np.nonzero(np.diff(best))[0] + 1
        first, last = np.r_[0, cut], np.r_[cut, len(best)] - 1
        spot = best[first]
        parts.append((spot + at, first + at, last + at, hashes[spot]))
    if not parts:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64))
    spot, first, last, grams = (np.concatenate(x) for x in zip(*parts))
    # runs of one anchor that a block's edge has cut are one run
    head = np.nonzero(np.r_[True, np.diff(spot) != 0])[0]
    return spot[head], first[head], last[np.r_[head[1:], len(spot)] - 1], grams[head]


def digests(data, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """128-bit BLAKE2 digests of byte ranges, as rows of two longs."""
    view, blake = memoryview(data), hashlib.blake2b
    found = b"".join([blake(view[a:b], digest_size=16).digest() for a, b in zip(starts.tolist(), ends.tolist())])
    return np.frombuffer(found, np.int64).reshape(-1, 2)


class Suffixes:
    """Strings of bounded length in one matrix, ordered by a mergesort that compares prefix hashes."""

    def __init__(self, strings: list[bytes]):
        self.sizes = np.fromiter(map(len, strings), np.int64, len(strings))
        width = int(self.sizes.max(initial=0))
        self.bytes = np.zeros((len(strings), width + 1), np.uint8)
        flat = np.frombuffer(b"".join(strings), np.uint8)
        self.bytes[np.arange(width + 1)[None, :] < self.sizes[:, None]] = flat
        self.hashes = np.zeros((len(strings), width + 1), np.uint64)
        np.cumsum(_LETTERS[self.bytes[:, :-1]] * powers(BASE, width), axis=1, out=self.hashes[:, 1:])
        self.width = width

    def common(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Common extension of pairs, by binary search over prefix hashes."""
        low, high = np.zeros(len(i), np.int64), np.minimum(self.sizes[i], self.sizes[j])
        for _ in range(int(self.width).bit_length() + 1):
            middle = (low + high + 1) // 2
            same = self.hashes[i, middle] == self.hashes[j, middle]
            low, high = np.where(same, middle, low), np.where(same, high, middle - 1)
            high = np.maximum(low, high)
        return low

    def before(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Whether string i comes before j, ties by position."""
        k = self.common(i, j)
        a = np.where(k < self.sizes[i], self.bytes[i, k].astype(np.int64) + 1, 0)
        b = np.where(k < self.sizes[j], self.bytes[j, k].astype(np.int64) + 1, 0)
        return (a < b) | ((a == b) & (i < j))

    def order(self) -> np.ndarray:
        """Positions in suffix order: runs of doubling size are merged, each element finding its place in the other run."""
        n = len(self.sizes)
        order, size = np.arange(n), 1
        while size < n:
            spots = np.arange(n)
            run = spots // size
            other = np.where(run % 2 == 0, run + 1, run - 1) * size
            start, stop = np.minimum(other, n), np.minimum(other + size, n)
            low, high = start.copy(), stop.copy()
            for _ in range(size.bit_length()):
                open_ = low < high
                if not open_.any():
                    break
                middle = (low + high) // 2
                who, there = order[spots[open_]], order[middle[open_]]
                after = self.before(there, who)
                low[open_] = np.where(after, middle[open_] + 1, low[open_])
                high[open_] = np.where(after, high[open_], middle[open_])
            merged = np.empty_like(order)
            base = np.minimum(run // 2 * 2 * size, n)
            merged[base + (spots - run * size) + (low - start)] = order
            order, size = merged, size * 2
        return order

    def sorted_runs(self) -> tuple[np.ndarray, np.ndarray]:
        """Suffix order and the true common extension of each with the one before it."""
        order = self.order()
        claimed = self.common(order[1:], order[:-1])
        true = self._bytes_common(order)
        if not np.array_equal(claimed, true):
            # a collision: sort the bytes themselves
            keyed = [self.bytes[k, : self.sizes[k]].tobytes() for k in range(len(order))]
            order = np.array(sorted(range(len(keyed)), key=keyed.__getitem__))
            true = self._bytes_common(order)
        return order, np.r_[-1, true]

    def _bytes_common(self, order: np.ndarray) -> np.ndarray:
        out = np.zeros(max(0, len(order) - 1), np.int64)
        for at in range(0, len(out), 2048):
            a, b = order[at + 1 : at + 2049], order[at : at + len(order[at + 1 : at + 2049])]
            differ = self.bytes[a] != self.bytes[b]
            first = np.where(differ.any(axis=1), differ.argmax(axis=1), self.width)
            out[at : at + len(a)] = np.minimum(first, np.minimum(self.sizes[a], self.sizes[b]))
        return out


def repeated_strings(lefts: list[bytes], rights: list[bytes], length: int = LENGTH) -> np.ndarray:
    """Matrix [suffix, x]: whether the string that starts x bytes before the anchor repeats among these.

    ``lefts`` are the bytes before each anchor in reverse, ``rights`` those from it on. A string that does not
    fit into its neighbourhood is never set.
    """
    sides = []
    for strings in (lefts, rights):
        suffixes = Suffixes(strings)
        order, shared = suffixes.sorted_runs()
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        sides.append((suffixes.sizes, shared, place))
    (l_sizes, l_shared, l_place), (r_sizes, r_shared, r_place) = sides
    n, most = len(lefts), int(l_sizes.max(initial=0))
    out = np.zeros((n, most + 1), bool)
    for x in range(most + 1):
        fits = np.nonzero((l_sizes >= x) & (r_sizes >= length - x))[0]
        if len(fits) < 2:
            continue
        left = np.cumsum(l_shared < x)[l_place[fits]]
        right = np.cumsum(r_shared < length - x)[r_place[fits]]
        _, where, many = np.unique(left * (n + 1) + right, return_inverse=True, return_counts=True)
        out[fits, x] = many[where] > 1
    return out


KEY = ["doc_id", "mark"]


def _keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, mark, text as bytes): rows that repeat in both have the same key and the same answer."""
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 62))).alias("doc_id"), text.alias("data")).withColumn("mark", F.xxhash64("data", "doc_id"))


def find_anchors(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """Anchors of all texts: (doc_id, mark, spot, before, after, gram, around, proof), the last two the digest of the neighbourhood."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, marks = batch.column("doc_id").to_numpy(), batch.column("mark").to_numpy()
            rows, around = [], []
            for k in range(batch.num_rows):
                data = batch.column("data")[k].as_buffer()
                rows.append(anchors(np.frombuffer(data, np.uint8), length, gram))
                around.append(digests(data, rows[-1][1], rows[-1][2] + length))
            many = [len(r[0]) for r in rows]
            if not sum(many):
                continue
            spot, first, last, grams = (np.concatenate(x) for x in zip(*rows))
            one, two = np.concatenate(around).T
            columns = [np.repeat(ids, many), np.repeat(marks, many), spot.astype(np.int64), (spot - first).astype(np.int16), (last - spot).astype(np.int16), grams.view(np.int64), np.ascontiguousarray(one), np.ascontiguousarray(two)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["doc_id", "mark", "spot", "before", "after", "gram", "around", "proof"])

    long_enough = docs.where(F.octet_length("data") >= length).select("doc_id", "mark", "data")
    return long_enough.mapInArrow(scan, "doc_id long, mark long, spot long, before short, after short, gram long, around long, proof long")


def with_common_keys(rows: DataFrame, counted: DataFrame, keys: list[str], total: int) -> DataFrame:
    """``rows`` joined with ``counted`` (the keys, ``n`` rows of each, and more), where keys of many rows are broadcast.

    Those are the keys that hold more than 1 / ``HOT_KEYS`` of all rows, so there are at most ``HOT_KEYS`` of them.
    """
    common = F.col("n") > max(1000, total // HOT_KEYS)
    hot = materialise(counted.where(common))
    if not hot.limit(1).count():
        return rows.join(counted, keys)
    rest = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(counted.where(~common), keys)
    return rows.join(F.broadcast(hot), keys).unionByName(rest)


def repeated_ranges(keyed: DataFrame, length: int = LENGTH, gram: int = GRAM, group_limit: int = GROUP_LIMIT) -> DataFrame:
    """(doc_id, mark, start, stop): byte ranges that together are exactly the bytes to remove."""
    found = materialise(find_anchors(keyed, length, gram))
    total = found.count()
    again = materialise(found.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    open_ = materialise(with_common_keys(found, again, ["gram"], total).drop("n"))
    whole = ["gram", "around", "proof"]
    kinds = materialise(open_.groupBy(*whole).agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("doc_id", "mark", "spot", "before", "after")).alias("one")))
    settled = with_common_keys(open_, kinds.where("n > 1").select(*whole, "n"), whole, total)
    ranges = settled.select(*KEY, (F.col("spot") - F.col("before")).alias("start"), (F.col("spot") + F.col("after") + length).alias("stop"))
    # anchors with several neighbourhoods, at least one of them alone
    mixed = kinds.groupBy("gram").agg(F.count(F.lit(1)).alias("n"), F.min("n").alias("least")).where("n > 1 and least = 1")
    mixed = materialise(mixed.select("gram", "n", (F.col("n") > group_limit).alias("crowded")))
    one = kinds.select("gram", "one", (F.col("n") == 1).alias("alone"))
    suspects = with_common_keys(one, mixed, ["gram"], total).select("one.*", "gram", "alone", "crowded")
    per_text = materialise(suspects.groupBy(*KEY).agg(F.collect_list(F.struct("spot", "before", "after", "gram", "alone", "crowded")).alias("spots")))

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for doc_id, mark, data, spots in zip(batch["doc_id"], batch["mark"], batch["data"], batch["spots"]):
                for s in spots:
                    spot, start, stop = s["spot"], s["spot"] - s["before"], s["spot"] + s["after"] + length
                    rows.append((doc_id, mark, spot, s["gram"], s["alone"], s["crowded"], bytes(data[start:spot])[::-1], bytes(data[spot:stop])))
            yield pd.DataFrame(rows, columns=["doc_id", "mark", "spot", "gram", "alone", "crowded", "left_side", "right_side"])

    schema = "doc_id long, mark long, spot long, gram long, alone boolean, crowded boolean, left_side binary, right_side binary"
    sides = materialise(keyed.join(per_text, KEY).select(*KEY, "data", "spots").mapInPandas(cut, schema).dropDuplicates(["doc_id", "mark", "spot"]))

    def ranges_of(frame: pd.DataFrame, hit: np.ndarray) -> pd.DataFrame:
        row, x = np.nonzero(hit & frame["alone"].to_numpy()[:, None])
        spot = frame["spot"].to_numpy()[row]
        return pd.DataFrame({"doc_id": frame["doc_id"].to_numpy()[row], "mark": frame["mark"].to_numpy()[row], "start": spot - x, "stop": spot - x + length})

    def settle(frame: pd.DataFrame) -> pd.DataFrame:
        hit = repeated_strings([bytes(b) for b in frame["left_side"]], [bytes(b) for b in frame["right_side"]], length)
        return ranges_of(frame, hit)

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        rows = 0
        for batch in batches:
            held.append(batch)
            rows += len(batch)
            if rows >= BLOCK:
                whole = pd.concat(held, ignore_index=True)
                keep = int((whole["gram"] == whole["gram"].iloc[-1]).sum())
                if len(whole) > keep:
                    yield settle(whole.iloc[: len(whole) - keep].reset_index(drop=True))
                held, rows = [whole.iloc[len(whole) - keep :]], keep
        if held:
            yield settle(pd.concat(held, ignore_index=True))

    quiet = sides.where(~F.col("crowded")).repartition("gram").sortWithinPartitions("gram")
    compared = quiet.mapInPandas(compare, "doc_id long, mark long, start long, stop long")

    def strings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.to_pylist()
            for k in range(0, len(rows), 256):
                many, starts, found = [], [], []
                for row in rows[k : k + 256]:
                    data = row["left_side"][::-1] + row["right_side"]
                    at = np.arange(len(data) - length + 1)
                    many.append(len(at))
                    starts.append(row["spot"] - len(row["left_side"]) + at)
                    found.append(digests(data, at, at + length))
                one, two = np.concatenate(found).T
                each = lambda c: np.repeat([r[c] for r in rows[k : k + 256]], many)  # noqa: E731,B023
                columns = [each("doc_id"), each("mark"), np.concatenate(starts), each("alone"), np.ascontiguousarray(one), np.ascontiguousarray(two)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["doc_id", "mark", "start", "alone", "h", "g"])

    crowded = sides.where("crowded")
    if crowded.limit(1).count():
        singles = materialise(crowded.mapInArrow(strings, "doc_id long, mark long, start long, alone boolean, h long, g long"))
        many = materialise(singles.groupBy("h", "g").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
        counted = with_common_keys(singles.where("alone"), many, ["h", "g"], singles.count())
        compared = compared.unionByName(counted.select(*KEY, "start", (F.col("start") + length).alias("stop")))
    return ranges.unionByName(compared)


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, group_limit: int = GROUP_LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept per row of (doc_id, text).

    Texts count as UTF-8 bytes, null as empty. Rows that repeat are different texts to each other, so each
    loses what the other has. ``kept`` is the rest as bytes. Extra columns are ignored; an empty table gives
    an empty result.
    """
    small_batches(docs.sparkSession, 500)
    keyed = _keyed(docs)
    ranges = repeated_ranges(keyed, length, gram, group_limit)
    merged = materialise(ranges.groupBy(*KEY).agg(F.array_sort(F.collect_set(F.struct("start", "stop"))).alias("ranges")))

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for doc_id, data, ranges in zip(batch["doc_id"], batch["data"], batch["ranges"]):
                kept, at, removed, spans = [], 0, 0, 0
                for start, stop in joined(ranges if ranges is not None else ()):
                    kept.append(bytes(data[at:start]))
                    removed, spans, at = removed + stop - start, spans + 1, stop
                rest = b"".join([*kept, bytes(data[at:])])
                rows.append((doc_id, len(data), removed, spans, hashlib.sha256(rest).hexdigest(), rest))
            yield pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    done = keyed.join(merged, KEY, "left").select("doc_id", "data", "ranges")
    out = done.mapInPandas(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    return out.withColumn("doc_id", F.when(F.col("doc_id") != -(1 << 62), F.col("doc_id")))


def joined(ranges) -> Iterator[tuple[int, int]]:
    """Maximal runs of sorted ranges; ranges that touch are one run."""
    open_ = None
    for r in ranges:
        start, stop = int(r["start"]), int(r["stop"])
        if open_ and start <= open_[1]:
            open_ = (open_[0], max(open_[1], stop))
        else:
            if open_:
                yield open_
            open_ = (start, stop)
    if open_:
        yield open_


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without bytes of 200-byte strings that occur again."""
    done = remove_repeats(table(spark, sf_dir, "documents"))
    return done.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
