"""SimHash near-duplicate groups by a Gray-order hierarchical index.

Fingerprints are sorted by their rank in the Gray sequence, so that neighbours in
the order share long bit patterns. A tree over that order keeps in every node the
bits on which all of its members agree. A pair of nodes is given up, with
everything below it, once the differences on the bits shared so far exceed the
radius; a child only counts the bits that its parent had not shared yet.

Across the cluster the fingerprint is cut into blocks; two fingerprints within the
radius agree on all but ``radius`` of the blocks, so one copy is sent to every choice of
agreeing blocks and the trees are built per choice and key. A key that many distinct
fingerprints share is cut again in the same way on its remaining bits, until the free bits
bound the group. Links inside a group are reported as a spanning forest, never as all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from residual_marginals.llm.common import connected_components, materialise, small_batches

SEED = 42
LEAF = 16
FANOUT = 8
#: Distinct fingerprints in one key before it is cut again.
GROUP_LIMIT = 1 << 16
CHUNK = 1 << 16
#: Rows whose groups are compared at once.
RUN = 1 << 15
#: Standard errors beyond the expected bits within which wide fingerprints link.
TOLERANCE = 1.0


#: Each byte value as eight counters of one byte.
_LANES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").copy().view(np.uint64).ravel()


def bit_counts(hashes: np.ndarray) -> np.ndarray:
    """How many of the hashes have each of the 64 bits set; counters of one byte add up to 255 hashes at once."""
    lanes = _LANES[hashes.view(np.uint8).reshape(-1, 8)]
    sums = np.add.reduceat(lanes, np.arange(0, len(lanes), 255), axis=0)
    return sums.view(np.uint8).reshape(len(sums), 64).sum(axis=0, dtype=np.int64)


def _remixed(hashes: np.ndarray, k: int) -> np.ndarray:
    """Further independent hashes of the same shingles."""
    h = (hashes ^ np.uint64(k * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(29))


def wide_fingerprint(text: str | None, width: int, words: int) -> bytes:
    """Majority fingerprint of ``words`` 64-bit words, the first from the shingles' own hashes."""
    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not tokens:
        return bytes(8 * words)
    joined = b" ".join(tokens)
    sizes = np.fromiter(map(len, tokens), np.int64, len(tokens))
    ends = np.cumsum(sizes + 1) - 1
    starts = ends - sizes
    if len(tokens) > width:
        starts, ends = starts[: len(tokens) - width + 1], ends[width - 1 :]
    else:
        starts, ends = starts[:1], ends[-1:]
    digest = xxhash.xxh64_intdigest
    ones = np.zeros((words, 64), np.int64)
    for at in range(0, len(starts), CHUNK):
        span = zip(starts[at : at + CHUNK].tolist(), ends[at : at + CHUNK].tolist())
        hashes = np.array([digest(joined[a:b], SEED) for a, b in span], np.uint64)
        for k in range(words):
            ones[k] += bit_counts(hashes if k == 0 else _remixed(hashes, k))
    return np.packbits(ones.ravel() * 2 > len(starts), bitorder="little").tobytes()


def fingerprint(text: str | None, width: int) -> int:
    """Unsigned 64-bit majority fingerprint of the word shingles of one text."""
    return int.from_bytes(wide_fingerprint(text, width, 1), "little")


def fingerprints(docs: DataFrame, width: int = 3, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, fp) and the columns ``carry``: the fingerprint of every row as a signed long. Null and wordless texts get zero."""
    small_batches(docs.sparkSession, 1000)

    @pandas_udf("long")
    def fp(texts: pd.Series) -> pd.Series:
        values = np.fromiter((fingerprint(t, width) for t in texts), np.uint64, len(texts))
        return pd.Series(values.view(np.int64))

    return docs.select("doc_id", *carry, fp(F.col("text").cast("string")).alias("fp"))


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Position of each code in the reflected Gray sequence (prefix XOR of its bits); codes of several words (rows) get as many rank words."""
    rank = codes.copy()
    for step in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(step)
    if rank.ndim > 1:
        # a word is read backwards if the bits before it are odd
        odd = np.bitwise_xor.accumulate(rank & np.uint64(1), axis=1)
        rank[:, 1:] ^= np.uint64(0) - odd[:, :-1]
    return rank


def differing(a: np.ndarray, b: np.ndarray, where: np.ndarray | None = None) -> np.ndarray:
    """Differing bits of codes (last axis: words), counted where given."""
    apart = a ^ b if where is None else (a ^ b) & where
    return np.bitwise_count(apart).sum(axis=-1, dtype=np.int64)


class GrayTree:
    """Static tree over distinct codes (rows of words) in Gray order; every node keeps its members' shared bits."""

    def __init__(self, codes: np.ndarray):
        codes = codes if codes.ndim > 1 else codes[:, None]
        self.order = np.lexsort(gray_rank(codes).T[::-1])
        self.codes = codes[self.order]
        leaf_starts = np.arange(0, len(self.codes), LEAF)
        both = np.bitwise_and.reduceat(self.codes, leaf_starts)
        any_ = np.bitwise_or.reduceat(self.codes, leaf_starts)
        self.levels = [(both, ~(both ^ any_))]
        while len(both) > 1:
            starts = np.arange(0, len(both), FANOUT)
            both, any_ = np.bitwise_and.reduceat(both, starts), np.bitwise_or.reduceat(any_, starts)
            self.levels.append((both, ~(both ^ any_)))

    def close_pairs(self, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Batches of positions (i < j, in Gray order) whose codes differ in at most ``radius`` bits."""
        top = len(self.levels) - 1
        zero = np.zeros(1, np.int64)
        chunk = CHUNK // self.codes.shape[1]
        stack = [(top, zero, zero, np.zeros(1, np.int64), np.zeros((1, self.codes.shape[1]), np.uint64))]
        while stack:
            level, a, b, spent, seen = stack.pop()
            pattern, shared = self.levels[level]
            common = shared[a] & shared[b]
            spent = spent + differing(pattern[a], pattern[b], common & ~seen)
            keep = spent <= radius
            a, b, spent, common = a[keep], b[keep], spent[keep], common[keep]
            if not len(a):
                continue
            if level == 0:
                yield from self._leaves(a, b, radius)
                continue
            below = len(self.levels[level - 1][0])
            x = (a[:, None] * FANOUT + np.arange(FANOUT))[:, :, None]
            y = (b[:, None] * FANOUT + np.arange(FANOUT))[:, None, :]
            ok = (x < below) & (y < below) & (x <= y)
            row, i, j = np.nonzero(ok)
            left, right = a[row] * FANOUT + i, b[row] * FANOUT + j
            for at in range(0, len(row), chunk):
                part = slice(at, at + chunk)
                stack.append((level - 1, left[part], right[part], spent[row[part]], common[row[part]]))

    def _leaves(self, a: np.ndarray, b: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        n = len(self.codes)
        step = max(1, 1024 // self.codes.shape[1])
        for at in range(0, len(a), step):
            x = a[at : at + step, None] * LEAF + np.arange(LEAF)
            y = b[at : at + step, None] * LEAF + np.arange(LEAF)
            apart = differing(self.codes[np.minimum(x, n - 1)][:, :, None], self.codes[np.minimum(y, n - 1)][:, None, :])
            ok = (apart <= radius) & (x < n)[:, :, None] & (y < n)[:, None, :] & (x[:, :, None] < y[:, None, :])
            row, i, j = np.nonzero(ok)
            yield x[row, i], y[row, j]


def close_in_groups(codes: np.ndarray, group: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Batches of pairs of rows of one group within ``radius`` bits; rows come sorted by group.

    A group of one leaf is compared as it stands, all such groups at once; larger ones by their tree.
    """
    cut = np.nonzero(np.diff(group))[0] + 1
    starts, ends = np.r_[0, cut], np.r_[cut, len(group)]
    sizes = ends - starts
    small = np.repeat(sizes <= LEAF, sizes)
    for step in range(1, min(LEAF, int(sizes.max(initial=0)))):
        i = np.nonzero((group[step:] == group[:-step]) & small[step:])[0]
        i = i[differing(codes[i], codes[i + step]) <= radius]
        yield i, i + step
    for k in np.nonzero(sizes > LEAF)[0].tolist():
        tree = GrayTree(codes[starts[k] : ends[k]])
        at = starts[k] + tree.order
        for i, j in tree.close_pairs(radius):
            yield at[i], at[j]


def forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Smallest member reachable from each of n members over batches of pairs."""
    parent = np.arange(n)
    for i, j in pairs:
        while True:
            ri, rj = parent[i], parent[j]
            differ = ri != rj
            if not differ.any():
                break
            low, high = np.minimum(ri, rj)[differ], np.maximum(ri, rj)[differ]
            np.minimum.at(parent, high, low)
            while True:
                higher = parent[parent]
                if (higher == parent).all():
                    break
                parent = higher
    return parent


def block_masks(free: list[int], blocks: int, radius: int) -> list[int]:
    """Masks of every choice of ``blocks - radius`` of the blocks into which the bits ``free`` are cut."""
    parts = [[int(x) for x in p] for p in np.array_split(np.array(free), blocks)]
    return [sum(1 << bit for part in chosen for bit in part) for chosen in combinations(parts, blocks - radius)]


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >= 1 << 63 else mask


def _keyed(codes: DataFrame, masks: list[int], first: int) -> DataFrame:
    """One row per mask: (choice, key, fp)."""
    choices = F.array(*[F.struct(F.lit(first + k).alias("choice"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for k, m in enumerate(masks)])
    return codes.select("fp", F.explode(choices).alias("c")).select("c.choice", "c.key", "fp")


def links(codes: DataFrame, radius: int = 2, blocks: int = 4, group_limit: int = GROUP_LIMIT) -> DataFrame:
    """(u, v): links between distinct fingerprints ``fp`` that connect all those within ``radius`` bits."""
    masks = block_masks(list(range(64)), blocks, radius)
    keyed = _keyed(codes, masks, 0)
    counts = keyed.groupBy("choice", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    crowded = materialise(counts.where(F.col("n") > group_limit).select("choice", "key"))
    parts = [keyed.join(F.broadcast(crowded) if crowded.count() < 10_000 else crowded, ["choice", "key"], "left_anti")]
    for k, mask in enumerate(masks):
        # the crowded keys of this choice, cut again on the bits that the choice leaves free
        free = [b for b in range(64) if not mask >> b & 1]
        inner = [mask | m for m in block_masks(free, blocks, radius)]
        own = keyed.where(F.col("choice") == k).join(crowded, ["choice", "key"], "left_semi").select("fp")
        parts.append(_keyed(own, inner, (k + 1) * 1000))
    rows = parts[0]
    if crowded.count():
        for more in parts[1:]:
            rows = rows.unionByName(more)

    def solve(frame: pd.DataFrame, group: np.ndarray) -> pd.DataFrame:
        nodes = frame["fp"].to_numpy()
        parent = forest(len(nodes), close_in_groups(nodes.view(np.uint64)[:, None], group, radius))
        linked = np.nonzero(parent != np.arange(len(nodes)))[0]
        return pd.DataFrame({"u": nodes[linked], "v": nodes[parent[linked]]})

    dealt = rows.repartition("choice", "key").sortWithinPartitions("choice", "key")
    return dealt.mapInPandas(_by_whole_groups(solve), "u long, v long")


def _by_whole_groups(solve):
    """A mapInPandas function that gives ``solve`` runs of whole groups of (choice, key), with the rows' group numbers."""

    def numbered(frame: pd.DataFrame) -> np.ndarray:
        choice, key = frame["choice"].to_numpy(), frame["key"].to_numpy()
        return np.cumsum(np.r_[False, (choice[1:] != choice[:-1]) | (key[1:] != key[:-1])])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, rows, goal = [], 0, RUN
        for batch in batches:
            if not len(batch):
                continue
            held.append(batch)
            rows += len(batch)
            if rows >= goal:
                whole = pd.concat(held, ignore_index=True)
                group = numbered(whole)
                done = int(np.searchsorted(group, group[-1]))
                if done:
                    yield solve(whole.iloc[:done], group[:done])
                held, rows = [whole.iloc[done:]], rows - done
                goal = max(RUN, 2 * rows)
        if held:
            whole = pd.concat(held, ignore_index=True)
            yield solve(whole, numbered(whole))

    return run


def allowed_bits(bits: int, similarity: float, tolerance: float = TOLERANCE) -> int:
    """Differing bits up to which fingerprints link: expected at that similarity, plus ``tolerance`` standard errors."""
    share = np.arccos(2 * similarity / (1 + similarity)) / np.pi
    return int(bits * share + tolerance * np.sqrt(bits * share * (1 - share)))


def similar_groups(docs: DataFrame, width: int = 5, similarity: float = 0.8, words: int = 8, block_bits: int = 14, carry: tuple[str, ...] = (), group_limit: int = GROUP_LIMIT, tolerance: float = TOLERANCE) -> DataFrame:
    """Groups by similarity rather than by a fixed number of bits: doc_id, the columns ``carry``, fingerprint (hex), component_id.

    The share of equal bits of wide fingerprints estimates the angle between shingle sets, and so their
    Jaccard similarity s: equal bits are expected at 1 - arccos(2 s / (1 + s)) / pi. Fingerprints that agree on a
    whole block of ``block_bits`` bits meet in the Gray tree of that block's key, which is pruned by the whole fingerprint's shared bits, and link within ``allowed_bits``.
    With 512 bits the standard error of the share is 0.016, and 36 blocks of 14 bits let pairs of similarity 0.8, 0.85 and 0.9 meet
    with probability 0.98, 0.996 and 0.9999. A key holds about n / 2 ** block_bits fingerprints: take more bits beyond some
    hundred million texts. A key with more than ``group_limit`` distinct fingerprints is dealt to parts, and each pair of parts
    gets a tree of its own, so no comparison is lost. Rows are treated as in ``near_groups``.
    """
    small_batches(docs.sparkSession, 1000)
    most = allowed_bits(64 * words, similarity, tolerance)

    @pandas_udf("binary")
    def fp(texts: pd.Series) -> pd.Series:
        return pd.Series([wide_fingerprint(t, width, words) for t in texts], dtype=object)

    marked = materialise(docs.select("doc_id", *carry, fp(F.col("text").cast("string")).alias("fp")).withColumn("node", F.xxhash64("fp")))
    codes = materialise(marked.groupBy("node", "fp").agg(F.min("doc_id").alias("low")))
    if not 1 <= block_bits <= 48:
        raise ValueError("block_bits must be 1 to 48")

    def block(k: int) -> Column:
        """The bits of block k, read from the bytes that hold them."""
        first, last = k * block_bits // 8, ((k + 1) * block_bits - 1) // 8
        bits = F.conv(F.hex(F.substring("fp", first + 1, last - first + 1)), 16, 10).cast("long")
        return F.shiftright(bits, 8 * (last + 1) - (k + 1) * block_bits).bitwiseAND(F.lit((1 << block_bits) - 1).cast("long"))

    choices = F.explode(F.array(*[F.struct(F.lit(k).alias("choice"), block(k).alias("key")) for k in range(64 * words // block_bits)]))
    rows = codes.select("node", "fp", choices.alias("c")).select("c.choice", "c.key", "node", "fp")
    counts = rows.groupBy("choice", "key").agg(F.count(F.lit(1)).alias("n"))
    crowded = materialise(counts.where(F.col("n") > group_limit).select("choice", "key", F.ceil(F.col("n") / group_limit).cast("int").alias("parts")))
    if crowded.count():
        # parts a and b of a crowded key meet in the group of (a, b), whose number goes above the block's bits
        whole = rows.join(crowded, ["choice", "key"], "left_anti")
        own = F.pmod(F.xxhash64("node", F.lit(7)), F.col("parts")).cast("int")
        dealt = rows.join(crowded, ["choice", "key"]).withColumn("a", own).withColumn("b", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        pair = F.least("a", "b") * F.col("parts") + F.greatest("a", "b") + 1
        rows = whole.unionByName(dealt.select("choice", (F.col("key") + pair.cast("long") * (1 << block_bits)).alias("key"), "node", "fp"))

    def solve(frame: pd.DataFrame, group: np.ndarray) -> pd.DataFrame:
        nodes = frame["node"].to_numpy()
        bits = np.frombuffer(b"".join(frame["fp"]), np.uint64).reshape(len(frame), words)
        parent = forest(len(nodes), close_in_groups(bits, group, most))
        linked = np.nonzero(parent != np.arange(len(nodes)))[0]
        return pd.DataFrame({"u": nodes[linked], "v": nodes[parent[linked]]})

    dealt = rows.repartition("choice", "key").sortWithinPartitions("choice", "key")
    roots = materialise(connected_components(materialise(dealt.mapInPandas(_by_whole_groups(solve), "u long, v long").distinct())))
    rooted = materialise(codes.select("node", "low").join(roots, "node", "left").select("node", "low", F.coalesce("root", "node").alias("root")))
    lows = materialise(rooted.groupBy("root").agg(F.min("low").alias("component_id")))
    named = materialise(rooted.select("node", "root").join(lows, "root").select("node", "component_id").distinct())
    return marked.join(named, "node").select("doc_id", *carry, F.lower(F.hex("fp")).alias("fingerprint"), "component_id")


def near_groups(docs: DataFrame, width: int = 3, radius: int = 2, blocks: int | None = None, group_limit: int = GROUP_LIMIT, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per input row: doc_id, fingerprint (hex), component_id (smallest doc_id reachable), and the columns ``carry``.

    Null or wordless texts have fingerprint zero and link like any other; rows that repeat stay as
    rows; a null doc_id stays null and never becomes a component id unless it is alone in its group
    (then the id is null). Extra columns are ignored. An empty table gives an empty result.
    """
    marked = materialise(fingerprints(docs, width, carry))
    codes = materialise(marked.groupBy("fp").agg(F.min("doc_id").alias("low")))
    found = materialise(links(codes.select("fp"), radius, blocks or radius + 2, group_limit))
    roots = materialise(connected_components(found))
    rooted = materialise(codes.join(roots, codes["fp"] == roots["node"], "left").select("fp", "low", F.coalesce("root", "fp").alias("root")))
    lows = materialise(rooted.groupBy("root").agg(F.min("low").alias("component_id")))
    named = materialise(rooted.select("fp", "root").join(lows, "root").select("fp", "component_id"))
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint")
    return marked.join(named, "fp").select("doc_id", *carry, hexed, "component_id")


def op4_simhash_groups(spark, sf_dir: str) -> DataFrame:
    """Near-duplicate groups of all documents."""
    from residual_marginals.llm.common import table

    return near_groups(table(spark, sf_dir, "documents"))
