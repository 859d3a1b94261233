"""Operators on documents against brute force, with odd and empty input."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from residual_marginals.llm import best_fit_packing, label_sharding, pii_semicrf, pu_quality, registry, simhash_gray, suffix_dedup, template_leaks
from residual_marginals.llm.common import clear_scratch, connected_components, materialise, table, vocabulary, with_rank
from tests.llm.helpers import no_docs, odd_docs


def roots(pairs, n):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(k) for k in range(n)]


def plain_fingerprint(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    if not words:
        return 0
    shingles = [b" ".join(words[k : k + 3]) for k in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


# --- op4 ---

def test_op4_against_brute_force(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").collect()
    prints = [plain_fingerprint(r["text"]) for r in docs]
    codes = np.array(prints, np.uint64)
    close = np.argwhere(np.bitwise_count(codes[:, None] ^ codes[None, :]) <= 2)
    own = roots([(a, b) for a, b in close if a < b], len(docs))
    low = defaultdict(list)
    for k, r in enumerate(own):
        low[r].append(docs[k]["doc_id"])
    want = sorted((docs[k]["doc_id"], f"{prints[k]:016x}", min(low[own[k]])) for k in range(len(docs)))
    got = sorted((r["doc_id"], r["fingerprint"], r["component_id"]) for r in registry.QUERIES["op4_simhash_groups"](spark, sf_dir).collect())
    assert got == want


@pytest.mark.parametrize("radius,blocks,limit", [(2, 4, 1 << 16), (2, 4, 8), (3, 6, 1 << 16), (1, 3, 4)])
def test_links_join_what_is_close(spark, radius, blocks, limit):
    rng = np.random.default_rng(radius)
    codes = set(rng.integers(0, 1 << 62, 60).tolist())
    for c in list(codes)[:20]:
        for _ in range(20):
            x = c
            for b in rng.integers(0, 63, rng.integers(1, 4)):
                x ^= 1 << int(b)
            codes.add(x)
    codes = sorted(codes)
    found = simhash_gray.links(spark.createDataFrame([(c,) for c in codes], "fp long"), radius, blocks, limit).collect()
    at = {c: k for k, c in enumerate(codes)}
    array = np.array(codes, np.uint64)
    close = np.argwhere(np.bitwise_count(array[:, None] ^ array[None, :]) <= radius)
    assert roots([(at[r["u"]], at[r["v"]]) for r in found], len(codes)) == roots(map(tuple, close), len(codes))


def test_gray_tree_prunes_exactly():
    codes = np.unique(np.random.default_rng(0).integers(0, 1 << 12, 700).astype(np.uint64))
    tree = simhash_gray.GrayTree(codes)
    got = sum(len(i) for i, _ in tree.close_pairs(2))
    assert got == (np.triu(np.bitwise_count(codes[:, None] ^ codes[None, :]) <= 2, 1)).sum()
    ranks = simhash_gray.gray_rank(tree.codes[:, 0])
    assert (np.diff(ranks.astype(np.int64)) > 0).all()


def test_wide_gray_ranks_count_through_the_sequence():
    # neighbours in the sequence of two-word codes differ in one bit, and the rank counts them
    at = [(0, 0), (0, 1), (0, (1 << 64) - 1), (1, 0), (1, 1), (2, 5)]
    numbers = [(a << 64) + b for a, b in at]
    codes = np.array([[(n ^ n >> 1) >> 64, (n ^ n >> 1) & (1 << 64) - 1] for n in numbers], np.uint64)
    assert simhash_gray.gray_rank(codes).tolist() == [list(x) for x in at]


@pytest.mark.parametrize("radius", [3, 40, 100])
def test_wide_tree_and_groups_against_all_pairs(radius):
    rng = np.random.default_rng(radius)
    centres = rng.integers(0, 1 << 63, (12, 8), dtype=np.uint64)
    codes = np.repeat(centres, 25, axis=0)
    for row in codes:
        for b in rng.integers(0, 512, rng.integers(0, 60)):
            row[b // 64] ^= np.uint64(1 << int(b % 64))
    group = np.sort(np.r_[np.zeros(150, int), rng.integers(1, 40, 150)])
    codes = codes[rng.permutation(300)]
    near = simhash_gray.differing(codes[:, None], codes[None]) <= radius
    want = {(i, j) for i, j in np.argwhere(np.triu(near & (group[:, None] == group[None]), 1)).tolist()}
    got = {tuple(sorted(p)) for i, j in simhash_gray.close_in_groups(codes, group, radius) for p in zip(i.tolist(), j.tolist())}
    assert got == want
    tree = simhash_gray.GrayTree(codes)
    assert sum(len(i) for i, _ in tree.close_pairs(radius)) == np.triu(near, 1).sum()


def test_tree_prunes_whole_groups_of_wide_codes():
    rng = np.random.default_rng(2)
    codes = np.repeat(rng.integers(0, 1 << 63, (20, 8), dtype=np.uint64), 64, axis=0)
    for row in codes:
        for b in rng.integers(0, 512, 3):
            row[b // 64] ^= np.uint64(1 << int(b % 64))
    tree, compared = simhash_gray.GrayTree(codes), []
    leaves = tree._leaves
    tree._leaves = lambda a, b, radius: compared.append(len(a)) or leaves(a, b, radius)
    assert sum(len(i) for i, _ in tree.close_pairs(81)) >= 20 * 64 * 63 / 2
    # 80 leaves make 3,240 pairs; most of those of different groups are given up unseen
    assert sum(compared) < 1620


def test_similarity_groups(spark):
    rng = np.random.default_rng(11)
    rows, want = [], {}
    for base in range(8):
        words = [f"w{x}" for x in rng.integers(0, 50_000, 400)]
        for copy, edits in enumerate((0, 0, 2, 4, 60)):
            own = list(words)
            for at in rng.choice(400, edits, replace=False):
                own[at] = f"n{rng.integers(0, 10**6)}"
            rows.append((10 * base + copy, " ".join(own)))
            want[10 * base + copy] = 10 * base if edits < 60 else 10 * base + copy
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in simhash_gray.similar_groups(frame, carry=("text",)).collect()}
    assert got == want
    split = simhash_gray.similar_groups(frame, carry=("text",), group_limit=1)
    assert {r["doc_id"]: r["component_id"] for r in split.collect()} == want
    odd = simhash_gray.similar_groups(odd_docs(spark)).collect()
    assert len(odd) == 12 and {r["component_id"] for r in odd if r["doc_id"] in (3, 4, 6)} == {3}
    assert simhash_gray.similar_groups(no_docs(spark)).count() == 0


def test_bit_counts():
    h = np.random.default_rng(0).integers(0, 1 << 63, 1000, dtype=np.uint64)
    assert simhash_gray.bit_counts(h).tolist() == [int((h >> np.uint64(b) & np.uint64(1)).sum()) for b in range(64)]


def test_scratch_can_be_cleared(spark):
    kept = materialise(spark.range(3))
    assert kept.count() == 3 and clear_scratch(spark) >= 1


def test_op4_odd_input(spark):
    got = simhash_gray.near_groups(odd_docs(spark)).collect()
    assert len(got) == 12
    groups = {(r["doc_id"], r["fingerprint"]): r["component_id"] for r in got}
    zero = "0" * 16
    assert groups[3, zero] == groups[4, zero] == groups[6, zero] == 3 and groups[None, zero] == 3
    assert sum(r["doc_id"] == 2 and r["component_id"] == 1 for r in got) == 2
    assert simhash_gray.near_groups(no_docs(spark)).count() == 0


def test_components(spark):
    chain = [(k, k + 1) for k in range(0, 200)] + [(500, 400), (500, 500), (None, 3)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(chain, "u long, v long")).collect()}
    assert got == {**{k: 0 for k in range(201)}, 500: 400, 400: 400}


def test_ranks_are_gapless(spark):
    frame = spark.range(1000).selectExpr("id % 3 as k", "id", "1 as _part", "2 as _inner", "3 as _n", "4 as _start")
    got = defaultdict(list)
    for r in with_rank(frame, ["k"], [F.col("id")], F.col("id"), "rank", 8).collect():
        got[r["k"]].append(r["rank"])
    assert all(sorted(v) == list(range(len(v))) for v in got.values())
    assert with_rank(frame, ["k"], [F.col("id")], F.col("id"), "rank", 8).columns == [*frame.columns, "rank"]


# --- op7 ---

def plain_removal(rows, length):
    seen = Counter()
    for _, t in rows:
        b = (t or "").encode()
        seen.update(b[k : k + length] for k in range(len(b) - length + 1))
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - length + 1):
            if seen[b[k : k + length]] > 1:
                gone[k : k + length] = True
        kept = bytes(c for c, g in zip(b, gone) if not g)
        starts = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum()) if len(b) else 0
        out.append((i, len(b), int(gone.sum()), starts, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("limit", [2000, 3])
def test_op7_against_brute_force(spark, limit):
    rng = np.random.default_rng(5)
    words = ["ab", "cde", "f", "ghij", "klm ", "é", "xxx"]
    phrases = ["".join(rng.choice(words, rng.integers(5, 60))) for _ in range(12)]
    rows = [(k, "".join(rng.choice(phrases) if rng.random() < 0.6 else rng.choice(words) * int(rng.integers(1, 4)) for _ in range(rng.integers(0, 8)))) for k in range(80)]
    rows += [(200, "a" * 300), (201, ""), (202, None), (203, rows[3][1]), (203, rows[3][1]), (None, "a" * 40)]
    got = suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 20, 8, limit)
    assert sorted((tuple(r)[:5] for r in got.collect()), key=str) == plain_removal(rows, 20)


def test_op7_common_neighbourhoods_are_broadcast(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT_KEYS", 10**9)
    rows = spark.range(6000).selectExpr("case when id < 4000 then 1 else id end as k", "id")
    counted = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    got = suffix_dedup.with_common_keys(rows, counted, ["k"], 6000)
    assert sorted((r["id"], r["n"]) for r in got.collect()) == [(i, 4000 if i < 4000 else 1) for i in range(6000)]


def test_op7_repeats_at_block_edges(spark, monkeypatch):
    rng = np.random.default_rng(8)
    noise = lambda n: "".join(rng.choice(list("abcdefgh"), n))
    texts = [noise(400) for _ in range(12)]
    for k in range(0, 12, 2):
        passage, a, b = noise(26), 96 - 13 + k, 250 + 5 * k
        texts[k] = texts[k][:a] + passage + texts[k][a + 26 :]
        texts[k + 1] = texts[k + 1][:b] + passage + texts[k + 1][b + 26 :]
    datas = [np.frombuffer(t.encode(), np.uint8) for t in texts]
    whole = [suffix_dedup.anchors(d, 20, 8) for d in datas]
    for stride in (96, 5):
        monkeypatch.setattr(suffix_dedup, "STRIDE", stride)
        for d, want in zip(datas, whole):
            assert all(np.array_equal(a, b) for a, b in zip(suffix_dedup.anchors(d, 20, 8), want))
    rows = list(enumerate(texts))
    got = suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 20, 8)
    assert sorted((tuple(r)[:5] for r in got.collect()), key=str) == plain_removal(rows, 20)


def test_op7_whole_query(spark, sf_dir):
    rows = [(r["doc_id"], r["text"]) for r in table(spark, sf_dir, "documents").collect()]
    assert sorted((tuple(r) for r in registry.QUERIES["op7_suffix_dedup"](spark, sf_dir).collect()), key=str) == plain_removal(rows, 200)


def test_op7_odd_input(spark):
    got = suffix_dedup.remove_repeats(odd_docs(spark)).collect()
    assert len(got) == 12 and {r["n_removed"] for r in got if r["doc_id"] == 8} == {1500}
    assert suffix_dedup.remove_repeats(no_docs(spark)).count() == 0


@settings(max_examples=30, deadline=None)
@given(st.lists(st.binary(max_size=30), min_size=1, max_size=40))
def test_suffix_order(strings):
    suffixes = suffix_dedup.Suffixes(strings)
    order, shared = suffixes.sorted_runs()
    assert [strings[k] for k in order] == sorted(strings)
    for k in range(1, len(order)):
        a, b = strings[order[k - 1]], strings[order[k]]
        n = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
        assert shared[k] == n


def test_suffix_collisions_are_caught():
    suffixes = suffix_dedup.Suffixes([b"bbb", b"aaa", b"abc", b"aab"])
    suffixes.hashes[:] = 0  # every prefix collides
    order, shared = suffixes.sorted_runs()
    assert order.tolist() == [1, 3, 2, 0] and shared.tolist() == [-1, 2, 1, 0]


# --- op8 ---

def check_packing(rows, capacity):
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_op8_round_trip_and_count(spark, sf_dir):
    from tokenizers import Tokenizer

    encoder = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    rows = registry.QUERIES["op8_best_fit"](spark, sf_dir).collect()
    used = check_packing(rows, 2048)
    total = 0
    own = defaultdict(list)
    for r in rows:
        own[r["doc_id"]].append(r)
    for r in table(spark, sf_dir, "documents").collect():
        ids = [*encoder.encode(r["text"], add_special_tokens=False).ids, 0]
        total += len(ids)
        at = 0
        for k, p in enumerate(sorted(own[r["doc_id"]], key=lambda x: x["piece"])):
            assert (p["piece"], p["start"]) == (k, at) and (k == 0 or p["length"] == 2048)
            assert p["ids_crc32"] == zlib.crc32(np.array(ids[at : at + p["length"]], "<u4").tobytes())
            at += p["length"]
        assert at == len(ids)
    assert used == len(sequential_best_fit([r["length"] for r in rows], 2048)) <= total / 2048 * 1.01 + 1


def sequential_best_fit(lengths, capacity):
    """Gaps left by best-fit decreasing, one piece at a time."""
    gaps = []
    for n in sorted(lengths, reverse=True):
        fits = [g for g in gaps if g >= n]
        gap = min(fits) if fits else capacity
        if fits:
            gaps.remove(gap)
        gaps.append(gap - n)
    return sorted(gaps)


def plain_sweep(sizes, slots):
    """Pieces and gaps that meet when a piece always takes the smallest open gap."""
    stack, met = [], []
    for k in sorted(range(len(sizes)), key=lambda k: (-sizes[k], slots[k] == 0, k)):
        if slots[k]:
            stack += [k] * slots[k]
        elif stack:
            met.append((k, stack.pop()))
    return sorted(met), Counter(stack)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 30), st.integers(0, 3)), max_size=40))
def test_op8_sweep(rows):
    sizes, slots = (np.array([r[k] for r in rows], np.int64) for k in (0, 1))
    piece, gap, alone, spare, many = best_fit_packing.sweep(sizes, slots, np.arange(len(rows)))
    met, left = plain_sweep(sizes.tolist(), slots.tolist())
    assert sorted(zip(piece.tolist(), gap.tolist())) == met and dict(zip(spare.tolist(), many.tolist())) == left
    assert sorted([*piece.tolist(), *alone.tolist()]) == np.nonzero(slots == 0)[0].tolist()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 30), st.integers(0, 3)), max_size=40), st.integers(1, 5))
def test_op8_ranges_swept_apart_equal_one_sweep(rows, parts):
    sizes, slots = (np.array([r[k] for r in rows], np.int64) for k in (0, 1))
    order = np.lexsort((np.arange(len(rows)), slots == 0, -sizes))
    met, left, lone, spare = [], [], {}, {}
    for part, own in enumerate(np.array_split(order, parts)):
        piece, gap, alone, free, many = best_fit_packing.sweep(sizes[own], slots[own], own)
        met += zip(own[piece].tolist(), own[gap].tolist())
        lone[part], spare[part] = own[alone].tolist(), np.repeat(own[free], many).tolist()
        left.append((part, len(lone[part]), len(spare[part])))
    for a, low, n, b, end, _ in best_fit_packing.conflicts(left):
        met += [(lone[a][low + k], spare[b][end - 1 - k]) for k in range(n)]
    assert sorted(met) == plain_sweep(sizes.tolist(), slots.tolist())[0]


@pytest.mark.parametrize("sweep_rows", [40, 1 << 16])
def test_op8_against_sequential_best_fit(spark, sweep_rows):
    rng = np.random.default_rng(3)
    lengths = np.r_[rng.integers(1, 30, 300), np.full(40, 2), rng.integers(14, 22, 60)].tolist()
    clashing = "_part int, _inner int, p_length int, seq int, size int, turn int, gap int, _row int, at int, pair long"
    frame = spark.createDataFrame([(k, 0, n) for k, n in enumerate(lengths)], "doc_id long, piece int, length long")
    for f in clashing.split(", "):
        frame = frame.selectExpr("*", f"cast(7 as {f.split()[1]}) as {f.split()[0]}")
    rows = best_fit_packing.pack(frame, 30, sweep_rows=sweep_rows).collect()
    want = len(sequential_best_fit(lengths, 30))
    assert sorted((r["doc_id"], r["length"], r["_row"], r["at"]) for r in rows) == [(k, n, 7, 7) for k, n in enumerate(lengths)]
    used = check_packing(rows, 30)
    assert used == want if sweep_rows > 1000 else used <= want * 1.03


def test_both_encoders_agree():
    encoder = best_fit_packing.TextEncoder(vocabulary("byte_bpe_50k.json"))
    assert encoder.fast != encoder._whole
    rng = np.random.default_rng(0)
    signs = list(" \n\t\r  abcXYZ019'sdlvtre.,!?<>|_-é漢🙂\u00a0\u200b\u3000\x1c\x85")
    points = [c for c in range(0, 0x110000, 13) if not 0xD800 <= c < 0xE000]
    texts = ["a  b", " a", "a \n b", "\n", "  ", "", "<|endoftext|> k", "é  \r\n q", "we'll  're x", "1234 5678 ٣٤", "a" * 20_000, " " * 20_000, "\n \n" * 5000]
    texts += ["".join(rng.choice(signs, rng.integers(0, 40))) for _ in range(3000)]
    texts += [f"a{chr(c)}b 1{chr(c)}2 {chr(c)}{chr(c)} .{chr(c)}!" for c in points]
    want = [e.ids for e in encoder.tokenizer.encode_batch(texts, add_special_tokens=False)]
    assert all(np.frombuffer(b, "<u4").tolist() == w for b, w in zip(encoder.encode(texts), want))


def test_op8_odd_input(spark):
    docs = odd_docs(spark)
    cut = best_fit_packing.pieces(docs, keep_ids=True)
    rows = best_fit_packing.pack(cut).collect()
    check_packing(rows, 2048)
    assert sum(r["doc_id"] is None for r in rows) == 2 and sum(r["doc_id"] == 2 for r in rows) == 2
    assert all(len(r["ids"]) == r["length"] for r in rows)
    assert best_fit_packing.pack(best_fit_packing.pieces(no_docs(spark))).count() == 0
    with pytest.raises(ValueError):
        best_fit_packing.pack(spark.createDataFrame([(1, 0, 5000)], "doc_id long, piece int, length long"))


# --- op9 ---

def test_op9_counts_slots_and_groups(spark, sf_dir):
    texts = {r["doc_id"]: r["text"] for r in table(spark, sf_dir, "documents").collect()}
    rows = registry.QUERIES["op9_label_shards"](spark, sf_dir).collect()
    assert sorted(r["doc_id"] for r in rows) == sorted(texts)
    by, groups = defaultdict(list), defaultdict(set)
    for r in rows:
        by[r["shard"]].append(r["slot"])
        groups[texts[r["doc_id"]]].add(r["shard"])
        assert r["size"] == len(texts[r["doc_id"]].encode()) + 8 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]].encode())
        assert r["law"] == "rows" and r["grown_shard"] is None
    sizes = [len(by[k]) for k in range(24)]
    assert max(sizes) - min(sizes) <= 1 and all(sorted(v) == list(range(len(v))) for v in by.values())
    assert max(map(len, groups.values())) == 1


def test_op9_hot_group_and_odd_input(spark):
    rows = [(k, "copy") for k in range(60)] + [(100 + k, f"t{k}") for k in range(60)] + [(500 + k, f"p{k // 2}") for k in range(60)]
    got = label_sharding.shard_documents(spark.createDataFrame(rows, "doc_id long, text string"), 6).collect()
    sizes = Counter(r["shard"] for r in got)
    assert set(sizes.values()) == {30}
    hot = Counter(r["shard"] for r in got if r["doc_id"] < 60)
    # a shard holds half of the copies; at first every one held ten
    assert sum(sorted(hot.values())[-2:]) >= 44
    assert label_sharding.quotas({0: 4, 1: 21, 2: 10, 3: 25}, 30) == [(0, 5, 3), (5, 14, 1)]
    odd = label_sharding.shard_documents(odd_docs(spark), 5).collect()
    assert len(odd) == 12 and max(Counter(r["shard"] for r in odd).values()) == 3
    assert label_sharding.shard_documents(no_docs(spark)).count() == 0


def least_cut(groups, shards):
    """Fewest documents outside the main shard of their group over all assignments whose counts are at most one apart."""
    n = len(groups)
    room = [n // shards + (k < n % shards) for k in range(shards)]
    best = n

    def place(k, left, by):
        nonlocal best
        if k == n:
            cut = sum(sum(c) - max(c) for c in by.values())
            best = min(best, cut)
            return
        for s in range(shards):
            if left[s]:
                left[s] -= 1
                by[groups[k]][s] += 1
                place(k + 1, left, by)
                left[s] += 1
                by[groups[k]][s] -= 1

    place(0, room, {g: [0] * shards for g in set(groups)})
    return best


@pytest.mark.parametrize("groups", [list("aabbccdd"), list("aaabbbccc"), list("aaaabbcd"), list("abababcc"), list("aaaaabbbc")])
def test_op9_cut_against_all_assignments(spark, groups):
    shards = 3 if len(groups) == 9 else 2
    rows = spark.createDataFrame([(k, 5 * ord(g)) for k, g in enumerate(groups)], "doc_id long, grp long")
    placed = label_sharding.assign(rows, shards, spread=2)
    counts = Counter(r["shard"] for r in placed.collect())
    assert max(counts.values()) - min(counts.get(s, 0) for s in range(shards)) <= 1
    assert label_sharding.cut_links(placed).first()["cut"] <= least_cut(groups, shards) + 1


def test_moves_keep_counts():
    moves = label_sharding.exchange({(0, 1): 5, (1, 0): 3, (2, 1): 4}, {0: 1, 1: 4, 2: 0})
    change = Counter()
    for a, _, low, high, b in moves:
        change[a] -= high - low
        change[b] += high - low
    assert not any(change.values()) and moves


# --- op1 ---

def test_op1_held_out_accuracy(spark):
    sf_dir = "/root/testdata/sf0.01"
    rows = registry.QUERIES["op1_pu_quality"](spark, sf_dir).collect()
    quality = {r["doc_id"]: r["quality"] for r in table(spark, sf_dir, "labels").collect()}
    assert len(rows) == table(spark, sf_dir, "documents").count()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in rows)
    judged = [(quality[r["doc_id"]], r["predicted"], r["score"]) for r in rows if r["held_out"] and quality.get(r["doc_id"]) is not None]
    good, bad = [s for q, _, s in judged if q == 1], [s for q, _, s in judged if q == 0]
    # of a good and a bad text, the good one scores higher; and most bad ones are caught, which the share of good ones alone would not tell
    assert len(bad) > 5 and np.mean([(g > b) + 0.5 * (g == b) for g in good for b in bad]) > 0.97
    assert np.mean([p == 0 for q, p, _ in judged if q == 0]) > 0.8 and np.mean([p == 1 for q, p, _ in judged if q == 1]) > 0.9


def test_op1_held_out_labels_are_not_used(spark, sf_dir):
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    turned = labels.withColumn("quality", F.when(pu_quality.held_out(F.col("doc_id")), 1 - F.col("quality")).otherwise(F.col("quality")))
    assert np.allclose(pu_quality.train(docs, labels), pu_quality.train(docs, turned))


def test_op1_prior_is_the_mean_of_all_usable_labels(spark, sf_dir, monkeypatch):
    seen = []
    monkeypatch.setattr(pu_quality, "PRIOR_LABELS", 3, raising=False)
    monkeypatch.setattr(pu_quality, "fit", lambda positive, unlabelled, prior: seen.append(prior) or np.zeros(pu_quality.WIDTH))
    labels = table(spark, sf_dir, "labels")
    pu_quality.train(table(spark, sf_dir, "documents"), labels)
    usable = [r["quality"] for r in labels.where(~pu_quality.held_out(F.col("doc_id"))).collect() if r["quality"] is not None]
    assert np.isclose(seen[0], np.mean(usable)) and not np.isclose(np.mean(usable[:3]), np.mean(usable))


def test_op1_non_negative_risk():
    rng = np.random.default_rng(0)
    make = lambda n, good: np.hstack([rng.random((n, pu_quality.HASHED)) * 0.01, np.ones((n, 1)), rng.normal(2 * good - 1, 0.5, (n, pu_quality.STATISTICS - 1))])
    weights = pu_quality.fit(make(200, 1), np.vstack([make(240, 1), make(160, 0)]), 0.6)
    good, bad = make(300, 1) @ weights, make(300, 0) @ weights
    assert (good > 0).mean() > 0.9 and (bad < 0).mean() > 0.9


def test_op1_odd_input(spark):
    docs = odd_docs(spark)
    labels = spark.createDataFrame([(1, 1), (2, None), (None, 1), (8, 0)], "doc_id long, quality int")
    rows = pu_quality.score(docs.select("doc_id", "text"), pu_quality.train(docs, labels)).collect()
    assert len(rows) == 12 and all(0 <= r["score"] <= 1 for r in rows)
    assert {r["score"] for r in rows if not (r["text"] or "").strip()} == {0.0}
    none = pu_quality.train(no_docs(spark), labels)
    assert not none.any() and pu_quality.score(no_docs(spark), none).count() == 0


# --- op3 ---

def plain_spans(text):
    out = []
    for kind, pattern in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(pattern, text):
            digits = re.sub(r"[^0-9]", "", m[0])
            if kind == "ip" and any(int(p) > 255 for p in m[0].split(".")):
                continue
            if kind == "card" and not (14 <= len(digits) <= 19 and sum(sum(map(int, str(int(d) * (1 + k % 2)))) for k, d in enumerate(reversed(digits))) % 10 == 0):
                continue
            if kind == "phone" and not 10 <= len(digits) <= 15:
                continue
            out.append((*m.span(), kind))
    return sorted(out, key=lambda x: (x[0], pii_semicrf.KINDS.index(x[2])))


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="ab1279.@+-_ ()é\n", max_size=60))
def test_base_spans_equal_the_patterns(text):
    assert pii_semicrf.base_spans(text) == plain_spans(text)


def test_op3_base_and_added(spark, sf_dir):
    texts = {r["doc_id"]: r["text"] for r in table(spark, sf_dir, "documents").collect()}
    for r in registry.QUERIES["op3_pii"](spark, sf_dir).collect():
        base = plain_spans(texts[r["doc_id"]])
        said = ",".join(f"{k}:{s}:{e}" for s, e, k in base)
        assert r["base_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert [r[f"n_{k}"] for k in pii_semicrf.KINDS] == [sum(x[2] == k for x in base) for k in pii_semicrf.KINDS]
        every = r["spans"].split(",") if r["spans"] else []
        assert {f"{k}:{s}:{e}" for s, e, k in base} <= set(every)
        assert [int(x.split(":")[1]) for x in every] == sorted(int(x.split(":")[1]) for x in every)


def test_field_finds_what_patterns_miss():
    texts = [f"word mail{k}.x@site{k}.example.com and +1 ({200 + k}) 555-{6000 + k} or 10.0.{k}.7 then 4532015112830366 end" for k in range(60)]
    model = pii_semicrf.SemiMarkov().fit(pii_semicrf.examples_from(texts))
    base, every = pii_semicrf.spans_of("call +1 (269) 555-3296 4532015112830366 now", model)
    assert not [b for b in base if b[2] == "phone"] and (5, 22, "phone") in every
    assert pii_semicrf.spans_of("it was 2019, 12 of 300 people paid 45,000.00 for version 1.2.3 at noon", model)[1] == []
    assert "[email]" in pii_semicrf.mask("write to a.b@c.example.com please", model)


def test_field_reads_whole_stretches():
    texts = [f"word mail{k}.x@site{k}.example.com and +1 ({200 + k}) 555-{6000 + k} or 10.0.{k}.7 then 4532015112830366 end" for k in range(60)]
    model = pii_semicrf.SemiMarkov().fit(pii_semicrf.examples_from(texts))
    span = "+1 (269) 555-3296"
    for pad in (3, 98, 99, 198, 398, 399):
        text = "7x " * pad + span + " 4532015112830366 now"
        assert (3 * pad, 3 * pad + len(span), "phone") in pii_semicrf.spans_of(text, model)[1], pad


def segmenter(text, model):
    """Best worth of any segmentation of each stretch, tried one segment after the other without bounds on where they start."""
    for words in pii_semicrf.stretches(text):
        segments = list(model.segments(text, words))
        by_end = defaultdict(list)
        for i, j, _, _, feats in segments:
            by_end[j].append((i, max(model.scores(feats)) - pii_semicrf.MARGIN))
        best = [0.0]
        for j in range(1, len(words) + 1):
            best.append(max([best[j - 1], *(best[i] + w for i, w in by_end[j])]))
        yield words, segments, best[-1]


@pytest.mark.parametrize("pad", range(90, 111, 4))
def test_field_against_a_plain_segmenter(pad):
    texts = [f"word mail{k}.x@site{k}.example.com and +1 ({200 + k}) 555-{6000 + k} or 10.0.{k}.7 then 4532015112830366 end" for k in range(40)]
    model = pii_semicrf.SemiMarkov().fit(pii_semicrf.examples_from(texts), rounds=4)
    text = "9 " * pad + "+1 (269) 555-3296 4532015112830366 9"
    for words, segments, worth in segmenter(text, model):
        at = {(s, e): (max(model.scores(f)) - pii_semicrf.MARGIN) for _, _, s, e, f in segments}
        got = model.best(len(words), segments)
        assert np.isclose(sum(at[s, e] for s, e, _ in got), worth)
    assert (2 * pad, 2 * pad + 17, "phone") in pii_semicrf.spans_of(text, model)[1]


def test_op3_recall_of_added_spans():
    """Phones and addresses in writings that the patterns do not know, planted between plain words."""
    rng = np.random.default_rng(5)
    texts = [f"word mail{k}.x@site{k}.example.com and +1 ({200 + k}) 555-{6000 + k} or 10.0.{k}.7 then 4532015112830366 end" for k in range(60)]
    model = pii_semicrf.SemiMarkov().fit(pii_semicrf.examples_from(texts))
    found = clean = 0
    for k in range(200):
        a, b, c = rng.integers(200, 999), rng.integers(200, 999), rng.integers(1000, 9999)
        new = [f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}", f"name{a} at host{b} dot example dot com"][k % 4]
        text = f"please write or call {new} before noon"
        found += any(s <= 21 + 2 and e >= 21 + len(new) - 2 for s, e, _ in pii_semicrf.spans_of(text, model)[1])
        clean += not pii_semicrf.spans_of(f"in {rng.integers(1900, 2030)} about {b} of {c} people paid {a},{b}.00 at {rng.integers(1, 12)}:30", model)[1]
    assert found >= 180 and clean >= 190


@pytest.mark.parametrize("gap", ["\n" * 500, " "])
def test_spelled_addresses_far_apart(gap):
    model = pii_semicrf.SemiMarkov({"bias": [-5.0] * 4, "spelled=2": [9.0, 0.0, 0.0, 0.0]})
    text = f"write john{'n' * 100}{gap}at mail dot example now"
    found = pii_semicrf.spans_of(text, model)[1]
    # words that stand far apart in white space are no one entity
    assert found and all(e - s <= pii_semicrf.MAX_CHARS for s, e, _ in found) and (min(found)[0] == 6) == (gap == " ")


@pytest.mark.parametrize("text", ["write john <at> mail <dot> example now", "write john at\nmail dot example now", "write john\nat mail dot example now"])
def test_spelled_addresses_without_digits(text):
    model = pii_semicrf.SemiMarkov({"bias": [-5.0] * 4, "spelled=2": [9.0, 0.0, 0.0, 0.0]})
    assert [k for _, _, k in pii_semicrf.spans_of(text, model)[1]] == ["email"]


def test_bounded_program_is_exact():
    text = "a1 b2 c3 d4 e5"
    model = pii_semicrf.SemiMarkov()
    words = next(pii_semicrf.stretches(text))
    lattice = model.lattice(text, words)
    rng = np.random.default_rng(1)
    table_ = {(i, j): rng.normal(0.2, 1, 4).tolist() for i, j, *_ in lattice}
    model.scores = lambda feats: table_[feats[0]]
    keyed = [(i, j, s, e, [(i, j)]) for i, j, s, e, _ in lattice]

    def best(at):
        if at == len(words):
            return 0.0
        return max([best(at + 1)] + [max(table_[i, j]) - pii_semicrf.MARGIN + best(j) for i, j, *_ in keyed if i == at])

    spans = {(s, e): (i, j) for i, j, s, e, _ in keyed}
    got = sum(table_[spans[s, e]][pii_semicrf.KINDS.index(k)] - pii_semicrf.MARGIN for s, e, k in model.best(len(words), keyed))
    assert np.isclose(got, best(0))


def test_op3_odd_input(spark):
    docs = odd_docs(spark)
    rows = pii_semicrf.find(docs, pii_semicrf.train(docs)).collect()
    assert len(rows) == 12 and sum(r["doc_id"] is None for r in rows) == 2
    assert {r["base_sha256"] for r in rows if r["doc_id"] in (3, 4)} == {hashlib.sha256(b"").hexdigest()}
    assert pii_semicrf.find(no_docs(spark), pii_semicrf.train(no_docs(spark))).count() == 0


# --- op10 ---

def test_op10_exact_leaks(spark, sf_dir):
    docs = [(r["doc_id"], " ".join(r["text"].lower().split())) for r in table(spark, sf_dir, "documents").collect()]
    want = set()
    for r in table(spark, sf_dir, "benchmark").collect():
        words = r["text"].lower().split()
        grams = [" ".join(words[k : k + 10]) for k in range(max(1, len(words) - 9))]
        want |= {(i, r["item_id"]) for i, t in docs if any(g in t for g in grams)}
    got = {(r["doc_id"], r["item_id"]) for r in registry.QUERIES["op10_template_leaks"](spark, sf_dir).collect()}
    assert want and got >= want and len(got - want) <= 0.05 * len(want)


ITEM = "Yesterday the farmer Anna bought 12 apples for 30 dollars and Anna then sold 12 pears to Peter near the mill"


@pytest.mark.parametrize("limit", [500_000, 0])
def test_op10_slots(spark, limit):
    items = spark.createDataFrame([(1, ITEM), (2, "too short"), (3, None), (None, ITEM)], "item_id long, text string")
    texts = [
        ("exact", ITEM.upper()), ("reparameterised", ITEM.replace("Anna", "Maria").replace("12", "15").replace("dollars", "euros").replace("Peter", "Olaf")),
        (None, ITEM.replace("Anna bought", "Maria bought").replace("12 apples", "15 apples").replace("30", "31").replace("Anna then sold 12", "Olga then sold 19").replace("Peter", "Olaf")), (None, "nothing of it"), (None, None),
    ]
    docs = spark.createDataFrame([(k, t) for k, (_, t) in enumerate(texts)] + [(None, ITEM)], "doc_id long, text string")
    got = {r["doc_id"]: r["kind"] for r in template_leaks.find_leaks(docs, items, filter_limit=limit).collect()}
    assert got == {k: kind for k, (kind, _) in enumerate(texts) if kind}


def test_op10_copies_are_judged_apart(spark):
    items = spark.createDataFrame([(1, ITEM)], "item_id long, text string")
    mixed = ITEM.replace("12 apples", "15 apples").replace("sold 12", "sold 19")
    texts = [ITEM.replace("12", "15") + " . And " + ITEM.replace("12", "19"), ITEM.replace("12", "15") + " . And " + mixed.replace("30", "31"), mixed.replace("30", "31").replace("Anna", "Maria").replace("Peter", "Olaf")]
    docs = spark.createDataFrame([(k, t.replace("mill", "barn").replace("farmer", "baker")) for k, t in enumerate(texts)], "doc_id long, text string")
    got = {r["doc_id"]: (r["kind"], r["n_changed"]) for r in template_leaks.find_leaks(docs, items).collect()}
    assert got == {0: ("reparameterised", 1), 1: ("reparameterised", 1)}


def test_op10_names_that_begin_sentences(spark):
    story = "Tom has 5 apples. Tom buys 3 more. Tom eats 2. How many are left?"
    short = "Tom has 8 pears and wants some more"
    items = spark.createDataFrame([(1, story), (2, short)], "item_id long, text string")
    other = story.replace("Tom", "Ann").replace("5", "6").replace("3", "4")
    texts = [other, "Question - " + other, short.replace("Tom", "Ann"), other.replace("Ann eats", "Bob eats").replace("Ann buys", "Eve buys"), "Ann has"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"], r["kind"]) for r in template_leaks.find_leaks(docs, items).collect()}
    assert got == {(0, 1, "reparameterised"), (1, 1, "reparameterised"), (2, 2, "reparameterised")}


def test_op10_short_items_are_whole_sentences(spark):
    items = spark.createDataFrame([(1, "Too short"), (2, "Why?"), (3, "seven 7 words are not so few now")], "item_id long, text string")
    texts = ["It was. Too short! Indeed", "it was too short indeed", "why", "why not", "Well: why? yes", "", "7 words are not so few now"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"], r["kind"]) for r in template_leaks.find_leaks(docs, items).collect()}
    assert got == {(0, 1, "exact"), (2, 2, "exact"), (4, 2, "exact")}


def plain_leaks(docs, items, width=10):
    """Documents and items by the definitions, one pair after the other."""
    def read(text):
        words, ends, out = text.split(), True, []
        for w in words:
            bare = template_leaks.core(w)
            first, ends = ends, (any(c in ".!?:" for c in (w[w.rfind(bare) + len(bare) :] if bare else w))) or (not bare and ends)
            if not bare:
                if out and ends:
                    out[-1] = (*out[-1][:3], True)
                continue
            low = bare.lower()
            number = low in template_leaks.NUMBER_WORDS or bool(bare[0].isdigit() and template_leaks.NUMBER.fullmatch(low))
            kind = "number" if number else "unit" if low in template_leaks.UNITS and out and out[-1][1] == "number" else "title" if low not in template_leaks.UNITS and bare[0].isupper() and bare[1:].islower() else ""
            out.append((low, kind, first, ends))
        return out

    def views(words):
        narrow = ["name" if k == "title" and not f else "" if k == "title" else k for _, k, f, _ in words]
        wide = ["name" if k == "title" else k for _, k, f, _ in words]
        return narrow, wide

    def windows(words, size):
        """Windows by what they look like: literal, narrow and wide."""
        shapes = [[""] * len(words), *views(words)]
        for v, kinds in enumerate(shapes):
            seen = [f"<{k}>" if k else w[0] for k, w in zip(kinds, words)]
            for at in range(len(words) - size + 1):
                if not v or (any(kinds[at : at + size]) and sum(not k for k in kinds[at : at + size]) >= 3):
                    yield v, at, tuple(kinds[at : at + size]), tuple(seen[at : at + size])

    found = set()
    for i, a in items:
        item = read(a)
        size = min(width, len(item))
        wanted = defaultdict(list)
        for v, at, kinds, look in windows(item, size):
            wanted[v > 0, kinds, look].append((v, at))
        for d, b in docs:
            doc, hits, exact = read(b or ""), defaultdict(lambda: defaultdict(set)), False
            for v, q, kinds, look in windows(doc, size):
                for u, p in wanted.get((v > 0, kinds, look), ()):
                    x, y = item[p : p + size], doc[q : q + size]
                    if not v:
                        exact = True
                    elif sum(m[0] == n[0] for m, n in zip(x, y)) >= min(5, size):
                        for s, m, n in zip(kinds, x, y):
                            if s:
                                # one view with the slots of both, one with those of the narrow view alone
                                hits[q - p, "wide"][s, m[0]].add(n[0])
                                if u == v == 1:
                                    hits[q - p, "narrow"][s, m[0]].add(n[0])
            if exact or any(h and all(len(v) == 1 for v in h.values()) for h in hits.values()):
                found.add((d, i))
    return found


TEMPLATES = {
    "en": "A train with {n} wagons left for {p} at {m} km/h while {q} counted {n} trees along the line before {p} waved",
    "de": "Der Bauer {q} kaufte {n} Äpfel für {m} Euro und {q} verkaufte danach {n} Birnen an {p} neben der alten Mühle",
    "fr": "Le marchand {q} vend {n} pommes pour {m} euros et {q} donne ensuite {n} poires à {p} près du vieux moulin",
    "es": "El granjero {q} compró {n} manzanas por {m} euros y {q} vendió luego {n} peras a {p} cerca del viejo molino",
}


@pytest.mark.parametrize("lang", sorted(TEMPLATES))
def test_op10_recall_of_reparameterised_items(spark, lang):
    rng = np.random.default_rng(7)
    people = ["Anna", "Peter", "Olaf", "Maria", "Ivan", "Lena", "Tomas", "Ines"]
    pick = lambda: dict(n=int(rng.integers(2, 99)), m=int(rng.integers(100, 900)), p=people[rng.integers(4)], q=people[4 + rng.integers(4)])
    items = [(1, TEMPLATES[lang].format(**pick()))]
    texts = ["so " * 8 + "Nun. " + TEMPLATES[lang].format(**pick()) + " und so weiter" for _ in range(40)]
    # the same form, but a value of the item stands for two values
    for _ in range(40):
        a, b = pick(), pick()
        b["n"] = a["n"] + 100
        first, second = TEMPLATES[lang].format(**a), TEMPLATES[lang].format(**b)
        half = first.split().index(str(a["n"])) + 1
        texts.append(" ".join(first.split()[:half] + second.split()[half:]))
    docs = list(enumerate(texts))
    got = {(r["doc_id"], r["item_id"]) for r in template_leaks.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert len([d for d, _ in got if d < 40]) >= 38 and not [d for d, _ in got if d >= 40]
    assert got == plain_leaks(docs, items)


def test_op10_odd_input(spark, sf_dir):
    items = table(spark, sf_dir, "benchmark")
    assert template_leaks.find_leaks(odd_docs(spark), items).count() == 0
    assert template_leaks.find_leaks(no_docs(spark), items).count() == 0
    assert template_leaks.find_leaks(odd_docs(spark), spark.createDataFrame([], "item_id long, text string")).count() == 0
