"""Benchmark decontamination by template canonicalisation.

Words lose outer punctuation and case. In the template view numbers, names (capitalised
words inside a sentence) and units (after a number) become typed placeholders; in the wide template view capitalised words that begin a sentence are names, too;
the literal view keeps every word. Windows of ``width`` words of the template views or of the literal view are hash-joined with those of the benchmark. A template match
counts if at least ``LITERAL`` words of it are the same in both texts, be they literal or slots with one value (so languages that capitalise every noun
lose nothing). For each document, item and shift between them (one copy) the placeholders of matched windows are
read as slots: if in one copy every value in the item always stands for the same value in the document, the item was copied or
re-parameterised; if in none, it only shares a form and is left alone. An item shorter than the window is
one window; below ``least`` words it must make up whole sentences of the document, word for word.
"""

from __future__ import annotations

import re
import string
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.llm.common import materialise, small_batches, table

WIDTH, LEAST = 10, 5
#: Fewest words of a matched template window that are the same in both texts, and fewest literal ones that it is looked up with.
LITERAL, HASHED_LITERAL = 5, 3
#: Benchmark windows up to this many are given to the scan of the texts as a filter (24 bytes each); beyond, every window is joined.
FILTER_LIMIT = 500_000
CACHE_LIMIT = 800_000
#: Characters of texts that are hashed together.
TOGETHER = 1 << 18

NUMBER = re.compile(r"\d[\d.,:/]*(?:st|nd|rd|th|%|[a-z]{1,3})?")
#: Number words and units in English, German, French and Spanish.
NUMBER_WORDS = set(
    "zero one two three four five six seven eight nine ten eleven twelve twenty thirty forty fifty hundred thousand million dozen "
    "null eins zwei drei vier fünf sechs sieben acht neun zehn elf zwölf zwanzig dreißig vierzig fünfzig hundert tausend dutzend "
    "zéro deux trois quatre cinq sept huit neuf dix onze douze vingt trente quarante cinquante cent mille douzaine "
    "cero dos tres cuatro cinco seis siete ocho nueve diez once doce veinte treinta cuarenta cincuenta cien mil millón docena".split()
)
UNITS = set(
    "mm cm m km mg g kg ml l s ms min h hz w kw v a mph km/h inches inch feet foot yards miles mile meters metres meter metre kilometers kilometres grams kilograms pounds ounces liters litres "
    "seconds minutes hours hour days day weeks months years dollars cents euros euro percent degrees "
    "zoll kilometer gramm kilogramm pfund liter sekunden minuten stunden stunde tage tagen wochen monate jahre jahren prozent grad "
    "mètres mètre kilomètres grammes kilogrammes litre secondes heures heure jours jour semaines mois ans années degrés "
    "metros metro kilómetros gramos kilogramos litros litro segundos minutos horas hora días día semanas meses años dólares grados".split()
)
MARKS, ENDS = string.punctuation, frozenset(".!?:")
PLAIN, NUM, TITLE, UNIT, SKIP = range(5)
KINDS = ("", "number", "name", "unit")
_MIXERS = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F))


def word_hash(word: str) -> int:
    return xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))


_PLACEHOLDERS = np.array([0, *(word_hash(f"<{k}>") for k in KINDS[1:])], np.uint64)


def core(word: str) -> str:
    """The word without punctuation at its ends."""
    a, b = 0, len(word)
    while a < b and not word[a].isalnum():
        a += 1
    while b > a and not word[b - 1].isalnum():
        b -= 1
    return word[a:b]


class Words(dict):
    """Numbers of words, with their hash, class and whether they end a sentence."""

    def __init__(self):
        super().__init__()
        self.rows: list[tuple[int, int, bool]] = []
        self.filled = 0
        self.tables = (np.zeros(4096, np.uint64), np.zeros(4096, np.int8), np.zeros(4096, bool))

    def __missing__(self, word: str) -> int:
        if word.isalpha():
            bare, ends = word, False
        else:
            bare = word.strip(MARKS)
            if not (bare and bare[0].isalnum() and bare[-1].isalnum()):
                bare = core(bare)
            ends = not ENDS.isdisjoint(word[word.rfind(bare) + len(bare) :] if bare else word)
        low = bare.lower()
        if not bare:
            kind = SKIP
        elif low in NUMBER_WORDS or bare[0].isdigit() and NUMBER.fullmatch(low):
            kind = NUM
        elif low in UNITS:
            kind = UNIT
        elif bare[0].isupper() and bare[1:].islower():
            kind = TITLE
        else:
            kind = PLAIN
        self.rows.append((word_hash(low), kind, ends))
        self[word] = found = self.filled + len(self.rows) - 1
        return found

    def arrays(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if self.rows:
            fresh = zip(*self.rows)
            end = self.filled + len(self.rows)
            if end > len(self.tables[0]):
                self.tables = tuple(np.concatenate([t, np.zeros(end, t.dtype)]) for t in self.tables)
            for table, values in zip(self.tables, fresh):
                table[self.filled : end] = values
            self.filled = end
            self.rows = []
        return self.tables


def rolled(tokens: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of every window of ``width`` tokens, for each row of tokens."""
    n = tokens.shape[-1] - width + 1
    out = np.zeros((*tokens.shape[:-1], n), np.uint64)
    for k in range(width):
        out = (out ^ tokens[..., k : k + n]) * _MIXERS[k % 2] + np.uint64(k + 1)
        out ^= out >> np.uint64(31)
    return out


class Windows:
    """Window hashes of some texts in all views; positions count words over all of them."""

    def __init__(self, texts: list[str], words: Words):
        parts = [t.split() for t in texts]
        self.words = list(chain.from_iterable(parts))
        ids = np.fromiter(map(words.__getitem__, self.words), np.int64, len(self.words))
        owner = np.repeat(np.arange(len(parts)), [len(p) for p in parts])
        hashes, kinds, ends = words.arrays()
        self.at = np.nonzero(kinds[ids] != SKIP)[0]
        # a sentence ends with the word before, or with punctuation alone behind it
        stops = np.cumsum(ends[ids])
        ids, self.owner = ids[self.at], owner[self.at]
        kind = kinds[ids]
        begins = np.ones(len(ids), bool)
        begins[1:] = self.owner[1:] != self.owner[:-1]
        self.first = begins.copy()
        if len(ids):
            here = self.at[1:] - 1
            self.first[1:] |= stops[here] > stops[self.at[:-1]] - ends[ids[:-1]]
        #: Behind which word a sentence ends.
        self.last = np.ones(len(ids), bool)
        self.last[:-1] = self.first[1:]
        before = np.zeros(len(ids), bool)
        before[1:] = (kind[:-1] == NUM) & ~begins[1:]
        title = kind == TITLE
        slot = np.where(kind == NUM, NUM, np.where(title & ~self.first, TITLE, np.where((kind == UNIT) & before, UNIT, PLAIN)))
        opens = title & self.first
        self.literal = hashes[ids]
        #: Slots of the template view, and of the wide one if it differs.
        self.slot = np.stack([slot, np.where(opens, TITLE, slot)] if opens.any() else [slot])
        self.views = np.empty((1 + len(self.slot), len(ids)), np.uint64)
        self.views[0] = self.literal
        for view, own in zip(self.views[1:], self.slot):
            np.copyto(view, self.literal)
            typed = np.nonzero(own)[0]
            view[typed] = _PLACEHOLDERS[own[typed]]
        #: Where each text begins among the words that count.
        self.starts = np.searchsorted(self.owner, np.arange(len(parts)))

    def hashes(self, width: int, least: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(hash, start, view) of the windows: all literal ones (view 0), and template (1) and other wide (2) ones with a slot and enough literal words; below ``least`` words only literal ones that are whole sentences."""
        n = len(self.literal) - width + 1
        if n <= 0 or width <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        whole = self.owner[:n] == self.owner[width - 1 :]
        if width < least:
            start = np.nonzero(whole & self.first[:n] & self.last[width - 1 :])[0]
            return rolled(self.literal, width)[start], start, np.zeros(len(start), np.int64)
        slots = np.zeros((len(self.slot), len(self.literal) + 1), np.int64)
        np.cumsum(self.slot > 0, axis=1, out=slots[:, 1:])
        inside = slots[:, width:] - slots[:, :n]
        typed = (inside > 0) & (width - inside >= min(HASHED_LITERAL, width)) & whole
        typed[1:] &= inside[1:] > inside[0]
        all_hashes = rolled(self.views, width)
        view, start = np.nonzero(typed)
        plain = np.nonzero(whole)[0]
        return np.concatenate([all_hashes[0][plain], all_hashes[1:][typed]]), np.concatenate([plain, start]), np.concatenate([np.zeros(len(plain), np.int64), view + 1])

    def slots(self, start: int, width: int, view: int) -> list[str]:
        """Place, kind and value of the slots in a window of a template view, counted from its start; none for a literal window."""
        own = self.slot[view - 1] if view else ()
        return [f"{k}\t{KINDS[own[start + k]]}\t{core(self.words[self.at[start + k]]).lower()}" for k in range(width) if own[start + k]] if view else []


def benchmark_windows(items: DataFrame, width: int = WIDTH, least: int = LEAST) -> DataFrame:
    """(h, size, typed, item_id, item_at, item_wide, item_slots) of all benchmark windows."""

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words = Words()
        for batch in batches:
            rows = []
            for item_id, text in zip(batch["item_id"].tolist(), batch["text"]):
                own = Windows([text or ""], words)
                size = min(width, len(own.literal))
                if not size:
                    continue
                # a short item is one window as it stands
                h, start, view = own.hashes(size)
                for h, at, view in zip(h.view(np.int64).tolist(), start.tolist(), view.tolist()):
                    if size < least and view:
                        continue
                    rows.append((h, size, view > 0, item_id, at, view == 2, own.slots(at, size, view)))
            yield pd.DataFrame(rows, columns=["h", "size", "typed", "item_id", "item_at", "item_wide", "item_slots"])

    source = items.where("item_id is not null").select(F.col("item_id").cast("long"), F.col("text").cast("string"))
    return source.mapInPandas(cut, "h long, size int, typed boolean, item_id long, item_at int, item_wide boolean, item_slots array<string>")


def text_windows(docs: DataFrame, sizes: list[int], wanted: np.ndarray | None, least: int = LEAST) -> DataFrame:
    """(h, size, typed, doc_id, doc_at, doc_wide, doc_slots): windows of all texts whose hash is in ``wanted`` (None: all)."""
    if wanted is not None:
        wanted = np.unique(wanted.view(np.uint64))
        shift = np.uint64(64 - 22)
        seen = np.zeros(1 << 22, bool)
        seen[(wanted >> shift).astype(np.int64)] = True
        context = (wanted, np.packbits(seen))
    else:
        context = None

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        words = Words()
        if context is not None:
            known, seen = context[0], np.unpackbits(context[1]).astype(bool)
        for batch in batches:
            if not len(batch):
                continue
            rows = []
            if len(words) > CACHE_LIMIT:
                words = Words()
            ids, texts = batch["doc_id"].to_numpy(), [t or "" for t in batch["text"]]
            # texts go through the arrays together, as many as their length allows
            ends = np.cumsum([len(t) for t in texts]) // TOGETHER
            for group in np.split(np.arange(len(texts)), np.nonzero(np.diff(ends))[0] + 1):
                own = Windows([texts[k] for k in group], words)
                for size in sizes:
                    h, at, view = own.hashes(size, least)
                    if context is not None:
                        near = np.nonzero(seen[(h >> np.uint64(42)).astype(np.int64)])[0]
                        place = np.minimum(np.searchsorted(known, h[near]), len(known) - 1)
                        near = near[known[place] == h[near]]
                        h, at, view = h[near], at[near], view[near]
                    owner = own.owner[at]
                    found = zip(h.view(np.int64).tolist(), ids[group[owner]].tolist(), at.tolist(), (at - own.starts[owner]).tolist(), view.tolist())
                    rows += [(x, size, v > 0, doc_id, place_, v == 2, own.slots(a, size, v)) for x, doc_id, a, place_, v in found]
            yield pd.DataFrame(rows, columns=["h", "size", "typed", "doc_id", "doc_at", "doc_wide", "doc_slots"])

    source = docs.where("doc_id is not null").select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return source.mapInPandas(scan, "h long, size int, typed boolean, doc_id long, doc_at int, doc_wide boolean, doc_slots array<string>")


def find_leaks(docs: DataFrame, items: DataFrame, width: int = WIDTH, least: int = LEAST, filter_limit: int = FILTER_LIMIT) -> DataFrame:
    """doc_id, item_id, n_windows, n_slots, n_changed, kind for every document and item that it holds.

    ``kind`` is ``exact`` if a literal window matched, else ``reparameterised``. Null ids and null or wordless
    texts match nothing; rows that repeat count as one document; extra columns are ignored; empty tables give
    an empty result.
    """
    small_batches(docs.sparkSession, 1000)
    own = materialise(benchmark_windows(items, width, least))
    facts = own.agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_set("size")).alias("sizes")).first()
    wanted = None
    if facts["n"] <= filter_limit:
        wanted = np.array([r["h"] for r in own.select("h").distinct().collect()], np.int64)
        if not len(wanted):
            wanted = np.zeros(1, np.int64)
    found = text_windows(docs, list(facts["sizes"]), wanted, least)
    small = own if wanted is None else F.broadcast(own)
    # slots carry place, kind and value, so those that both windows list are unchanged
    same = F.col("size") - F.size("item_slots") + F.size(F.array_intersect("item_slots", "doc_slots"))
    enough = ~F.col("typed") | (same >= F.least(F.lit(LITERAL), "size"))
    pairs = materialise(found.join(small, ["h", "size", "typed"]).where(enough).drop("h"))
    # of the template windows, those aligned with the same shift are one copy and are judged together
    shift = (F.col("doc_at") - F.col("item_at")).alias("shift")
    # each copy with the slots of the template view alone, and with those of the wide view as well
    wide = (F.col("item_wide") | F.col("doc_wide")).alias("wide")
    slots = pairs.where("typed").select("doc_id", "item_id", shift, wide, F.explode(F.arrays_zip("item_slots", "doc_slots")).alias("s"))
    value = lambda c: F.substring_index(F.col(c), "\t", -1)
    kind = F.split("s.item_slots", "\t")[1].alias("kind")
    read = slots.select("doc_id", "item_id", "shift", "wide", kind, value("s.item_slots").alias("was"), value("s.doc_slots").alias("is"))
    narrow = F.when(~F.col("wide"), F.col("is"))
    by_value = read.groupBy("doc_id", "item_id", "shift", "kind", "was").agg(
        F.min("is").alias("low"), F.max("is").alias("high"), F.min(narrow).alias("narrow_low"), F.max(narrow).alias("narrow_high")
    )

    def facts_of(low: str, high: str) -> Column:
        """(clean, n_slots, minus the changed ones); a view without slots is not clean."""
        clean = F.coalesce(F.max((F.col(low) != F.col(high)).cast("int")) == 0, F.lit(False))
        return F.struct(clean.alias("clean"), F.count(low).alias("n_slots"), (-F.count(F.when(F.col(low) != F.col("was"), 1))).alias("kept"))

    by_shift = by_value.groupBy("doc_id", "item_id", "shift").agg(facts_of("low", "high").alias("wide"), facts_of("narrow_low", "narrow_high").alias("narrow"))
    # the slots told are those of the consistent copy with the most of them, then of that with the fewest changed
    best = F.max(F.greatest("wide", "narrow")).alias("best")
    judged = by_shift.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "best.clean", "best.n_slots", (-F.col("best.kept")).alias("n_changed"))
    counted = pairs.groupBy("doc_id", "item_id").agg(F.count_distinct("doc_at").alias("n_windows"), F.min(F.col("typed").cast("int")).alias("only_typed"))
    both = counted.join(judged, ["doc_id", "item_id"], "left")
    kept = both.where((F.col("only_typed") == 0) | F.coalesce("clean", F.lit(False)))
    return kept.select(
        "doc_id", "item_id", "n_windows",
        F.coalesce("n_slots", F.lit(0)).alias("n_slots"),
        F.coalesce("n_changed", F.lit(0)).alias("n_changed"),
        F.when(F.col("only_typed") == 0, "exact").otherwise("reparameterised").alias("kind"),
    )


def op10_template_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items in all documents."""
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
