"""Personal data by fixed patterns and a semi-Markov conditional random field.

The patterns give the base spans. The field then reads the stretches of text that hold
digits, at-signs or spelled-out address parts, as words; a segment of up to ``MAX_WORDS`` words and ``MAX_CHARS`` characters, the bound of an entity, is
scored as a whole by features of the complete span (digit groups, checksum, octet range, separators,
shape, words around it), and a dynamic program bounded by that length picks boundaries and types
jointly. Its weights maximise the conditional likelihood of segmentations of a bounded sample
of the input, labelled by the patterns, with rewritten copies of the labelled spans (other separators,
dropped plus signs, spelled-out addresses) and spoiled copies that are no personal data. Spans it
finds that touch no base span are added.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections.abc import Iterator
from itertools import islice

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.llm.common import small_batches, table

KINDS = ("email", "ip", "card", "phone")
#: Bound of an entity: words, and characters (the longest address that mail allows, spelled out).
MAX_WORDS, MAX_CHARS = 9, 340
#: Bounds of the fitting sample: texts, and of each text labelled spans and other numbers (the first ones); longer stretches are left out of the fit.
SAMPLE_ROWS, SAMPLE_SPANS, SAMPLE_NUMBERS, SAMPLE_WORDS = 400, 8, 4, 60
#: Score by which a segmentation with the added span must beat the best one without.
MARGIN = 0.5

#: The base patterns.
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")

HINT = re.compile(r"[0-9@]")
WORD = re.compile(r"\S+")
SPELLED = re.compile(r"(?<!\S)[\[(<]?at[\])>]?(?!\S)")
HOT = re.compile(r"[0-9@]|^\W*(?:at|dot)\W*$", re.I)
#: What may stand at either end of a segment.
EDGE = re.compile(r"^[^A-Za-z0-9+(]+|[^A-Za-z0-9)]+$")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        x = int(d) * (1 + k % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def digits_of(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost non-overlapping addresses, in time linear in the text."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL:
            start -= 1
        tail = DOMAIN.match(text, at + 1) if start < at else None
        if tail:
            yield start, tail.end()
            done = tail.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind as listed."""
    found = []
    if not HINT.search(text):
        return found
    found += [(s, e, "email") for s, e in emails(text)]
    for m in IP.finditer(text):
        if all(len(p) < 4 and int(p or 0) <= 255 for p in (x.lstrip("0") for x in m[0].split("."))):
            found.append((*m.span(), "ip"))
    for m in CARD.finditer(text):
        if 14 <= len(d := digits_of(m[0])) <= 19 and luhn(d):
            found.append((*m.span(), "card"))
    if "+" in text:
        found += [(*m.span(), "phone") for m in PHONE.finditer(text) if 10 <= len(digits_of(m[0])) <= 15]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2]), x[1]))


def listed(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def stretches(text: str) -> Iterator[list[tuple[int, int]]]:
    """Runs of neighbouring words (start, end) of which each holds a digit, an at-sign or a spelled-out address part, with one word more on either side of such a part."""
    done = 0
    for hint in HINT.finditer(text):
        if hint.start() < done:
            continue
        start = hint.start()
        while start > done and not text[start - 1].isspace():
            start -= 1
        words = []
        for m in WORD.finditer(text, start):
            if not HOT.search(m[0]):
                break
            words.append(m.span())
        done = words[-1][1] if words else hint.end()
        if words:
            yield words
    # spelled-out addresses hold no digit or at-sign, so they start from their middle word
    for m in SPELLED.finditer(text):
        words = [w.span() for w in islice(WORD.finditer(text, m.start()), MAX_WORDS - 1)]
        if any(re.fullmatch(r"\W*dot\W*", text[a:b]) for a, b in words[1:4]):
            end = m.start()
            while end and text[end - 1].isspace():
                end -= 1
            start = end
            while start and not text[start - 1].isspace():
                start -= 1
            if end:
                yield [(start, end), *words]


def trimmed(text: str, start: int, end: int) -> tuple[int, int]:
    """The span without punctuation at its ends."""
    while start < end and not (text[start].isalnum() or text[start] in "+("):
        start += 1
    while end > start and not (text[end - 1].isalnum() or text[end - 1] == ")" and "(" in text[start:end]):
        end -= 1
    return start, end


def features(text: str, start: int, end: int) -> list[str]:
    """Features of a whole segment."""
    span = text[start:end]
    digits = digits_of(span)
    groups = re.findall(r"[0-9]+", span)
    letters = sum(c.isalpha() for c in span)
    before = text[max(0, start - 24) : start].split()
    clean = bool(re.fullmatch(r"[0-9+().\x20-]+", span))
    # a part of a longer number looks like a number of its own, but for the word before it
    led = "none" if not before or span[:1] == "+" else "plus" if before[-1][0] == "+" else "digits" if any("0" <= c <= "9" for c in before[-1]) else "word"
    return [
        "bias",
        f"digits={min(len(digits), 20)}",
        f"groups={min(len(groups), 8)}",
        f"letters={min(letters, 3)}",
        f"plus={span[:1] == '+'}",
        f"at={span.count('@')}",
        f"spelled={len(re.findall(r'(?i)(?<!\S)\W?(?:at|dot)\W?(?!\S)', span))}",
        f"address={bool(re.fullmatch(r'[\w.%+-]+ ?(?:@|[\[(<]?at[\])>]?) ?[\w-]+(?: ?(?:\.|[\[(<]?dot[\])>]?) ?[\w-]+)+', span))}",
        f"clean={clean}",
        f"card={clean and '.' not in span and 14 <= len(digits) <= 19 and luhn(digits) and span[:1] != '+'}",
        f"octets={clean and len(groups) == 4 and all(len(g) < 4 and int(g) < 256 for g in groups)}:{span.count('.') == 3}",
        f"phone={clean and 10 <= len(digits) <= 15 and len(groups) >= 3}:{span[:1] == '+'}",
        f"led={led}:{clean and 10 <= len(digits) <= 15}:{min(len(groups), 3)}",
        f"separators={''.join(sorted(set(re.sub(r'[0-9A-Za-z]', '', span))))[:6]}" if clean else "mixed",
        f"words={span.count(' ')}",
        f"said={before[-1].strip(':.,').lower()[:10]}" if before and before[-1].endswith(":") else "unsaid",
    ]


class SemiMarkov:
    """Weights by (feature, kind); words outside segments score zero."""

    def __init__(self, weights: dict[str, list[float]] | None = None):
        self.weights = weights or {}

    def segments(self, text: str, words: list[tuple[int, int]]) -> Iterator[tuple[int, int, int, int, list[str]]]:
        """Candidate segments (first word, after last word, start, end, features), by first word."""
        for i in range(len(words)):
            for j in range(i + 1, min(len(words), i + MAX_WORDS) + 1):
                start, end = trimmed(text, words[i][0], words[j - 1][1])
                if end > start and end > words[j - 1][0] and start < words[i][1] and end - start <= MAX_CHARS:
                    yield i, j, start, end, features(text, start, end)

    def lattice(self, text: str, words: list[tuple[int, int]]):
        """All candidate segments at once."""
        return list(self.segments(text, words))

    def scores(self, feats: list[str]) -> list[float]:
        total = [0.0] * len(KINDS)
        for f in feats:
            for k, w in enumerate(self.weights.get(f, ())):
                total[k] += w
        return total

    def best(self, n: int, lattice) -> list[tuple[int, int, str]]:
        """Best segmentation of n words: (start, end, kind); segments come by their first word and are not kept."""
        value, back = [0.0] * (n + 1), [None] * (n + 1)
        reached = 0
        offers: dict[int, tuple] = {}

        def settle(upto: int) -> None:
            """Values of the words that no later segment can end at."""
            nonlocal reached
            while reached < upto:
                reached += 1
                value[reached] = value[reached - 1]
                offer = offers.pop(reached, None)
                if offer and offer[0] > value[reached]:
                    value[reached], back[reached] = offer

        for i, j, start, end, feats in lattice:
            settle(i)
            scored = self.scores(feats)
            k = max(range(len(KINDS)), key=scored.__getitem__)
            worth = value[i] + scored[k] - MARGIN
            if j not in offers or worth > offers[j][0]:
                offers[j] = worth, (i, start, end, KINDS[k])
        settle(n)
        out, j = [], n
        while j:
            if back[j]:
                i, start, end, kind = back[j]
                out.append((start, end, kind))
                j = i
            else:
                j -= 1
        return out[::-1]

    def fit(self, examples, rounds: int = 16, rate: float = 0.3, decay: float = 1e-3) -> SemiMarkov:
        """Gradient ascent on the conditional log-likelihood; examples: (n words, lattice, {(start, end): kind})."""
        squares: dict[str, list[float]] = {}
        for _ in range(rounds):
            for n, lattice, truth in examples:
                scored = [self.scores(seg[4]) for seg in lattice]
                forward, backward = _sums(n, lattice, scored)
                for seg, s in zip(lattice, scored):
                    i, j, start, end, feats = seg
                    for k, kind in enumerate(KINDS):
                        expected = math.exp(min(0.0, forward[i] + s[k] + backward[j] - forward[n]))
                        pull = (truth.get((start, end)) == kind and (i, j) == truth.get((start, end, "at"))) - expected
                        if abs(pull) < 1e-4:
                            continue
                        for f in feats:
                            w = self.weights.setdefault(f, [0.0] * len(KINDS))
                            g = squares.setdefault(f, [1e-6] * len(KINDS))
                            step = pull - decay * w[k]
                            g[k] += step * step
                            w[k] += rate * step / math.sqrt(g[k])
        return self


def _sums(n: int, lattice, scored) -> tuple[list[float], list[float]]:
    """Log sums over segmentations up to and from each word."""
    ends, starts = {}, {}
    for seg, s in zip(lattice, scored):
        ends.setdefault(seg[1], []).append((seg[0], s))
        starts.setdefault(seg[0], []).append((seg[1], s))
    forward, backward = [0.0] * (n + 1), [0.0] * (n + 1)
    for j in range(1, n + 1):
        forward[j] = _log_sum([forward[j - 1], *(forward[i] + x for i, s in ends.get(j, ()) for x in s)])
    for i in range(n - 1, -1, -1):
        backward[i] = _log_sum([backward[i + 1], *(backward[j] + x for j, s in starts.get(i, ()) for x in s)])
    return forward, backward


def _log_sum(xs: list[float]) -> float:
    top = max(xs)
    return top + math.log(sum(math.exp(x - top) for x in xs))


def _rewritten(kind: str, span: str, dice: random.Random) -> tuple[str, bool]:
    """Another writing of a span, and whether it still is personal data."""
    digits = digits_of(span)
    if kind == "email":
        local, _, domain = span.partition("@")
        domain = dice.choice([domain, ".".join(domain.split(".")[-2:])])
        return local + dice.choice([" at ", " [at] ", " (at) "]) + domain.replace(".", dice.choice([" dot ", " [dot] ", " (dot) "])), True
    if kind == "phone":
        a, b, c = digits[-10:-7], digits[-7:-4], digits[-4:]
        return dice.choice([(f"({a}) {b}-{c}", True), (f"{a}-{b}-{c}", True), (f"{a}.{b}.{c}", True), (f"{b}-{c}", False), (f"{a} {c}", False)])
    if kind == "card":
        spoiled = digits[:-1] + str((int(digits[-1]) + dice.randint(1, 9)) % 10)
        return dice.choice([("/".join([digits[:4], digits[4:8], digits[8:12], digits[12:]]), False), (spoiled, False), (digits[:9], False)])
    parts = span.split(".")
    return dice.choice([(".".join(parts[:3]), False), (".".join([*parts[:3], "999"]), False), (" . ".join(parts), False), (parts[0], False)])


def examples_from(texts: list[str], seed: int = 7):
    """Training lattices from texts: pattern-labelled stretches and rewritten spans in their place."""
    dice, model, out = random.Random(seed), SemiMarkov(), []

    def add(text: str, spans) -> None:
        for words in stretches(text):
            if len(words) > SAMPLE_WORDS:
                continue
            lattice = model.lattice(text, words)
            truth, free = {}, 0
            for i, j, start, end, _ in lattice:
                for s, e, kind in spans:
                    if (s, e) == (start, end) and i >= free:
                        truth[start, end], truth[start, end, "at"] = kind, (i, j)
                        free = j
            out.append((len(words), lattice, truth))

    for text in texts:
        spans = base_spans(text)
        near = [(max(0, s - 60), min(len(text), e + 60), s, e, k) for s, e, k in spans[:SAMPLE_SPANS]]
        for a, b, s, e, kind in near:
            window = text[a:b]
            add(window, base_spans(window))
            new, real = _rewritten(kind, text[s:e], dice)
            changed = text[a:s] + new + text[e:b]
            add(changed, [(s - a, s - a + len(new), kind)] if real else [])
        for m in islice(re.finditer(r"[0-9]+", text), SAMPLE_NUMBERS):
            window = text[max(0, m.start() - 40) : m.end() + 40]
            add(window, base_spans(window))
    # plain numbers, dates, amounts and versions are no personal data
    for _ in range(200):
        n = dice.randint
        filler = dice.choice([f"{n(1900, 2030)}", f"{n(1, 28)}.{n(1, 12)}.{n(1900, 2030)}", f"{n(1, 9)}.{n(0, 20)}.{n(0, 20)}", f"{n(1, 999)},{n(100, 999)}.{n(10, 99)}", f"{n(1000, 9999)}-{n(1000, 9999)}", "x@y", f"{n(10**8, 10**13)}", f"{n(2000, 2030)}-{n(10, 12)}-{n(10, 28)} {n(10, 23)}:{n(10, 59)}", f"{n(100, 999)} {n(100, 999)} {n(100, 999)}"])
        add(f"word {filler} word", [])
    return out


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> SemiMarkov:
    """Fit on at most ``sample_rows`` different texts that hold three digits in a row or an at-sign (those of least hash)."""
    hinted = docs.select(F.col("text").cast("string").alias("text")).where(F.col("text").rlike("[0-9]{3}|@")).withColumn("h", F.xxhash64("text"))
    # hashes alone are sorted, so what reaches the driver does not grow with the number of tasks' texts
    least = hinted.select("h").distinct().orderBy("h").limit(sample_rows)
    rows = hinted.join(F.broadcast(least), "h").groupBy("h").agg(F.min("text").alias("text")).orderBy("h").limit(sample_rows).collect()
    return SemiMarkov().fit(examples_from([r["text"] for r in rows]))


def spans_of(text: str, model: SemiMarkov) -> tuple[list, list]:
    """Base spans and all spans of one text."""
    base = base_spans(text)
    added = []
    taken = [(s, e) for s, e, _ in base]
    for words in stretches(text):
        if len(words) == 1 and any(s < words[0][1] and words[0][0] < e for s, e in taken):
            continue
        for start, end, kind in model.best(len(words), model.segments(text, words)):
            if not any(s < end and start < e for s, e in taken):
                added.append((start, end, kind))
                taken.append((start, end))
    return base, sorted(base + added, key=lambda x: (x[0], KINDS.index(x[2]), x[1]))


def find(docs: DataFrame, model: SemiMarkov) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans (all), per row of (doc_id, text).

    Null and empty texts have no spans (the digest of the empty string); rows that repeat stay; extra columns
    are ignored; an empty table gives an empty result.
    """
    small_batches(docs.sparkSession, 1000)
    weights = model.weights

    def search(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        field = SemiMarkov(weights)
        for batch in batches:
            rows = []
            for text in batch["text"]:
                base, every = spans_of(text or "", field)
                counts = [sum(k == kind for _, _, k in base) for kind in KINDS]
                rows.append((*counts, hashlib.sha256(listed(base).encode()).hexdigest(), listed(every)))
            out = pd.DataFrame(rows, columns=["n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"])
            out.insert(0, "doc_id", batch["doc_id"].to_numpy())
            yield out

    schema = "doc_id string, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"
    found = docs.select(F.col("doc_id").cast("string"), F.col("text").cast("string")).mapInPandas(search, schema)
    return found.withColumn("doc_id", F.col("doc_id").cast("long"))


def mask(text: str, model: SemiMarkov) -> str:
    """The text with every found span replaced by its kind in brackets; overlapping spans go together."""
    out, done = [], 0
    for start, end, kind in spans_of(text, model)[1]:
        if start >= done:
            out += [text[done:start], f"[{kind}]"]
        done = max(done, end)
    return "".join([*out, text[done:]])


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data in all documents."""
    docs = table(spark, sf_dir, "documents")
    return find(docs, train(docs))
