"""Quality scores by positive-unlabelled learning.

A linear model over word shapes and text statistics is fitted by minimising the non-negative
unbiased risk: with prior p, the loss of trusted positives counted as positive, plus the loss of
unlabelled text counted as negative less p times the positives' share of it, where that
difference is never allowed below zero (a batch that would take it below is stepped the other
way). The prior is the mean of all labels of the training fold. Only trusted positives and unlabelled text
enter the risk. Labels of the held-out fold, lang, source and ids are never inputs.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from operator import eq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from residual_marginals.llm.common import small_batches, table

#: Bounds of the fitting sample: trusted positives, unlabelled texts.
POSITIVES, UNLABELLED = 3000, 6000
HASHED = 256
STATISTICS = 16
WIDTH = HASHED + STATISTICS
CACHE_LIMIT = 300_000
#: Least spread by which a column is divided, so that rare shapes do not decide alone.
FLOOR = 0.03


def shape(word: str) -> tuple[int, int, int, int]:
    """(hashed shape, upper-case flag, symbol characters, letters) of a word; runs of a class count once, symbols as they are."""
    out, upper, letters, symbols = [], 0, 0, 0
    for c in word:
        if c.isalpha():
            letters += 1
            kind = "X" if c.isupper() else "x"
            upper += kind == "X"
        elif c.isdigit():
            kind = "9"
        else:
            kind = c
            symbols += 1
        if not out or out[-1] != kind or kind not in "Xx9":
            out.append(kind)
    key = zlib.crc32("".join(out[:24]).encode("utf-8", "surrogatepass")) % HASHED
    return key, int(upper > 1 and upper == letters), symbols, letters


class Shapes(dict):
    """Shapes by word, filled as words come."""

    def __missing__(self, word: str) -> tuple[int, int, int, int]:
        self[word] = found = shape(word)
        return found


def features(text: str, shapes: Shapes) -> np.ndarray:
    """Feature vector of a whole text: square roots of shape shares, then statistics."""
    out = np.zeros(WIDTH, np.float32)
    words = text.split()
    counts = Counter(words)
    n = len(words)
    if n:
        caps = symbols = letters = 0
        for word, many in counts.items():
            key, cap, sym, let = shapes[word]
            out[key] += many
            caps += cap * many
            symbols += sym * many
            letters += let * many
        np.sqrt(out / n, out=out)
        lines = text.split("\n")
        kinds = Counter(x.strip() for x in lines if x.strip())
        full = sum(kinds.values()) or 1
        repeated = sum(v for v in kinds.values() if v > 1) / full
        common = max(counts.values()) / n
        spread = len(counts) / n
        adjacent = sum(map(eq, words, words[1:])) / n
        size = max(1, len(text))
        stats = (
            1, caps / n, symbols / size, letters / size, repeated, common if n > 30 else 0.05, spread if n > 30 else 0.7, spread * math.log1p(n) / 5,
            math.log1p(n) / 10, letters / n / 10, max(kinds.values(), default=0) / full, len(lines) / n, min(1, n / 20), sum(v for k, v in counts.items() if len(k) > 25) / n,
            math.sqrt(adjacent), 2 * min(0.5, 5 * adjacent),
        )
        out[HASHED:] = stats
    return out


def fit(positive: np.ndarray, unlabelled: np.ndarray, prior: float, rounds: int = 300, rate: float = 0.05, decay: float = 1e-4) -> np.ndarray:
    """Weights that minimise the non-negative unbiased logistic risk; the first statistic is the constant one.

    Columns are centred and scaled by the unlabelled text for the descent, and the scaling is folded back.
    """
    centre, scale = unlabelled.mean(axis=0), unlabelled.std(axis=0)
    used = scale > 1e-6
    centre, scale = np.where(used, centre, 0.0), np.where(used, np.maximum(scale, FLOOR), 1.0)
    centred = lambda x: np.where(used | (np.arange(x.shape[1]) == HASHED), (x - centre) / scale, 0.0).astype(np.float32)
    positive, unlabelled = centred(positive), centred(unlabelled)
    w = np.zeros(positive.shape[1], np.float32)
    m, v = np.zeros_like(w), np.zeros_like(w)
    sigma = lambda z: 1 / (1 + np.exp(-np.clip(z, -30, 30)))
    loss = lambda z: np.logaddexp(0, -z)
    for step in range(1, rounds + 1):
        zp, zu = positive @ w, unlabelled @ w
        as_negative = loss(-zu).mean() - prior * loss(-zp).mean()
        g_negative = unlabelled.T @ sigma(zu) / len(zu) - prior * (positive.T @ sigma(zp)) / len(zp)
        if as_negative >= 0:
            g = g_negative - prior * (positive.T @ sigma(-zp)) / len(zp) + decay * w
        else:
            g = -g_negative
        m = 0.9 * m + 0.1 * g
        v = 0.999 * v + 0.001 * g * g
        w -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    folded = w.astype(np.float64) / scale
    folded[HASHED] -= (folded * centre).sum()
    return folded


def held_out(doc_id: Column, folds: int = 3, fold: int = 1) -> Column:
    """True for the fold kept from training: crc32 of the id as text, modulo ``folds``."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == fold, F.lit(False))


def _vectors(texts: DataFrame, ids: DataFrame, most: int) -> np.ndarray:
    """Feature vectors of at most ``most`` picked texts; texts of any length stay on the executors."""
    small_batches(texts.sparkSession, 1000)

    @pandas_udf("array<float>")
    def vector(column: pd.Series) -> pd.Series:
        return pd.Series([features(t, _shapes()) for t in column], dtype=object)

    rows = texts.join(F.broadcast(ids), "doc_id").limit(most).select(vector("text").alias("x")).collect()
    return np.array([r["x"] for r in rows], np.float64).reshape(len(rows), WIDTH)


def train(docs: DataFrame, labels: DataFrame) -> np.ndarray:
    """Fit on bounded samples (least hash first) of trusted positives and of unlabelled text.

    Labels are (doc_id, quality); null and held-out ones are not used. Without a positive or without text the
    weights are zero, so every score is one half.
    """
    usable = labels.select(F.col("doc_id").cast("long"), F.col("quality").cast("int")).where(~held_out(F.col("doc_id")) & F.col("quality").isNotNull())
    share = usable.agg(F.avg("quality")).first()[0]
    trusted = usable.where("quality = 1").select("doc_id").distinct()
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).where("text is not null")
    least = [F.xxhash64("doc_id"), F.col("doc_id")]
    picked = trusted.orderBy(*least).limit(POSITIVES)
    ids = texts.select("doc_id").where(~held_out(F.col("doc_id"))).orderBy(F.xxhash64("doc_id", F.lit(3)), "doc_id").limit(UNLABELLED)
    positive, unlabelled = _vectors(texts, picked, POSITIVES), _vectors(texts, ids.distinct(), UNLABELLED)
    if not len(positive) or not len(unlabelled):
        return np.zeros(WIDTH)
    prior = min(0.98, max(0.02, share))
    return fit(positive, unlabelled, prior)


def score(docs: DataFrame, weights: np.ndarray) -> DataFrame:
    """Adds ``score`` (0 to 1) and ``predicted`` to any table with a ``text`` column. Null counts as empty; wordless texts have no features and score 0."""
    small_batches(docs.sparkSession, 1000)

    @pandas_udf("double")
    def scored(texts: pd.Series) -> pd.Series:
        out = []
        for text in texts:
            x = features(text or "", _shapes())
            out.append(float(1 / (1 + np.exp(-np.clip(x @ weights, -30, 30)))) if x.any() else 0.0)
        return pd.Series(out, dtype="float64")

    return docs.withColumn("score", scored(F.col("text").cast("string"))).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


_CACHE = Shapes()


def _shapes() -> Shapes:
    """The worker's cache, emptied when it is full."""
    if len(_CACHE) > CACHE_LIMIT:
        _CACHE.clear()
    return _CACHE


def op1_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of all documents: one row per row, also for rows that repeat; null and wordless texts score 0, a null id is in no fold."""
    docs = table(spark, sf_dir, "documents")
    weights = train(docs, table(spark, sf_dir, "labels"))
    scored = score(docs.select("doc_id", "text"), weights)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
