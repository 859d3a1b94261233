"""Corpus pipeline: quality, near-dedup, benchmark decontamination, personal data, packing.

Each stage takes (spark, docs, sf_dir), where docs has the columns of ``documents``, and works on all
that its predecessor kept. All but the last return those columns again. Rows whose text is
null count as empty texts; empty tables pass through as empty tables.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from residual_marginals.llm import best_fit_packing, pii_semicrf, pu_quality, simhash_gray, template_leaks
from residual_marginals.llm.common import materialise, scratch_dir, small_batches, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Near-duplicates: shingles of five words, this similarity or more.
SHINGLE_WORDS, SIMILARITY = 5, 0.8
#: Keys (16 bytes each) up to which a set of rows to drop is broadcast.
BROADCAST_KEYS = 1_000_000


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts."""
    weights = pu_quality.train(docs, table(spark, sf_dir, "labels"))
    return pu_quality.score(docs, weights).where("predicted = 1").select(*COLUMNS)


def without(docs: DataFrame, dropped: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of ``docs`` whose keys are not in ``dropped``, which is broadcast only if it is known to be small."""
    dropped = materialise(dropped.select(*keys).distinct())
    return docs.join(F.broadcast(dropped) if dropped.count() <= BROADCAST_KEYS else dropped, keys, "left_anti")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group: that with the smallest doc_id, then the least hash of its text; of rows that repeat both, one."""
    keys = ["_id", "_text"]
    keyed = docs.withColumn("_id", F.coalesce(F.col("doc_id"), F.lit(-(1 << 62)))).withColumn("_text", F.xxhash64("text", "doc_id"))
    groups = materialise(simhash_gray.similar_groups(keyed, SHINGLE_WORDS, SIMILARITY, carry=tuple(keys)))
    # a group is named by its smallest doc_id; groups of null ids alone go by their fingerprint
    name = F.struct("component_id", F.when(F.col("component_id").isNull(), F.col("fingerprint")).alias("only"))
    best = materialise(groups.groupBy(name.alias("group")).agg(F.min(F.struct("_id", "_text")).alias("one")).select("one.*"))
    kept = without(keyed, groups.join(best, keys, "left_anti"), keys)
    repeats = groups.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
    return (kept.dropDuplicates(keys) if repeats else kept).select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    leaks = template_leaks.find_leaks(docs, table(spark, sf_dir, "benchmark"))
    return without(docs, leaks, ["doc_id"]).select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced by its kind in brackets and n_chars counted anew."""
    small_batches(spark, 1000)
    weights = pii_semicrf.train(docs).weights

    @pandas_udf("string")
    def masked(texts: pd.Series) -> pd.Series:
        field = pii_semicrf.SemiMarkov(weights)
        return texts.map(lambda t: t if t is None else pii_semicrf.mask(t, field))

    return docs.withColumn("text", masked("text")).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents as pieces of packed sequences of at most 2048 ids; rows that repeat are packed as often as they come."""
    return best_fit_packing.pack(best_fit_packing.pieces(docs))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", quality),
    ("near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("packing", packing),
]

#: Scores, fingerprints and token ids are beyond SQL; a test holds every stage against plain Python on the given documents.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``, each written as Parquet and read back."""
    docs = table(spark, sf_dir, "documents")
    base = scratch_dir(spark)
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), f"{base}/{name}")
    return docs
