"""Marginals over event streams: windowed counts, bounded contributions, one release per closed window."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter

from residual_marginals.domain import Domain
from residual_marginals.operators.noise import keyed_uniform
from residual_marginals.plans.privacy import Ledger
from residual_marginals.sources.io import cut, exists


def coded_events(events: DataFrame, domain: Domain) -> DataFrame:
    """Event time, user, and one code column per attribute."""
    codes = [F.least(F.greatest(F.coalesce(F.expr(a.coder).cast("int"), F.lit(0)), F.lit(0)), F.lit(a.n - 1)).alias(a.name) for a in domain.attributes]
    return events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id", *codes)


def stream_marginals(coded: DataFrame, domain: Domain, masks: list[int], window: str = "1 day", slide: str | None = None, watermark: str | None = "1 hour") -> DataFrame:
    """(window_start, gamma, cell, value): counts per time window, on a stream or a batch. Rows later than the watermark are dropped by the stream."""
    if watermark:
        coded = coded.withWatermark("ts", watermark)
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    pairs = F.array(*[F.struct(F.lit(m).cast("long").alias("gamma"), domain.cell(m).alias("cell")) for m in masks])
    rows = coded.select("ts", F.explode(pairs).alias("p"))
    counted = rows.groupBy(span.alias("w"), "p.gamma", "p.cell").agg(F.count(F.lit(1)).alias("value"))
    return counted.select(F.col("w.start").alias("window_start"), "gamma", "cell", "value")


def session_marginals(coded: DataFrame, attribute: str, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    """(attribute, sessions, events): activity sessions per user and code."""
    if watermark:
        coded = coded.withWatermark("ts", watermark)
    sessions = coded.groupBy(F.session_window("ts", gap), "user_id", attribute).agg(F.count(F.lit(1)).alias("n"))
    return sessions.groupBy(attribute).agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Events once per id; on a stream as far as the watermark remembers."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def bounded_contribution(events: DataFrame, k: int, key: str = "bound", user: str = "user_id", row: str = "event_id") -> DataFrame:
    """At most k rows per user, chosen by a keyed hash. Protecting a user then costs k squared times a row's rho."""
    order = Window.partitionBy(user).orderBy(keyed_uniform(key, F.col(row)), row)
    return events.withColumn("_place", F.row_number().over(order)).where(F.col("_place") <= k).drop("_place")


def bounded_stream(events: DataFrame, k: int) -> DataFrame:
    """The same on a stream: the first k rows of each user pass, by state per user."""
    schema = events.schema

    def keep(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        for batch in batches:
            room = max(0, k - seen)
            seen += min(room, len(batch))
            yield batch.iloc[:room]
        state.update((seen,))

    return events.groupBy("user_id").applyInPandasWithState(keep, schema, "seen int", "append", "NoTimeout")


def late_rows(events: DataFrame, watermark_seconds: int, run: int = 100_000) -> DataFrame:
    """(late, rows): how many rows of a batch in event_id order came later than a watermark behind the latest time seen before.

    Rows are looked at in runs of ``run`` ids; what a run starts from is the latest time of the runs before it, so only one row a run is ordered as a whole.
    """
    numbered = events.select("event_id", "ts", F.floor(F.col("event_id") / run).alias("_run"))
    tops = numbered.groupBy("_run").agg(F.max("ts").alias("_top"))
    earlier = F.max("_top").over(Window.orderBy("_run").rowsBetween(Window.unboundedPreceding, -1)).alias("_before")
    within = F.max("ts").over(Window.partitionBy("_run").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    seen = numbered.withColumn("_within", within).join(tops.select("_run", earlier), "_run")
    before = F.greatest("_within", "_before")
    late = F.coalesce(F.unix_timestamp(before) - F.unix_timestamp("ts") > watermark_seconds, F.lit(False))
    return seen.withColumn("late", late).groupBy("late").agg(F.count(F.lit(1)).alias("rows"))


def window_ledger(spark: SparkSession, store: str) -> DataFrame:
    """(window_start, rho, batch): what each released window was charged."""
    schema = "window_start timestamp, rho double, batch long"
    return spark.read.schema(schema).parquet(store) if exists(spark, store) else spark.createDataFrame([], schema)


def release_windows(counts: DataFrame, release: Callable[[DataFrame, int], float], budget: float, store: str, overlap: int = 1) -> DataStreamWriter:
    """A ``foreachBatch`` writer that releases each closed window once, also over restarts.

    Disjoint windows compose in parallel, so one budget serves all; windows that overlap ``overlap`` times share it.
    ``release`` gets (counts of windows that were never released, batch id) and returns the rho that it spends on each window. The ledger lies
    in the folder ``store`` and is written before ``release`` is called: a window is charged its whole share, and a restarted stream, with or without its checkpoint,
    finds it there and leaves it out. A window whose release failed after the charge stays unreleased.
    """
    spark, share = counts.sparkSession, budget / overlap

    def write(batch: DataFrame, batch_id: int) -> None:
        # the batch is read whole, so that its state is committed
        batch = cut(batch)
        known = window_ledger(spark, store).select("window_start")
        # closed windows of one batch: one row each
        fresh = batch.select("window_start").distinct().join(known, "window_start", "left_anti").collect()
        if not fresh:
            return
        rows = [(r["window_start"], share, batch_id) for r in fresh]
        spark.createDataFrame(rows, "window_start timestamp, rho double, batch long").coalesce(1).write.mode("append").parquet(store)
        new = F.broadcast(spark.createDataFrame([(r[0],) for r in rows], "window_start timestamp"))
        Ledger(share).spend("window", release(batch.join(new, "window_start", "left_semi"), batch_id), str(batch_id))

    return counts.writeStream.outputMode("append").foreachBatch(write)
