"""Reading the given tables; storing and resuming releases."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from residual_marginals.shipping import ship

DEFAULT_SHARED = "/tmp/checkpoints"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_path(spark: SparkSession) -> str:
    """A fresh folder that every executor sees: below ``spark.checkpoint.dir``; where that is unset, a default in local mode, an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = DEFAULT_SHARED
    return f"{base.rstrip('/')}/marginals-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Write and read back: later work starts from the stored table."""
    path = shared_path(df.sparkSession)
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def exists(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def save_by_round(df: DataFrame, path: str) -> None:
    """Store a frame with a ``round`` column partitioned by it; only the rounds that the frame holds are overwritten."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("round").parquet(path)


def save_release(frames: dict[str, DataFrame], path: str, round_: int | None = None) -> None:
    """Store released frames; one folder per frame and round, overwritten whole, so a round can be stored again safely."""
    for name, df in frames.items():
        if name.startswith("_"):
            raise ValueError("frames of the trusted zone are never stored")
        df.write.mode("overwrite").parquet(f"{path}/{name}" + (f"/round={round_}" if round_ is not None else ""))


def resume(spark: SparkSession, path: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{path}/{name}")


def export_csv(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").option("header", True).csv(path)


def export_json(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)
