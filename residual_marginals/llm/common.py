"""Shared pieces: table access, scratch tables, gapless ranks, graph components.

Scratch tables go to the folder named by ``spark.checkpoint.dir`` (a folder that
every executor sees) and are read back, which cuts lineage so that a lost
executor never forces a long recomputation.
"""

from __future__ import annotations

import os
import uuid
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from residual_marginals.shipping import ship

DEFAULT_CHECKPOINT_DIR = "/tmp/checkpoints"
_SCRATCH: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; also makes this package known to the executors."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """A fresh folder below ``spark.checkpoint.dir``; where that is unset, a default in local mode, an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = DEFAULT_CHECKPOINT_DIR
    _SCRATCH.append(f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}")
    return _SCRATCH[-1]


def clear_scratch(spark: SparkSession) -> int:
    """Delete the scratch folders made so far by this driver, once results that read from them are stored; returns how many were there."""
    gone = 0
    for path in _SCRATCH:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        gone += at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _SCRATCH.clear()
    return gone


def materialise(df: DataFrame, path: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back with the same schema."""
    spark = df.sparkSession
    path = path or scratch_dir(spark)
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small_batches(spark: SparkSession, rows: int) -> None:
    """Prepare for Python workers: ship this package, and bound the rows of an Arrow batch, as rows may be whole texts."""
    ship(spark)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key, "10000")) > rows:
        spark.conf.set(key, str(rows))


def unused(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of the frame has it (names differ by more than case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def with_rank(df: DataFrame, keys: list[str], order: list[Column], spread: Column, name: str, buckets: int | None = None) -> DataFrame:
    """Gapless 0-based ``name`` within ``keys`` without one task per key.

    Rows of a key are dealt to ``buckets`` parts by ``spread`` (by default one for each 50,000 rows of ``df``, at least 16); part sizes are counted
    (at most keys x buckets counts), a running sum over the counts gives each part its start,
    and ``row_number`` streams inside a part.
    """
    buckets = buckets or max(16, min(1 << 16, df.count() // 50_000))
    part = F.pmod(F.xxhash64(spread, F.lit(17)), F.lit(buckets)).cast("int")
    at, many, start, place = (unused(df, c) for c in ("_part", "_n", "_start", "_inner"))
    parted = df.withColumn(at, part)
    grouped = [*keys, at]
    sizes = parted.groupBy(*grouped).agg(F.count(F.lit(1)).alias(many))
    running = Window.partitionBy(*keys).orderBy(at).rowsBetween(Window.unboundedPreceding, -1)
    starts = materialise(sizes.withColumn(start, F.coalesce(F.sum(many).over(running), F.lit(0))).drop(many))
    inner = F.row_number().over(Window.partitionBy(*grouped).orderBy(*order))
    ranked = parted.withColumn(place, inner)
    same = reduce(lambda a, b: a & b, [F.col(f"l.{k}").eqNullSafe(F.col(f"r.{k}")) for k in grouped])
    joined = ranked.alias("l").join(starts.alias("r"), same)
    rank = (F.col(f"r.{start}") + F.col(f"l.{place}") - 1).cast("long").alias(name)
    return joined.select(*[F.col(f"l.{c}") for c in df.columns if c != name], rank)


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Components of an undirected graph given as (u, v) rows of longs: (node, root), root the smallest node.

    Alternates the two star contractions until nothing moves; each round is cut off by a scratch table.
    Nodes without an edge to another node are not returned. Null endpoints are ignored.
    """
    ends = (F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    live = materialise(edges.where("u is not null and v is not null and u <> v").select(*ends).distinct())
    mark = _mark(live)
    for _ in range(rounds if mark[0] else 1):
        if mark[0] == 0:
            break
        both = live.unionByName(live.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = materialise(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = materialise(both.join(low, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        low = materialise(large.groupBy("u").agg(F.min("v").alias("m")))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), "m")
        live = materialise(small.select(F.greatest("u", "m").alias("u"), F.least("u", "m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        now = _mark(live)
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = live.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def _mark(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0)).alias("h")).first()
    return int(row["n"]), int(row["h"])


def empty(spark: SparkSession, schema: T.StructType | str) -> DataFrame:
    return spark.createDataFrame([], schema)


def vocabulary(name: str) -> str:
    """Path of a public tokenizer file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def local_threads() -> None:
    """Native libraries use one thread in each task."""
    os.environ.setdefault("RAYON_NUM_THREADS", "1")
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
