"""Exact top-k by distributed histogram selection.

Queries and candidates are packed once into bounded blocks of narrow integers, and each pair of a query and a candidate block is a cell of a grid. In every pass each grid cell
scores its whole block and reports, per query, a histogram of the scores inside the range
that may hold the k-th value; summed over the grid they narrow the range to one bin. Once the
bin is a single integer, one more pass keeps the scores above it and, of those equal to it,
as many of the smallest ids as are still needed.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from residual_marginals.llm.common import materialise, table

BINS = 1024
#: Vectors in a block at most, and fewest candidates worth a block. A pass ships each candidate block once per query block, and each query block once per candidate block.
QUERY_BLOCK, CANDIDATE_BLOCK, LEAST_BLOCK = 1 << 16, 1 << 16, 1 << 11
SCORED_AT_ONCE = 128


def quantise(vectors: DataFrame, scale: int = 64, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id, q): floor(scale * x) of every component. Null ids, null vectors and those with null or non-finite components are left out."""
    x = F.transform(F.col(vec_col), lambda v: v.cast("double"))
    good = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    kept = vectors.select(F.col(id_col).cast("long").alias("vec_id"), x.alias("x")).where("vec_id is not null and x is not null").where(good)
    return kept.select("vec_id", F.transform("x", lambda v: F.floor(v * scale).cast("long")).alias("q"))


def packed(vectors: DataFrame, block: Column, width: int, most: int) -> DataFrame:
    """(block, ids, data, size): the vectors of each block by id as one binary of the narrowest integers that hold ``most``; shorter vectors are padded by zeros."""
    kind = next(k for k in ("i1", "i2", "i4", "i8") if most <= np.iinfo(k).max)

    def pack(key: tuple, rows: pa.Table) -> pa.Table:
        ids = rows.column("vec_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        lists = rows.column("q").combine_chunks()
        sizes = np.asarray(lists.value_lengths(), dtype=np.int64)
        out = np.zeros((len(ids), width), kind)
        out[np.arange(width)[None, :] < sizes[:, None]] = lists.flatten().to_numpy(zero_copy_only=False)
        one = {"block": [key[0].as_py()], "ids": [ids[order].astype(np.int64).tobytes()], "data": [out[order].tobytes()], "kind": [kind]}
        return pa.table(one, schema=pa.schema([("block", pa.int32()), ("ids", pa.binary()), ("data", pa.binary()), ("kind", pa.string())]))

    return vectors.select("vec_id", "q", block.alias("block")).groupBy("block").applyInArrow(pack, "block int, ids binary, data binary, kind string")


def _scored(batches: Iterator[pa.RecordBatch], width: int):
    """Pieces (query ids, their lows and aboves, candidate ids, integer scores, own-pair mask) of the pairs of blocks in a task."""
    waiting: dict[int, dict] = {}
    for row in (r for b in batches for k in range(b.num_rows) for r in b.slice(k, 1).to_pylist()):
        other = waiting.pop(row["pair"], None)
        if other is None:
            waiting[row["pair"]] = row
            continue
        left, right = (row, other) if row["lows"] is not None else (other, row)
        q_ids, c_ids = (np.frombuffer(x["ids"], np.int64) for x in (left, right))
        q, c = (np.frombuffer(x["data"], x["kind"]).reshape(-1 if width else len(i), width) for x, i in ((left, q_ids), (right, c_ids)))
        lows, aboves = (np.frombuffer(left[x], np.int64) for x in ("lows", "aboves"))
        top = [float(np.abs(x.astype(np.float64)).max(initial=0)) for x in (q, c)]
        c = c.astype(np.float64 if top[0] * top[1] * max(width, 1) < 2.0**53 else np.int64)
        for at in range(0, len(q), SCORED_AT_ONCE):
            part = slice(at, at + SCORED_AT_ONCE)
            scores = (q[part].astype(c.dtype) @ c.T).astype(np.int64)
            yield q_ids[part], lows[part], aboves[part], c_ids, scores, q_ids[part][:, None] == c_ids[None, :]


def _histogram(k: int, step: int, reach: int, width: int):
    """Counts of the scores of a grid cell by (query, bin of ``step``) within ``reach`` above each query's low."""

    def histogram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, lows, aboves, _, scores, same in _scored(batches, width):
            over = scores - lows[:, None]
            inside = (over >= 0) & (over < reach) & ~same
            bins = over // step
            flat = (np.arange(len(ids))[:, None] * BINS + bins)[inside]
            counts = np.bincount(flat, minlength=len(ids) * BINS).reshape(-1, BINS)
            # bins below the block's own k-th value cannot hold the overall one
            behind = counts[:, ::-1].cumsum(axis=1)[:, ::-1] - counts + aboves[:, None]
            r, b = np.nonzero((counts > 0) & (behind < k))
            yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (ids[r], b, counts[r, b])], names=["vec_id", "bin", "n"])

    return histogram


def top_k(vectors: DataFrame, is_query, k: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k highest integer inner products, ties to the smaller vec_id.

    ``vectors`` is a result of ``quantise``; ``is_query`` a condition on vec_id. A query never meets rows with
    its own id; candidates that repeat stay as rows. Fewer candidates than k: all of them. No query or no vector: no rows.
    """
    vectors = materialise(vectors)
    norm = F.sqrt(F.aggregate("q", F.lit(0.0), lambda a, v: a + v.cast("double") * v))
    facts = vectors.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(is_query, 1)).alias("nq"), F.max(norm).alias("r"), F.max(F.when(is_query, norm)).alias("rq"), F.max(F.size("q")).alias("width"), F.max(F.array_max(F.transform("q", lambda v: F.abs(v)))).alias("most")).first().asDict()
    spark = vectors.sparkSession
    facts["most"] = facts["most"] or 0
    if not facts["n"] or not facts["nq"]:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    # blocks are as large as memory allows, but there are a few pairs of them for each core
    cores = spark.sparkContext.defaultParallelism
    rows = math.ceil(facts["nq"] / QUERY_BLOCK)
    cols = min(max(math.ceil(facts["n"] / CANDIDATE_BLOCK), math.ceil(2 * cores / rows)), math.ceil(facts["n"] / LEAST_BLOCK))
    own = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    # of rows that repeat a query's id, one is asked
    asked = materialise(vectors.where(is_query).groupBy("vec_id").agg(F.min("q").alias("q")))
    queries, candidates = (materialise(packed(x, own(n), facts["width"], facts["most"])) for x, n in ((asked, rows), (vectors, cols)))
    bound = math.ceil(facts["r"] * facts["rq"]) + 1
    state = materialise(asked.select("vec_id", F.lit(-bound).cast("long").alias("low"), F.lit(0).cast("long").alias("above")))
    span = 2 * bound + 1
    width = math.ceil(span / BINS)

    def levels(key: tuple, own: pa.Table) -> pa.Table:
        """The queries' states of one block, in the order of its ids."""
        order = np.argsort(own.column("vec_id").to_numpy(), kind="stable")
        low, above = (own.column(c).to_numpy()[order].astype(np.int64).tobytes() for c in ("low", "above"))
        return pa.table({"block": [key[0].as_py()], "lows": [low], "aboves": [above]}, schema=pa.schema([("block", pa.int32()), ("lows", pa.binary()), ("aboves", pa.binary())]))

    def cells(state: DataFrame) -> DataFrame:
        """Two rows per pair of a query block and a candidate block, in one task: every query is held against all rows."""
        told = state.withColumn("block", own(rows)).groupBy("block").applyInArrow(levels, "block int, lows binary, aboves binary")
        every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        left = queries.join(told, "block").withColumn("other", every(cols)).withColumn("pair", F.col("block").cast("long") * cols + F.col("other"))
        right = candidates.withColumn("other", every(rows)).withColumn("pair", F.col("other").cast("long") * cols + F.col("block"))
        right = right.withColumn("lows", F.lit(None).cast("binary")).withColumn("aboves", F.lit(None).cast("binary"))
        names = ["pair", "ids", "data", "kind", "lows", "aboves"]
        tasks = min(rows * cols, 1 << 17)
        return left.select(*names).unionByName(right.select(*names)).repartitionById(tasks, F.pmod("pair", F.lit(tasks)).cast("int"))

    while True:
        histogram = _histogram(k, width, span, facts["width"])
        # a query with fewer than k candidates in all ends in its lowest bin that holds any
        down = Window.partitionBy("vec_id").orderBy(F.desc("bin"))
        summed = cells(state).mapInArrow(histogram, "vec_id long, bin long, n long").groupBy("vec_id", "bin").agg(F.sum("n").alias("n"))
        before = F.coalesce(F.sum("n").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        reached = summed.join(state, "vec_id").withColumn("behind", before + F.col("above")).where(F.col("behind") < k)
        lowest = F.min(F.struct("bin", "behind", "low")).alias("s")
        state = materialise(reached.groupBy("vec_id").agg(lowest).select("vec_id", (F.col("s.low") + F.col("s.bin") * width).alias("low"), F.col("s.behind").alias("above")))
        if width == 1:
            break
        span, width = width, math.ceil(width / BINS)

    def survivors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, lows, aboves, c_ids, scores, same in _scored(batches, facts["width"]):
            level = lows[:, None]
            ties = (scores == level) & ~same
            # candidates are sorted by id, so the first ties are those with the smallest ids
            ties &= ties.cumsum(axis=1) <= (k - aboves)[:, None]
            r, c = np.nonzero(((scores > level) & ~same) | ties)
            yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (ids[r], c_ids[c], scores[r, c])], names=["query_id", "vec_id", "score"])

    best = cells(state).mapInArrow(survivors, "query_id long, vec_id long, score long")
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 best rows for each row whose vec_id is divisible by 20, over all embeddings."""
    return top_k(quantise(table(spark, sf_dir, "embeddings")), F.col("vec_id") % 20 == 0)


OP6_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS q FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT a.vec_id AS query_id, b.vec_id AS vec_id, list_inner_product(a.q, b.q)::BIGINT AS score
  FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 20 = 0
), r AS (
  SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INTEGER AS rank, vec_id, score FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""
