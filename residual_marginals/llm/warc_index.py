"""WARC archives with an index, and coalesced byte-range reads.

Writing: each task streams its records into gzip members of one archive file in the shared
folder and reports offset, length, URL and digest of each; the index is stored before anything
is read. The file's name carries the task attempt, and only files that the stored index names
are read, so a task that runs again leaves at most an unused file. Reading: the wanted index
rows are sorted by file and offset, near ranges are joined into one read, and every record is
checked against its digest.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from residual_marginals.llm.common import materialise, scratch_dir, small_batches, table

ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
DATE = "2024-01-01T00:00:00Z"
#: Ranges closer than this are read together, up to READ_LIMIT bytes at once.
GAP, READ_LIMIT = 1 << 16, 1 << 23
#: Archive bytes that one reading task gets at most, and the least that is worth a task.
SLICE, LEAST_SLICE = 1 << 26, 1 << 18
#: Read records whose bodies are handed on at once, in bytes.
HANDED_BYTES = 1 << 24
#: Digests of repeated payloads (40 bytes each) up to which they are broadcast.
BROADCAST_KEYS = 1_000_000

INDEX = "file string, offset long, length long, page_id long, url string, payload_digest string, payload_bytes long, record_type string, refers_to long"
RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def base32_sha1(data: Column) -> Column:
    """Upper-case base32 of the SHA-1 of a binary column: 160 bits are 32 letters, so there is no padding."""
    text = F.sha1(data)
    letters = []
    for k in range(8):
        five = F.conv(F.substring(text, 5 * k + 1, 5), 16, 10).cast("int")
        letters += [F.substring(F.lit(ALPHABET), F.shiftright(five, s).bitwiseAND(31) + 1, F.lit(1)) for s in (15, 10, 5, 0)]
    return F.concat(*letters)


def _file_system(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder)


def _record(row, payload: bytes) -> bytes:
    """One record as bytes; a revisit carries the response's headers only."""
    url = re.sub(r"[\x00-\x20]", lambda m: f"%{ord(m[0]):02X}", row.url or "")
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + payload if row.record_type == "response" else http
    head = [
        "WARC/1.1",
        f"WARC-Type: {row.record_type}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'record:{row.page_id}:{row.payload_digest}')}>",
        f"WARC-Date: {DATE}",
        f"WARC-Target-URI: {url}",
        f"WARC-Payload-Digest: sha1:{row.payload_digest}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if row.record_type == "revisit":
        head += [
            f"WARC-Refers-To: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'record:{row.refers_to}:{row.payload_digest}')}>",
            "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
        ]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers (lower-case names) of one record, and the body after its HTTP headers."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("not a WARC record")
    headers = {k.lower(): v for k, _, v in (x.partition(": ") for x in lines[1:])}
    block = rest[: int(headers["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    headers |= {"http-" + k.lower(): v for k, _, v in (x.partition(": ") for x in http.decode("utf-8").split("\r\n")[1:])}
    return headers, payload


def classify(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Adds payload, digest, record_type and refers_to to (page_id, url, html)."""
    payload = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), payload.alias("payload"))
    rows = rows.withColumn("payload_digest", base32_sha1(F.col("payload"))).withColumn("payload_bytes", F.octet_length("payload").cast("long"))
    shared = rows.where(F.col("payload_bytes") >= least_bytes).groupBy("payload_digest").agg(F.max("page_id").alias("first"), F.count(F.lit(1)).alias("n"))
    shared = materialise(shared.where("n > 1").drop("n"))
    # beyond a broadcast, a digest that very many pages have (mostly that of no payload) is split by adaptive execution
    shared = F.broadcast(shared) if shared.count() <= BROADCAST_KEYS else shared
    later = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")) & (F.col("payload_bytes") >= least_bytes)
    typed = rows.join(shared, "payload_digest", "left").withColumn("record_type", F.when(later, "revisit").otherwise("response"))
    return typed.withColumn("refers_to", F.when(later, F.col("first"))).drop("first")


def write_archives(pages: DataFrame, folder: str | None = None, least_bytes: int = 0) -> DataFrame:
    """Write one record per row of (page_id, url, html); return the stored index.

    Null html is an empty payload, null urls are empty. Equal payloads of ``least_bytes`` bytes or more are
    kept once, at the largest page_id (rows that repeat that id too stay responses); the others revisit it.
    A null page_id is written as a record without an id and never becomes a response others revisit.
    """
    spark = pages.sparkSession
    folder = folder or scratch_dir(spark) + "/archives"
    small_batches(spark, 1000)

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, base = _file_system(folder)
        task = TaskContext.get()
        name = f"{base}/part-{task.partitionId():06d}-{task.taskAttemptId()}.warc.gz"
        out, at = None, 0
        try:
            for batch in batches:
                if out is None and len(batch):
                    store.create_dir(base, recursive=True)
                    out = store.open_output_stream(name, compression=None)
                offsets, lengths = [], []
                for row in batch.itertuples(index=False):
                    packer = zlib.compressobj(3, zlib.DEFLATED, 31)
                    member = packer.compress(_record(row, bytes(row.payload))) + packer.flush()
                    out.write(member)
                    offsets.append(at)
                    lengths.append(len(member))
                    at += len(member)
                yield batch.drop(columns="payload").assign(file=name, offset=offsets, length=lengths)
        finally:
            if out is not None:
                out.close()

    typed = classify(pages, least_bytes).select("page_id", "url", "payload_digest", "payload_bytes", "record_type", "refers_to", "payload")
    # ids travel as text where pandas would turn nulls into floats
    as_text = typed.withColumn("page_id", F.col("page_id").cast("string")).withColumn("refers_to", F.col("refers_to").cast("string"))
    schema = "page_id string, url string, payload_digest string, payload_bytes long, record_type string, refers_to string, file string, offset long, length long"
    written = as_text.mapInPandas(write, schema)
    names = [x.split()[0] for x in INDEX.split(", ")]
    typed_index = written.withColumn("page_id", F.col("page_id").cast("long")).withColumn("refers_to", F.col("refers_to").cast("long"))
    return materialise(typed_index.select(*names).withColumn("_base", F.lit(folder)))


def read_records(wanted: DataFrame, payload: bool = True) -> DataFrame:
    """The records of some rows of an index, read back from the archives by joined byte ranges.

    Every response is checked against its digest; ``payload_bytes`` and ``payload_digest`` come from the
    archive. Rows that repeat are read as often as they come; no row gives no record. A revisit has no payload of its own (null). Without ``payload`` bodies are checked, then dropped.
    """
    small_batches(wanted.sparkSession, 1000)

    def fetch(rows: pd.DataFrame) -> Iterator[tuple]:
        store, _ = _file_system(rows["_base"].iloc[0])
        for name, own in rows.groupby("file", sort=False):
            starts, ends = own["offset"].to_numpy(), (own["offset"] + own["length"]).to_numpy()
            with store.open_input_file(name) as source:
                at = 0
                while at < len(own):
                    stop = at + 1
                    while stop < len(own) and starts[stop] - ends[stop - 1] <= GAP and ends[stop] - starts[at] <= READ_LIMIT:
                        stop += 1
                    data = source.read_at(int(ends[stop - 1] - starts[at]), int(starts[at]))
                    for k in range(at, stop):
                        row = own.iloc[k]
                        member = data[starts[k] - starts[at] : ends[k] - starts[at]]
                        yield _checked(row["page_id"], row["refers_to"], *parse(zlib.decompress(member, 31)), payload)
                    at = stop

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [x.split()[0] for x in RECORD.split(", ")]
        for batch in batches:
            rows, held = [], 0
            for row in fetch(batch) if len(batch) else ():
                rows.append(row)
                held += len(row[-1] or b"")
                if held >= HANDED_BYTES:
                    yield pd.DataFrame(rows, columns=names)
                    rows, held = [], 0
            if rows:
                yield pd.DataFrame(rows, columns=names)

    # a slice is a run of bytes of one file; there are a few for each core, unless that makes them too small or too large
    total = wanted.agg(F.sum("length")).first()[0] or 0
    cores = wanted.sparkSession.sparkContext.defaultParallelism
    size = max(LEAST_SLICE, min(SLICE, total // (2 * cores) + 1))
    tasks = max(1, -(-total // size))
    sliced = wanted.withColumn("_slice", F.floor(F.col("offset") / size))
    # the number of tasks is given, so that adaptive execution does not join small index partitions whose archives are large
    sliced = sliced.repartition(tasks, "file", "_slice").sortWithinPartitions("file", "offset")
    as_text = sliced.select("file", "offset", "length", "_base", F.col("page_id").cast("string").alias("page_id"), F.col("refers_to").cast("string").alias("refers_to"))
    schema = RECORD.replace("page_id long", "page_id string").replace("refers_to long", "refers_to string")
    return as_text.mapInPandas(read, schema).withColumn("page_id", F.col("page_id").cast("long")).withColumn("refers_to", F.col("refers_to").cast("long"))


def _checked(page_id, refers_to, headers: dict[str, str], body: bytes, keep: bool) -> tuple:
    kind, said = headers["warc-type"], headers["warc-payload-digest"].removeprefix("sha1:")
    size = int(headers["http-content-length"])
    if kind == "response":
        digest = base64.b32encode(hashlib.sha1(body).digest()).decode()
        if digest != said or len(body) != size:
            raise ValueError(f"record of page {page_id} does not match its digest")
    return page_id, headers["warc-target-uri"], size, said, kind, refers_to, body if keep and kind == "response" else None


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages through archives and back."""
    index = write_archives(table(spark, sf_dir, "pages"))
    return read_records(index, payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


_LETTERS = " || ".join(
    f"substr('{ALPHABET}', ((('0x' || substr(h, {5 * k + 1}, 5))::BIGINT >> {s}) & 31)::INTEGER + 1, 1)" for k in range(8) for s in (15, 10, 5, 0)
)
OP2_SQL = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS payload FROM pages),
h AS (SELECT page_id, strlen(payload)::BIGINT AS payload_bytes, sha1(payload) AS h FROM p),
d AS (SELECT page_id, payload_bytes, {_LETTERS} AS payload_digest FROM h),
m AS (SELECT payload_digest, max(page_id) AS first FROM d GROUP BY payload_digest)
SELECT d.page_id, d.payload_bytes, d.payload_digest,
  CASE WHEN d.page_id = m.first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN d.page_id = m.first THEN NULL ELSE m.first END AS refers_to
FROM d JOIN m USING (payload_digest)
"""
