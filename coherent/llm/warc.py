"""Deterministic sharded WARC writer and reader.

Pages are range-sorted by page_id into shards; each task streams its shard's records into gzip members and rolls to a new
file when the compressed size passes `ROLL_BYTES`. A file is written under a temporary name that only this attempt uses
and then moved to its final name, so a lost or repeated task leaves the same bytes under the same names. The job commits
by writing a manifest of the files (records, bytes, sha256); only files in the manifest belong to the archive, and
the reader checks each against it. Headers and digests are made anew from the payload; record ids follow from page_id.

Of the pages with equal payloads of at least `REVISIT_BYTES`, the one with the largest page_id is the response and the
others are revisits of it. The choice travels to the writer as one small row a page, so the html is exchanged once.

Edge cases: a null html is an empty payload; a null url is written as an empty target; null page_ids come last, are
always responses and are refused as targets; pages of equal page_id are all written, in the order of their digests; an
empty table gives an archive of no files and an empty result; other columns are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

REVISIT_BYTES, ROLL_BYTES, DATE, RANGES = 1000, 16 << 20, "2024-01-01T00:00:00Z", 8
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
MANIFEST = "file string, records long, bytes long, sha256 string"
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, file string, intact boolean"


def _filesystem(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


def record_id(page_id: int | None, digest: str) -> str:
    return f"<urn:page:{'none-' + digest if page_id is None else page_id}>"


def record(page_id: int | None, url: str, payload: bytes, digest: str, size: int, target: int | None) -> bytes:
    """One WARC record. A revisit stores the HTTP headers only, with the full payload's digest and length."""
    block = HTTP if target is not None else HTTP + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if target is None else 'revisit'}",
        f"WARC-Record-ID: {record_id(page_id, digest)}",
        f"WARC-Date: {DATE}",
        "WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"),
        "Content-Type: application/http; msgtype=response",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{hashlib.sha1(block).hexdigest()}",
        f"X-Payload-Length: {size}",
    ]
    if target is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(target, digest)}"]
    return ("\r\n".join([*head, f"Content-Length: {len(block)}", "", ""])).encode() + block + b"\r\n\r\n"


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record in the bytes of an uncompressed archive."""
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record at byte {at}")
        head = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
        size = int(head["Content-Length"])
        yield head, data[end + 4 : end + 4 + size]
        at = end + 4 + size + 4


class _Roll:
    """Files of one shard, each written under a temporary name and moved when full."""

    def __init__(self, root: str, shard: int, roll: int) -> None:
        self.fs, self.root = _filesystem(root)
        self.shard, self.roll, self.seq, self.done = shard, roll, 0, []
        self._open()

    def _open(self) -> None:
        self.temp = f"{self.root}/_temporary/{self.shard:06d}-{self.seq:05d}-{uuid.uuid4().hex}"
        self.out, self.size, self.records, self.sha = None, 0, 0, hashlib.sha256()

    def add(self, data: bytes) -> None:
        if self.out is None:
            self.fs.create_dir(f"{self.root}/_temporary", recursive=True)
            self.out = self.fs.open_output_stream(self.temp, compression=None)
        packed = gzip.compress(data, 6, mtime=0)
        self.out.write(packed)
        self.sha.update(packed)
        self.size, self.records = self.size + len(packed), self.records + 1
        if self.size >= self.roll:
            self.close()

    def close(self) -> None:
        if self.out is None:
            return
        self.out.close()
        name = f"pages-{self.shard:06d}-{self.seq:05d}.warc.gz"
        self.fs.move(self.temp, f"{self.root}/{name}")
        self.done.append((name, self.records, self.size, self.sha.hexdigest()))
        self.seq += 1
        self._open()


def _writer(root: str, roll: int):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard: _Roll | None = None
        told: dict = {}
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                part = whole.slice(at, 256)
                for bucket, page_id, kind, url, html, digest, size, target in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    if shard is None or shard.shard != bucket:
                        if shard:
                            shard.close()
                            yield _manifest(shard)
                        shard = _Roll(root, bucket, roll)
                    if kind == 0:  # the decision on a page comes right before the page
                        told = {(page_id, digest): target} | (told if any(k[0] == page_id for k in told) else {})
                        continue
                    payload = (html or "").encode()
                    shard.add(record(page_id, url or "", payload, digest, size, told.get((page_id, digest))))
        if shard:
            shard.close()
            yield _manifest(shard)

    return write


def _manifest(shard: _Roll) -> pa.RecordBatch:
    columns = list(zip(*shard.done, strict=True)) or [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int64(), pa.int64(), pa.string()), strict=True)], names=["file", "records", "bytes", "sha256"])


def write(pages: DataFrame, root: str, roll: int = ROLL_BYTES) -> DataFrame:
    """Write `pages` (page_id, url, html) as WARC files under `root`; returns the committed manifest."""
    spark = pages.sparkSession
    html = F.coalesce(F.col("html"), F.lit(""))
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.sha1(html.cast("binary")).alias("_digest"), F.octet_length(html).cast("long").alias("_size"))
    ranges = RANGES * common.partitions(spark)
    p = common.range_bucketed(p, "page_id", ranges, "_bucket")
    # Pages without a number come in the order of their digests, in as many ranges of their own.
    of_digest = F.conv(F.substring("_digest", 1, 4), 16, 10).cast("int") * ranges / 65536
    p = p.withColumn("_bucket", F.col("_bucket") + F.when(F.col("page_id").isNull(), of_digest.cast("int")).otherwise(0))
    small = common.durable(p.select("_bucket", "page_id", "_digest", "_size"), "warc-pages")
    large = small.where((F.col("_size") >= REVISIT_BYTES) & F.col("page_id").isNotNull())
    chosen = large.groupBy(F.col("_digest").alias("_d")).agg(F.max("page_id").alias("_to"), F.count(F.lit(1)).alias("_of")).where("_of > 1").drop("_of")
    told = large.join(chosen, (F.col("_digest") == F.col("_d")) & (F.col("page_id") != F.col("_to")))
    none = F.lit(None)
    rows = p.select("_bucket", "page_id", F.lit(1).alias("_kind"), "url", "html", "_digest", "_size", none.cast("long").alias("_to")).unionByName(
        told.select("_bucket", "page_id", F.lit(0).alias("_kind"), none.cast("string").alias("url"), none.cast("string").alias("html"), "_digest", "_size", "_to")
    )
    sorted_ = rows.repartition(common.partitions(spark), "_bucket").sortWithinPartitions("_bucket", F.col("page_id").asc_nulls_last(), "_kind", "_digest", "url")
    # Every range writes its archives in its own task and leaves a row a file; the commit gathers those few rows.
    files = common.durable(sorted_.mapInArrow(_writer(root, roll), MANIFEST), "warc-files")
    files.repartition(1).write.parquet(f"{root}/_manifest")
    return spark.read.schema(MANIFEST).parquet(f"{root}/_manifest")


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.bool_())
    names = [x.split()[0] for x in RECORD.split(", ")]
    for batch in batches:
        for file, sha, size, content in zip(*(batch.column(c) for c in ("file", "sha256", "bytes", "content")), strict=True):
            data, rows = content.as_py(), []
            if hashlib.sha256(data).hexdigest() != sha.as_py() or len(data) != size.as_py():
                raise ValueError(f"{file} differs from the manifest")
            for head, block in parse(gzip.GzipFile(fileobj=io.BytesIO(data)).read()):
                page = head["WARC-Record-ID"].removeprefix("<urn:page:").rstrip(">")
                to = head.get("WARC-Refers-To", "").removeprefix("<urn:page:").rstrip(">")
                digest, kind = head["WARC-Payload-Digest"].removeprefix("sha1:"), head["WARC-Type"]
                payload = block[block.index(b"\r\n\r\n") + 4 :]
                if kind == "response":
                    digest_read, length = hashlib.sha1(payload).hexdigest(), len(payload)
                else:
                    digest_read, length = digest, int(head["X-Payload-Length"])
                intact = digest_read == digest and hashlib.sha1(block).hexdigest() == head["WARC-Block-Digest"].removeprefix("sha1:")
                rows.append((None if page.startswith("none-") else int(page), length, digest_read, kind, int(to) if to else None, head["WARC-Target-URI"], file.as_py(), intact))
            for at in range(0, len(rows), 5000):
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[at : at + 5000], strict=True), kinds, strict=True)], names=names)


def read(spark: SparkSession, root: str) -> DataFrame:
    """The records of the archive at `root`, one row each (see RECORD), every file checked against the manifest."""
    manifest = spark.read.schema(MANIFEST).parquet(f"{root}/_manifest")
    if manifest.isEmpty():
        return spark.createDataFrame([], RECORD)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(root)
    named = files.select(F.element_at(F.split("path", "/"), -1).alias("_name"), "content")
    return named.join(F.broadcast(manifest) if manifest.count() <= 100_000 else manifest, F.col("_name") == F.col("file")).select("file", "sha256", "bytes", "content").mapInArrow(_reader, RECORD)


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = common.fresh_path(spark, "warc")
    write(common.table(spark, sf_dir, "pages"), root)
    return read(spark, root).drop("file")


ORACLE = f"""
WITH p AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest, coalesce(url, '') AS url FROM pages),
m AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS last FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= {REVISIT_BYTES} AND page_id < last THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= {REVISIT_BYTES} AND page_id < last THEN last END AS refers_to, url, true AS intact
FROM m
"""
