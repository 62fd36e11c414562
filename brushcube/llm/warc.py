"""WARC archives with embedded zstandard dictionaries (.warc.zst).

Writer: every task streams its rows into archives of at most ARCHIVE_MB of records. For each archive a dictionary is built from records spread over
it and stored in a leading skippable frame; every record is a frame of its own, so single records stay addressable. Records whose payload
(of at least REVISIT_BYTES) also stands elsewhere are revisits of the one with the largest id.
Reader: Spark reads whole archives, Python decodes them record by record and checks every stored payload against its digest.

Archives are written through pyarrow's filesystems into the shared folder, first under a name of the task's attempt; only
archives listed in the manifest of finished tasks are read, so a lost executor's leftovers don't count.

Defined results: a null html is an empty payload; a null url or id leaves its header out and reads back as null; equal
payloads under one repeated (largest) id are all responses; a null id never keeps a payload that a known id has;
an empty table gives no archive and no rows; other columns are not archived.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import new_folder, table

ARCHIVE_MB, DICT_BYTES, REVISIT_BYTES, LEVEL = 24, 65_536, 1000, 6
#: First four bytes of the frame that holds the dictionary.
DICT_MAGIC = 0x184D2A5D
MANIFEST = "archive string, n_records long, raw_bytes long, stored_bytes long"
RECORD = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"


def _id(page_id: int | None) -> str:
    return f"<urn:x-page:{page_id}>" if page_id is not None else f"<urn:uuid:{uuid.uuid4()}>"


def record_bytes(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One WARC/1.1 record: a response with its payload, or a revisit without."""
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {_id(page_id)}", "WARC-Date: 1970-01-01T00:00:00Z"]
    if url is not None:
        head.append("WARC-Target-URI: " + base64.b64encode(url.encode()).decode() if any(c in url for c in "\r\n") else f"WARC-Target-URI: {url}")
        if any(c in url for c in "\r\n"):
            head.append("X-Target-Encoding: base64")
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_id(refers_to)}"]
    head += [f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def build_dictionary(records: list[bytes], size: int = DICT_BYTES) -> bytes:
    """Dictionary bytes from records spread over the archive."""
    import zstandard

    step = max(1, len(records) // 400)
    samples = [r[:32_768] for r in records[::step]]
    size = min(size, sum(map(len, samples)) // 4)
    try:
        return zstandard.train_dictionary(size, samples, level=LEVEL).as_bytes()
    except (zstandard.ZstdError, ValueError):  # too few or too uniform samples: their bytes themselves
        return b"".join(samples)[-size:] if size else b""


def archive_bytes(records: list[bytes]) -> bytes:
    """A .warc.zst: the skippable dictionary frame, then a frame per record."""
    import zstandard

    raw = build_dictionary(records)
    c = zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(raw) if raw else None)
    return struct.pack("<II", DICT_MAGIC, len(raw)) + raw + b"".join(c.compress(r) for r in records)


def read_records(content: bytes) -> Iterator[tuple]:
    """(page_id, url, type, payload length, digest, refers_to, payload or None) of each record of an archive."""
    import zstandard

    magic, size = struct.unpack_from("<II", content)
    if magic != DICT_MAGIC:
        raise ValueError("archive without a dictionary frame")
    raw = content[8 : 8 + size]
    d = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(raw) if raw else None)
    stream = io.BufferedReader(d.stream_reader(io.BytesIO(content[8 + size :]), read_across_frames=True), 1 << 16)
    while stream.readline():
        head = {}
        while (line := stream.readline()) not in (b"\r\n", b""):
            name, _, value = line[:-2].partition(b": ")
            head[name] = value.decode()
        block = stream.read(int(head[b"Content-Length"]))
        stream.read(4)
        kind, digest = head[b"WARC-Type"], base64.b32decode(head[b"WARC-Payload-Digest"][5:]).hex()
        payload = block.partition(b"\r\n\r\n")[2] if kind == "response" else None
        if payload is not None and (hashlib.sha1(payload).hexdigest() != digest or len(payload) != int(head[b"X-Payload-Length"])):
            raise ValueError(f"damaged record {head[b'WARC-Record-ID']}")
        page = lambda x: int(x[len("<urn:x-page:") : -1]) if x and x.startswith("<urn:x-page:") else None
        url = head.get(b"WARC-Target-URI")
        if b"X-Target-Encoding" in head:
            url = base64.b64decode(url).decode()
        yield page(head[b"WARC-Record-ID"]), url, kind, int(head[b"X-Payload-Length"]), digest, page(head.get(b"WARC-Refers-To")), payload


def with_revisits(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """page_id, url, payload and refers_to (null: a response). Only digests are grouped, never payloads."""
    rows = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("payload"))
    rows = rows.withColumn("digest", F.when(F.octet_length("payload") >= least, F.sha1(F.col("payload").cast("binary"))))
    keepers = rows.where("digest is not null").groupBy("digest").agg(F.max("page_id").alias("keeper"), F.count("*").alias("n")).where("n > 1 and keeper is not null")
    out = rows.join(keepers.select(F.col("digest").alias("kept_digest"), "keeper"), F.col("digest") == F.col("kept_digest"), "left")
    revisit = F.col("keeper").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("keeper"))
    return out.select("page_id", "url", "payload", F.when(revisit, F.col("keeper")).alias("refers_to"))


def write_archives(pages: DataFrame, folder: str, archive_mb: int = ARCHIVE_MB) -> DataFrame:
    """Write ``pages`` (page_id, url, payload, refers_to) to ``folder``; returns the manifest, itself a table beside the archives."""

    def write(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyarrow import fs
        from pyspark import TaskContext

        task = TaskContext.get()
        store, at = fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)
        store.create_dir(f"{at}/archives", recursive=True)
        held, size, done = [], 0, 0

        def flush() -> pd.DataFrame:
            nonlocal held, size, done
            name = f"part-{task.partitionId():06d}-{task.taskAttemptId()}-{done:04d}.warc.zst"
            content = archive_bytes(held)
            with store.open_output_stream(f"{at}/archives/{name}", compression=None) as f:
                f.write(content)
            row = pd.DataFrame([(name, len(held), size, len(content))], columns=["archive", "n_records", "raw_bytes", "stored_bytes"])
            held, size, done = [], 0, done + 1
            return row

        for pdf in batches:
            for p, u, html, ref in zip(pdf["page_id"], pdf["url"], pdf["payload"], pdf["refers_to"], strict=True):
                record = record_bytes(None if pd.isna(p) else int(p), u, html.encode(), None if pd.isna(ref) else int(ref))
                held.append(record)
                size += len(record)
                if size >= archive_mb << 20:
                    yield flush()
        if held:
            yield flush()

    spark = pages.sparkSession
    # ids as strings: 64-bit integers with nulls would pass through floats
    ids = pages.withColumns({"page_id": F.col("page_id").cast("string"), "refers_to": F.col("refers_to").cast("string")})
    ids.mapInPandas(write, MANIFEST).write.parquet(f"{folder}/manifest")
    return spark.read.schema(MANIFEST).parquet(f"{folder}/manifest")


def read_archives(spark: SparkSession, folder: str, payloads: bool = True) -> DataFrame:
    """Every record of the archives in the manifest."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [c.split()[0] for c in RECORD.split(", ")]

        def frame(rows: list[tuple]) -> pd.DataFrame:  # ids never pass through floats
            cols = dict(zip(names, zip(*rows, strict=True), strict=True))
            return pd.DataFrame({c: pd.array(v, "Int64") if c in ("page_id", "refers_to") else list(v) for c, v in cols.items()})

        for pdf in batches:
            for content in pdf["content"]:
                rows, size = [], 0
                for r in read_records(content):
                    rows.append(r if payloads else (*r[:6], None))
                    size += len(r[6] or b"") if payloads else 0
                    if len(rows) >= 5000 or size > 16 << 20:
                        yield frame(rows)
                        rows, size = [], 0
                if rows:
                    yield frame(rows)

    listed = spark.read.schema(MANIFEST).parquet(f"{folder}/manifest").select(F.col("archive").alias("listed"))
    if listed.isEmpty():
        return spark.createDataFrame([], RECORD)
    files = spark.read.format("binaryFile").load(f"{folder}/archives").select(F.element_at(F.split("path", "/"), -1).alias("archive"), "content")
    # one archive per batch: a batch of whole files must not add up
    return files.join(listed, F.col("archive") == F.col("listed"), "left_semi").select("content").mapInPandas(read, RECORD)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    folder = new_folder(spark, "warc")
    write_archives(with_revisits(pages), folder)
    return read_archives(spark, folder, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha1(h) AS payload_digest FROM p),
k AS (SELECT payload_digest, max(page_id) AS keeper FROM d WHERE payload_bytes >= 1000 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN keeper IS NULL OR page_id IS NOT DISTINCT FROM keeper THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN keeper IS NULL OR page_id IS NOT DISTINCT FROM keeper THEN NULL ELSE keeper END AS refers_to
FROM d LEFT JOIN k USING (payload_digest)
"""
