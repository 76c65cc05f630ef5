"""WARC archives: one gzip member per record, read back sequentially.

Writing turns each partition into archive files in the shared folder. The reader is incremental: it feeds
fixed-size chunks to zlib, takes a new decompressor at each member's end, frames the payload by
Content-Length and checks both digests, so memory is bounded by one record.

Of records with equal payloads of at least `min_bytes` bytes the one with the least page_id is a response
and the others are revisits that refer to it; shorter payloads are always responses.

Defined cases: a null payload is empty; rows whose page_id is null are never referred to unless all copies
lack an id (then all are responses); rows that share the least page_id are all responses.
"""

from __future__ import annotations

import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import fresh_path, keep_table, read_table

CRLF = b"\r\n"
CHUNK = 1 << 18
# Fixed value: the profile that names a revisit of an identical payload.
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def record_bytes(
    record_id: str, target: str | None, payload: bytes, digest: str, refers_to: int | None, page_id: int | None
) -> bytes:
    """One WARC record as one gzip member. Revisits keep no payload, only its digest and length."""
    body = b"" if refers_to is not None else payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:uuid:{record_id}>",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"WARC-Block-Digest: sha256:{hashlib.sha256(body).hexdigest()}",
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: text/html; charset=utf-8",
        f"Content-Length: {len(body)}",
    ]
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    if target is not None:
        head.append("WARC-Target-URI: " + target.replace("\r", "%0D").replace("\n", "%0A"))
    if refers_to is not None:
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"X-Refers-To: {refers_to}"]
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    raw = CRLF.join(x.encode("utf-8", "surrogatepass") for x in head) + CRLF * 2 + body + CRLF * 2
    return packer.compress(raw) + packer.flush()


def read_members(stream) -> Iterator[bytes]:
    """The gzip members of a byte stream, one by one, decompressed a chunk at a time."""
    pending = b""
    while True:
        pending = pending or stream.read(CHUNK)
        if not pending:
            return
        unpacker, parts = zlib.decompressobj(31), []
        while True:
            parts.append(unpacker.decompress(pending))
            if unpacker.eof:
                pending = unpacker.unused_data
                break
            pending = stream.read(CHUNK)
            if not pending:
                raise ValueError("archive ends inside a gzip member")
        yield b"".join(parts)


def parse_record(member: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and block, framed by Content-Length; raises if framing or a digest is wrong."""
    head, mark, rest = member.partition(CRLF * 2)
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not mark or not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.lower(): v for k, _, v in (x.partition(": ") for x in lines[1:])}
    size = int(fields["content-length"])
    body, tail = rest[:size], rest[size:]
    if len(body) != size or tail != CRLF * 2:
        raise ValueError("content length does not frame the block")
    if fields["warc-block-digest"] != "sha256:" + hashlib.sha256(body).hexdigest():
        raise ValueError("block digest mismatch")
    if fields["warc-type"] == "response" and fields["warc-payload-digest"] != fields["warc-block-digest"]:
        raise ValueError("payload digest mismatch")
    return fields, body


def open_store(base: str):
    """(file system, path) of a folder URI, by pyarrow: local, HDFS and the object stores it knows."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(base) if "://" in base or base.startswith("file:") else (fs.LocalFileSystem(), base)


def mark_revisits(pages: DataFrame, *, min_bytes: int = 100) -> DataFrame:
    """page_id, url, payload -> + payload_bytes, payload_digest, refers_to."""
    raw = F.coalesce(F.col("payload"), F.lit("")).cast("binary")
    rows = pages.withColumn("payload_bytes", F.octet_length(raw).cast("long")).withColumn(
        "payload_digest", F.sha2(raw, 256)
    )
    # only digests that occur more than once and the least id travel; the rest needs no partner
    copies = (
        rows.select("page_id", "payload_bytes", "payload_digest")
        .where(F.col("payload_bytes") >= min_bytes)
        .groupBy("payload_digest")
        .agg(F.min("page_id").alias("first_id"), F.count("*").alias("n"))
        .where("n > 1")
    )
    copies = keep_table(copies, "warc-copies")
    # digests of more than a 512th of the rows, at most 512 of them, are broadcast; their rows then go anywhere
    limit = max(copies.agg(F.sum("n")).first()[0] or 0, 1 << 19) // 512
    hot = copies.where(F.col("n") > limit).select("payload_digest", F.col("first_id").alias("hot_id"), F.lit(True).alias("hot"))
    cold = copies.where(F.col("n") <= limit).select(F.col("payload_digest").alias("met"), "first_id")
    rows = rows.join(F.broadcast(hot), "payload_digest", "left")
    met = F.when(F.col("hot"), F.concat(F.lit("-"), F.xxhash64("page_id").cast("string"))).otherwise(F.col("payload_digest"))
    rows = rows.withColumn("met", met).join(cold, "met", "left")
    first_id = F.when(F.col("hot"), F.col("hot_id")).otherwise(F.col("first_id"))
    first = F.when(~F.col("page_id").eqNullSafe(first_id), first_id)
    return rows.withColumn("refers_to", first).select(*pages.columns, "payload_bytes", "payload_digest", "refers_to")


def write_archives(pages: DataFrame, base: str, *, records_per_file: int = 20000) -> DataFrame:
    """Write rows of (page_id, url, payload, payload_digest, refers_to); returns (path, n_records).
    A task that runs again writes files of its own; only those that the manifest names count."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, folder = open_store(base)
        store.create_dir(folder, recursive=True)
        sink, path, n = None, "", 0
        for pdf in batches:
            for page, url, payload, digest, refers in zip(
                pdf["page_id"], pdf["url"], pdf["payload"], pdf["payload_digest"], pdf["refers_to"]
            ):
                if sink is None:
                    path = f"{folder}/{uuid.uuid4().hex}.warc.gz"
                    sink, n = store.open_output_stream(path, compression=None), 0
                body = (payload or "").encode("utf-8", "surrogatepass")
                page, refers = (None if pd.isna(x) else int(x) for x in (page, refers))
                sink.write(record_bytes(str(uuid.uuid4()), url, body, digest, refers, page))
                n += 1
                if n >= records_per_file:
                    sink.close()
                    yield pd.DataFrame({"path": [path], "n_records": [n]})
                    sink = None
        if sink is not None:
            sink.close()
            yield pd.DataFrame({"path": [path], "n_records": [n]})

    rows = pages.select(
        F.col("page_id").cast("string").alias("page_id"),
        "url",
        "payload",
        "payload_digest",
        F.col("refers_to").cast("string").alias("refers_to"),
    )
    return keep_table(rows.mapInPandas(run, "path string, n_records long"), "warc-manifest")


_RECORD = T.StructType(
    [
        T.StructField("path", T.StringType()),
        T.StructField("page_id", T.LongType()),
        T.StructField("url", T.StringType()),
        T.StructField("record_type", T.StringType()),
        T.StructField("payload_digest", T.StringType()),
        T.StructField("payload_bytes", T.LongType()),
        T.StructField("refers_to", T.LongType()),
    ]
)


def read_archives(manifest: DataFrame, base: str, *, with_payload: bool = False) -> DataFrame:
    """The records of the named archives; with_payload adds the block as text."""
    schema = T.StructType(_RECORD.fields + [T.StructField("payload", T.StringType())] * with_payload)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store, _ = open_store(base)
        names = [f.name for f in schema.fields]
        for pdf in batches:
            for path, expected in zip(pdf["path"], pdf["n_records"]):
                rows, seen = [], 0
                with store.open_input_stream(path, compression=None) as stream:
                    for member in read_members(io.BufferedReader(stream)):
                        fields, body = parse_record(member)
                        page, refers = fields.get("x-page-id"), fields.get("x-refers-to")
                        row = [
                            path,
                            page and int(page),
                            fields.get("warc-target-uri"),
                            fields["warc-type"],
                            fields["warc-payload-digest"].partition(":")[2],
                            int(fields["x-payload-length"]),
                            refers and int(refers),
                        ]
                        rows.append(row + [body.decode("utf-8", "surrogatepass")] * with_payload)
                        seen += 1
                        if len(rows) >= 2000:
                            yield _frame(rows, names)
                            rows = []
                if seen != expected:
                    raise ValueError(f"{path}: {seen} records, {expected} expected")
                if rows:
                    yield _frame(rows, names)

    return manifest.repartition(max(1, manifest.count()), "path").mapInPandas(run, schema)


def _frame(rows: list[list], names: list[str]) -> pd.DataFrame:
    pdf = pd.DataFrame(rows, columns=names, dtype=object)
    for c in ("page_id", "payload_bytes", "refers_to"):
        pdf[c] = pdf[c].astype("Int64")
    return pdf


def round_trip(pages: DataFrame, *, min_bytes: int = 100) -> DataFrame:
    """Write page_id, url, html as archives and read them back."""
    spark = pages.sparkSession
    base = fresh_path(spark, "warc")
    marked = mark_revisits(pages.select("page_id", "url", F.col("html").alias("payload")), min_bytes=min_bytes)
    return read_archives(write_archives(marked, base), base)


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(read_table(spark, sf_dir, "pages")).select(
        "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"
    )


OP4_SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest
  FROM pages),
f AS (SELECT payload_digest, min(page_id) AS first_id FROM p WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
  CASE WHEN first_id IS NULL OR first_id IS NOT DISTINCT FROM page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN first_id IS DISTINCT FROM page_id THEN first_id END AS refers_to
FROM p LEFT JOIN f USING (payload_digest)
"""
