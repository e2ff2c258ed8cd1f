"""Operator 9, WARC: write archives, read them back, assemble transactions.

Each capture is written as a request, a response or revisit, and a metadata record; request
and metadata name the response by ``WARC-Concurrent-To``.  Reading joins the records of a
capture by that identifier and gives one nested row.

Writing: each task rolls gzip archives (one member a record) of a bounded size in the shared
folder and returns a manifest row for each.  The manifest is a written table, so only the files of
the committed attempt of each task are ever read; files of lost attempts are not named in it.

Defined cases: null html is the empty payload; a null url is written as an empty target and
read as null; a null page id is written as no field and read as null, and among equal payloads a non-null id is
elected first; if the largest id repeats, each of its rows is a response, and revisits name its page but no record; targets are
written without white space, and the metadata record keeps the url as it was; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import json
import uuid
from collections.abc import Iterator
from urllib.parse import urlsplit

import pandas as pd
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import new_path, read_table, slices, text_bytes, write_read

ARCHIVE_BYTES = 32 << 20
#: Payloads below this size are never written as revisits.
MIN_REVISIT_BYTES = 0
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def elect_responses(pages: DataFrame, min_bytes: int = MIN_REVISIT_BYTES) -> DataFrame:
    """Rows (page_id, url, html, first_page, n_first): the id that captures of one payload refer to, and how many rows have it.

    Equal payloads meet by digest in partial aggregates, so a payload that a third of all pages share costs one row a task; the join
    back is one that adaptive execution can split.  ``n_first`` is null where a payload is the only one of its kind.
    """
    rows = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html")).withColumn("digest", F.sha1("html"))
    ids = rows.filter(F.octet_length("html") >= min_bytes).groupBy("digest", "page_id").agg(F.count("*").alias("n"))
    best = ids.groupBy("digest").agg(F.max(F.struct(F.coalesce("page_id", F.lit(-(1 << 63))).alias("p"), F.col("page_id").alias("page"), F.col("n").alias("n"))).alias("best"), F.sum("n").alias("n"))
    best = best.filter("n > 1").select("digest", F.col("best.page").alias("first_page"), F.col("best.n").alias("n_first"))
    return rows.join(best, "digest", "left").drop("digest")


def record(kind: str, rid: str, fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = [("WARC-Type", kind), ("WARC-Record-ID", f"<{rid}>"), ("WARC-Date", DATE), *fields, ("Content-Length", str(len(block)))]
    return ("WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head) + "\r\n").encode() + block + b"\r\n\r\n"


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def capture_records(run: str, page, url: str | None, payload: bytes, first_page, n_first: int | None) -> list[bytes]:
    """The three records of one capture.

    The response that others refer to is named by its digest and page, which they know too; all other names are random.
    """
    fresh = lambda: f"urn:uuid:{uuid.uuid4()}"
    digest = "sha1:" + base32_sha1(payload)
    known = f"urn:uuid:{uuid.uuid5(uuid.UUID(run), f'{digest}/{first_page}')}" if n_first == 1 else None
    revisit = n_first is not None and page != first_page
    target, me = "".join((url or "").split()), known if known and not revisit else fresh()
    parts = urlsplit(target) if "[" not in target else urlsplit("")
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    to = [("WARC-Target-URI", target)] if url is not None else []
    also = [("WARC-Concurrent-To", f"<{me}>")]
    if revisit:
        main = record("revisit", me, [*to, ("WARC-Profile", PROFILE), *([("WARC-Refers-To", f"<{known}>")] if known else []), ("WARC-Payload-Digest", digest), ("WARC-Truncated", "length"), ("Content-Type", "application/http;msgtype=response")], http)
    else:
        main = record("response", me, [*to, ("WARC-Payload-Digest", digest), ("Content-Type", "application/http;msgtype=response")], http + payload)
    ask = f"GET {parts.path or '/'}{'?' + parts.query if parts.query else ''} HTTP/1.1\r\nHost: {parts.netloc}\r\n\r\n".encode()
    about = "".join(f"{k}: {v}\r\n" for k, v in (("page-id", page), ("page-url", None if url is None else json.dumps(url)), ("refers-to-page", first_page if revisit else None)) if v is not None).encode()
    return [
        record("request", fresh(), [*to, *also, ("Content-Type", "application/http;msgtype=request")], ask),
        main,
        record("metadata", fresh(), [*to, *also, ("Content-Type", "application/warc-fields")], about),
    ]


def write_archives(elected: DataFrame, folder: str, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Write the captures to ``folder``; gives the manifest (path, n_records, n_bytes)."""
    run = str(uuid.uuid4())

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        out, path, n, size = None, "", 0, 0
        row = lambda: pa.RecordBatch.from_pydict({"path": [f"{folder}/{path}"], "n_records": [n], "n_bytes": [size]})
        for batch in batches:
            for part in slices(batch, "html"):
                payloads = text_bytes(part.column("html")).to_pylist()
                cols = [part.column(k).to_pylist() for k in ("page_id", "url", "first_page", "n_first")]
                for payload, page, url, first_page, n_first in zip(payloads, *cols):
                    if out is None:
                        path, n, size = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                        out = store.open_output_stream(f"{base}/{path}", compression=None)
                    for r in capture_records(run, page, url, payload, first_page, n_first):
                        member = gzip.compress(r, 1)
                        out.write(member)
                        n, size = n + 1, size + len(member)
                    if size >= archive_bytes:
                        out.close()
                        out = None
                        yield row()
        if out is not None:
            out.close()
            yield row()

    return elected.select("page_id", "url", "html", "first_page", "n_first").mapInArrow(write, "path string, n_records long, n_bytes long")


def parse_archive(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields in lower case, block) of each record of an uncompressed stream."""
    while line := stream.readline():
        if not line.startswith(b"WARC/"):
            if line.strip():
                raise ValueError(f"not a WARC record: {line[:40]!r}")
            continue
        head = {}
        while (line := stream.readline()) not in (b"\r\n", b"\n", b""):
            k, _, v = line.decode("utf-8", "replace").partition(":")
            head[k.strip().lower()] = v.strip()
        block = stream.read(int(head["content-length"]))
        if len(block) != int(head["content-length"]):
            raise ValueError("a record is cut short")
        yield head, block


RECORDS = "record_type string, record_id string, concurrent_to string, target_uri string, warc_date string, payload_bytes long, payload_digest string, refers_to_id string, page_id long, url string, refers_to long, payload binary"


def read_archives(manifest: DataFrame, with_payload: bool = True) -> DataFrame:
    """One row a record.  Sizes and digests of responses are taken from the payload read back."""

    def read(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for path in frame["path"]:
                store, base = fs.FileSystem.from_uri(path)
                rows, held = [], 0
                with store.open_input_stream(base, compression=None) as raw, gzip.GzipFile(fileobj=raw) as stream:
                    for head, block in parse_archive(stream):
                        kind, bare = head["warc-type"], lambda k: head.get(k, "").strip("<>") or None  # noqa: B023
                        n = digest = page = url = ref = payload = None
                        if kind in ("response", "revisit"):
                            http, _, body = block.partition(b"\r\n\r\n")
                            said = dict(x.split(b":", 1) for x in http.split(b"\r\n")[1:])
                            n, digest = int(said[b"Content-Length"]), head["warc-payload-digest"].removeprefix("sha1:")
                            if kind == "response":
                                n, digest, payload = len(body), base32_sha1(body), body if with_payload else None
                                if "sha1:" + digest != head["warc-payload-digest"]:
                                    raise ValueError(f"damaged payload in {path}")
                        elif kind == "metadata":
                            f = dict(x.split(": ", 1) for x in block.decode().split("\r\n") if x)
                            page, url, ref = f.get("page-id"), json.loads(f.get("page-url", "null")), f.get("refers-to-page")
                        rows.append((kind, bare("warc-record-id"), bare("warc-concurrent-to"), bare("warc-target-uri"), head.get("warc-date"), n, digest, bare("warc-refers-to"), page and int(page), url, ref and int(ref), payload))
                        held += len(block)
                        if len(rows) >= 5000 or held >= 8 << 20:
                            yield as_frame(rows)
                            rows, held = [], 0
                if rows:
                    yield as_frame(rows)

    names = [x.split()[0] for x in RECORDS.split(", ")]

    def as_frame(rows):
        out = pd.DataFrame(rows, columns=names)
        return out.astype({k: "Int64" for k in ("payload_bytes", "page_id", "refers_to")})

    return manifest.select("path").mapInPandas(read, RECORDS)


def assemble(records: DataFrame) -> DataFrame:
    """Join the records of each capture by concurrent-to: (capture_id, request, response, metadata).

    One shuffle of record rows; keys are record ids, so no key has more than a capture's records.
    Captures without a request or metadata record get a null there.
    """
    main = F.col("record_type").isin("response", "revisit")
    part = lambda cond, *cols: F.first(F.when(cond, F.struct(*cols)), ignorenulls=True)
    return (
        records.withColumn("capture_id", F.coalesce("concurrent_to", "record_id"))
        .groupBy("capture_id")
        .agg(
            part(F.col("record_type") == "request", "record_id", "target_uri").alias("request"),
            part(main, "record_type", "record_id", "target_uri", "warc_date", "payload_bytes", "payload_digest", "refers_to_id", "payload").alias("response"),
            part(F.col("record_type") == "metadata", "record_id", "page_id", "url", "refers_to").alias("metadata"),
        )
    )


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    elected = elect_responses(read_table(spark, sf_dir, "pages"))
    manifest = write_read(write_archives(elected, new_path(spark, "warc")), "manifest")
    # One archive a task at most: the manifest's few rows are dealt out before the archives are opened.
    dealt = manifest.repartition(spark.sparkContext.defaultParallelism * 2)
    found = assemble(read_archives(dealt, with_payload=False))
    return found.select(
        F.col("metadata.page_id").alias("page_id"),
        F.col("response.payload_bytes").alias("payload_bytes"),
        F.col("response.payload_digest").alias("payload_digest"),
        F.col("response.record_type").alias("record_type"),
        F.col("metadata.refers_to").alias("refers_to"),
        F.col("metadata.url").alias("url"),
    )


OP9_SQL = """
WITH p AS (
  SELECT page_id, coalesce(html, '') AS html, url FROM pages
), d AS (
  SELECT page_id, url, strlen(html) AS payload_bytes, sha1(html) AS h,
         max(page_id) OVER (PARTITION BY html) AS first_page FROM p
)
SELECT page_id, url, CAST(payload_bytes AS BIGINT) AS payload_bytes,
       list_aggregate(list_transform(range(32), lambda i:
         substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
                CAST((CAST('0x' || substr(h, CAST(5 * (i // 4) + 1 AS INT), 5) AS INT) >> CAST(15 - 5 * (i % 4) AS INT)) & 31 AS INT) + 1, 1)),
         'string_agg', '') AS payload_digest,
       CASE WHEN page_id = first_page THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id = first_page THEN NULL ELSE first_page END AS refers_to
FROM d
"""
