"""Content-addressed WARC archive.

``write`` stores each distinct payload once, under its SHA-256, and the exact record
headers (WARC and HTTP) of every page apart from it; ``read`` joins the two, rebuilds
the records and verifies both digests of what it gets back. Only payloads that were
compressed in the scan are shuffled, and copies meet in partial aggregation, so a
payload that a third of all pages share costs one row per task.
"""

from __future__ import annotations

import base64
import hashlib

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, new_path

VERSION = b"WARC/1.1"
DATE = "2024-01-01T00:00:00Z"
LEVEL = 6
#: A payload that more records share is dealt to a join in parts of about so many.
HOT_RECORDS = 50_000


def _sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _digests(texts: pa.Array) -> pa.Array:
    """Length, digests and compressed bytes of each payload, in one pass."""
    press = zstandard.ZstdCompressor(level=LEVEL)
    rows = [(x.as_py() or "").encode("utf-8", "surrogatepass") for x in texts]
    return pa.StructArray.from_arrays(
        [
            pa.array([len(r) for r in rows], pa.int64()),
            pa.array([_sha1(r) for r in rows], pa.string()),
            pa.array([hashlib.sha256(r).digest() for r in rows], pa.binary()),
            pa.array([press.compress(r) for r in rows], pa.binary()),
        ],
        ["n", "sha1", "sha256", "packed"],
    )


def _header(page_id: int | None, url: str | None, n: int, sha1: str, first: int | None, revisit: bool) -> bytes:
    """The exact bytes of a record before its payload: WARC header, blank line, HTTP header, blank line."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {n}\r\n\r\n".encode()
    clean = (url or "").replace("\r", "%0D").replace("\n", "%0A")  # a header field is one line
    lines = [
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {DATE}",
        f"WARC-Target-URI: {clean}",
        f"WARC-Payload-Digest: sha1:{sha1}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(http) + (0 if revisit else n)}",
    ]
    if revisit:
        lines += [f"WARC-Refers-To: <urn:page:{first}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    return b"\r\n".join([VERSION, *(x.encode("utf-8", "surrogatepass") for x in lines)]) + b"\r\n\r\n" + http


def _headers(page_ids: pa.Array, urls: pa.Array, ns: pa.Array, sha1s: pa.Array, firsts: pa.Array, revisits: pa.Array) -> pa.Array:
    columns = [c.to_pylist() for c in (page_ids, urls, ns, sha1s, firsts, revisits)]
    return pa.array([_header(*row) for row in zip(*columns)], pa.binary())


def parse(head: bytes) -> dict[str, str]:
    """Fields of a record's WARC header; raises on anything that isn't one."""
    warc, _, _ = head.partition(b"\r\n\r\n")
    version, *lines = warc.split(b"\r\n")
    if version != VERSION:
        raise ValueError(f"not a WARC record: {version[:20]!r}")
    return dict(x.decode("utf-8", "surrogatepass").split(": ", 1) for x in lines)


def record(head: bytes, payload: bytes) -> bytes:
    """The original record, as it stands in a WARC file."""
    body = b"" if parse(head)["WARC-Type"] == "revisit" else payload
    return head + body + b"\r\n\r\n"


def _verified(heads: pa.Array, keys: pa.Array, packed: pa.Array) -> pa.Array:
    unpress = zstandard.ZstdDecompressor()
    out = []
    for head, key, some in zip(heads.to_pylist(), keys.to_pylist(), packed.to_pylist()):
        payload = unpress.decompress(some) if some else b""
        fields = parse(head)
        sha1 = _sha1(payload)
        if hashlib.sha256(payload).digest() != key or fields["WARC-Payload-Digest"] != f"sha1:{sha1}":
            raise ValueError(f"digest mismatch in record {fields['WARC-Record-ID']}")
        page, refers = (fields.get(f, "")[len("<urn:page:") : -1] for f in ("WARC-Record-ID", "WARC-Refers-To"))
        out.append((int(page) if page else None, len(payload), sha1, fields["WARC-Type"], int(refers) if refers else None))
    names = ("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())
    columns = zip(*out) if out else [()] * 5
    return pa.StructArray.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], list(names))


def _join_by_payload(records: DataFrame, payloads: DataFrame, number: Column) -> DataFrame:
    """``records`` with the columns of ``payloads`` (one row a sha256), none lost if a payload is missing.

    Records of a payload with more than ``HOT_RECORDS`` are dealt to parts by a hash of ``number``
    and the payload's row is repeated for each part. What is broadcast is a row for each such
    payload: at most the number of records over ``HOT_RECORDS``."""
    hot = records.groupBy("sha256").agg(F.count("*").alias("n")).where(F.col("n") > HOT_RECORDS)
    hot = cut(hot.select("sha256", F.ceil(F.col("n") / HOT_RECORDS).cast("int").alias("parts")), "warc-hot")
    parts = F.coalesce("parts", F.lit(1))
    left = records.join(F.broadcast(hot), "sha256", "left").withColumn("part", F.pmod(F.xxhash64(number), parts).cast("int")).drop("parts")
    right = payloads.join(F.broadcast(hot), "sha256", "left").withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("parts")
    return left.join(right, ["sha256", "part"], "left").drop("part")


def write(pages: DataFrame, min_bytes: int = 0, page_id: str = "page_id", url: str = "url", html: str = "html") -> tuple[str, str]:
    """Write the archive of ``pages`` and return its two paths (headers, payloads).

    A null html is the empty payload, a null url an empty address. Of pages with equal
    payloads of at least ``min_bytes`` bytes the smallest page_id is the response and the
    others revisit it; rows that repeat the winning page_id are the same response again.
    Rows with a null page_id revisit if their payload has any page_id, else are responses.
    Line breaks in an address are written as %0D and %0A. A payload is handled whole, so the
    longest must fit a task's memory. Other columns are ignored; an empty table gives an empty archive.
    """
    spark = pages.sparkSession
    at_headers, at_payloads = new_path(spark, "warc-headers"), new_path(spark, "warc-payloads")
    digest = F.arrow_udf(_digests, "n long, sha1 string, sha256 binary, packed binary")(F.col(html))
    read = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).alias("url"), digest.alias("d"))
    read.select("d.sha256", "d.packed").groupBy("sha256").agg(F.first("packed").alias("packed")).write.option("compression", "none").parquet(at_payloads)
    rows = cut(read.select("page_id", "url", "d.n", "d.sha1", "d.sha256"), "warc-rows")
    first = cut(rows.where(F.col("n") >= min_bytes).groupBy("sha256").agg(F.min("page_id").alias("first")), "warc-first")
    marked = _join_by_payload(rows, first, F.struct("page_id", "url")).withColumn(
        "revisit", F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    )
    head = F.arrow_udf(_headers, "binary")("page_id", "url", "n", "sha1", "first", "revisit")
    marked.select("sha256", head.alias("header")).write.parquet(at_headers)
    return at_headers, at_payloads


def records(spark, at_headers: str, at_payloads: str) -> DataFrame:
    """``(header, sha256, packed)`` of every record, by joining headers and payloads."""
    headers = spark.read.schema("sha256 binary, header binary").parquet(at_headers)
    payloads = spark.read.schema("sha256 binary, packed binary").parquet(at_payloads)
    return _join_by_payload(headers, payloads, F.col("header"))


def read(spark, at_headers: str, at_payloads: str) -> DataFrame:
    """Parse and verify every record: ``(page_id, payload_bytes, payload_digest, record_type, refers_to)``."""
    kind = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"
    check = F.arrow_udf(_verified, kind)("header", "sha256", "packed")
    return records(spark, at_headers, at_payloads).select(check.alias("r")).select("r.*")


def export(spark, at_headers: str, at_payloads: str) -> DataFrame:
    """``(page_id, record)``: the bytes of each original record, ready to concatenate to a WARC file."""

    def whole(heads: pa.Array, packed: pa.Array) -> pa.Array:
        unpress = zstandard.ZstdDecompressor()
        return pa.array([record(h, unpress.decompress(p) if p else b"") for h, p in zip(heads.to_pylist(), packed.to_pylist())], pa.binary())

    page = F.regexp_extract(F.decode("header", "utf-8"), r"WARC-Record-ID: <urn:page:(-?\d*)>", 1)
    return records(spark, at_headers, at_payloads).select(
        F.when(page != "", page.cast("long")).alias("page_id"), F.arrow_udf(whole, "binary")("header", "packed").alias("record")
    )
