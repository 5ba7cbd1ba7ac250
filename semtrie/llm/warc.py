"""WARC archives: write captures, read records back, assemble transactions.

A capture is three records: the response (or a revisit of an equal payload), its
request and its metadata, tied together by concurrent-to identifiers.

Defined cases: a null payload is an empty one; a null URL becomes ``urn:none``;
CR and LF in a URL are percent-encoded; rows that repeat both page id and payload
are one capture, with its request and metadata listed once per row; a null page id is the text ``null`` in the identifiers and
reads back as null; payloads may hold any text, record delimiters included; an
empty table writes an empty archive that reads back as no record.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semtrie.llm.common import components, materialize, scratch, table

CRLF = "\r\n"
VERSION = "WARC/1.1\r\n"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

RECORD_SCHEMA = (
    "record_id string, record_type string, target_uri string, date string, concurrent_to array<string>, refers_to string, "
    "declared_digest string, declared_bytes long, status int, fields map<string,string>, payload binary"
)


def base32_sha1(payload: Column) -> Column:
    """Bare upper-case base32 of the SHA-1: 160 bits are four 40-bit groups of eight base-32 digits."""
    digest = F.sha1(payload)
    groups = [F.lpad(F.conv(F.substring(digest, 1 + 10 * i, 10), 16, 32), 8, "0") for i in range(4)]
    return F.translate(F.concat(*groups), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def plan_captures(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", min_revisit_bytes: int = 0) -> DataFrame:
    """Add payload size and digest, and the page a revisit refers to (null: the page is the response).

    Only narrow digest rows are grouped; payloads that occur once need no match,
    so the join side holds repeated payloads only.
    """
    payload = F.coalesce(F.col(payload_col), F.lit("")).cast("binary")
    rows = pages.select(
        F.col(id_col).alias("page_id"),
        F.regexp_replace(F.regexp_replace(F.coalesce(F.col(url_col), F.lit("urn:none")), "\r", "%0D"), "\n", "%0A").alias("url"),
        F.octet_length(payload).cast("long").alias("bytes"),
        base32_sha1(payload).alias("digest"),
        payload.alias("payload"),
    )
    repeated = (
        rows.filter(F.col("bytes") >= min_revisit_bytes)
        .groupBy("digest", "bytes")
        .agg(F.max("page_id").alias("original"), F.count(F.lit(1)).alias("n"))
        .filter("n > 1")
        .drop("n")
    )
    joined = rows.join(repeated, ["digest", "bytes"], "left")
    return joined.withColumn("original", F.when(~F.col("page_id").eqNullSafe(F.col("original")), F.col("original")))


def _record(kind: Column | str, record_id: Column, uri: Column, extra: list[Column], content_type: str, block: Column, end: str = CRLF + CRLF) -> Column:
    kind = F.lit(kind) if isinstance(kind, str) else kind
    lines = [
        F.concat(F.lit("WARC-Type: "), kind, F.lit(CRLF)),
        F.concat(F.lit("WARC-Record-ID: <"), record_id, F.lit(">" + CRLF)),
        F.lit("WARC-Date: 2024-01-01T00:00:00Z" + CRLF),
        F.concat(F.lit("WARC-Target-URI: "), uri, F.lit(CRLF)),
        *extra,
        F.concat(F.lit(f"Content-Type: {content_type}{CRLF}Content-Length: "), F.octet_length(block).cast("string"), F.lit(CRLF + CRLF)),
    ]
    return F.concat(F.lit(VERSION), *lines, block, F.lit(end))


def write_warc(captures: DataFrame, path: str) -> None:
    """Write planned captures as gzip-compressed WARC files, three records per capture."""
    name = lambda role, page: F.concat(F.lit("urn:page:"), F.coalesce(page.cast("string"), F.lit("null")), F.lit(":"), F.col("digest"), F.lit(":" + role))
    anchor, request, metadata = (name(r, F.col("page_id")) for r in ("response", "request", "metadata"))
    is_revisit = F.col("original").isNotNull()
    tie = F.concat(F.lit("WARC-Concurrent-To: <"), anchor, F.lit(">" + CRLF))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("bytes").cast("string"), F.lit(CRLF + CRLF))
    body = F.concat(http, F.when(is_revisit, F.lit("")).otherwise(F.col("payload").cast("string")))
    refers = F.when(is_revisit, F.concat(F.lit("WARC-Refers-To: <"), name("response", F.col("original")), F.lit(f">{CRLF}WARC-Profile: {REVISIT_PROFILE}{CRLF}"))).otherwise(F.lit(""))
    digest = F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest"), F.lit(CRLF))
    records = F.concat(
        _record(F.when(is_revisit, F.lit("revisit")).otherwise(F.lit("response")), anchor, F.col("url"), [digest, refers], "application/http; msgtype=response", body),
        _record("request", request, F.col("url"), [tie], "application/http; msgtype=request", F.concat(F.lit("GET "), F.col("url"), F.lit(f" HTTP/1.1{CRLF}{CRLF}"))),
        _record("metadata", metadata, F.col("url"), [tie], "application/warc-fields", F.concat(F.lit("page-id: "), F.coalesce(F.col("page_id").cast("string"), F.lit("null")), F.lit(CRLF)), CRLF),
    )
    # the writer's line separator completes the last record's closing empty lines
    captures.select(records.alias("value")).write.option("lineSep", CRLF).option("compression", "gzip").option("maxRecordsPerFile", 200_000).text(path)


def _headers(raw: bytes) -> tuple[dict[str, str], list[str]]:
    head: dict[str, str] = {}
    ties: list[str] = []
    for line in raw.decode("utf-8", "replace").split(CRLF):
        key, colon, value = line.partition(":")
        if colon:
            key, value = key.strip().lower(), value.strip()
            if key == "warc-concurrent-to":
                ties.append(value.strip("<>"))
            else:
                head[key] = value
    return head, ties


def parse_record(raw: bytes) -> dict | None:
    """One record from the bytes after its version line; None while it is incomplete."""
    cut = raw.find(b"\r\n\r\n")
    if cut < 0:
        return None
    head, ties = _headers(raw[:cut])
    size = int(head.get("content-length", "0"))
    block = raw[cut + 4 : cut + 4 + size]
    if len(block) < size:
        return None
    kind, media = head.get("warc-type", ""), head.get("content-type", "")
    out = {
        "record_id": head.get("warc-record-id", "").strip("<>"), "record_type": kind, "target_uri": head.get("warc-target-uri"), "date": head.get("warc-date"),
        "concurrent_to": ties, "refers_to": head.get("warc-refers-to", "").strip("<>") or None,
        "declared_digest": head.get("warc-payload-digest", "").removeprefix("sha1:") or None, "declared_bytes": None, "status": None, "fields": None, "payload": None,
    }
    if media.startswith("application/http") and "request" not in media:
        end = block.find(b"\r\n\r\n")
        inner, _ = _headers(block[:end])
        words = block[: block.find(b"\r\n")].split(b" ")
        out["status"] = int(words[1]) if len(words) > 1 and words[1].isdigit() else None
        out["declared_bytes"] = int(inner["content-length"]) if inner.get("content-length", "").isdigit() else None
        out["payload"] = block[end + 4 :] if kind == "response" else None
    elif media == "application/warc-fields":
        out["fields"] = list(_headers(block)[0].items())
    elif kind in ("response", "resource", "conversion"):
        out["payload"] = block
    return out


def _parse(batches: Iterator[pa.RecordBatch], schema: pa.Schema, flush_bytes: int = 1 << 22) -> Iterator[pa.RecordBatch]:
    rows: list[dict] = []
    held, held_file, size = b"", None, 0
    for batch in batches:
        for chunk, name in zip(batch.column(0), batch.column(1), strict=True):
            chunk, name = chunk.as_py(), name.as_py()
            if name != held_file:
                held, held_file = b"", name
            held = held + VERSION.encode() + chunk if held else chunk
            if not held:
                continue
            record = parse_record(held)
            if record is None:  # the delimiter stood inside the block: wait for the rest
                continue
            held = b""
            rows.append(record)
            size += len(chunk)
            if size > flush_bytes:
                yield pa.RecordBatch.from_pylist(rows, schema)
                rows, size = [], 0
    if rows:
        yield pa.RecordBatch.from_pylist(rows, schema)


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of WARC files as rows; streams through each file, so memory holds one record, not one file."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    schema = to_arrow_schema(StructType.fromDDL(RECORD_SCHEMA))
    chunks = spark.read.format("text").option("lineSep", VERSION).load(path)
    raw = chunks.select(F.col("value").cast("binary").alias("chunk"), F.input_file_name().alias("file"))
    return raw.mapInArrow(lambda batches: _parse(batches, schema), RECORD_SCHEMA)


def _captures_of(records: DataFrame, depth: int | None) -> DataFrame:
    """(record_id, capture_id) of every record, by its ties.

    Anchors (responses, revisits, resources) are their own capture.  A record
    belongs to every anchor it is tied to, in either direction; a record without
    such a tie belongs to the captures of the records it is tied to, and so on for
    as many steps as it takes.  What no anchor reaches is grouped among itself
    under the identifier it waits for, or else its smallest record id.
    """
    is_anchor = F.col("record_type").isin("response", "revisit", "resource")
    known = records.select("record_id", is_anchor.alias("anchor"), "concurrent_to")
    ties = known.select(F.col("record_id").alias("x"), F.explode("concurrent_to").alias("y")).filter("x <> y")
    ties = materialize(ties.union(ties.select("y", "x")).distinct(), "ties")
    ids = materialize(known.groupBy("record_id").agg(F.max("anchor").alias("anchor")), "record-ids")
    reached = ids.filter("anchor").select("record_id", F.col("record_id").alias("capture_id"))
    front, open_ = reached, ids.filter("NOT anchor").select("record_id")
    step = 0
    while depth is None or step < depth:
        met = open_.join(ties, open_.record_id == ties.x).select("record_id", "y").join(front.select(F.col("record_id").alias("y"), "capture_id"), "y")
        front = materialize(met.select("record_id", "capture_id").distinct(), f"captures-{step}")
        reached = reached.unionByName(front)
        open_ = materialize(open_.join(front.select("record_id").distinct(), "record_id", "left_anti"), f"open-{step}")
        step += 1
        if front.isEmpty() or open_.isEmpty():
            break
    if open_.isEmpty():
        return reached
    # identifiers without a record sort before those with one
    missing = ties.select(F.col("y").alias("record_id")).distinct().join(ids, "record_id", "left_anti").withColumn("lost", F.lit("0"))
    left = ties.join(open_.withColumnRenamed("record_id", "x"), "x", "left_semi").join(missing.withColumnRenamed("record_id", "y"), "y", "left")
    grouped = components(left.select(F.concat(F.lit("1"), "x").alias("a"), F.concat(F.coalesce("lost", F.lit("1")), "y").alias("b")), "lost")
    name = F.concat(F.lit("1"), "record_id")
    lost = open_.join(grouped, name == grouped.id, "left").select("record_id", F.coalesce(F.substring("component", 2, 1 << 30), F.col("record_id")).alias("capture_id"))
    return reached.unionByName(lost)


def assemble_transactions(records: DataFrame, *, chain: bool = True) -> DataFrame:
    """One nested row per capture: ``capture_id``, ``response``, ``requests``, ``metadata``.

    Records meet through all their concurrent-to identifiers; with ``chain`` (the
    default) also through other records, to any depth, without it by direct ties
    only.  A nested record keeps all columns, its payload too.  A request or
    metadata whose response is missing gives a capture with a null response.
    ``records`` is read twice, so hand over a written table where parsing is dear.
    """
    is_anchor = F.col("record_type").isin("response", "revisit", "resource")
    whole = F.struct(*[F.col(c) for c in records.columns])
    keyed = records.join(_captures_of(records, None if chain else 1), "record_id")
    return keyed.groupBy("capture_id").agg(
        F.first(F.when(is_anchor, whole), ignorenulls=True).alias("response"),
        F.collect_list(F.when(F.col("record_type") == "request", whole)).alias("requests"),
        F.collect_list(F.when(F.col("record_type") == "metadata", whole)).alias("metadata"),
    )


def op1_warc_transactions(spark, sf_dir) -> DataFrame:
    """Contract query of operator 1: archives written from ``pages``, read back and assembled.

    Payloads are measured as they are read and not carried on, as no column asks for them.
    """
    path = scratch(spark, "warc")
    write_warc(plan_captures(table(spark, sf_dir, "pages").select("page_id", "url", "html")), path)
    records = (
        read_warc(spark, path)
        .withColumn("payload_bytes", F.coalesce(F.octet_length("payload").cast("long"), F.col("declared_bytes")))
        .withColumn("payload_digest", F.coalesce(base32_sha1(F.col("payload")), F.col("declared_digest")))
        .drop("payload")
    )
    records = materialize(records, "records")
    page_of = lambda name: name.try_cast("long")
    captures = assemble_transactions(records)
    return captures.filter("response IS NOT NULL").select(
        page_of(F.get("metadata", F.lit(0))["fields"]["page-id"]).alias("page_id"),
        F.col("response.payload_bytes").alias("payload_bytes"),
        F.col("response.payload_digest").alias("payload_digest"),
        F.col("response.record_type").alias("record_type"),
        page_of(F.split_part(F.col("response.refers_to"), F.lit(":"), F.lit(3))).alias("refers_to"),
    )


OP1_SQL = """
WITH p AS (
  SELECT page_id, coalesce(html, '') AS body FROM pages
), d AS (
  SELECT DISTINCT page_id, CAST(strlen(body) AS BIGINT) AS payload_bytes, sha1(body) AS hex FROM p
), b AS (
  SELECT *, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
      CAST((CAST(('0x' || substr(hex, CAST(1 + 10 * (i // 8) AS INT), 10)) AS BIGINT) >> CAST(35 - 5 * (i % 8) AS INT)) & 31 AS INT) + 1, 1)), '') AS payload_digest,
    max(page_id) OVER (PARTITION BY hex, payload_bytes) AS original
  FROM d
)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN original = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN original <> page_id THEN original END AS refers_to
FROM b
"""
