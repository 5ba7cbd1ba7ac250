"""Token counts from flat token files that have no index.

A flat file is a run of little-endian unsigned 16-bit numbers: each token id plus
one, and 0 as the end-of-document mark.  Counting needs no index: each block of
the file is searched for the mark in one vectorised pass, and documents that
cross block borders are stitched by a prefix scan (running maximum of the last
mark's position) over the blocks.

Documents may start with a header of ``HEADER`` numbers that carries the row's
integer id (five 15-bit digits, a null flag), so that counts find their rows.

Defined cases: null and empty texts have 0 tokens; a null id comes back as null;
repeated rows give repeated counts; an empty table gives no row.
"""

from __future__ import annotations

import base64
import functools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semtrie.llm.common import pieces, scratch, table

DEFAULT_RANKS = "/opt/tokenizers/byte_bpe_50k.tiktoken"
# Fixed value: the pre-tokenisation pattern published with this vocabulary.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
HEADER = 6
MARK = b"\0\0"
CHUNK = 8 << 20
CHUNKS_PER_FILE = 16
DIGITS = 5


@functools.lru_cache(maxsize=2)
def encoding(ranks_path: str):
    import tiktoken

    with open(ranks_path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("flat", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def header_of(doc_id: int | None) -> list[int]:
    value = (doc_id or 0) & ((1 << 64) - 1)
    return [((value >> (15 * i)) & 0x7FFF) + 1 for i in range(DIGITS)] + [2 if doc_id is None else 1]


def id_of(header: np.ndarray) -> list[int | None]:
    """Ids from an (n, HEADER) array of header numbers."""
    digits = header[:, :DIGITS].astype(object) - 1
    out = []
    for row, flag in zip(digits, header[:, DIGITS], strict=True):
        value = sum(int(d) << (15 * i) for i, d in enumerate(row))
        out.append(None if flag == 2 else value - (1 << 64) if value >= 1 << 63 else value)
    return out


def _encode(batches: Iterator[pa.RecordBatch], ranks_path: str, chunk_bytes: int) -> Iterator[pa.RecordBatch]:
    """Stretches of the flat file of about ``chunk_bytes``, whole documents each; the last end mark is left to the writer."""
    enc = encoding(ranks_path)
    held, size = [], 0
    for part in pieces(batches, "text"):
        for doc_id, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), strict=True):
            ids = np.array(enc.encode_ordinary(text or ""), dtype=np.uint16) + np.uint16(1)
            held.append(np.array(header_of(doc_id), dtype="<u2").tobytes() + ids.astype("<u2").tobytes())
            size += len(held[-1]) + 2
            if size >= chunk_bytes:
                yield pa.RecordBatch.from_arrays([pa.array([MARK.join(held)], pa.binary())], ["value"])
                held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array([MARK.join(held)], pa.binary())], ["value"])


def write_flat_tokens(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text", ranks_path: str = DEFAULT_RANKS, chunk_bytes: int = CHUNK, chunks_per_file: int = CHUNKS_PER_FILE) -> None:
    """Tokenise documents into gzip-compressed flat files; the writer's line separator is the end mark.

    A file ends after ``chunks_per_file`` stretches of about ``chunk_bytes``, so
    its size is bounded in bytes whatever the documents' sizes (one longer
    document is a stretch of its own).
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    encoded = rows.mapInArrow(lambda b: _encode(b, ranks_path, chunk_bytes), "value binary")
    encoded.select(F.col("value").cast("string")).write.option("lineSep", "\0\0").option("compression", "gzip").option("maxRecordsPerFile", chunks_per_file).text(path)


BLOCK_SCHEMA = "file string, block long, first_mark long, last_mark long, n_marks long, head array<int>, tail array<int>, inner array<struct<doc_id:long,n_tokens:long>>"


def scan_block(numbers: np.ndarray, base: int, header: int = HEADER) -> dict:
    """Marks of one block that starts at position ``base`` of its file.

    Positions are absolute; documents that lie wholly inside come back counted,
    the first ``header`` numbers before the first and after the last mark serve
    those that cross a border.
    """
    marks = np.flatnonzero(numbers == 0)
    if len(marks) == 0:
        edge = numbers[:header].tolist()
        return {"first_mark": None, "last_mark": None, "n_marks": 0, "head": edge, "tail": [], "inner": []}
    starts, ends = marks[:-1] + 1, marks[1:]
    counts = ends - starts - header
    ids = id_of(numbers[starts[:, None] + np.arange(header)]) if header and len(starts) else [None] * len(starts)
    return {
        "first_mark": base + int(marks[0]), "last_mark": base + int(marks[-1]), "n_marks": len(marks),
        "head": numbers[: marks[0]][:header].tolist(), "tail": numbers[marks[-1] + 1 :][:header].tolist(),
        "inner": [{"doc_id": i, "n_tokens": int(c)} for i, c in zip(ids, counts, strict=True)],
    }


def _blocks(content: bytes, size: int) -> Iterator[bytes]:
    """Blocks of ``size`` bytes of a plain or gzip file, decompressed step by step."""
    if content[:2] != b"\x1f\x8b":
        for i in range(0, len(content), size):
            yield content[i : i + size]
        return
    held, data = b"", memoryview(content)
    while len(data):
        stream = zlib.decompressobj(31)
        while not stream.eof and len(data):
            held += stream.decompress(data[: 1 << 20], size)
            data = data[1 << 20 :]
            while stream.unconsumed_tail:
                while len(held) >= size:
                    yield held[:size]
                    held = held[size:]
                held += stream.decompress(stream.unconsumed_tail, size)
            while len(held) >= size:
                yield held[:size]
                held = held[size:]
        if stream.unused_data:
            data = memoryview(bytes(stream.unused_data) + bytes(data))
        held += stream.flush()
    while held:
        yield held[:size]
        held = held[size:]


def _scan(batches: Iterator[pa.RecordBatch], block_bytes: int, header: int, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for name, content in zip(batch.column(0), batch.column(1), strict=True):
            base = 0
            for block, raw in enumerate(_blocks(content.as_py(), block_bytes)):
                numbers = np.frombuffer(raw[: len(raw) // 2 * 2], dtype="<u2")
                yield pa.RecordBatch.from_pylist([{"file": name.as_py(), "block": block} | scan_block(numbers, base, header)], schema)
                base += len(numbers)


def count_tokens(spark: SparkSession, path: str, *, block_bytes: int = 1 << 18) -> DataFrame:
    """(file, doc_id, n_tokens) for every end mark in the flat files under ``path``."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    if block_bytes < 2 * HEADER or block_bytes % 2:
        raise ValueError("a block holds at least one header and whole numbers")
    schema = to_arrow_schema(StructType.fromDDL(BLOCK_SCHEMA))
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("path", "content")
    # the search needs no order; stitching touches one small row per block
    blocks = files.mapInArrow(lambda b: _scan(b, block_bytes, HEADER, schema), BLOCK_SCHEMA)
    order = Window.partitionBy("file").orderBy("block")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    follow = F.slice(F.concat("tail", F.coalesce(F.lead("head").over(order), F.array().cast("array<int>"))), 1, HEADER)
    stitched = (
        blocks.withColumn("previous", F.coalesce(F.max("last_mark").over(before), F.lit(-1)))
        .withColumn("start_header", F.when(F.col("n_marks") > 0, follow))
        .withColumn("file_header", F.slice(F.concat("head", F.coalesce(F.lead("head").over(order), F.array().cast("array<int>"))), 1, HEADER))
        .withColumn("first_header", F.coalesce(F.last("start_header", ignorenulls=True).over(before), F.first("file_header").over(order)))
    )
    digit = lambda i: F.shiftleft((F.get("first_header", F.lit(i)) - 1).cast("long"), 15 * i)
    crossing_id = F.when(F.get("first_header", F.lit(DIGITS)) == 1, digit(0) + digit(1) + digit(2) + digit(3) + digit(4))
    crossing = F.when(
        F.col("n_marks") > 0,
        F.array(F.struct(crossing_id.alias("doc_id"), (F.col("first_mark") - F.col("previous") - 1 - HEADER).alias("n_tokens"))),
    ).otherwise(F.array().cast("array<struct<doc_id:bigint,n_tokens:bigint>>"))
    return stitched.select("file", F.explode(F.concat(crossing, "inner")).alias("d")).select("file", "d.doc_id", "d.n_tokens")


def op9_token_counts(spark, sf_dir) -> DataFrame:
    """Query of operator 9 over every whole text of ``documents``: doc_id, n_tokens."""
    path = scratch(spark, "flat")
    write_flat_tokens(table(spark, sf_dir, "documents"), path)
    return count_tokens(spark, path).select("doc_id", "n_tokens")
