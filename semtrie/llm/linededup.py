"""Line de-duplication within an edit bound of one character, by a deletion-neighbourhood join.

A line occurrence goes if the same line, or a line within one insertion,
deletion or substitution of it, occurs earlier (by document id, then line
number); the earliest stays.  Lines are compared without blanks, tabs and
carriage returns at their ends.  The edit bound holds among lines of
``min_chars`` characters or more; with ``short_lines`` shorter lines (but empty
ones) go if the same line occurs earlier, without it they stay always.

Lines within one edit agree outside one of ``SEGMENTS`` equal segments, so a
line first emits one key per segment: the hash of all it holds outside it.  Only
lines that share a key emit their deletion variants (of the segment alone),
hashed with the key.  Lines with the same variant and place differ by a
substitution there; a line that equals another's variant differs by that
deletion.  Both are minima over hash groups, so no pair is ever listed; the
earliest candidate of each line is verified by the edit distance of the texts.

Defined cases: null and empty texts have one empty line, which stays; rows with a
null id are neither compared nor changed; rows that share an id are one document
as to order, and each loses the lines marked for that id; other columns pass
through untouched.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.llm.common import BROADCAST_ROWS, materialize, mix64, pieces, small, table
from semtrie.llm.shingles import BASE, powers, prefix_sums

SEGMENTS = 4
MIN_CHARS = 20
ENDS = " \t\r"
#: Line numbers to take out, in all, up to which they are broadcast; beyond, the documents shuffle.
BROADCAST_LINES = 1_000_000


class _Strings:
    """Prefix sums over the code points of many strings, for hashes of any part of any of them."""

    def __init__(self, strings: list[str]):
        self.size = np.array([len(s) for s in strings], dtype=np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.size)])
        codes = np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
        self.total = prefix_sums(mix64(codes + np.uint64(1)))

    def part(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        """Polynomial hash of code points [start, stop) of the joined text, independent of its place."""
        return (self.total[stop] - self.total[start]) * powers(start, True)


def _borders(m: np.ndarray, i: int) -> tuple[np.ndarray, np.ndarray]:
    return i * m // SEGMENTS, (i + 1) * m // SEGMENTS


def segment_keys(s: _Strings) -> np.ndarray:
    """(n, 2 * SEGMENTS) keys: for base length m = len and m = len - 1 and each segment, the hash of the rest of the line."""
    start, stop = s.at[:-1], s.at[1:]
    out = np.empty((len(s.size), 2 * SEGMENTS), dtype=np.uint64)
    for less in (0, 1):
        m = s.size - less
        for i in range(SEGMENTS):
            a, b = _borders(m, i)
            rest = s.part(start, start + a) + s.part(stop - (m - b), stop) * powers(a)
            out[:, less * SEGMENTS + i] = mix64(rest ^ mix64(m.astype(np.uint64) * np.uint64(SEGMENTS) + np.uint64(i + 1)))
    return out


KEYS = [f"k{i}" for i in range(2 * SEGMENTS)]


def _lines(batches: Iterator[pa.RecordBatch], min_chars: int, short_lines: bool) -> Iterator[pa.RecordBatch]:
    """Hashes of the lines; the keys of lines below ``min_chars`` are null, so that no edit is sought for them."""
    for part in pieces(batches, "text"):
        ids, numbers, lines = [], [], []
        for doc_id, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), strict=True):
            if text and doc_id is not None:
                for number, line in enumerate(text.split("\n")):
                    line = line.strip(ENDS)
                    if len(line) >= min_chars or (short_lines and line):
                        ids.append(doc_id)
                        numbers.append(number)
                        lines.append(line)
        s = _Strings(lines)
        whole = s.part(s.at[:-1], s.at[1:]) if lines else np.zeros(0, np.uint64)
        # a second, independent identity: sums of mixed pieces of the line
        halves = s.part(s.at[:-1], s.at[:-1] + s.size // 2) if lines else whole
        h1 = mix64(whole + s.size.astype(np.uint64) * np.uint64(BASE))
        h2 = mix64(mix64(halves ^ np.uint64(0x5851F42D4C957F2D)) + whole * np.uint64(0x2545F4914F6CDD1D))
        keys = segment_keys(s) if lines else np.zeros((0, 2 * SEGMENTS), np.uint64)
        brief = s.size < min_chars
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(numbers, pa.int32()), pa.array(h1.view(np.int64)), pa.array(h2.view(np.int64)), *(pa.array(np.ascontiguousarray(c).view(np.int64), mask=brief) for c in keys.T)],
            ["doc_id", "line_no", "h1", "h2", *KEYS],
        )


LINES = "doc_id long, line_no int, h1 long, h2 long, " + ", ".join(f"{k} long" for k in KEYS)


def _variants(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Hashes of a segment and of its single-character deletions, under the segment's key."""
    for part in pieces(batches, "line", 1 << 18):
        s = _Strings(part.column("line").to_pylist())
        slot = part.column("slot").to_numpy()
        key = part.column("key").to_numpy().view(np.uint64)
        less, i = slot // SEGMENTS, slot % SEGMENTS
        m = s.size - less
        a, b = i * m // SEGMENTS, (i + 1) * m // SEGMENTS
        lo, hi = s.at[:-1] + a, s.at[1:] - (m - b)
        n = hi - lo
        row = np.repeat(np.arange(len(n)), n)
        at = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + lo[row]
        gone = s.part(lo[row], at) + s.part(at + 1, hi[row]) * powers(at - lo[row])
        variant = mix64(gone + key[row] + (n[row] - 1).astype(np.uint64))
        itself = mix64(s.part(lo, hi) + key + n.astype(np.uint64))
        rows = np.concatenate([np.arange(len(n)), row])
        take = pa.array(rows)
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate([itself, variant]).view(np.int64)), pa.array(np.concatenate([np.full(len(n), -1), at - lo[row]]).astype(np.int32)), *(part.column(c).take(take) for c in ("h1", "h2", "doc_id", "line_no"))],
            ["variant", "place", "h1", "h2", "doc_id", "line_no"],
        )


def _pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The asked lines of each document, its text split once."""
    for part in pieces(batches, "text"):
        lines, first, second = [], [], []
        for text, asked in zip(part.column("text").to_pylist(), part.column("asked").to_pylist(), strict=True):
            own = (text or "").split("\n")
            for a in asked:
                if a["line_no"] < len(own):
                    lines.append(own[a["line_no"]].strip(ENDS))
                    first.append(a["h1"])
                    second.append(a["h2"])
        yield pa.RecordBatch.from_arrays([pa.array(first, pa.int64()), pa.array(second, pa.int64()), pa.array(lines, pa.string())], ["h1", "h2", "line"])


def near_earlier(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """(h1, h2) of the distinct lines that have an earlier line within one edit."""
    keyed = classes.filter(F.col(KEYS[0]).isNotNull()).select("h1", "h2", "first", F.posexplode(F.array(*KEYS)).alias("slot", "key"))
    shared = keyed.groupBy("key").agg(F.min("h1").alias("low"), F.max("h1").alias("high")).filter("low <> high").select("key")
    found = materialize(keyed.join(small(materialize(shared, "keys")), "key", "left_semi"), "survivors")
    wanted = materialize(found.select("h1", "h2", F.col("first.doc_id").alias("doc_id"), F.col("first.line_no").alias("line_no")).distinct(), "wanted")
    # one row per document, which holds at most the document's own lines
    asked = wanted.groupBy("doc_id").agg(F.collect_list(F.struct("line_no", "h1", "h2")).alias("asked"))
    side = F.broadcast(asked) if wanted.count() <= BROADCAST_ROWS else asked
    texts = docs.join(side, "doc_id").select("text", "asked").mapInArrow(_pick, "h1 long, h2 long, line string")
    # an id may repeat with another text: keep the copies that really hold the line
    texts = materialize(texts.groupBy("h1", "h2").agg(F.max("line").alias("line")), "lines")
    spread = found.join(texts, ["h1", "h2"]).select("key", "slot", "h1", "h2", F.col("first.doc_id").alias("doc_id"), F.col("first.line_no").alias("line_no"), "line")
    variants = spread.mapInArrow(_variants, "variant long, place int, h1 long, h2 long, doc_id long, line_no int")
    own = F.struct("doc_id", "line_no", "h1", "h2")
    # both groups are bounded: the distinct lines that hold one more character than the variant
    same, place = Window.partitionBy("variant"), Window.partitionBy("variant", "place")
    candidate = F.when(F.col("place") < 0, F.min(F.when(F.col("place") >= 0, own)).over(same)).otherwise(F.least(F.min(own).over(place), F.min(F.when(F.col("place") < 0, own)).over(same)))
    earlier = variants.select("h1", "h2", own.alias("own"), candidate.alias("best")).filter("best < own").groupBy("h1", "h2").agg(F.min("best").alias("best"))
    other = texts.select(F.col("h1").alias("b1"), F.col("h2").alias("b2"), F.col("line").alias("other"))
    checked = earlier.join(texts, ["h1", "h2"]).join(other, (F.col("best.h1") == F.col("b1")) & (F.col("best.h2") == F.col("b2")))
    return checked.filter((F.levenshtein("line", "other", 1) >= 0)).select("h1", "h2")


def mark_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, max_edits: int = 1, short_lines: bool = False) -> DataFrame:
    """(doc_id, gone): the line numbers, from 0, that each document loses; documents that lose none do not occur."""
    if max_edits not in (0, 1):
        raise ValueError("the edit bound is 0 or 1")
    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    lines = narrow.mapInArrow(lambda b: _lines(b, min_chars, short_lines), LINES)
    classes = materialize(
        lines.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "line_no")).alias("first"), F.count(F.lit(1)).alias("n"), *[F.first(k).alias(k) for k in KEYS]),
        "classes",
    )
    if max_edits:
        late = materialize(near_earlier(narrow, classes), "late")
    else:
        late = classes.select("h1", "h2").limit(0)
    marked = classes.select("h1", "h2", "first", "n").join(late.withColumn("late", F.lit(True)), ["h1", "h2"], "left").filter("n > 1 OR late").select("h1", "h2", "first", F.coalesce("late", F.lit(False)).alias("late"))
    occurrences = lines.select("doc_id", "line_no", "h1", "h2").join(small(materialize(marked, "marked")), ["h1", "h2"])
    gone = occurrences.filter(F.col("late") | (F.struct("doc_id", "line_no") != F.col("first")))
    return gone.groupBy("doc_id").agg(F.collect_set("line_no").alias("gone"))


def dedup_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, max_edits: int = 1, short_lines: bool = False, marks: tuple[str, str] | None = None) -> DataFrame:
    """Documents with the repeated lines taken out of the text; ``marks`` names two added columns, lines before and lines gone."""
    gone = materialize(mark_lines(docs, id_col=id_col, text_col=text_col, min_chars=min_chars, max_edits=max_edits, short_lines=short_lines), "gone")
    side = gone.select(F.col("doc_id").alias("__line_doc"), F.array_sort("gone").alias("__line_gone"))
    if (gone.agg(F.sum(F.size("gone"))).first()[0] or 0) <= BROADCAST_LINES:
        side = F.broadcast(side)
    joined = docs.join(side, F.col(id_col) == F.col("__line_doc"), "left")
    # marks in line order, one character a line up to the last one gone: lines and marks pair up in one pass
    last = F.transform("__line_gone", lambda n, i: n - F.coalesce(F.get("__line_gone", i - 1), F.lit(-1)) - 1)
    marked = F.split(F.array_join(F.transform(last, lambda gap: F.concat(F.repeat(F.lit("0"), gap), F.lit("1"))), ""), "", -1)
    pairs = F.arrays_zip(F.split(F.col(text_col), "\n", -1).alias("line"), marked.alias("mark"))
    kept = F.transform(F.filter(pairs, lambda p: p["line"].isNotNull() & ~p["mark"].eqNullSafe("1")), lambda p: p["line"])
    out = F.when(F.col("__line_gone").isNull(), F.col(text_col)).otherwise(F.array_join(kept, "\n"))
    columns = [out.alias(c) if c == text_col else F.col(c) for c in docs.columns]
    if marks:
        columns += [F.size(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)).cast("long").alias(marks[0]), F.coalesce(F.size("__line_gone"), F.lit(0)).cast("long").alias(marks[1])]
    return joined.select(*columns)


def op7_line_dedup(spark, sf_dir) -> DataFrame:
    """Query of operator 7 over all of ``documents``: lines before, lines gone, digest of what is left."""
    done = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"), short_lines=True, marks=("n_lines", "n_gone"))
    return done.select("doc_id", "n_lines", "n_gone", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))


OP7_SQL = """
WITH docs AS (
  SELECT doc_id, coalesce(text, '') AS body, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents
), raw AS (
  SELECT doc_id, unnest(range(0, len(parts))) AS line_no, unnest(parts) AS part FROM docs
), l AS (
  SELECT doc_id, line_no, part, trim(part, ' ' || chr(9) || chr(13)) AS line FROM raw
), u AS (
  SELECT line, length(line) AS n, min({'d': doc_id, 'l': line_no}) AS f FROM l WHERE line <> '' GROUP BY line
), k AS (
  SELECT line, n, f, m, i, line[1:CAST(floor(i * m / 4.0) AS INT)] AS head, right(line, CAST(m - floor((i + 1) * m / 4.0) AS INT)) AS rest
  FROM (SELECT *, unnest([n, n - 1]) AS m FROM u WHERE n >= 20) CROSS JOIN (SELECT unnest(range(0, 4)) AS i)
), late AS (
  SELECT DISTINCT x.line FROM k x JOIN k y ON x.m = y.m AND x.i = y.i AND x.head = y.head AND x.rest = y.rest
  WHERE y.f < x.f AND x.line <> y.line AND (
    (x.n = y.n AND len(list_filter(range(0, x.n), lambda p: x.line[1:p] = y.line[1:p] AND x.line[p + 2:] = y.line[p + 2:])) > 0)
    OR (x.n = y.n + 1 AND len(list_filter(range(0, x.n), lambda p: x.line[1:p] = y.line[1:p] AND x.line[p + 2:] = y.line[p + 1:])) > 0)
    OR (y.n = x.n + 1 AND len(list_filter(range(0, y.n), lambda p: x.line[1:p] = y.line[1:p] AND y.line[p + 2:] = x.line[p + 1:])) > 0))
), marked AS (
  SELECT l.doc_id, l.line_no, l.part,
    coalesce(u.line IS NOT NULL AND (late.line IS NOT NULL OR u.f <> {'d': l.doc_id, 'l': l.line_no}), false) AS gone
  FROM l LEFT JOIN u ON l.line = u.line LEFT JOIN late ON l.line = late.line
)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(*) FILTER (WHERE gone) AS BIGINT) AS n_gone,
  sha256(coalesce(string_agg(part, chr(10) ORDER BY line_no) FILTER (WHERE NOT gone), '')) AS text_sha256
FROM marked GROUP BY doc_id
"""
