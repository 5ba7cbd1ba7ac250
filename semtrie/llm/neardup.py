"""Near-duplicate documents: SuperMinHash signatures, banding, exact verification, union-find grouping.

Texts of equal shingle sets are one class; only class representatives are
compared.  A band bucket is first verified against its smallest member (a star);
pairs of the same bucket that the stars leave in different components are then
compared among themselves, in bounded blocks, so no pair of a bucket is left out
and no bucket is ever expanded into all its pairs.  A pair is confirmed on the
full shingle sets.

Defined cases: null, empty and word-less texts have an empty set and link with
nothing; a null id links with nothing and is kept; rows that repeat an id and its
set are one row; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semtrie.llm.common import components, materialize, mix64, pieces, small, table, text_bytes
from semtrie.llm.shingles import jaccard_at_least, shingle_sets, super_minhash

SLOTS, ROWS = 128, 4
#: Rows, and shingles in all, of one block of a bucket's members or of its outsiders.
BLOCK, BLOCK_SHINGLES = 2048, 1 << 22
#: Signature agreement below which a pair is not verified; a pair of 80 % is below it with a chance of about 1e-8.
ESTIMATE = 0.60


def _sketch(batches: Iterator[pa.RecordBatch], k: int, slots: int, rows: int) -> Iterator[pa.RecordBatch]:
    bands = slots // rows
    for part in pieces(batches, "text", 1 << 20):
        sets, offsets = shingle_sets(*text_bytes(part.column("text")), k)
        n = len(offsets) - 1
        sizes = np.diff(offsets)
        signature = super_minhash(sets, offsets, slots)
        keys = np.tile(np.arange(1, bands + 1, dtype=np.uint64), (n, 1))
        for r in range(rows):
            keys = mix64(keys * np.uint64(0x9E3779B97F4A7C15) + signature[:, r::rows])
        ends = np.append(np.uint64(0), np.cumsum(mix64(sets + np.uint64(1)), dtype=np.uint64))[offsets]
        other = np.append(np.uint64(0), np.cumsum(mix64(sets ^ np.uint64(0xA5A5A5A5A5A5A5A5)), dtype=np.uint64))[offsets]
        yield pa.RecordBatch.from_arrays(
            [
                part.column("doc_id"),
                pa.array(sizes),
                pa.array((ends[1:] - ends[:-1]).view(np.int64)),
                pa.array((other[1:] - other[:-1]).view(np.int64)),
                pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * bands), pa.array(np.ascontiguousarray(keys).view(np.int64).ravel())),
                pa.array([s.tobytes() for s in (mix64(signature) >> np.uint64(56)).astype(np.uint8)], pa.binary()),
            ],
            ["doc_id", "n_shingles", "set_a", "set_b", "bands", "signature"],
        )


SKETCH = "doc_id long, n_shingles long, set_a long, set_b long, bands array<long>, signature binary"


def sketch(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", words: int = 4, slots: int = SLOTS, rows: int = ROWS) -> DataFrame:
    """Set size, set identity, band keys and one-byte signature slots per document."""
    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(lambda b: _sketch(b, words, slots, rows), SKETCH)


def _agree(batches: Iterator[pa.RecordBatch], floor: float) -> Iterator[pa.RecordBatch]:
    """Keep pairs whose signatures agree enough."""
    for batch in batches:
        if not batch.num_rows:
            continue
        a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), dtype=np.uint8).reshape(batch.num_rows, -1) for c in ("sig_a", "sig_b"))
        near = (a == b).mean(axis=1) >= floor
        yield pa.RecordBatch.from_arrays([batch.column("a").filter(pa.array(near)), batch.column("b").filter(pa.array(near))], ["a", "b"])


def _compare_block(block: pa.Table, percent: int) -> pa.Table:
    """Outsiders of one block against its members of other components, by their full sets.

    The sets come as 32-bit values, of which an outsider's may match too many but
    never too few, so a pair that reaches the similarity is always found.  Of an
    outsider's pairs with one component the closest goes on to be confirmed.
    """
    home = ~block.column("outsider").to_numpy()
    ids, component, size = (block.column(c).to_numpy() for c in ("id", "component", "size"))
    sets = [np.frombuffer(x, dtype="<u4") for x in block.column("values").to_pylist()]
    _, value = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.cumsum([len(x) for x in sets])
    starts = ends - [len(x) for x in sets]
    members = np.flatnonzero(home)
    joined = np.concatenate([value[starts[i] : ends[i]] for i in members]) if len(members) else value[:0]
    heads = np.cumsum([0, *[len(sets[i]) for i in members]])[:-1]
    left, right = [], []
    for i in np.flatnonzero(~home) if len(members) else ():
        mark = np.zeros(value.max() + 1, dtype=np.int64)
        mark[value[starts[i] : ends[i]]] = 1
        common = np.add.reduceat(mark[joined], heads)
        near = np.flatnonzero((component[members] != component[i]) & (100 * common >= percent * (size[members] + size[i] - common)))
        near = near[np.argsort(-common[near], kind="stable")]
        near = near[np.sort(np.unique(component[members][near], return_index=True)[1])]
        left += [max(ids[i], x) for x in ids[members][near]]
        right += [min(ids[i], x) for x in ids[members][near]]
    return pa.table({"a": pa.array(left, pa.int64()), "b": pa.array(right, pa.int64())})


def _values(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    for part in pieces(batches, "text", 1 << 20):
        sets, offsets = shingle_sets(*text_bytes(part.column("text")), k)
        low = (sets & np.uint64(0xFFFFFFFF)).astype("<u4")
        yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([low[a:b].tobytes() for a, b in zip(offsets[:-1], offsets[1:], strict=True)], pa.binary())], ["id", "values"])


def texts_of(texts: DataFrame, ids: DataFrame, tag: str) -> DataFrame:
    """Texts of the documents in ``ids(doc_id)``, fetched once."""
    return materialize(texts.join(small(materialize(ids.distinct(), f"{tag}-ids")), "doc_id", "left_semi"), tag)


def _verify(batches: Iterator[pa.RecordBatch], k: int, percent: int) -> Iterator[pa.RecordBatch]:
    for part in pieces(pieces(batches, "text_a"), "text_b"):
        sa, oa = shingle_sets(*text_bytes(part.column("text_a")), k)
        sb, ob = shingle_sets(*text_bytes(part.column("text_b")), k)
        ok = [jaccard_at_least(sa[oa[i] : oa[i + 1]], sb[ob[i] : ob[i + 1]], percent) for i in range(part.num_rows)]
        keep = pa.array(ok, pa.bool_())
        yield pa.RecordBatch.from_arrays([part.column("a").filter(keep), part.column("b").filter(keep)], ["a", "b"])


def confirm(pairs: DataFrame, texts: DataFrame, *, words: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full shingle sets reach the similarity."""
    own = texts_of(texts, pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))), "pair-texts")
    one = own.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a"))
    two = own.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))
    return pairs.join(one, "a").join(two, "b").mapInArrow(lambda b: _verify(b, words, percent), "a long, b long")


def near_duplicates(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    words: int = 5,
    percent: int = 80,
    slots: int = SLOTS,
    rows: int = ROWS,
) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id (smallest id reachable over confirmed links), kept."""
    marks = materialize(sketch(docs, id_col=id_col, text_col=text_col, words=words, slots=slots, rows=rows), "sketch")
    real = marks.filter((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull())
    classes = real.groupBy("n_shingles", "set_a", "set_b").agg(F.min("doc_id").alias("rep"))
    chosen = classes.select(F.col("rep").alias("doc_id"))
    # an id may repeat with another text: its first sketch by set identity stands for it in comparisons
    reps = real.join(chosen, "doc_id", "left_semi").groupBy("doc_id").agg(F.min(F.struct("set_a", "set_b", "n_shingles", "bands", "signature")).alias("s"))
    reps = materialize(reps.select(F.col("doc_id").alias("id"), F.col("s.n_shingles").alias("size"), F.col("s.bands").alias("bands"), F.col("s.signature").alias("signature")), "reps")
    keys = reps.select("id", F.explode("bands").alias("key"))
    full = materialize(keys.groupBy("key").agg(F.min("id").alias("pivot"), F.count(F.lit(1)).alias("n")).filter("n > 1"), "buckets")

    member = materialize(keys.join(full.select("key", "pivot"), "key"), "members")
    stars = member.filter("id <> pivot").select(F.col("id").alias("a"), F.col("pivot").alias("b")).distinct()
    narrow = reps.select("id", "size", "signature")
    side = lambda c: narrow.select(F.col("id").alias(c), F.col("size").alias(f"size_{c}"), F.col("signature").alias(f"sig_{c}"))
    sized = stars.join(side("a"), "a").join(side("b"), "b").filter(100 * F.least("size_a", "size_b") >= percent * F.greatest("size_a", "size_b"))
    likely = materialize(sized.select("a", "b", "sig_a", "sig_b").mapInArrow(lambda b: _agree(b, ESTIMATE), "a long, b long"), "likely")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    star_links = materialize(confirm(likely, texts, words=words, percent=percent), "stars")
    grouped = components(star_links)

    extra = materialize(_cross_links(member, reps.select("id", "size"), grouped, texts, words, percent), "cross")
    links = star_links
    if not extra.isEmpty():
        links = star_links.union(confirm(extra, texts, words=words, percent=percent))
        grouped = components(links)

    class_of = classes.join(grouped.withColumnRenamed("id", "rep"), "rep", "left").select("n_shingles", "set_a", "set_b", F.coalesce("component", "rep").alias("component_id"))
    rows_ = marks.select("doc_id", "n_shingles", "set_a", "set_b").distinct()
    out = rows_.join(class_of, ["n_shingles", "set_a", "set_b"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def _cross_links(member: DataFrame, sizes: DataFrame, grouped: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """Pairs of one bucket in different components whose sets reach the similarity.

    Each bucket's members outside its largest component are compared with all
    its members.  Both lie in blocks bounded in rows and in shingles, and every
    block of outsiders visits every block of members.
    """
    told = member.select("key", "id").join(grouped, "id", "left").select("key", "id", F.coalesce("component", "id").alias("component"))
    told = told.join(sizes, "id")
    parts = told.groupBy("key", "component").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("s"))
    largest = F.struct("n", "component", "s")
    mixed = parts.groupBy("key").agg(F.max(largest).alias("largest"), F.sum("n").alias("n"), F.sum("s").alias("s"), F.count(F.lit(1)).alias("k")).filter("k > 1")
    cut = lambda n, s: F.ceil(F.greatest(n / BLOCK, s / BLOCK_SHINGLES)).cast("int")
    mixed = mixed.select("key", F.col("largest.component").alias("main"), cut(F.col("n"), F.col("s")).alias("blocks"), cut(F.col("n") - F.col("largest.n"), F.col("s") - F.col("largest.s")).alias("rounds"))
    rows = materialize(told.join(mixed, "key"), "mixed")
    own = texts_of(texts, rows.select(F.col("id").alias("doc_id")), "mixed-texts")
    values = materialize(own.mapInArrow(lambda b: _values(b, words), "id long, values binary").dropDuplicates(["id"]), "mixed-sets")
    rows = rows.join(values, "id")
    deal = lambda c: F.pmod(F.xxhash64("id"), F.col(c)).cast("int")
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    at_home = rows.withColumn("block", deal("blocks")).withColumn("round", every("rounds")).withColumn("outsider", F.lit(False))
    guests = rows.filter("component <> main").withColumn("round", deal("rounds")).withColumn("block", every("blocks")).withColumn("outsider", F.lit(True))
    columns = ["key", "block", "round", "id", "component", "size", "values", "outsider"]
    both = at_home.select(columns).union(guests.select(columns))
    return both.groupBy("key", "block", "round").applyInArrow(lambda t: _compare_block(t, percent), "a long, b long").distinct()


def op4_near_duplicates(spark, sf_dir) -> DataFrame:
    """Contract query of operator 4 over every whole text of ``documents``: four-word shingles, similarity 0.8."""
    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"), words=4)


OP4_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS s FROM w
), x AS (
  SELECT doc_id, unnest(s) AS x FROM s
), p AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n FROM x a JOIN x b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY 1, 2
), l AS (
  SELECT a, b FROM p JOIN s i ON i.doc_id = a JOIN s j ON j.doc_id = b WHERE 100 * n >= 80 * (len(i.s) + len(j.s) - n)
), r AS (
  SELECT doc_id AS id, doc_id AS c FROM s UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.id WHERE r.c < l.b
), c AS (
  SELECT id, min(c) AS component FROM r GROUP BY 1
)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component AS component_id, component = doc_id AS kept FROM s JOIN c ON c.id = s.doc_id
"""
