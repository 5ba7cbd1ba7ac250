"""A training-data pipeline over ``documents``: five corpus operators, each stage written and read again.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor
kept; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semtrie.llm import linededup, mixing, neardup, quality, segment
from semtrie.llm.common import materialize, table
from semtrie.shipping import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the preference ranking accepts; the ranking is fitted on the labelled ones among ``docs``.

    Null and empty texts are scored like any other; rows of a null or repeated id
    are judged by their own text; without labels of both kinds, or on an empty
    table, nothing is rejected.
    """
    ship(spark)
    ranker = quality.fit_ranker(docs, table(spark, sf_dir, "labels"))
    scored = quality.score_documents(docs.select(*COLUMNS), ranker, out_col="__score")
    return scored.filter(F.col("__score") >= quality.ACCEPT).select(*COLUMNS)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the lines that occur earlier in the corpus; a text may become empty, its row stays.

    Null texts stay null; rows of a null id are left as they are; of equal lines
    the one of smallest id, then line number, stays; an empty table stays empty.
    """
    ship(spark)
    done = linededup.dedup_lines(docs.select(*COLUMNS), short_lines=True)
    return done.withColumn("n_chars", F.coalesce(F.char_length("text"), F.lit(0)).cast("long")).select(*COLUMNS)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8): the one of smallest id.

    Documents without words (null texts too) belong to no group and stay, as do
    rows of a null id; rows that repeat an id stay or go together; an empty table
    stays empty.
    """
    ship(spark)
    groups = neardup.near_duplicates(docs, words=5, percent=80)
    gone = groups.filter(~F.col("kept") & F.col("doc_id").isNotNull()).select("doc_id").distinct()
    return docs.select(*COLUMNS).join(gone, "doc_id", "left_anti").select(*COLUMNS)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture itself: rows by the Pfair schedule (weights: square roots of the sources' sizes).

    The schedule runs until every source has been read once; a shorter source
    starts over, so its documents recur and the sources' shares of the rows are
    their weights.  Rows lie in files by hash and in each file in the order of
    the schedule, so a file is a sample of the mixture; one order over all files
    would not outlive the next reading, as Spark packs files by size.  A null
    source is a source of its own; texts are not read; repeated rows are rows like
    any other; an empty table stays empty.
    """
    ship(spark)
    mixed = mixing.mix_sources(docs.select(*COLUMNS), temperature=0.5)
    return mixed.sortWithinPartitions("mix_position", "doc_id").select(*COLUMNS)


def segmentation_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Two distinct sampled segmentations per row, as piece ids with scores.

    A null or empty text gives one segmentation of no piece; equal ids and texts
    give equal samples; an empty table gives an empty result.
    """
    ship(spark)
    # executors still hold the earlier stages' memory here
    return segment.sample_segmentations(docs, k=2, batch_bytes=1 << 18)


STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("MinHash near-dedup", near_duplicate_stage),
    ("mixing sources to target weights", mixing_stage),
    ("SentencePiece encoding", segmentation_stage),
]

#: The classifier's fit, the schedule and the sampler have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
