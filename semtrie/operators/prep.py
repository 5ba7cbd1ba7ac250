"""Preparation of access logs: first accesses, history filter, test split, arrival order."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.hashing import portable_hash
from semtrie.operators.lists import by_user


def first_access(access: DataFrame) -> DataFrame:
    """Earliest record per (user, document); ties by the remaining columns in order.  One shuffle with partial minima."""
    rest = [c for c in access.columns if c not in ("user_id", "doc_id")]
    best = access.groupBy("user_id", "doc_id").agg(F.min(F.struct(*rest)).alias("r"))
    return best.select("user_id", "doc_id", "r.*")


def min_history(holding: DataFrame, min_docs: int = 30) -> DataFrame:
    """Holdings of users with at least ``min_docs`` distinct documents."""
    by_user = Window.partitionBy("user_id")
    rank = F.dense_rank().over(by_user.orderBy(F.desc_nulls_last("doc_id")))  # the documents are counted where they lie: no join with a second reading
    ranked = holding.withColumn("__rank", F.when(F.col("doc_id").isNotNull(), rank)).withColumn("__docs", F.max("__rank").over(by_user))
    return ranked.filter(F.col("user_id").isNotNull() & (F.col("__docs") >= min_docs)).select(holding.columns)


def split_holdings(holding: DataFrame, n_test: int = 10, seed: int = 42, by: str = "random") -> DataFrame:
    """Add ``is_test``: per user the ``n_test`` smallest hashes, or with ``by='ts'`` the latest accesses."""
    h = portable_hash(seed, F.col("user_id"), F.col("doc_id"))
    order = [F.desc("ts"), h, F.col("doc_id")] if by == "ts" else [h, F.col("doc_id")]
    w = Window.partitionBy("user_id").orderBy(*order)
    return holding.withColumn("is_test", F.row_number().over(w) <= n_test)


def _split(users: np.ndarray, docs: pa.Array, min_docs: int, n_test: int, seed: int) -> pa.RecordBatch:
    """Lists of whole users, whose rows come in order of user and document (null first)."""
    null = docs.is_null().to_numpy(zero_copy_only=False)
    doc = docs.fill_null(0).to_numpy()
    first = np.ones(len(users), bool)
    first[1:] = (users[1:] != users[:-1]) | (doc[1:] != doc[:-1]) | (null[1:] != null[:-1])
    users, doc, null = users[first], doc[first], null[first]
    have, start = np.unique(users, return_index=True)
    enough = np.add.reduceat((~null).astype(np.int64), start) >= min_docs
    n = np.diff(np.append(start, len(users)))
    good = np.repeat(enough, n)
    users, doc, null, have, n = users[good], doc[good], null[good], have[enough], n[enough]
    text = (f"{seed}|{u}" if gone else f"{seed}|{u}|{d}" for u, d, gone in zip(users.tolist(), doc.tolist(), null.tolist(), strict=True))
    key = np.fromiter((int(hashlib.md5(t.encode()).hexdigest()[:15], 16) for t in text), np.int64, len(users))
    of = np.repeat(np.arange(len(have)), n)
    order = np.lexsort((np.arange(len(of)), key, of))
    is_test = np.zeros(len(of), bool)
    is_test[order] = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n) < n_test
    lists = []
    for side in (~is_test, is_test):
        ends = np.append(0, np.cumsum(np.bincount(of[side], minlength=len(have)))).astype(np.int32)
        lists.append(pa.ListArray.from_arrays(ends, pa.array(doc[side], pa.int64(), mask=null[side])))
    return pa.RecordBatch.from_arrays([pa.array(have, pa.int64()), *lists], ["user_id", "train", "test"])


def split_lists(access: DataFrame, min_docs: int = 30, n_test: int = 10, seed: int = 42) -> DataFrame:
    """(user_id, train, test): per user the documents of ``split_holdings(min_history(access.distinct()))`` as two arrays.

    For integer ids.  Rows travel once, by user, and are put in order once; what is distinct, how many there are and
    which are held out is told from each user's run.
    """
    runs = access.filter("user_id IS NOT NULL").select(F.col("user_id").cast("long").alias("user_id"), F.col("doc_id").cast("long").alias("doc_id"))
    runs = runs.repartition("user_id").sortWithinPartitions("user_id", "doc_id")
    split = lambda t: _split(t.column(0).to_numpy(), t.column(1).combine_chunks(), min_docs, n_test, seed)
    return runs.mapInArrow(lambda batches: map(split, by_user(batches)), "user_id long, train array<long>, test array<long>")


def arrival_order(profile: DataFrame, seed: int = 42) -> DataFrame:
    """Add ``arrival``: a hash whose order is the order of joining, so no global sort is needed."""
    return profile.withColumn("arrival", portable_hash(seed, F.lit("arrival"), F.col("user_id")))


def thin_holders(train: DataFrame, docs: DataFrame, holders: int, seed: int = 42) -> DataFrame:
    """Keep each document of ``docs`` with only the ``holders`` users of smallest hash; other documents stay as they are."""
    w = Window.partitionBy("doc_id").orderBy(portable_hash(seed, F.lit("thin"), F.col("doc_id"), F.col("user_id")), "user_id")
    wanted = docs.select("doc_id").distinct().withColumn("thin", F.lit(True))
    marked = train.join(wanted, "doc_id", "left").withColumn("rn", F.row_number().over(w))
    return marked.filter(F.col("thin").isNull() | (F.col("rn") <= holders)).select(train.columns)


def query_noise(queries: DataFrame, size: float, seed: int = 42) -> DataFrame:
    """Queries whose vectors are moved by a seeded offset, uniform in (-size / 2, size / 2) per component: a query that is not its document."""
    draw = lambda i: portable_hash(seed, F.lit("noise"), F.col("query_id"), i) / F.lit(float(1 << 60)) - 0.5
    return queries.withColumn("emb", F.transform("emb", lambda x, i: x + size * draw(i)))
