"""Document vectors and user profiles."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.feature import IDF, HashingTF
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

from semtrie.functions.hashing import portable_hash
from semtrie.functions.vectors import as_double, vec_mean
from semtrie.plans.store import places, sent_vectors


def grams(text: Column, n: int = 3) -> Column:
    """Character n-grams of the lower-cased text.

    The text is split into characters once, as finding the i-th character of a
    string means walking there.
    """
    chars = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "", -1), lambda c: c != "")
    out = chars
    for i in range(1, n):
        # the shorter side runs out with null, which makes the last, incomplete grams null
        out = F.zip_with(out, F.slice(chars, i + 1, 1 << 30), lambda a, b: F.concat(a, b))
    return F.filter(out, lambda g: g.isNotNull())


def embed_text(df: DataFrame, col: str = "text", out: str = "emb", *, model: str | Callable[[pd.Series], pd.Series] = "hash_ngram", dim: int = 64, max_df: int | None = None) -> DataFrame:
    """Add a vector per text.

    ``hash_ngram``: counts of character trigrams in ``dim`` buckets of the portable
    hash, all in expressions.  ``tfidf``: hashed words weighted by inverse document
    frequency, fitted on all rows.  A callable is any encoder: it maps a series of
    texts to a series of float lists and is loaded once per Python worker.
    """
    if model == "hash_ngram":
        buckets = F.transform(grams(F.col(col)), lambda g: F.pmod(portable_hash(g), F.lit(dim)).cast("int"))
        zero = F.array_repeat(F.lit(0.0), dim)
        counted = F.aggregate(buckets, zero, lambda acc, b: F.transform(acc, lambda x, i: x + F.when(i == b, 1.0).otherwise(0.0)))
        return df.withColumn(out, counted)
    if model == "tfidf":
        words = df.withColumn("__words", F.filter(F.split(F.lower(F.coalesce(F.col(col), F.lit(""))), r"\s+"), lambda w: w != ""))
        counted = HashingTF(inputCol="__words", outputCol="__tf", numFeatures=dim).transform(words)
        fitted = IDF(inputCol="__tf", outputCol="__idf").fit(counted)
        return fitted.transform(counted).withColumn(out, vector_to_array("__idf")).drop("__words", "__tf", "__idf")
    encoder = model

    @F.pandas_udf("array<double>")
    def encoded(texts: pd.Series) -> pd.Series:
        return encoder(texts.fillna(""))

    return df.withColumn(out, encoded(F.col(col)))


def embed_lookup(df: DataFrame, vectors: DataFrame) -> DataFrame:
    """Vectors from a table (doc_id, emb)."""
    return df.join(vectors, "doc_id")


def user_profiles(holding: DataFrame, doc_vectors: DataFrame) -> DataFrame:
    """(user_id, n_docs, emb): the mean of the user's document vectors, summed partially before the shuffle."""
    return holding.join(doc_vectors.select("doc_id", as_double(F.col("emb")).alias("emb")), "doc_id").groupBy("user_id").agg(F.count(F.lit(1)).alias("n_docs"), vec_mean(F.col("emb")).alias("emb"))


def _means(batches: Iterator[pa.RecordBatch], sent) -> Iterator[pa.RecordBatch]:
    """Means of the vectors that each row's list names; lists without any leave no row."""
    ids, x = sent.value
    for batch in batches:
        docs = batch.column("docs")
        who = np.repeat(np.arange(batch.num_rows), docs.value_lengths().to_numpy(zero_copy_only=False))
        at = places(ids, docs.flatten().to_numpy(zero_copy_only=False))
        order = np.lexsort((at, who))  # sums in the order of the documents, whatever that of the list
        who, at = who[order], at[order]
        who, at = who[at >= 0], at[at >= 0]
        have, start = np.unique(who, return_index=True)
        n = np.diff(np.append(start, len(who)))
        out = np.zeros((len(have), x.shape[1]))
        for lo in range(0, len(have), 256):
            cut = start[lo : lo + 256]
            stop = start[lo + 256] if lo + 256 < len(start) else len(at)
            out[lo : lo + 256] = np.add.reduceat(x[at[cut[0] : stop]], cut - cut[0])
        out /= n[:, None]
        emb = pa.ListArray.from_arrays(np.arange(len(have) + 1, dtype=np.int32) * x.shape[1], out.ravel())
        yield pa.RecordBatch.from_arrays([batch.column("user_id").take(pa.array(have)), pa.array(n, pa.int64()), emb], ["user_id", "n_docs", "emb"])


def profiles_by_lookup(holding: DataFrame, doc_vectors: DataFrame) -> DataFrame:
    """``user_profiles`` with a table of vectors counted to be small sent to the tasks: what travels is user and document.

    A larger table is joined as there.
    """
    whole = dict(holding.dtypes)["doc_id"] in ("bigint", "int")
    sent = sent_vectors(doc_vectors.select("doc_id", as_double(F.col("emb")).alias("emb"))) if whole else None
    if sent is None:
        return user_profiles(holding, doc_vectors)
    return _profiles(holding.filter(F.col("user_id").isNotNull()).groupBy("user_id").agg(F.collect_list(F.col("doc_id").cast("long")).alias("docs")), sent)


def _profiles(lists: DataFrame, sent) -> DataFrame:
    schema = StructType([lists.schema["user_id"], StructField("n_docs", LongType()), StructField("emb", ArrayType(DoubleType()))])
    return lists.mapInArrow(lambda batches: _means(batches, sent), schema)


def profiles_of_lists(lists: DataFrame, doc_vectors: DataFrame) -> DataFrame:
    """``profiles_by_lookup`` of holdings that lie in one row per user (user_id, docs): nothing travels but the vectors."""
    sent = sent_vectors(doc_vectors.select("doc_id", as_double(F.col("emb")).alias("emb")))
    if sent is None:
        return user_profiles(lists.select("user_id", F.explode("docs").alias("doc_id")), doc_vectors)
    return _profiles(lists.select("user_id", F.array_compact("docs").alias("docs")), sent)
