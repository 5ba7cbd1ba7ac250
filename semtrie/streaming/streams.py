"""Structured Streaming: arriving accesses, windows, profiles kept up to date, arrivals placed in a frozen trie.

``events.ts`` is a time without zone, on which no watermark is allowed: streams
cast it to a timestamp (session time zone UTC) first.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semtrie.plans.store import materialize, shared_dir
from semtrie.sources.tables import SCHEMAS

LATENESS = "30 days"


def events_stream(spark: SparkSession, sf_dir: str, *, lateness: str = LATENESS, files_per_trigger: int = 1) -> DataFrame:
    """Events as a stream with event time ``ts`` and a watermark."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events*.parquet").option("maxFilesPerTrigger", files_per_trigger).parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("long")).withWatermark("ts", lateness)


def run_to_table(stream: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Process all that is available and return what reached the sink.

    Batches go to files named by their number, so a batch that is retried
    replaces itself; with ``keys`` the last row of each key wins (update mode),
    and in complete mode the last batch.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/semtrie/stream-{uuid.uuid4().hex}"
    schema = stream.schema

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(save).start()
    query.awaitTermination()
    out = spark.read.schema(schema.add("batch", "long") if "batch" not in schema.names else schema).parquet(f"{base}/out")
    if mode == "complete":
        last = out.agg(F.max("batch").alias("last"))
        out = out.join(F.broadcast(last), F.col("batch") == F.col("last")).drop("last")
    elif keys:
        w = Window.partitionBy(*keys).orderBy(F.desc("batch"))
        out = out.withColumn("rn", F.row_number().over(w)).filter("rn = 1").drop("rn")
    return out.drop("batch")


def tumbling(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "7 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Bursts of one user."""
    return stream.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def first_accesses(stream: DataFrame) -> DataFrame:
    """First event per (user, k) within the watermark."""
    return stream.dropDuplicatesWithinWatermark(["user_id", "k"])


def late_rows(batch: DataFrame, watermark) -> DataFrame:
    """The audit side path of a foreachBatch sink: rows behind the last watermark, which stateful operators drop."""
    return batch.filter(F.col("ts") < F.lit(watermark))


PROFILE = "user_id long, n_docs long, emb array<double>"


def _fold(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Keep the sum and count of a user's vectors; a user idle beyond the watermark leaves."""
    if state.hasTimedOut:
        state.remove()
        return
    n, total = state.get if state.exists else (0, None)
    total = None if total is None else np.array(total, dtype=float)
    for frame in frames:
        if len(frame):
            x = np.array(frame["emb"].tolist(), dtype=float)
            n, total = n + len(x), x.sum(0) if total is None else total + x.sum(0)
    state.update((int(n), total.tolist()))
    if state.getCurrentWatermarkMs() > 0:
        state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + 90 * 86_400_000)
    yield pd.DataFrame({"user_id": [key[0]], "n_docs": [n], "emb": [(total / n).tolist()]})


def streaming_profiles(stream: DataFrame, doc_vectors: DataFrame, doc_col: str = "doc_id") -> DataFrame:
    """Profiles that move as users gain documents: stream-static join, then a state of (count, sum) per user."""
    joined = stream.join(doc_vectors, doc_col).select("user_id", "ts", "emb")
    return joined.groupBy("user_id").applyInPandasWithState(_fold, PROFILE, "n long, total array<double>", "update", "EventTimeTimeout")


class LiveTrie:
    """A trie that grows with a stream of new users: the body of a foreachBatch sink.

    Each batch is inserted by ``insert_trie``, so leaves that overflow split.  A
    batch number seen before is a retry and changes nothing.  ``members`` are the
    users held so far with their order of arrival.
    """

    def __init__(self, trie, members: DataFrame):
        self.trie = trie
        self.members = members.select("user_id", "emb", "arrival")
        self.batch = -1

    def __call__(self, batch: DataFrame, number: int) -> None:
        from semtrie.operators.trie import insert_trie

        if number <= self.batch:
            return
        fresh = materialize(batch.select("user_id", "emb", "arrival"), "batch")
        self.trie = insert_trie(self.trie, self.members, fresh)
        self.members = self.members.unionByName(fresh)
        self.batch = number

    def follow(self, stream: DataFrame):
        """Insert all that the stream of (user_id, emb, arrival) has now."""
        base = f"{shared_dir(stream.sparkSession)}/semtrie/live-{uuid.uuid4().hex}"
        query = stream.writeStream.option("checkpointLocation", base).trigger(availableNow=True).foreachBatch(self).start()
        query.awaitTermination()
        return self.trie


def reroute(profiles: DataFrame, trie) -> DataFrame:
    """(user_id, path) of users whose profiles have moved: each walks down the trie again."""
    from semtrie.operators.trie import join_trie

    return join_trie(profiles.select("user_id", "emb"), trie).select("user_id", "path")


def answered_queries(queries: DataFrame, accesses: DataFrame, within: str = "INTERVAL 1 HOUR") -> DataFrame:
    """Stream-stream join: views followed by a purchase of the same user and k within an interval."""
    q = queries.select(F.col("user_id").alias("q_user"), F.col("k").alias("q_k"), F.col("ts").alias("q_ts"), F.col("event_id").alias("q_id"))
    a = accesses.select("user_id", "k", "ts", "event_id")
    return q.join(a, F.expr(f"q_user = user_id AND q_k = k AND ts >= q_ts AND ts <= q_ts + {within}")).select("q_id", "event_id", "user_id", "k")
