"""Minimum hop distance from users to any holder of a document."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from semtrie.functions.hashing import portable_hash
from semtrie.operators.overlay import numbered
from semtrie.plans.store import materialize, places

#: Edges, and holdings of the documents asked for, up to which both go to the tasks; and users met in all searches up to which they end there.
LOCAL_ROWS, LOCAL_MET = 5_000_000, 500_000_000
#: Users met at once by the searches of one task.
MET = 2_000_000


def _search(batches: Iterator[pa.RecordBatch], sent, max_depth: int, spread: int) -> Iterator[pa.RecordBatch]:
    """Distances of a batch of (query_id, user_id, doc_id) by breadth-first steps over a graph and holdings that fit a task."""
    users, start, peers, docs, held = sent.value
    n = max(1, len(users))
    for batch in batches:
        at, doc = places(users, batch.column("user_id").to_numpy(zero_copy_only=False)), places(docs, batch.column("doc_id").to_numpy(zero_copy_only=False))
        dist = np.full(len(at), -1, np.int32)
        size = max(1, MET // max(1, spread))
        for lo in range(0, len(at), size):
            rows = np.arange(lo, min(lo + size, len(at)))
            rows = rows[(at[rows] >= 0) & (doc[rows] >= 0)]
            front = seen = rows * n + at[rows]
            for d in range(max_depth + 1):
                row, node = np.divmod(front, n)
                dist[np.unique(row[places(held, doc[row] * n + node) >= 0])] = d
                front = front[dist[row] < 0]
                if d == max_depth or not len(front):
                    break
                row, node = np.divmod(front, n)
                fan = start[node + 1] - start[node]
                edge = np.repeat(start[node] - np.cumsum(fan) + fan, fan) + np.arange(int(fan.sum()))
                front = np.unique(np.repeat(row, fan) * n + peers[edge])
                front = front[places(seen, front) < 0]
                seen = np.sort(np.concatenate([seen, front]), kind="stable")
        out = pa.array(dist, mask=dist < 0)
        yield pa.RecordBatch.from_arrays([*batch.columns, out], [*batch.schema.names, "dist"])


def _whole(graph: DataFrame, back: DataFrame) -> tuple:
    """(users, where each one's peers start, places of peers, documents, sorted pairs of document and holder); both were counted first."""
    edges, held = graph.select("src", "dst").toArrow(), back.select("doc_id", "user_id").toArrow()
    src, dst, holder = (t.column(c).to_numpy() for t, c in ((edges, "src"), (edges, "dst"), (held, "user_id")))
    users = np.unique(np.concatenate([src, dst, holder]))
    src, dst = places(users, src), places(users, dst).astype(np.int32)
    order = np.argsort(src, kind="stable")
    docs, doc = np.unique(held.column("doc_id").to_numpy(), return_inverse=True)
    return users, np.searchsorted(src[order], np.arange(len(users) + 1)), dst[order], docs, np.unique(doc * max(1, len(users)) + places(users, holder))


def _local_spread(graph: DataFrame, back: DataFrame, asked: DataFrame, max_depth: int) -> int | None:
    """Users that one search meets at most, if all searches may end in the tasks by counts and types."""
    kinds = [*dict(graph.dtypes).values(), *dict(back.dtypes).values()]
    if set(kinds) - {"bigint", "int"} or graph.count() > LOCAL_ROWS or back.count() > LOCAL_ROWS:
        return None
    fan = graph.groupBy("src").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)), F.coalesce(F.max("n"), F.lit(0))).first()
    spread = 1 + min(fan[0] + fan[1], sum(fan[1] ** d for d in range(1, max_depth + 1)))
    return spread if spread * asked.count() <= LOCAL_MET else None


def distances_to_holders(edges: DataFrame, holding: DataFrame, docs: DataFrame, max_depth: int = 6) -> DataFrame:
    """(doc_id, user_id, dist): breadth-first over reversed edges from all holders of each distinct document."""
    wanted = docs.select("doc_id").distinct()
    front = materialize(holding.select("doc_id", "user_id").distinct().join(wanted, "doc_id", "left_semi").withColumn("dist", F.lit(0)), "bfs-0")
    back = materialize(edges.select(F.col("dst").alias("user_id"), F.col("src").alias("from_user")).distinct(), "bfs-edges")
    seen = front
    for d in range(1, max_depth + 1):
        step = front.join(back, "user_id").select("doc_id", F.col("from_user").alias("user_id")).distinct()
        front = materialize(step.join(seen.select("doc_id", "user_id"), ["doc_id", "user_id"], "left_anti").withColumn("dist", F.lit(d)), f"bfs-{d}")
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
    return seen


def min_hops(edges: DataFrame, holding: DataFrame, queries: DataFrame, users: DataFrame, *, max_depth: int = 6, start: str = "random", seed: int = 42, local: bool | None = None) -> DataFrame:
    """(query_id, user_id, doc_id, dist): distance from a random user (by hash) or the query's own; null if out of reach.

    Searches from both ends: users reached from the start, per query, and users
    that reach a holder, per document.  Each step lets one side grow, for open
    queries only, and looks for a common user; so the wide outer rings are made
    for the few queries that need them.  Where graph, holdings and what searches
    can meet are counted to be small (``local`` decides otherwise), graph and
    holdings go to the tasks, and every search ends there without moving a row.
    """
    asked = queries.select("query_id", "user_id", F.col("target_doc").alias("doc_id"))
    if start == "random":
        number = numbered(users)
        n = number.count()
        asked = asked.drop("user_id").withColumn("number", F.pmod(portable_hash(seed, F.lit("start"), F.col("query_id")), F.lit(n))).join(number, "number").drop("number")
    asked = materialize(asked.select("query_id", "user_id", "doc_id"), "asked")
    graph = materialize(edges.select("src", "dst").distinct(), "bfs-edges")
    front = asked.select("query_id", "doc_id", "user_id")
    back = materialize(holding.select("doc_id", "user_id").distinct().join(asked.select("doc_id").distinct(), "doc_id", "left_semi"), "bfs-holders")
    spread = _local_spread(graph, back, asked, max_depth) if local is None else 1 << 16 if local else None
    if spread is not None:
        sent = graph.sparkSession.sparkContext.broadcast(_whole(graph.dropna(), back.dropna()))
        schema = StructType([*asked.schema.fields, StructField("dist", IntegerType())])
        known = asked.filter("user_id IS NOT NULL AND doc_id IS NOT NULL")
        found = known.mapInArrow(lambda batches: _search(batches, sent, max_depth, spread), schema)
        return found.unionByName(asked.filter("user_id IS NULL OR doc_id IS NULL").withColumn("dist", F.lit(None).cast("int")))
    seen_front, seen_back = front, back
    open_ = asked.join(back.select("doc_id").distinct(), "doc_id", "left_semi").select("query_id", "user_id", "doc_id")
    found = None
    for d in range(max_depth + 1):
        if d % 2:
            back = back.join(open_.select("doc_id").distinct(), "doc_id", "left_semi")
            step = back.join(graph.select(F.col("dst").alias("user_id"), "src"), "user_id").select("doc_id", F.col("src").alias("user_id")).distinct()
            back = materialize(step.join(seen_back, ["doc_id", "user_id"], "left_anti"), f"back-{d}")
            seen_back = seen_back.unionByName(back)
        elif d:
            front = front.join(open_.select("query_id"), "query_id", "left_semi")
            step = front.join(graph.select(F.col("src").alias("user_id"), "dst"), "user_id").select("query_id", "doc_id", F.col("dst").alias("user_id")).distinct()
            front = materialize(step.join(seen_front, ["query_id", "doc_id", "user_id"], "left_anti"), f"front-{d}")
            seen_front = seen_front.unionByName(front)
        met = front.join(back, ["doc_id", "user_id"]).select("query_id").distinct()
        now = materialize(met.join(open_.select("query_id"), "query_id", "left_semi").withColumn("dist", F.lit(d)), f"met-{d}")
        found = now if found is None else found.unionByName(now)
        open_ = materialize(open_.join(now, "query_id", "left_anti"), f"open-{d}")
        if open_.isEmpty():
            break
    return asked.join(found, "query_id", "left").select("query_id", "user_id", "doc_id", "dist")
