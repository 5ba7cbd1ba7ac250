"""Diffusion of user vectors over a graph with a teleport weight."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semtrie.functions.vectors import as_double, vec_add, vec_l2, vec_mean, vec_scale
from semtrie.plans.store import discard, materialize, places, sent_vectors

#: Edges up to which a graph goes to the tasks, each of which mixes some components of all vectors.
LOCAL_EDGES, COMPONENTS = 5_000_000, 8


def steps_for(alpha: float, tol: float = 1e-3) -> int:
    """Steps after which the error has shrunk to ``tol``: it contracts by 1 - alpha each time."""
    return 0 if alpha >= 1 else math.ceil(math.log(tol) / math.log(1 - alpha))


def _mix(batches: Iterator[pa.RecordBatch], sent, graph, alpha: float, steps: int) -> Iterator[pa.RecordBatch]:
    """All steps for one block of components: components do not meet in a mean, so blocks need nothing of each other."""
    (ids, x), (src, start, dst, scale) = sent.value, graph.value
    n = np.diff(np.append(start, len(dst)))[:, None]
    for batch in batches:
        for block in batch.column("id").to_pylist():
            own = x[:, block * COMPONENTS : (block + 1) * COMPONENTS]
            now = own.copy()
            for _ in range(steps if len(src) else 0):
                around = np.add.reduceat(now[dst] * scale[:, None], start) / n
                now[src] = alpha * own[src] + (1 - alpha) * around
            for lo in range(0, len(ids), 8192):
                part = np.ascontiguousarray(now[lo : lo + 8192])
                flat = pa.ListArray.from_arrays(np.arange(len(part) + 1, dtype=np.int32) * part.shape[1], part.ravel())
                yield pa.RecordBatch.from_arrays([pa.array(ids[lo : lo + 8192]), pa.array(np.full(len(part), block)), flat], ["user_id", "block", "part"])


def _diffuse_by_components(base: DataFrame, graph: DataFrame, sent, alpha: float, steps: int) -> DataFrame:
    """(user_id, emb) of ``diffuse`` with vectors and edges, both counted, in every task."""
    ids, x = sent.value
    rows = graph.dropna().toArrow()
    src, dst = (places(ids, rows.column(c).to_numpy()) for c in ("src", "dst"))
    both = (src >= 0) & (dst >= 0)
    order = np.lexsort((dst[both], src[both]))
    src, dst, scale = src[both][order], dst[both][order].astype(np.int32), rows.column("scale").to_numpy()[both][order]
    src, start = np.unique(src, return_index=True)
    spark = base.sparkSession
    put = spark.sparkContext.broadcast((src, start, dst, scale))
    blocks = -(-x.shape[1] // COMPONENTS)
    kind = base.schema["user_id"].dataType.simpleString()
    mixed = spark.range(0, blocks, 1, blocks).mapInArrow(lambda b: _mix(b, sent, put, alpha, steps), "user_id long, block long, part array<double>")
    parts = mixed.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("block", "part"))).alias("p"))
    return parts.select(F.col("user_id").cast(kind).alias("user_id"), F.flatten(F.transform("p", lambda p: p["part"])).alias("emb"))


def diffuse(edges: DataFrame, profile: DataFrame, alpha: float, *, n_iter: int | None = None, tol: float | None = None, norm: str = "row") -> DataFrame:
    """(user_id, emb) after repeated ``alpha * own + (1 - alpha) * neighbours``.

    ``norm='row'`` averages the neighbours; ``'sym'`` scales by the square roots of
    both degrees.  A user without neighbours keeps its vector.  ``alpha = 1``
    changes nothing.  With ``tol`` the loop ends once no vector moves further;
    without, vectors and graphs counted to be small go to the tasks, which take
    all steps for some components each.
    """
    base = profile.select("user_id", as_double(F.col("emb")).alias("own"))
    if alpha >= 1:
        return base.withColumnRenamed("own", "emb")
    base = materialize(base, "diffuse-base")
    graph = edges.select("src", "dst").distinct()
    out_deg = graph.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    if norm == "sym":
        in_deg = graph.groupBy("dst").agg(F.count(F.lit(1)).alias("deg_in"))
        graph = graph.join(out_deg, "src").join(in_deg, "dst").withColumn("scale", F.col("deg") / F.sqrt(F.col("deg") * F.col("deg_in")))
    else:
        graph = graph.withColumn("scale", F.lit(1.0))
    graph = materialize(graph.select("src", "dst", "scale"), "diffuse-graph")
    sent = sent_vectors(base) if tol is None and {dict(graph.dtypes)[c] for c in ("src", "dst")} <= {"bigint", "int"} and graph.count() <= LOCAL_EDGES else None
    if sent is not None and len(sent.value[0]) == base.count():
        return materialize(_diffuse_by_components(base, graph, sent, alpha, steps_for(alpha) if n_iter is None else n_iter), "diffused")
    now = base.select("user_id", F.col("own").alias("emb"))
    for i in range(steps_for(alpha) if n_iter is None else n_iter):
        sent = graph.join(now.withColumnRenamed("user_id", "dst"), "dst").select("src", vec_scale(F.col("emb"), F.col("scale")).alias("emb"))
        around = sent.groupBy(F.col("src").alias("user_id")).agg(vec_mean(F.col("emb")).alias("around"))
        mixed = base.join(around, "user_id", "left").select(
            "user_id", "own", F.when(F.col("around").isNull(), F.col("own")).otherwise(vec_add(vec_scale(F.col("own"), F.lit(alpha)), vec_scale(F.col("around"), F.lit(1 - alpha)))).alias("emb")
        )
        nxt = materialize(mixed.select("user_id", "emb"), f"diffuse-{i}")
        if tol is not None:
            moved = nxt.join(now.withColumnRenamed("emb", "old"), "user_id").agg(F.max(vec_l2(F.col("emb"), F.col("old")))).first()[0]
        else:
            moved = None
        discard(now)
        now = nxt
        if tol is not None and (moved is None or moved < tol):
            break
    return now
