"""Exact nearest users and exact central search, in blocks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.vectors import pack_unit, unpack
from semtrie.plans.store import materialize
from semtrie.plans.store import places as places_of

#: Rows of one block of items and of one block of queries.
ITEMS = 32_768
QUERIES = 4_096
#: Blocks of items that even a small table is cut into, so that all cores take part, and the least rows worth a block.
SPREAD, LEAST = 16, 256
#: Queries of one block where the vectors are with the tasks and only ids travel.
SENT_QUERIES = 1_024


def at_least_kth(scores: np.ndarray, k: int, room: float = 1e-9) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) pairs that hold each row's k largest finite scores, and some more, with ``room`` for rounding.

    The columns are dealt into some groups: the k-th largest of the groups' largest
    is at most the k-th largest of all, so what lies below it is left out without
    any row being put in order.
    """
    n = scores.shape[1]
    groups = 8 * k
    if n > 4 * groups:
        whole = n // groups * groups
        largest = np.fmax.reduce(scores[:, :whole].reshape(len(scores), n // groups, groups), axis=1)
        least = np.partition(np.where(np.isnan(largest), -np.inf, largest), groups - k, axis=1)[:, groups - k]
    elif n > k:
        least = np.partition(np.where(np.isnan(scores), -np.inf, scores), n - k, axis=1)[:, n - k]
    else:
        least = np.full(len(scores), -np.inf)
    r, c = np.divmod(np.flatnonzero(scores >= (least - room)[:, None]), n) if n else (np.zeros(0, int), np.zeros(0, int))
    finite = np.isfinite(scores[r, c])
    return r[finite], c[finite]


def first_k(rows: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k largest scores of each row, ties to the smaller id; equal vectors tie whatever the order of summation."""
    order = np.lexsort((ids, -np.round(scores, 12), rows))
    ordered = rows[order]
    return order[np.arange(len(order)) - np.searchsorted(ordered, ordered) < k]


def top_k(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Columns of the k largest per row, ties to the smaller id: (row, column) pairs."""
    r, c = at_least_kth(scores, k)
    first = first_k(r, ids[c], scores[r, c], k)
    return r[first], c[first]


def _block(queries: pa.Table, items: pa.Table, k: int, exclude_same: bool) -> pa.Table:
    """Exact top k of one block of items for one block of queries: one matrix product, in slices."""
    rows, found, sims = [], [], []
    if queries.num_rows and items.num_rows:
        qid, ids = queries.column("id").to_numpy(), items.column("id").to_numpy()
        q, x = unpack(queries.column("unit").to_pylist()), unpack(items.column("unit").to_pylist())
        for lo in range(0, len(qid), 256):
            s = q[lo : lo + 256] @ x.T
            if exclude_same:
                s[qid[lo : lo + 256][:, None] == ids[None]] = -np.inf
            r, c = top_k(s, ids, k)
            rows.append(qid[lo + r])
            found.append(ids[c])
            sims.append(s[r, c])
    cat = lambda parts, kind: np.concatenate(parts) if parts else np.zeros(0, kind)
    return pa.table({"query": pa.array(cat(rows, np.int64)), "item": pa.array(cat(found, np.int64)), "sim": pa.array(cat(sims, np.float64))})


def blocked_top_k(queries: DataFrame, items: DataFrame, k: int, *, exclude_same: bool) -> DataFrame:
    """(query, item, sim): exact top k of ``items(id, unit)`` for each of ``queries(id, unit)``.

    Both sides are packed unit vectors with bigint ids.  Each is dealt into blocks
    of bounded size and every pair of blocks meets in one task, which keeps k rows
    per query; a final rank merges them.  Nothing but two counts reaches the
    driver, and no task holds more than one block of either side.  The exact
    answer for all N rows is N * N products: at scale pass a sample of queries.
    """
    queries, items = materialize(queries.select("id", "unit"), "queries"), materialize(items.select("id", "unit"), "items")
    n, m = queries.count(), items.count()
    i_blocks = max(1, -(-m // ITEMS), min(SPREAD, m // LEAST))
    q_blocks = max(1, -(-n // QUERIES))
    deal = lambda blocks: F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    every = lambda blocks: F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    q = queries.select(deal(q_blocks).alias("qb"), every(i_blocks).alias("ib"), "id", "unit")
    x = items.select(every(q_blocks).alias("qb"), deal(i_blocks).alias("ib"), "id", "unit")
    out = q.groupBy("qb", "ib").cogroup(x.groupBy("qb", "ib")).applyInArrow(lambda a, b: _block(a, b, k, exclude_same), "query long, item long, sim double")
    w = Window.partitionBy("query").orderBy(F.desc(F.round("sim", 12)), "item")
    return out.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def _leaf_block(queries: pa.Table, items: pa.Table, k: int) -> pa.Table:
    """Exact top k among the items of its own leaf for each query of a block; a block holds one leaf's rows or those of many small ones.

    The matrix product picks candidates with room for its rounding; the pairs' own
    inner products, summed as everywhere else, decide.
    """
    rows, found, sims = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
    if queries.num_rows and items.num_rows:
        number = {leaf: i for i, leaf in enumerate(pc.unique(queries.column("leaf")).to_pylist())}
        place = lambda t: np.array([number.get(v, -1) for v in t.column("leaf").to_pylist()])
        q_leaf, x_leaf = place(queries), place(items)
        q_order, x_order = np.argsort(q_leaf, kind="stable"), np.argsort(x_leaf, kind="stable")
        qid, ids = queries.column("row").to_numpy()[q_order], items.column("id").to_numpy()[x_order]
        own = queries.column("id").to_numpy()[q_order]
        q, x = unpack(queries.column("unit").to_pylist())[q_order], unpack(items.column("unit").to_pylist())[x_order]
        q_leaf, x_leaf = q_leaf[q_order], x_leaf[x_order]
        for leaf in range(len(number)):
            a, b = np.searchsorted(q_leaf, (leaf, leaf + 1)), np.searchsorted(x_leaf, (leaf, leaf + 1))
            of, to = ids[b[0] : b[1]], x[b[0] : b[1]]
            if not len(of):
                continue
            for lo in range(a[0], a[1], 256):
                hi = min(lo + 256, a[1])
                s = q[lo:hi] @ to.T
                s[own[lo:hi][:, None] == of[None]] = -np.inf
                r, c = at_least_kth(s, k)
                sim = np.concatenate([np.zeros(0)] + [(q[lo + r[i : i + 65_536]] * to[c[i : i + 65_536]]).sum(1) for i in range(0, len(r), 65_536)])
                first = first_k(r, of[c], sim, k)
                rows.append(qid[lo + r[first]])
                found.append(of[c[first]])
                sims.append(sim[first])
    return pa.table({"row": pa.array(np.concatenate(rows)), "item": pa.array(np.concatenate(found)), "sim": pa.array(np.concatenate(sims))})


def _sent_blocks(batches: Iterator[pa.RecordBatch], sent, k: int) -> Iterator[pa.RecordBatch]:
    """Exact top k for each row's queries among its items.

    Products in single precision pick candidates, with room for twice the error they can have between unit vectors;
    the pairs' own inner products in double precision, summed as everywhere else, decide.
    """
    ids, x = sent.value
    room = (x.shape[1] + 8) * 2.0**-23
    for batch in batches:
        queries, items = batch.column("queries"), batch.column("items")
        for i in range(batch.num_rows):
            at, to = (places_of(ids, side[i].values.to_numpy()) for side in (queries, items))
            at, to = np.sort(at[at >= 0]), np.sort(to[to >= 0])
            if not len(at) or not len(to):
                continue
            of, q, t = ids[to], x[at].astype(np.float32), np.ascontiguousarray(x[to].astype(np.float32).T)
            step = max(16, min(256, (1 << 20) // len(to)))
            rows, found, sims = [], [], []
            for lo in range(0, len(at), step):
                s = q[lo : lo + step] @ t
                own = np.minimum(np.searchsorted(to, at[lo : lo + step]), len(to) - 1)
                same = to[own] == at[lo : lo + step]
                s[np.flatnonzero(same), own[same]] = -np.inf
                r, c = at_least_kth(s, k, room)
                a, b = at[lo + r], to[c]
                sim = np.concatenate([np.zeros(0)] + [(x[a[j : j + 8192]] * x[b[j : j + 8192]]).sum(1) for j in range(0, len(a), 8192)])
                first = first_k(r, of[c], sim, k)
                rows.append(lo + r[first])
                found.append(of[c[first]])
                sims.append(sim[first])
            row = np.concatenate(rows)  # in order, as are the vectors' places
            ends = np.append(0, np.cumsum(np.bincount(row, minlength=len(at)))).astype(np.int32)
            leaf = [batch.column(c).take(pa.array(np.full(len(at), i))) for c in ("tree_id", "path")]
            lists = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate(v))) for v in (found, sims)]
            yield pa.RecordBatch.from_arrays([*leaf, pa.array(ids[at]), *lists], ["tree_id", "path", "user_id", "peers", "sims"])


def leaf_lists(places: DataFrame, k: int, sent) -> tuple[DataFrame, bool]:
    """(tree_id, path, user_id, peers, sims) for ``leaf_top_k`` with the vectors in the tasks, and whether that is one row per placement.

    Lists of ids travel, one row for each meeting of two blocks of a leaf; a leaf of more than ``ITEMS`` users leaves
    several rows per placement to be merged.
    """
    key = ["tree_id", "path"]
    rows = places.select(*key, F.col("user_id").cast("long").alias("user_id"))
    sizes = rows.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    most, meetings = sizes.agg(F.max("n"), F.sum(F.ceil(F.col("n") / SENT_QUERIES) * F.ceil(F.col("n") / ITEMS))).first()
    dealt = rows.join(sizes, key)
    block = lambda size, of: dealt.groupBy(*key, F.pmod(F.xxhash64("user_id"), F.ceil(F.col("n") / size)).alias("block")).agg(F.collect_list("user_id").alias(of)).drop("block")
    tasks = max(1, min(meetings or 0, 8 * places.sparkSession.sparkContext.defaultParallelism))
    met = block(SENT_QUERIES, "queries").join(block(ITEMS, "items"), key).repartition(tasks)
    out = met.mapInArrow(lambda batches: _sent_blocks(batches, sent, k), "tree_id string, path string, user_id long, peers array<long>, sims array<double>")
    return out.withColumn("user_id", F.col("user_id").cast(places.schema["user_id"].dataType)), (most or 0) <= ITEMS


def flat_leaf_lists(lists: DataFrame, whole: bool, k: int) -> DataFrame:
    """``leaf_top_k`` from ``leaf_lists``."""
    key = ["tree_id", "path", "user_id"]
    out = lists.select(*key, F.inline(F.arrays_zip("peers", "sims"))).toDF(*key, "peer_id", "sim")
    if whole:
        return out
    w = Window.partitionBy(*key).orderBy(F.desc(F.round("sim", 12)), "peer_id")
    return out.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).drop("rank")


def leaf_top_k(places: DataFrame, unit: DataFrame, k: int, sent=None) -> DataFrame:
    """(tree_id, path, user_id, peer_id, sim): per placement the exact k most similar other users of its leaf.

    As ``blocked_top_k``, leaf by leaf: a large leaf's users are dealt into blocks
    of bounded size, of which every pair meets in one task and keeps k rows per
    query; small leaves share a task.  No pair but those leaves a task.  With the
    unit vectors ``sent`` to the tasks none of them travels.
    """
    if sent is not None:
        return flat_leaf_lists(*leaf_lists(places, k, sent), k)
    key = ["tree_id", "path"]
    rows = materialize(places.select(*key, "user_id").join(unit.select(F.col("id").alias("user_id"), "unit"), "user_id").withColumn("row", F.monotonically_increasing_id()), "leaf-rows")
    sizes = rows.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    shared = max(1, -(-(sizes.filter(F.col("n") <= QUERIES).agg(F.sum("n")).first()[0] or 0) // QUERIES))
    up = lambda size: F.ceil(F.col("n") / size).cast("int")
    leaf = F.concat_ws(":", *key)
    task = F.when(F.col("n") <= QUERIES, F.pmod(F.xxhash64(*key), F.lit(shared)).cast("string")).otherwise(F.concat(F.lit("-"), leaf))
    dealt = rows.join(sizes, key).select("row", F.col("user_id").alias("id"), "unit", leaf.alias("leaf"), task.alias("task"), up(QUERIES).alias("qs"), up(ITEMS).alias("xs"))
    deal = lambda c: F.pmod(F.xxhash64("id"), F.col(c)).cast("int")
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    q = dealt.select("task", deal("qs").alias("qb"), every("xs").alias("xb"), "row", "id", "unit", "leaf")
    x = dealt.select("task", every("qs").alias("qb"), deal("xs").alias("xb"), "id", "unit", "leaf")
    x = x.select(*[F.col(c).alias(c) for c in x.columns])  # columns of its own, as both sides come from one table
    meet = ["task", "qb", "xb"]
    out = q.groupBy(*meet).cogroup(x.groupBy(*meet)).applyInArrow(lambda a, b: _leaf_block(a, b, k), "row long, item long, sim double")
    w = Window.partitionBy("row").orderBy(F.desc(F.round("sim", 12)), "item")
    best = out.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
    return best.join(rows.select("row", *key, "user_id"), "row").select(*key, "user_id", F.col("item").alias("peer_id"), "sim")


def exact_neighbors(profile: DataFrame, k: int = 50, sample: DataFrame | None = None) -> DataFrame:
    """(user_id, peer_id, sim, rank): the exact k nearest users by cosine, for all users or a sample of them."""
    items = pack_unit(profile.select(F.col("user_id").alias("id"), "emb")).select("id", "unit")
    queries = items if sample is None else items.join(sample.select(F.col("user_id").alias("id")).distinct(), "id", "left_semi")
    found = blocked_top_k(queries, items, k, exclude_same=True)
    return found.select(F.col("query").alias("user_id"), F.col("item").alias("peer_id"), "sim", "rank")


def central_search(queries: DataFrame, doc_vectors: DataFrame, k: int) -> DataFrame:
    """The central index as an upper bound: top k documents by cosine for each (query_id, emb)."""
    q = pack_unit(queries.select(F.col("query_id").alias("id"), "emb")).select("id", "unit")
    d = pack_unit(doc_vectors.select(F.col("doc_id").alias("id"), "emb")).select("id", "unit")
    found = blocked_top_k(q, d, k, exclude_same=False)
    return found.select(F.col("query").alias("query_id"), F.col("item").alias("doc_id"), "sim", "rank")


def _count_block(a: pa.Table, b: pa.Table, centre: float, width: float) -> pa.Table:
    n = 0
    if a.num_rows and b.num_rows:
        ids, others = a.column("id").to_numpy(), b.column("id").to_numpy()
        q, x = unpack(a.column("unit").to_pylist()), unpack(b.column("unit").to_pylist())
        for lo in range(0, len(q), 256):
            near = np.abs(q[lo : lo + 256] @ x.T - centre) < width
            n += int(np.count_nonzero(near & (ids[lo : lo + 256][:, None] < others[None])))
    return pa.table({"n": pa.array([n], pa.int64())})


def count_pairs(profile: DataFrame, centre: float, width: float) -> DataFrame:
    """One row, n: pairs of users, each counted once, whose cosine differs from ``centre`` by less than ``width``.

    Blocks of users in id order meet as in ``blocked_top_k``, a block only with
    those at or after it, and each meeting yields one number: every pair is
    compared and none is kept.
    """
    unit = materialize(pack_unit(profile.select(F.col("user_id").alias("id"), "emb")).select("id", "unit"), "pair-units")
    blocks = max(1, min(SPREAD, unit.count() // LEAST), -(-unit.count() // QUERIES))
    cuts = unit.agg(F.percentile_approx("id", [i / blocks for i in range(1, blocks)]).alias("c")).first()["c"] if blocks > 1 else []
    block = F.size(F.filter(F.array(*[F.lit(c) for c in cuts or []]).cast("array<long>"), lambda c: c < F.col("id")))
    dealt = unit.withColumn("block", block)
    a = dealt.select(F.col("block").alias("ab"), F.explode(F.sequence(F.col("block"), F.lit(blocks - 1))).alias("bb"), "id", "unit")
    b = dealt.select(F.explode(F.sequence(F.lit(0), F.col("block"))).alias("ab"), F.col("block").alias("bb"), "id", "unit")
    b = b.select(*[F.col(c).alias(c) for c in b.columns])
    met = a.groupBy("ab", "bb").cogroup(b.groupBy("ab", "bb")).applyInArrow(lambda p, q: _count_block(p, q, centre, width), "n long")
    return met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
