"""Data-set study: shared documents between users, and highest similarity to another user."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semtrie.functions.ranking import global_rank
from semtrie.operators.truth import exact_neighbors
from semtrie.plans.store import materialize

#: Holders of one document in one row; more are cut into several rows.
HOLDERS = 65_536
#: Holdings of one block of users, and pairs that a task counts at once.
BLOCK, PAIRS = 4_000_000, 4_000_000
#: Blocks that even a small table is cut into, so that all cores take part, and the least holdings worth a block.
SPREAD, LEAST = 5, 5_000


def doc_frequency(holding: DataFrame) -> DataFrame:
    return holding.groupBy("doc_id").agg(F.count_distinct("user_id").alias("df"))


def _entries(t: pa.Table, side: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(user ids, place among them, document number) of one side's holdings."""
    rows = np.flatnonzero(t.column("side").to_numpy() == side)
    lists = t.column("users").combine_chunks().take(pa.array(rows))
    ids, place = np.unique(lists.flatten().to_numpy(), return_inverse=True)
    return ids, place, np.repeat(t.column("doc").to_numpy()[rows], lists.value_lengths().to_numpy())


def _shared(u: np.ndarray, du: np.ndarray, o: np.ndarray, do: np.ndarray, n_others: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(user, other, documents both hold) for all pairs of two sides that share any, by user and other, some users at a time."""
    docs, number = np.unique(np.concatenate([du, do]), return_inverse=True)
    order = np.argsort(u, kind="stable")
    u, du = u[order], number[: len(du)][order]
    order = np.argsort(number[len(du) :], kind="stable")
    o, held = o[order], np.bincount(number[len(du) :], minlength=len(docs))
    begin, count = (np.cumsum(held) - held)[du], held[du]
    total = np.append(0, np.cumsum(count))
    users = np.append(np.flatnonzero(np.diff(u, prepend=-1)), len(u))  # where each user's holdings begin
    at = 0
    while at < len(users) - 1:
        stop = max(at + 1, int(np.searchsorted(total[users], total[users[at]] + PAIRS, side="right")) - 1)
        lo, hi = users[at], users[stop]
        n, first = total[hi] - total[lo], u[lo]
        width = int(u[hi - 1] - first + 1)
        at = stop
        if not n:
            continue
        key = lambda a, b: np.repeat((u[a:b] - first) * n_others, count[a:b]) + o[np.repeat(begin[a:b] - total[a:b], count[a:b]) + np.arange(total[a], total[b])]
        if width == 1 and n > PAIRS:  # one user with very many pairs: its documents in parts
            sums, a = np.zeros(n_others, np.int64), lo
            while a < hi:
                b = max(a + 1, int(np.searchsorted(total, total[a] + PAIRS, side="right")) - 1)
                sums += np.bincount(key(a, min(b, hi)), minlength=n_others)
                a = min(b, hi)
            found = np.flatnonzero(sums)
            sums = sums[found]
        elif width * n_others <= 4 * n:
            sums = np.bincount(key(lo, hi), minlength=width * n_others)
            found = np.flatnonzero(sums)
            sums = sums[found]
        else:
            found = np.sort(key(lo, hi))
            heads = np.flatnonzero(np.diff(found, prepend=-1))
            sums, found = np.diff(np.append(heads, len(found))), found[heads]
        yield found // n_others + first, found % n_others, sums


def _best_of_cell(t: pa.Table, both: bool) -> Iterator[pa.RecordBatch]:
    """Best partner of each user of a cell's own side, and with ``both`` of each user of the other side too."""
    (ids, u, du), (others, o, do) = _entries(t, 0), _entries(t, 1)
    shift = np.int64(1 << 32)  # the largest of count * shift - place is the largest count and, among equals, the smallest id
    mine, theirs = np.zeros(len(ids), np.int64), np.zeros(len(others), np.int64)
    for a, b, n in _shared(u, du, o, do, len(others)):
        keep = np.flatnonzero(ids[a] != others[b])
        a, b, n = a[keep], b[keep], n[keep]
        if not len(a):
            continue
        head = np.flatnonzero(np.diff(a, prepend=-1))
        mine[a[head]] = np.maximum.reduceat(n * shift - b, head)
        if both:
            np.maximum.at(theirs, b, n * shift - a)
    for whose, best, of in ((ids, mine, others), (others, theirs, ids)):
        some = np.flatnonzero(best)
        n = -(-best[some] // shift)
        yield pa.RecordBatch.from_arrays([pa.array(whose[some]), pa.array(of[n * shift - best[some]]), pa.array(n)], ["user_id", "other", "n"])


def _pairs_of_cell(t: pa.Table, same: bool, least: int) -> Iterator[pa.RecordBatch]:
    """Each pair of users once, smaller id first, that shares at least ``least`` documents."""
    (ids, u, du), (others, o, do) = _entries(t, 0), _entries(t, 1)
    for a, b, n in _shared(u, du, o, do, len(others)):
        a, b = ids[a], others[b]
        keep = np.flatnonzero((n >= least) & (a < b if same else a != b))
        for i in range(0, len(keep), 1 << 19):
            k = keep[i : i + (1 << 19)]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a[k], b[k])), pa.array(np.maximum(a[k], b[k])), pa.array(n[k])], ["user_id", "other", "n"])


def _cells(holding: DataFrame, df: DataFrame, sample: DataFrame | None, work) -> DataFrame:
    """(user_id, other, n) by ``work(table, same block)`` on every pair of blocks of users.

    Documents travel with the list of a block's holders, once for each block that
    block meets; no pair of users travels.  Every two blocks meet once, or, with a
    ``sample`` as the own side, each of its blocks meets every block.
    """
    keyed = df.select("doc_id", F.monotonically_increasing_id().alias("doc"), F.ceil(F.col("df") / HOLDERS).cast("int").alias("parts"))
    kept = materialize(holding.join(materialize(keyed, "shared-docs"), "doc_id").select(F.col("user_id").cast("long").alias("user_id"), "doc", "parts"), "shared-holdings")
    rows = kept.count()
    blocks = max(1, -(-rows // BLOCK), min(SPREAD, rows // LEAST))
    part = F.pmod(F.xxhash64("user_id", F.lit(1)), F.col("parts")).cast("int").alias("part")
    block = F.pmod(F.xxhash64("user_id"), F.lit(blocks)).cast("int").alias("block")
    lists = lambda d: d.groupBy("doc", block, part).agg(F.collect_list("user_id").alias("users"))
    own = kept if sample is None else kept.join(sample.select(F.col("user_id").cast("long").alias("user_id")).distinct(), "user_id", "left_semi")
    every = F.sequence(F.lit(0), F.lit(blocks - 1))
    above, below = (F.sequence(F.col("block"), F.lit(blocks - 1)), F.sequence(F.lit(0), F.col("block"))) if sample is None else (every, every)
    a = lists(own).select(F.col("block").alias("i"), F.explode(above).alias("j"), F.lit(0).alias("side"), "doc", "users")
    b = lists(kept).select(F.explode(below).alias("i"), F.col("block").alias("j"), F.lit(1).alias("side"), "doc", "users")

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        if len(np.unique(t.column("side").to_numpy())) == 2:
            yield from work(t, key[0].as_py() == key[1].as_py())

    return a.unionByName(b).groupBy("i", "j").applyInArrow(run, "user_id long, other long, n long")


def max_cooccurrence(holding: DataFrame, *, max_df: int | None = None, sample: DataFrame | None = None) -> DataFrame:
    """Per user the largest number of documents shared with one other user, and that user (ties: smallest id).

    Pairs are counted over documents held at least twice, one pair of blocks of
    users in a task, which keeps one partner per user (``_cells``).  ``max_df``
    leaves out documents held by more users (a stated approximation); ``sample``
    restricts the users for whom the answer is wanted, keeping it exact for them.
    """
    held = materialize(holding.select("user_id", "doc_id").distinct(), "held")
    df = held.groupBy("doc_id").agg(F.count(F.lit(1)).alias("df")).filter("df >= 2")
    if max_df is not None:
        df = df.filter(F.col("df") <= max_df)
    each = sample is None
    shared = _cells(held, df, sample, lambda t, same: _best_of_cell(t, each and not same))
    # the smallest struct of (-n, other) is the largest count and, among equals, the smallest id
    best = shared.groupBy("user_id").agg(F.min(F.struct((-F.col("n")).alias("m"), "other")).alias("b"))
    users = (held if sample is None else held.join(sample.select("user_id").distinct(), "user_id", "left_semi")).select("user_id").distinct()
    return users.join(best, "user_id", "left").select("user_id", F.coalesce(-F.col("b.m"), F.lit(0)).alias("max_shared"), F.col("b.other").alias("partner"))


def shared_pairs(holding: DataFrame, least: int) -> DataFrame:
    """(user_id, other, n): every pair of users, smaller id first, that shares at least ``least`` documents."""
    held = materialize(holding.select("user_id", "doc_id").distinct(), "held")
    df = held.groupBy("doc_id").agg(F.count(F.lit(1)).alias("df")).filter("df >= 2")
    return _cells(held, df, None, lambda t, same: _pairs_of_cell(t, same, least))


def isolated_users(holding: DataFrame) -> DataFrame:
    """Users who share no document with anybody."""
    shared = doc_frequency(holding).filter("df >= 2")
    linked = holding.join(shared, "doc_id", "left_semi").select("user_id").distinct()
    return holding.select("user_id").distinct().join(linked, "user_id", "left_anti")


def max_cosine(profile: DataFrame) -> DataFrame:
    """Per user the highest cosine to another user."""
    return exact_neighbors(profile, k=1).select("user_id", "peer_id", F.col("sim").alias("max_cos"))


def curve(values: DataFrame, value: str) -> DataFrame:
    """A per-user value as a sorted curve: rank from 1 at the largest."""
    return global_rank(values.select("user_id", value), value, "user_id", descending=True).select("rank", "user_id", value)
