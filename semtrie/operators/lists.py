"""Known lists as one row per user, each in order of rank."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, LongType

LISTS = "user_id long, peers array<long>, sims array<double>, rounds array<int>"
NAMES = ["user_id", "peers", "sims", "rounds"]


def rank_key(sim: np.ndarray) -> np.ndarray:
    """What similarities are compared by: 12 digits, and not-a-number above all as in the engine's order."""
    return np.where(np.isnan(sim), np.inf, np.round(sim, 12))


def list_columns(users: np.ndarray, of: np.ndarray, peers: np.ndarray, sims: np.ndarray, rounds: np.ndarray) -> list[pa.Array]:
    """Columns of one row per user from entries of the users' places ``of``: each list by similarity, ties to the smaller id."""
    order = np.lexsort((peers, -rank_key(sims), of))
    ends = np.append(0, np.cumsum(np.bincount(of, minlength=len(users)))).astype(np.int32)
    return [pa.array(users), *(pa.ListArray.from_arrays(ends, pa.array(v[order])) for v in (peers, sims, rounds.astype(np.int32)))]


def by_user(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Whole users from rows in order of the users: a batch's last user waits for the next batch."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        users = batch.column(0).to_numpy()
        cut = int(np.searchsorted(users, users[-1]))
        if held and (cut or held[-1].column(0)[-1].as_py() != users[0]):
            yield pa.Table.from_batches([*held, batch.slice(0, cut)]).combine_chunks()
            held = []
        elif cut:
            yield pa.Table.from_batches([batch.slice(0, cut)]).combine_chunks()
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows in by_user(batches):
        user, *rest = (c.to_numpy() for c in rows.columns)
        users, of = np.unique(user, return_inverse=True)
        yield pa.RecordBatch.from_arrays(list_columns(users, of, *rest), NAMES)


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows in by_user(batches):
        user, peers, sims = (c.combine_chunks() for c in rows.columns)
        users, place = np.unique(user.to_numpy(), return_inverse=True)
        of, peers, sims = np.repeat(place, peers.value_lengths().to_numpy()), peers.flatten().to_numpy(), sims.flatten().to_numpy()
        order = np.lexsort((sims, peers, of))
        last = np.ones(len(of), bool)
        last[:-1] = (of[order][1:] != of[order][:-1]) | (peers[order][1:] != peers[order][:-1])
        once = order[last]
        columns = list_columns(users, of[once], peers[once], sims[once], np.zeros(len(once), np.int32))
        full = pa.array(np.bincount(of, minlength=len(users)) > 0)  # an empty list is no list
        yield pa.RecordBatch.from_arrays([c.filter(full) for c in columns], NAMES)


def in_order(rows: DataFrame) -> DataFrame:
    return rows.repartition("user_id").sortWithinPartitions("user_id")


def pack_lists(known: DataFrame) -> DataFrame:
    """One row per user from rows (user_id, peer_id, sim, added_round)."""
    rows = known.select(F.col("user_id").cast("long"), F.col("peer_id").cast("long"), "sim", F.col("added_round").cast("int"))
    return in_order(rows).mapInArrow(_pack, LISTS)


def merged_lists(lists: DataFrame) -> DataFrame:
    """One row per user from some lists (user_id, peers, sims) of each: every peer once, added in round 0."""
    return in_order(lists.withColumn("user_id", F.col("user_id").cast("long"))).mapInArrow(_merge, LISTS)


def flat_lists(lists: DataFrame, user: DataType | None = None, peer: DataType | None = None) -> DataFrame:
    """Rows (user_id, peer_id, sim, added_round), with ids of the given types; ``_lists`` are the lists they come from."""
    rows = lists.select("user_id", F.inline(F.arrays_zip("peers", "sims", "rounds"))).toDF("user_id", "peer_id", "sim", "added_round")
    rows = rows.withColumn("user_id", F.col("user_id").cast(user or LongType())).withColumn("peer_id", F.col("peer_id").cast(peer or LongType()))
    rows._lists = lists
    return rows
