"""Greedy query routing over peer lists, all queries at once: one iteration per hop."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semtrie.functions.vectors import dot_packed, pack_unit, unpack
from semtrie.operators.neighbors import units
from semtrie.plans.store import materialize, places


#: Queries, and listed peers, of one scoring block: more at one user are dealt out, and every part of the one meets every part of the other.
CHUNK = 8192
#: Listed peers (and holdings of wanted documents), and vector bytes, up to which the whole graph goes to the tasks and walks end there.
LOCAL_PEERS, LOCAL_BYTES = 5_000_000, 64 << 20
#: Scores of one matrix product of such walks.
SCORES = 4_000_000


def _best_peers(queries: pa.Table, peers: pa.Table, revisit: bool) -> pa.Table:
    """Best peer of each query in one part of a list: one matrix product, visited peers masked, ties to the smaller id."""
    ids = queries.column("query_id")
    if not queries.num_rows or not peers.num_rows:
        return pa.table({"query_id": ids, "peer": pa.nulls(queries.num_rows, pa.int64()), "score": pa.nulls(queries.num_rows, pa.float64())})
    peer = peers.column("peer_id").to_numpy()
    order = np.argsort(peer, kind="stable")
    peer = peer[order]
    x = unpack(peers.column("peer_unit").to_pylist())[order]
    scores = np.round(unpack(queries.column("unit").to_pylist()) @ x.T, 12)
    if not revisit:
        for i, met in enumerate(queries.column("visited").to_pylist()):
            at = np.searchsorted(peer, met)
            hit = at < len(peer)
            at, met = at[hit], np.array(met)[hit]
            scores[i, at[peer[at] == met]] = -np.inf
    best = scores.argmax(1)
    top = scores[np.arange(len(scores)), best]
    return pa.table({"query_id": ids, "peer": pa.array(peer[best], mask=~np.isfinite(top)), "score": pa.array(top, mask=~np.isfinite(top))})


def next_contacts(open_: DataFrame, peers: DataFrame, revisit: bool) -> DataFrame:
    """(query_id, next) for open walks (query_id, cur, unit, visited) and lists (cur, peer_id, peer_unit, parts).

    Walks and lists meet per current user, so a list travels once per block of
    walks and not once per walk; lists where no walk stands do not travel, and a
    hub's list is cut into ``parts``, of whose bests the best is taken.
    """
    blocks = open_.groupBy("cur").agg(F.ceil(F.count(F.lit(1)) / CHUNK).cast("int").alias("blocks"))
    sizes = blocks.join(peers.groupBy("cur").agg(F.max("parts").alias("parts")), "cur", "left")
    walks = open_.join(sizes, "cur").withColumn("block", F.pmod(F.xxhash64("query_id"), F.col("blocks")).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)))
    lists = peers.join(blocks, "cur").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("part", F.pmod(F.xxhash64("peer_id"), F.col("parts")).cast("int"))
    walks = walks.select("cur", "block", "part", "query_id", "unit", "visited")
    key = ["cur", "block", "part"]
    lists = lists.select(*[F.col(c).alias(c) for c in (*key, "peer_id", "peer_unit")])
    offers = walks.groupBy(key).cogroup(lists.groupBy(key)).applyInArrow(lambda a, b: _best_peers(a, b, revisit), "query_id long, peer long, score double")
    # the smallest of (-score, peer) is the best score and, among equals, the smaller id; null where no peer is left
    return offers.groupBy("query_id").agg(F.min(F.when(F.col("peer").isNotNull(), F.struct((-F.col("score")).alias("s"), "peer"))).alias("b")).select("query_id", F.col("b.peer").alias("next"))


def _best_of_lists(cur: np.ndarray, q: np.ndarray, met: np.ndarray, graph: tuple, place_of: np.ndarray, revisit: bool) -> np.ndarray:
    """Place of the best peer of each walk, -1 where none is left; walks at one user share a matrix product."""
    users, start, stop, peers, (_, x) = graph
    best = np.full(len(cur), -1)
    owner = places(users, cur)
    order = np.argsort(owner, kind="stable")
    order = order[owner[order] >= 0]
    cuts = np.flatnonzero(np.diff(owner[order], prepend=-1, append=-1))
    for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
        rows = order[lo:hi]
        at = owner[rows[0]]
        row = peers[start[at] : stop[at]]
        place_of[row] = np.arange(len(row))
        y = x[row].T
        for part in np.array_split(rows, -(-len(rows) * len(row) // SCORES) or 1):
            s = np.round(q[part] @ y, 12)
            if not revisit:
                here = place_of[met[part]]  # -1 also for users without a vector: the last place is never set
                s[np.nonzero(here >= 0)[0], here[here >= 0]] = -np.inf
            top = s.argmax(1)  # peers lie in id order: the first of equals is the smallest
            best[part] = np.where(np.isfinite(s[np.arange(len(part)), top]), row[top], -1)
        place_of[row] = -1
    return best


def _walk(batches: Iterator[pa.RecordBatch], sent, max_hops: int, first: int, revisit: bool) -> Iterator[pa.RecordBatch]:
    """Whole walks of a batch of queries, hop by hop, over a graph and holdings that fit a task."""
    graph, (docs, holders, held) = sent.value
    ids = graph[4][0]
    place_of = np.full(len(ids) + 1, -1)
    for batch in batches:
        query = batch.column("query_id").to_numpy(zero_copy_only=False)
        cur = batch.column("cur").to_numpy(zero_copy_only=False)
        q = unpack(batch.column("unit").to_pylist())
        wanted = batch.column("docs")
        row = np.repeat(np.arange(len(query)), wanted.value_lengths().to_numpy(zero_copy_only=False))
        doc = places(docs, wanted.flatten().to_numpy(zero_copy_only=False))
        row, doc = row[doc >= 0], doc[doc >= 0]
        met, hop, out = places(ids, cur)[:, None], first, []
        live = np.arange(len(query))
        while len(live):
            have = np.zeros(len(query), bool)
            at = places(holders, cur)[row]
            some = at >= 0
            have[row[some][places(held, doc[some] * len(holders) + at[some]) >= 0]] = True
            status = np.where(have[live], "found", "max_hops" if hop >= max_hops else "open")
            out.append((query[live], np.full(len(live), hop), cur[live], status))
            live = live[status == "open"]
            best = _best_of_lists(cur[live], q[live], met[live], graph, place_of, revisit)
            stuck = live[best < 0]
            out.append((query[stuck], np.full(len(stuck), hop), cur[stuck], np.full(len(stuck), "dead_end")))
            live, best = live[best >= 0], best[best >= 0]
            step = np.full(len(query), -1)
            step[live] = best
            cur = cur.copy()
            cur[live] = ids[best]
            met = np.concatenate([met, step[:, None]], axis=1)
            open_ = np.zeros(len(query), bool)
            open_[live] = True
            row, doc = row[open_[row]], doc[open_[row]]
            hop += 1
        cols = [np.concatenate(c) if out else np.zeros(0) for c in zip(*out, strict=True)] if out else [np.zeros(0)] * 4
        types = (pa.int64(), pa.int32(), pa.int64(), pa.string())
        yield pa.RecordBatch.from_arrays([pa.array(c.tolist() if t == pa.string() else c.astype(t.to_pandas_dtype()), t) for c, t in zip(cols, types, strict=True)], ["query_id", "hop", "user_id", "status"])


def _whole_graph(unit: DataFrame, lists: DataFrame) -> tuple:
    """Lists and unit vectors as arrays (owners, start, stop, places of peers, (ids, vectors)); all were counted first."""
    vectors = unit.select("id", "unit").toArrow()
    ids = vectors.column("id").to_numpy()
    order = np.argsort(ids)
    ids, x = ids[order], unpack(vectors.column("unit").to_pylist())[order]
    pairs = lists.toArrow()
    owner, place = pairs.column("user_id").to_numpy(), places(ids, pairs.column("peer_id").to_numpy())
    owner, place = owner[place >= 0], place[place >= 0].astype(np.int32)
    order = np.lexsort((place, owner))
    owner, place = owner[order], place[order]
    users, start = np.unique(owner, return_index=True)
    return users, start, np.append(start[1:], len(owner))[: len(users)], place, (ids, x)


def _whole_holding(holding: DataFrame) -> tuple:
    """Holdings (doc_id, user_id) as (documents, holders, sorted pairs of their places)."""
    rows = holding.toArrow()
    docs, doc = np.unique(rows.column("doc_id").to_numpy(), return_inverse=True)
    holders, user = np.unique(rows.column("user_id").to_numpy(), return_inverse=True)
    return docs, holders, np.unique(doc * len(holders) + user)


def chain_hop(
    queries: DataFrame,
    lists: DataFrame,
    profile: DataFrame,
    holding: DataFrame,
    max_hops: int,
    *,
    count_self: bool = False,
    revisit: bool = False,
    targets: DataFrame | None = None,
    vectors: DataFrame | None = None,
    local: bool | None = None,
) -> DataFrame:
    """Trace (query_id, hop, user_id, status) of every contact.

    ``queries(query_id, user_id, target_doc, emb)`` start at their user, who looks
    at home first; then each contact is the member of the current user's list
    (``lists(user_id, peer_id)``) most similar to the query, ties to the smaller
    id, without users met before unless ``revisit``.  ``count_self`` charges the
    look at home as the first hop.  ``status``: open, found, max_hops, dead_end.
    ``targets(query_id, doc_id)`` gives several acceptable documents.  ``vectors``
    (user_id, emb) replaces the profiles' vectors (diffused ones, say).

    A graph and holdings counted to be small (``LOCAL_PEERS``, ``LOCAL_BYTES``; ``local``
    decides otherwise) go to the tasks, and every walk ends in one pass whatever
    ``max_hops``.  A larger one stays distributed: one row per open query and step
    travels, and finished queries leave the loop.
    """
    unit = materialize(units(vectors if vectors is not None else profile), "hop-units")
    wanted = targets if targets is not None else queries.select("query_id", F.col("target_doc").alias("doc_id"))
    first = 1 if count_self else 0
    held = materialize(holding.join(wanted.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "user_id"), "hop-held")
    whole = dict(held.dtypes)["doc_id"] in ("bigint", "int")
    if local is None:
        lists = materialize(lists.select("user_id", "peer_id"), "hop-peers")  # counted, then read
        size = unit.agg(F.coalesce(F.sum(F.octet_length("unit")), F.lit(0))).first()[0]
        local = whole and size <= LOCAL_BYTES and lists.count() <= LOCAL_PEERS and held.count() <= LOCAL_PEERS
    if local:
        if not whole:  # documents of other types get numbers
            number = materialize(wanted.select("doc_id").distinct().withColumn("number", F.monotonically_increasing_id()), "hop-documents")
            wanted, held = (d.join(number, "doc_id").drop("doc_id").withColumnRenamed("number", "doc_id") for d in (wanted, held))
        graph = _whole_graph(unit, lists.select("user_id", "peer_id"))
        sent = lists.sparkSession.sparkContext.broadcast((graph, _whole_holding(held.filter("doc_id IS NOT NULL AND user_id IS NOT NULL"))))
        begin = pack_unit(queries).withColumn("query_id", F.col("query_id").cast("long")).withColumnRenamed("user_id", "cur")
        none = F.array().cast("array<long>")
        if targets is None and whole:
            walks = begin.withColumn("docs", F.when(F.col("target_doc").isNotNull(), F.array(F.col("target_doc").cast("long"))).otherwise(none))
        else:
            at = wanted.groupBy(F.col("query_id").cast("long").alias("query_id")).agg(F.collect_set(F.col("doc_id").cast("long")).alias("docs"))
            walks = begin.join(at, "query_id", "left").withColumn("docs", F.coalesce("docs", none))
        walks = walks.select("query_id", "cur", "unit", "docs").repartition("query_id")  # queries of few documents lie in few files
        return materialize(walks.mapInArrow(lambda b: _walk(b, sent, max_hops, first, revisit), "query_id long, hop int, user_id long, status string"), "walks")
    holders = wanted.join(holding.select("user_id", "doc_id").distinct(), "doc_id").select("query_id", F.col("user_id").alias("cur")).distinct()
    peers = lists.select("user_id", "peer_id").join(unit.select(F.col("id").alias("peer_id"), F.col("unit").alias("peer_unit")), "peer_id")
    parts = lists.groupBy("user_id").agg(F.ceil(F.count(F.lit(1)) / CHUNK).cast("int").alias("parts"))
    peers = materialize(peers.join(parts, "user_id").select(F.col("user_id").alias("cur"), "peer_id", "peer_unit", "parts"), "hop-lists")
    holders = materialize(holders, "hop-holders")
    start = pack_unit(queries.select("query_id", "user_id", "emb")).select("query_id", F.col("user_id").alias("cur"), "unit", F.array("user_id").alias("visited"), F.lit(first).alias("hop"), F.lit(False).alias("stuck"))

    def settle(walk: DataFrame) -> DataFrame:
        met = walk.join(holders.withColumn("hit", F.lit(True)), ["query_id", "cur"], "left")
        status = F.when(F.col("stuck"), F.lit("dead_end")).when(F.col("hit"), F.lit("found")).when(F.col("hop") >= max_hops, F.lit("max_hops")).otherwise(F.lit("open"))
        return met.withColumn("status", status).drop("hit", "stuck")

    row = lambda d: d.select("query_id", "hop", F.col("cur").alias("user_id"), "status")
    walk = materialize(settle(start), "walk-0")
    trace = row(walk)
    while True:
        open_ = walk.filter("status = 'open'").drop("status")
        best = next_contacts(open_, peers, revisit)
        on = F.col("next").isNotNull()
        # one projection for both outcomes, so that a hop is scored once
        moved = open_.join(best, "query_id", "left").select(
            "query_id", F.coalesce("next", "cur").alias("cur"), "unit", F.when(on, F.concat("visited", F.array("next"))).otherwise(F.col("visited")).alias("visited"), (F.col("hop") + on.cast("int")).alias("hop"), (~on).alias("stuck")
        )
        both = materialize(settle(moved), "walk")
        trace = trace.unionByName(row(both))
        walk = both
        if both.filter("status = 'open'").isEmpty():
            return trace


def outcomes(trace: DataFrame) -> DataFrame:
    """(query_id, status, hops): how each query ended, and after how many contacts."""
    last = F.max_by(F.struct("status", "hop"), F.struct(F.col("hop"), (F.col("status") == "dead_end").cast("int")))
    return trace.groupBy("query_id").agg(last.alias("e")).select("query_id", F.col("e.status").alias("status"), F.col("e.hop").alias("hops"))


def random_query_expected(holding: DataFrame, queries: DataFrame, n_q: int, n_users: int) -> DataFrame:
    """(query_id, p): chance that ``n_q`` distinct random other users include a holder, in closed form."""
    holders = holding.select("user_id", "doc_id").distinct()
    per_query = queries.select("query_id", "user_id", F.col("target_doc").alias("doc_id")).join(holders.withColumnRenamed("user_id", "holder"), "doc_id", "left")
    h = per_query.groupBy("query_id").agg(F.count(F.when(F.col("holder") != F.col("user_id"), 1)).alias("h"))
    others = n_users - 1
    miss = F.aggregate(
        F.sequence(F.lit(0), F.lit(n_q - 1)), F.lit(1.0), lambda acc, i: acc * F.greatest(F.lit(0.0), (F.lit(float(others)) - F.col("h") - i) / (F.lit(float(others)) - i))
    )
    return h.select("query_id", "h", (F.lit(1.0) - miss).alias("p"))


def random_query_simulated(holding: DataFrame, queries: DataFrame, users: DataFrame, n_q: int, seed: int = 42) -> DataFrame:
    """(query_id, found): the same by drawing peers."""
    from semtrie.operators.overlay import random_lists

    quota = queries.select(F.col("query_id").alias("user_id"), F.explode(F.sequence(F.lit(1), F.lit(n_q))).alias("peer_id"))
    drawn = random_lists(quota, users, seed).select(F.col("user_id").alias("query_id"), "peer_id")
    joined = queries.select("query_id", "user_id", F.col("target_doc").alias("doc_id")).join(drawn, "query_id").filter("user_id <> peer_id")
    hits = joined.join(holding.select(F.col("user_id").alias("peer_id"), "doc_id").distinct(), ["peer_id", "doc_id"]).select("query_id").distinct()
    return queries.select("query_id").join(hits.withColumn("found", F.lit(True)), "query_id", "left").select("query_id", F.coalesce("found", F.lit(False)).alias("found"))


def rank_results(results: DataFrame, queries: DataFrame, doc_vectors: DataFrame, k: int) -> DataFrame:
    """Local ranking of returned documents (query_id, doc_id) by cosine with the query."""
    from pyspark.sql import Window

    q = pack_unit(queries.select("query_id", "emb"), out="qu").select("query_id", "qu")
    d = pack_unit(doc_vectors.select("doc_id", "emb"), out="du").select("doc_id", "du")
    scored = results.join(q, "query_id").join(d, "doc_id").withColumn("sim", dot_packed("qu", "du"))
    w = Window.partitionBy("query_id").orderBy(F.desc(F.round("sim", 12)), "doc_id")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "doc_id", "sim", "rank")
