"""Expansion rounds: every user asks one peer for somebody closer."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.hashing import portable_hash
from semtrie.functions.vectors import quantise_packed, quantised_rows, upper_bound_packed, upper_bounds
from semtrie.operators.lists import LISTS, flat_lists, list_columns, pack_lists, rank_key
from semtrie.operators.neighbors import ranked, sent_units, units, with_similarity
from semtrie.plans.store import materialize, places, small

#: Listed peers from which on offers are bounded by one-byte components before whole vectors travel.
QUANTISE_ROWS = 5_000_000


@dataclass
class Expansion:
    """Known lists after each round (index 0: before the first) and what each round cost."""

    rounds: list[DataFrame]
    costs: list[dict] = field(default_factory=list)

    @property
    def known(self) -> DataFrame:
        return self.rounds[-1]


def asks(known: DataFrame, round_no: int, n_cu: int, ask_from: str, seed: int) -> DataFrame:
    """(user_id, asked, bar): the peer each user asks, and the similarity an answer has to exceed.

    The peer is drawn by hash from the closest list (or the whole known list); the
    bar is the similarity of rank ``n_cu``, or none while the list is shorter.
    """
    lists = ranked(known)
    pool = lists.filter(F.col("rank") <= n_cu) if ask_from == "closest" else lists
    sizes = pool.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.max(F.when(F.col("rank") == n_cu, F.col("sim"))).alias("bar"))
    if ask_from != "closest":
        bars = lists.filter(F.col("rank") == n_cu).select("user_id", F.col("sim").alias("bar"))
        sizes = sizes.drop("bar").join(bars, "user_id", "left")
    pick = sizes.withColumn("rank", (F.pmod(portable_hash(seed, round_no, F.col("user_id")), F.col("n")) + 1).cast("int"))
    return pick.join(pool.select("user_id", "rank", F.col("peer_id").alias("asked")), ["user_id", "rank"]).select("user_id", "asked", "bar")


def one_round(known: DataFrame, unit: DataFrame, round_no: int, *, n_cu: int, ask_from: str, reply_limit: int | None, reply: str, seed: int, quantised: bool = False, sent=None) -> tuple[DataFrame, DataFrame]:
    """(asks, additions) of one round on a snapshot of the lists."""
    asked = asks(known, round_no, n_cu, ask_from, seed)
    theirs = known.select(F.col("user_id").alias("asked"), "peer_id")
    offered = asked.join(theirs, "asked").filter("user_id <> peer_id")
    fresh = offered.join(known.select("user_id", "peer_id"), ["user_id", "peer_id"], "left_anti")
    offers = fresh.select("user_id", "peer_id", "bar")
    if quantised and reply == "closer":
        qa = small(unit.select(F.col("id").alias("user_id"), F.col("q").alias("qa")))
        qb = small(unit.select(F.col("id").alias("peer_id"), F.col("q").alias("qb")))
        bounded = offers.join(qa, "user_id").join(qb, "peer_id").withColumn("most", upper_bound_packed("qa", "qb"))
        offers = bounded.filter(F.col("bar").isNull() | (F.col("most") >= F.col("bar"))).select("user_id", "peer_id", "bar")
    judged = with_similarity(offers, unit.select("id", "unit"), sent)
    if reply == "closer":
        judged = judged.filter(F.col("bar").isNull() | (F.round("sim", 12) > F.round("bar", 12)))
    if reply_limit is not None:
        w = Window.partitionBy("user_id").orderBy(F.desc(F.round("sim", 12)), "peer_id")
        judged = judged.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= reply_limit)
    return asked, judged.select("user_id", "peer_id", "sim", F.lit(round_no).alias("added_round"))


def _answers(batches: Iterator[pa.RecordBatch], sent, codes, round_no: int, reply_limit: int | None, reply: str) -> Iterator[pa.RecordBatch]:
    """The lists after a round, from rows with each user's list and that of the peer asked (``offered``)."""
    ids, x = sent.value
    for batch in batches:
        users = batch.column("user_id").to_numpy()
        own, sims, rounds, offered = (batch.column(c) for c in ("peers", "sims", "rounds", "offered"))
        size = lambda c: np.nan_to_num(c.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
        own_of, of = np.repeat(np.arange(len(users)), size(own)), np.repeat(np.arange(len(users)), size(offered))
        peers, peer = own.flatten().to_numpy(), offered.flatten().to_numpy()
        a, b = places(ids, users), places(ids, peer)
        good = (b >= 0) & (a[of] >= 0) & (peer != users[of])
        of, peer, b = of[good], peer[good], b[good]
        key = lambda of, at: of * len(ids) + at
        at = places(ids, peers)
        fresh = ~np.isin(key(of, b), key(own_of[at >= 0], at[at >= 0]))
        of, peer, b = of[fresh], peer[fresh], b[fresh]
        bar = batch.column("bar")
        none, bar = bar.is_null().to_numpy(zero_copy_only=False), bar.fill_null(0.0).to_numpy()
        cuts = range(0, len(of), 8192)
        if codes is not None and reply == "closer":
            scale, left, q = codes.value
            most = [upper_bounds(*((v[p[i : i + 8192]]) for p in (a[of], b) for v in (scale, left, q))) for i in cuts]
            may = none[of] | ~(np.concatenate([np.zeros(0), *most]) < bar[of])
            of, peer, b = of[may], peer[may], b[may]
            cuts = range(0, len(of), 8192)
        who = a[of]
        sim = np.concatenate([np.zeros(0)] + [(x[who[i : i + 8192]] * x[b[i : i + 8192]]).sum(1) for i in cuts])
        if reply == "closer":
            near = none[of] | (rank_key(sim) > rank_key(bar)[of])
            of, peer, sim = of[near], peer[near], sim[near]
        if reply_limit is not None:
            order = np.lexsort((peer, -rank_key(sim), of))
            order = order[np.arange(len(of)) - np.searchsorted(of[order], of[order]) < reply_limit]
            of, peer, sim = of[order], peer[order], sim[order]
        merged = [np.concatenate(v) for v in ((own_of, of), (peers, peer), (sims.flatten().to_numpy(), sim), (rounds.flatten().to_numpy(), np.full(len(of), round_no)))]
        yield pa.RecordBatch.from_arrays([*list_columns(users, *merged), pa.array(size(offered))], ["user_id", "peers", "sims", "rounds", "heard"])


def one_packed_round(lists: DataFrame, round_no: int, sent, codes, *, n_cu: int, ask_from: str, reply_limit: int | None, reply: str, seed: int) -> DataFrame:
    """``one_round`` on one row per user, with ``heard``, the length of the list asked for: a user's list meets that of the peer asked, once."""
    n = F.size("peers")
    pool = F.least(n, F.lit(n_cu)) if ask_from == "closest" else n
    pick = (F.pmod(portable_hash(seed, round_no, F.col("user_id")), pool) + 1).cast("int")
    asking = lists.select("user_id", "peers", "sims", "rounds", F.element_at("peers", pick).alias("asked"), F.try_element_at("sims", F.lit(n_cu)).alias("bar"))
    theirs = lists.select(F.col("user_id").alias("asked"), F.col("peers").alias("offered"))
    met = asking.join(theirs, "asked", "left").drop("asked")
    return met.mapInArrow(lambda batches: _answers(batches, sent, codes, round_no, reply_limit, reply), LISTS + ", heard long")


def expand_packed(known: DataFrame, sent, rounds: int, *, n_cu: int, quantised: bool, until_stable: bool, patience: int, keep_costs: bool, **options) -> Expansion:
    """``expand`` with the vectors in the tasks: lists travel whole, one row per user."""
    lists = getattr(known, "_lists", None) or materialize(pack_lists(known), "lists-0")
    flat = lambda: flat_lists(lists, known.schema["user_id"].dataType, known.schema["peer_id"].dataType)
    state = Expansion([flat()])
    codes = known.sparkSession.sparkContext.broadcast(quantised_rows(sent.value[1])) if quantised else None
    quiet = 0
    for t in range(1, rounds + 1):
        before = lists
        lists = materialize(one_packed_round(before, t, sent, codes, n_cu=n_cu, **options), f"lists-{t}")
        state.rounds.append(flat())
        if keep_costs:
            added = F.aggregate("rounds", F.lit(0), lambda n, r: n + F.when(r == t, 1).otherwise(0))
            cost = lists.agg(F.count(F.lit(1)).alias("messages"), F.coalesce(F.sum("heard"), F.lit(0)).alias("similarities"), F.coalesce(F.sum(added), F.lit(0)).alias("additions")).first()
            state.costs.append({"round": t, **cost.asDict()})
        if until_stable:
            entered = lists.filter(F.exists(F.slice("rounds", 1, n_cu), lambda r: r == t))
            quiet = quiet + 1 if entered.isEmpty() else 0
            if quiet >= patience:
                break
    return state


def expand(
    known: DataFrame,
    profile: DataFrame,
    rounds: int,
    *,
    n_cu: int = 50,
    ask_from: str = "closest",
    reply_limit: int | None = None,
    reply: str = "closer",
    seed: int = 42,
    until_stable: bool = False,
    patience: int = 2,
    keep_costs: bool = False,
    quantised: bool | None = None,
) -> Expansion:
    """Known lists over ``rounds`` synchronous rounds.

    ``ask_from``: closest | known; ``reply_limit``: peers per answer (all, if
    None); ``reply='everything'`` shares without the similarity test.
    ``quantised`` first rules offers out by a bound from one-byte components, so
    that whole vectors travel for the rest only; the lists are the same.  Unless
    told, that is done once the lists hold more than ``QUANTISE_ROWS`` peers.
    Vectors counted to be small go to the tasks once instead of travelling, and
    lists then travel as one row per user.  With ``until_stable`` the loop ends
    once no closest list changed for ``patience`` rounds.
    """
    columns = ["user_id", "peer_id", "sim", "added_round"]
    if getattr(known, "_lists", None) is None:
        known = known.select(*columns) if getattr(known, "_scratch_path", None) else materialize(known.select(*columns), "known-0")
    n, *full = known.agg(F.count(F.lit(1)), *[F.count(c) for c in columns]).first()
    if quantised is None:
        quantised = n > QUANTISE_ROWS
    sent = sent_units(profile)
    if sent is not None and full == [n] * 4 and all(dict(known.dtypes)[c] in ("bigint", "int") for c in columns[:2]):
        return expand_packed(
            known, sent, rounds, n_cu=n_cu, ask_from=ask_from, reply_limit=reply_limit, reply=reply, seed=seed, quantised=quantised, until_stable=until_stable, patience=patience, keep_costs=keep_costs
        )
    state = Expansion([known])
    unit = units(profile)
    unit = materialize(unit.withColumn("q", quantise_packed("unit")) if quantised else unit, "units")
    quiet = 0
    for t in range(1, rounds + 1):
        now = state.known
        asked, added = one_round(now, unit, t, n_cu=n_cu, ask_from=ask_from, reply_limit=reply_limit, reply=reply, seed=seed, quantised=quantised)
        added = materialize(added, f"added-{t}")
        nxt = materialize(now.unionByName(added), f"known-{t}")
        if keep_costs:
            sizes = now.groupBy(F.col("user_id").alias("asked")).agg(F.count(F.lit(1)).alias("n"))
            cost = asked.join(sizes, "asked", "left").agg(F.count(F.lit(1)).alias("messages"), F.coalesce(F.sum("n"), F.lit(0)).alias("similarities")).first()
            state.costs.append({"round": t, "messages": cost["messages"], "similarities": cost["similarities"], "additions": added.count()})
        state.rounds.append(nxt)
        if until_stable:
            entered = ranked(nxt).filter((F.col("rank") <= n_cu) & (F.col("added_round") == t))
            quiet = quiet + 1 if entered.isEmpty() else 0
            if quiet >= patience:
                break
    return state
