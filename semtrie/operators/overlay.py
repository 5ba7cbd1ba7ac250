"""Overlay graphs: from known lists, at random, by preferential attachment, and mixtures; the hash ring."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.hashing import portable_hash, portable_hash_py
from semtrie.plans.store import materialize


def overlay_graph(known: DataFrame) -> DataFrame:
    """Directed edges (src, dst) from known lists."""
    return known.select(F.col("user_id").alias("src"), F.col("peer_id").alias("dst"))


def numbered(users: DataFrame) -> DataFrame:
    """Users with a dense number from 0 in the order of the portable hash (ties by id), without one task ordering all of them.

    Local ranks within ranges of the hash plus the ranges' offsets.
    """
    h = portable_hash("number", F.col("user_id"))
    keyed = users.select("user_id").distinct().withColumn("h", h).withColumn("bucket", F.shiftright("h", 50).cast("int"))
    counts = keyed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    offsets = counts.withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    local = F.row_number().over(Window.partitionBy("bucket").orderBy("h", "user_id")) - 1
    # at most 1,024 buckets
    return keyed.withColumn("local", local).join(F.broadcast(offsets.select("bucket", "before")), "bucket").select("user_id", (F.col("before") + F.col("local")).alias("number"))


def random_lists(known: DataFrame, users: DataFrame, seed: int = 42, oversample: int = 4) -> DataFrame:
    """Random lists as long as each user's known list (of at most all others).

    Hash draws of user numbers, repeats and self dropped.  For lists that hold
    more than half of all users such draws would run short: there all users are
    ranked by a hash, which is of the order of the list itself.
    """
    number = numbered(users)
    n = number.count()
    wanted = known.groupBy("user_id").agg(F.count(F.lit(1)).alias("k")).withColumn("k", F.least("k", F.lit(n - 1)))
    most = wanted.filter(F.col("k") * 2 > n)
    ranks = most.withColumn("number", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))) if n else most.withColumn("number", F.lit(0).cast("long"))
    long_ = ranks.join(number.withColumnRenamed("user_id", "peer_id"), "number").filter("user_id <> peer_id").withColumn("i", portable_hash(seed, F.lit("full"), F.col("user_id"), F.col("number")))
    w = Window.partitionBy("user_id").orderBy("i", "peer_id")
    full = long_.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= F.col("k")).select("user_id", "peer_id")
    # the user's own number is left out, and repeats of a number, before any row is made of a draw
    draws = wanted.filter(F.col("k") * 2 <= n).join(number.withColumnRenamed("number", "own"), "user_id", "left")
    draw = lambda i: F.pmod(portable_hash(seed, F.lit("list"), F.col("user_id"), i), F.lit(n)).cast("long")
    drawn = F.array_distinct(F.transform(F.sequence(F.lit(0).cast("long"), F.col("k") * oversample + 40), draw))
    others = F.when(F.col("own").isNull(), F.col("drawn")).otherwise(F.array_remove("drawn", F.col("own").cast("long")))
    first = draws.withColumn("drawn", drawn).select("user_id", F.explode(F.slice(others, F.lit(1), F.col("k").cast("int"))).alias("number"))
    return first.join(number.withColumnRenamed("user_id", "peer_id"), "number").select("user_id", "peer_id").unionByName(full)


def match_m(known: DataFrame) -> int:
    """The attachment parameter whose mean degree 2 m is that of the known lists."""
    mean = known.groupBy("user_id").agg(F.count(F.lit(1)).alias("k")).agg(F.avg("k")).first()[0] or 2
    return max(1, round(mean / 2))


def resolve_slot(slot: int, seed: int) -> int:
    """Source number behind an endpoint slot: odd slots copy an earlier slot drawn by hash until an even one is met."""
    while slot % 2:
        e = slot // 2
        slot = portable_hash_py(seed, "pa", e) % slot
    return slot // 2


def pa_graph(users: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """Preferential attachment with ``m`` edges per user: (src, dst) in both directions.

    Edge e belongs to user number e div m.  Its other end copies the endpoint
    slot that a hash picks among the earlier ones; an even slot is a source, an
    odd one is resolved the same way.  Every edge resolves alone, so the graph
    needs no sequential state.  Loops and repeated edges are dropped.
    """
    number = numbered(users)
    edges = number.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(m - 1)))).select("number", (F.col("number") * m + F.col("j")).alias("e"))

    def resolve(batches):
        for pdf in batches:
            ends = [resolve_slot(2 * int(e) + 1, seed) // m for e in pdf["e"]]
            yield pdf.assign(other=ends)[["number", "other"]]

    # dealt to all cores, and resolved once for both directions and all that count the graph
    raw = materialize(edges.repartition("e").mapInPandas(resolve, "number long, other long").filter("number <> other"), "attachments")
    name = lambda c, out: number.select(F.col("number").alias(c), F.col("user_id").alias(out))
    named = raw.distinct().join(name("number", "src"), "number").join(name("other", "dst"), "other").select("src", "dst")
    return named.union(named.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def mixed_overlay(known: DataFrame, users: DataFrame, random_share: float = 0.2, seed: int = 42) -> DataFrame:
    """Trie peers plus random meetings: each user adds ``random_share`` of its list length in random peers (rounded up)."""
    wanted = known.groupBy("user_id").agg(F.ceil(F.count(F.lit(1)) * random_share).alias("k")).withColumn("row", F.explode(F.sequence(F.lit(1), F.col("k")))).select("user_id", F.col("row").alias("peer_id"))
    return overlay_graph(known).union(overlay_graph(random_lists(wanted, users, seed))).distinct()


RING_BITS = 32


def ring_position(key: Column) -> Column:
    """Place on a ring of 2^32: the leading bits of the portable hash."""
    return F.shiftright(portable_hash("ring", key), 60 - RING_BITS)


def ring_lookup(users: DataFrame, keys: DataFrame) -> DataFrame:
    """(key, position, owner): the first user at or after each key's place, wrapping around.

    A range join by binning: ranges of the ring are hashed to bins, each bin also
    knows the first user after it, so keys meet only the users of their bin.
    """
    bins = 10
    u = users.select("user_id").distinct().withColumn("at", ring_position(F.col("user_id"))).withColumn("bin", F.shiftright("at", RING_BITS - bins).cast("int"))
    k = keys.select("key").distinct().withColumn("position", ring_position(F.col("key"))).withColumn("bin", F.shiftright("position", RING_BITS - bins).cast("int"))
    firsts = u.groupBy("bin").agg(F.min(F.struct("at", "user_id")).alias("f"))
    all_bins = users.sparkSession.range(1 << bins).select(F.col("id").cast("int").alias("bin")).join(firsts, "bin", "left")
    after = Window.orderBy("bin").rowsBetween(1, Window.unboundedFollowing)
    whole = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    fallback = all_bins.select("bin", F.coalesce(F.first("f", ignorenulls=True).over(after), F.first("f", ignorenulls=True).over(whole)).alias("next"))  # 1,024 rows
    here = k.join(u, "bin", "left").groupBy("key", "position", "bin").agg(F.min(F.when(F.col("at") >= F.col("position"), F.struct("at", "user_id"))).alias("found"))
    return here.join(F.broadcast(fallback), "bin").select("key", "position", F.coalesce(F.col("found.user_id"), F.col("next.user_id")).alias("owner"))


def ring_hops(users: DataFrame, starts: DataFrame) -> DataFrame:
    """(key, user_id, hops): contacts of a finger-table lookup from a user to a key's owner.

    Fingers stand at powers of two, so each contact halves the ring distance: the
    count is the number of one-bits of the distance, over the bits that tell
    users apart.
    """
    n = users.select("user_id").distinct().count()
    bits = max(1, (max(n, 2) - 1).bit_length())
    distance = F.pmod(ring_position(F.col("key")) - ring_position(F.col("user_id")), F.lit(1 << RING_BITS))
    return starts.select("key", "user_id", F.bit_count(F.shiftright(distance, RING_BITS - bits)).cast("long").alias("hops"))
