"""Contacts of each placement, and the known and closest lists."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from semtrie.functions.hashing import portable_hash
from semtrie.functions.vectors import as_double, dot_packed, pack_unit, unit_rows
from semtrie.operators.lists import flat_lists, merged_lists
from semtrie.operators.truth import flat_leaf_lists, leaf_lists, leaf_top_k
from semtrie.plans.store import discard, materialize, small_vectors
from semtrie.plans.store import places as places_of


def units(profile: DataFrame) -> DataFrame:
    """(id, unit): packed unit vectors of users."""
    return pack_unit(profile.select(F.col("user_id").alias("id"), "emb")).select("id", "unit")


def sent_units(profile: DataFrame):
    """``sent_vectors`` of the users' unit vectors; those of a scratch table, which never changes, are sent once."""
    found = getattr(profile, "_sent_units", None)
    if found is None:
        vectors = small_vectors(profile.select(F.col("user_id").alias("id"), as_double(F.col("emb")).alias("emb")))
        if vectors is None:
            return None
        found = profile.sparkSession.sparkContext.broadcast((vectors[0], unit_rows(vectors[1])))
        if getattr(profile, "_scratch_path", None):
            profile._sent_units = found
    return found


def _similar(batches: Iterator[pa.RecordBatch], sent) -> Iterator[pa.RecordBatch]:
    ids, x = sent.value
    for batch in batches:
        a, b = (places_of(ids, batch.column(c).to_numpy(zero_copy_only=False)) for c in ("user_id", "peer_id"))
        good = (a >= 0) & (b >= 0)
        a, b = a[good], b[good]
        sim = np.concatenate([np.zeros(0)] + [(x[a[i : i + 8192]] * x[b[i : i + 8192]]).sum(1) for i in range(0, len(a), 8192)])
        kept = batch.filter(pa.array(good))
        yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(sim)], [*batch.schema.names, "sim"])


def with_similarity(pairs: DataFrame, unit: DataFrame, sent=None) -> DataFrame:
    """Add the cosine of ``user_id`` and ``peer_id`` as ``sim``; with the vectors ``sent`` to the tasks none of them is joined."""
    if sent is not None:
        schema = StructType([*pairs.schema.fields, StructField("sim", DoubleType())])
        return pairs.filter("user_id IS NOT NULL AND peer_id IS NOT NULL").mapInArrow(lambda batches: _similar(batches, sent), schema)
    a = unit.select(F.col("id").alias("user_id"), F.col("unit").alias("unit_a"))
    b = unit.select(F.col("id").alias("peer_id"), F.col("unit").alias("unit_b"))
    return pairs.join(a, "user_id").join(b, "peer_id").withColumn("sim", dot_packed("unit_a", "unit_b")).drop("unit_a", "unit_b")


def leaf_rings(placements: DataFrame, n_cc: int) -> DataFrame:
    """(tree_id, leaf, other, ring): leaves around each leaf by tree distance, nearest rings first, as far as needed.

    Two leaves are at distance D if their paths part below a common ancestor with
    D steps in all; that is an equi-join of the leaves' prefixes on the ancestor
    and the steps left, made for one D at a time and only for leaves that have met
    neither ``n_cc`` other users nor all users of their tree.  Never leaf by leaf.
    """
    places = placements.select("tree_id", "path", "user_id").distinct()
    leaves = places.groupBy("tree_id", "path").agg(F.count(F.lit(1)).alias("n"))
    depth = F.char_length("path")
    ups = F.when(depth > 0, F.sequence(F.lit(1), depth)).otherwise(F.array().cast("array<int>"))
    anc = leaves.select("tree_id", F.col("path").alias("leaf"), F.explode(ups).alias("up"))
    anc = materialize(anc.select("tree_id", "leaf", "up", F.substr("leaf", F.lit(1), F.char_length("leaf") - F.col("up")).alias("ancestor"), F.substr("leaf", F.char_length("leaf") - F.col("up") + 1, F.lit(1)).alias("side")), "ancestors")
    farthest = anc.groupBy("tree_id").agg(F.max("up").alias("h")).agg(F.max("h")).first()[0] or 0
    rings = materialize(leaves.select("tree_id", F.col("path").alias("leaf"), F.col("path").alias("other"), F.lit(0).alias("ring")), "ring-0")
    seen = rings
    everybody = places.groupBy("tree_id").agg(F.count_distinct("user_id").alias("all"))
    for d in range(2, 2 * farthest + 1):
        users = seen.join(places.select("tree_id", F.col("path").alias("other"), "user_id"), ["tree_id", "other"])
        short = users.groupBy("tree_id", "leaf").agg(F.count_distinct("user_id").alias("k")).filter(F.col("k") - 1 < n_cc)
        short = short.join(everybody, "tree_id").filter(F.col("k") < F.col("all")).select("tree_id", "leaf")
        short = materialize(short, f"short-{d}")
        if short.isEmpty():
            break
        a = anc.join(short, ["tree_id", "leaf"], "left_semi").withColumn("up_b", d - F.col("up"))
        b = anc.select("tree_id", F.col("leaf").alias("other"), F.col("up").alias("up_b"), "ancestor", F.col("side").alias("side_b"))
        pairs = a.join(b, ["tree_id", "ancestor", "up_b"]).filter(F.col("side") != F.col("side_b"))
        seen = seen.unionByName(materialize(pairs.select("tree_id", "leaf", "other", F.lit(d).alias("ring")), f"ring-{d}"))
        discard(short)
    return seen


def too_small(places: DataFrame, n_cc: int) -> bool:
    """Whether any leaf holds fewer than ``n_cc`` users besides each of its own, so that leaves around it matter."""
    sizes = places.groupBy("tree_id", "path").agg(F.count_distinct("user_id").alias("n"))
    least = sizes.agg(F.min("n")).first()[0]
    return least is not None and least - 1 < n_cc


def gather_contacts(placements: DataFrame, profile: DataFrame, n_cc: int = 50, seed: int = 42) -> DataFrame:
    """(tree_id, user_id, path, peer_id, ring, sim): up to ``n_cc`` contacts of each placement.

    The own leaf comes first, its most similar users first if it holds too many
    (``sim`` is their cosine, null for others); then the leaves around it by
    (distance, path), users of a leaf in hash order.  Pairs within a leaf are
    compared in blocks, so a leaf may be of any size.
    """
    places = materialize(placements.select("tree_id", "path", "user_id").distinct(), "places")
    sent = sent_units(profile)
    lists, whole = (None, False) if sent is None else leaf_lists(places, n_cc, sent)
    own = leaf_top_k(places, units(profile), n_cc) if sent is None else flat_leaf_lists(lists, whole, n_cc)
    own = own.withColumn("ring", F.lit(0)).withColumn("other", F.col("path"))
    if not too_small(places, n_cc):
        contacts = own.select("tree_id", "user_id", "path", "peer_id", "ring", "sim")
        if whole:
            contacts._placed_lists = lists
        return contacts
    rings = leaf_rings(placements, n_cc)
    around = rings.filter("ring > 0").join(places.select("tree_id", F.col("path").alias("other"), F.col("user_id").alias("peer_id")), ["tree_id", "other"])
    outer = places.join(around.withColumnRenamed("leaf", "path"), ["tree_id", "path"]).filter("user_id <> peer_id").withColumn("sim", F.lit(None).cast("double"))
    met = own.unionByName(outer)
    best = met.groupBy("tree_id", "user_id", "path", "peer_id").agg(F.min(F.struct("ring", "other", "sim")).alias("at"))
    key = F.when(F.col("ring") == 0, -F.round("sim", 12)).otherwise(portable_hash(seed, F.lit("contact"), F.col("peer_id")).cast("double"))
    best = best.select("tree_id", "user_id", "path", "peer_id", "at.ring", "at.other", "at.sim").withColumn("key", key)
    w = Window.partitionBy("tree_id", "user_id", "path").orderBy("ring", "other", "key", "peer_id")
    return best.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= n_cc).select("tree_id", "user_id", "path", "peer_id", "ring", "sim")


def init_lists(contacts: DataFrame, profile: DataFrame) -> DataFrame:
    """Known lists (user_id, peer_id, sim, added_round): the contacts of all placements, once each.

    Similarities that the contacts bring along are not computed again.  Contacts
    that are whole lists of placements become one list per user, of which the
    rows are a view.
    """
    placed = getattr(contacts, "_placed_lists", None)
    if placed is not None:
        lists = materialize(merged_lists(placed.select("user_id", "peers", "sims")), "lists-0")
        return flat_lists(lists, placed.schema["user_id"].dataType)
    pairs = contacts.filter("user_id <> peer_id")
    unit = units(profile)
    if "sim" not in contacts.columns:
        return with_similarity(pairs.select("user_id", "peer_id").distinct(), unit, sent_units(profile)).withColumn("added_round", F.lit(0))
    once = materialize(pairs.groupBy("user_id", "peer_id").agg(F.max("sim").alias("sim")), "contacts")
    if once.filter("sim IS NULL").isEmpty():
        return once.withColumn("added_round", F.lit(0))
    rest = with_similarity(once.filter("sim IS NULL").drop("sim"), unit, sent_units(profile))
    return once.filter("sim IS NOT NULL").unionByName(rest).withColumn("added_round", F.lit(0))


def ranked(known: DataFrame) -> DataFrame:
    """Known lists with each peer's rank by (similarity, id)."""
    w = Window.partitionBy("user_id").orderBy(F.desc(F.round("sim", 12)), "peer_id")
    return known.withColumn("rank", F.row_number().over(w))


def closest(known: DataFrame, n_cu: int = 50) -> DataFrame:
    return ranked(known).filter(F.col("rank") <= n_cu)
