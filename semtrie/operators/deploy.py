"""Deployment: custodians of split nodes, departures, sparse leaves."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.hashing import portable_hash
from semtrie.functions.paths import path_parent


def elect_custodians(nodes: DataFrame, placements: DataFrame, *, seed: int = 42, backups: int = 1) -> DataFrame:
    """One row per split node: custodian, backups, centres, child paths and the parent's custodian.

    The custodian is the member below the node of smallest hash, the backups the
    next ones.  Members reach their ancestors by exploding prefixes; each node
    keeps ``backups + 1`` of them (a per-group top k, cut before the shuffle).
    """
    splits = nodes.filter("kind = 'split'").select("tree_id", "path", "c0", "c1")
    depth = F.char_length("path")
    up = F.when(depth > 0, F.sequence(F.lit(0), depth - 1)).otherwise(F.array().cast("array<int>"))
    below = placements.select("tree_id", "user_id", "path").select("tree_id", "user_id", F.col("path").alias("leaf"), F.explode(up).alias("d")).select("tree_id", "user_id", F.substr("leaf", F.lit(1), F.col("d")).alias("path"))
    w = Window.partitionBy("tree_id", "path").orderBy(portable_hash(seed, F.lit("custodian"), F.col("path"), F.col("user_id")), "user_id")
    members = below.distinct().withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= backups + 1)
    chosen = members.groupBy("tree_id", "path").agg(F.max(F.when(F.col("rn") == 1, F.col("user_id"))).alias("user_id"), F.array_sort(F.collect_list(F.when(F.col("rn") > 1, F.struct("rn", "user_id")))).alias("b"))
    directory = splits.join(chosen, ["tree_id", "path"], "left").select("tree_id", "path", "user_id", F.transform("b", lambda x: x["user_id"]).alias("backups"), "c0", "c1", F.concat("path", F.lit("0")).alias("child0"), F.concat("path", F.lit("1")).alias("child1"), path_parent(F.col("path")).alias("parent_path"))
    parents = directory.select("tree_id", F.col("path").alias("parent_path"), F.col("user_id").alias("parent_user_id"))
    return directory.join(parents, ["tree_id", "parent_path"], "left")


def leave(placements: DataFrame, directory: DataFrame, gone: DataFrame, *, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(placements left, directory): departed users are removed; backups step in, and both offices are filled anew.

    ``event`` tells what happened at each node: kept, promoted (the backup took
    over), elected (both were gone) or lost (no member left below).
    """
    away = gone.select("user_id").distinct()
    stay = placements.join(away, "user_id", "left_anti")
    nodes = directory.select("tree_id", "path", F.lit("split").alias("kind"), "c0", "c1")
    fresh = elect_custodians(nodes, stay, seed=seed).select("tree_id", "path", F.col("user_id").alias("new_user"), F.col("backups").alias("new_backups"))
    was = directory.withColumn("backup", F.get("backups", F.lit(0))).join(away.select("user_id", F.lit(True).alias("c_gone")), "user_id", "left").join(away.select(F.col("user_id").alias("backup"), F.lit(True).alias("b_gone")), "backup", "left")
    event = F.when(F.col("c_gone").isNull() & F.col("user_id").isNotNull(), F.lit("kept")).when(F.col("new_user").isNull(), F.lit("lost")).when(F.col("b_gone").isNull() & F.col("backup").isNotNull(), F.lit("promoted")).otherwise(F.lit("elected"))
    joined = was.join(fresh, ["tree_id", "path"], "left")
    return stay, joined.select("tree_id", "path", "parent_path", F.col("new_user").alias("user_id"), F.col("new_backups").alias("backups"), "c0", "c1", event.alias("event"))


def merge_sparse(nodes: DataFrame, placements: DataFrame, *, capacity: int, min_fill: float = 0.5) -> DataFrame:
    """Placements after folding sibling leaves whose joint users fit ``capacity * min_fill`` into their parent (one pass)."""
    leaves = nodes.filter("kind <> 'split' AND depth > 0").select("tree_id", "path")
    per = placements.groupBy("tree_id", "path").agg(F.collect_set("user_id").alias("u"))  # a leaf holds about capacity users
    held = leaves.join(per, ["tree_id", "path"], "left").withColumn("parent", path_parent(F.col("path")))
    pairs = held.groupBy("tree_id", "parent").agg(F.count(F.lit(1)).alias("kids"), F.size(F.array_distinct(F.flatten(F.collect_list("u")))).alias("joint"))
    folded = pairs.filter((F.col("kids") == 2) & (F.col("joint") <= capacity * min_fill)).select("tree_id", "parent")
    moved = placements.withColumn("parent", path_parent(F.col("path"))).join(folded.withColumn("fold", F.lit(True)), ["tree_id", "parent"], "left")
    return moved.select("tree_id", "user_id", F.when(F.col("fold"), F.col("parent")).otherwise(F.col("path")).alias("path")).distinct()
