"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall_at(closest: DataFrame, truth: DataFrame) -> DataFrame:
    """(user_id, recall): how many of the exact nearest users are in the closest list; users without a hit count as 0."""
    hits = truth.select("user_id", "peer_id").join(closest.select("user_id", "peer_id").distinct(), ["user_id", "peer_id"])
    found = hits.groupBy("user_id").agg(F.count(F.lit(1)).alias("recall"))
    return truth.select("user_id").distinct().join(found, "user_id", "left").select("user_id", F.coalesce("recall", F.lit(0)).alias("recall"))


def clone_stats(placements: DataFrame) -> DataFrame:
    """Placements per user: median, mean, both standard deviations, and users never cloned."""
    per = placements.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return per.agg(
        F.count(F.lit(1)).alias("users"), F.percentile("n", 0.5).alias("median"), F.avg("n").alias("mean"), F.stddev_pop("n").alias("std_pop"), F.stddev_samp("n").alias("std_samp"), F.count_if(F.col("n") == 1).alias("never_cloned")
    )


def clone_histogram(placements: DataFrame) -> DataFrame:
    per = placements.groupBy("user_id").agg(F.count(F.lit(1)).alias("placements"))
    return per.groupBy("placements").agg(F.count(F.lit(1)).alias("users"))


def leaf_fill(placements: DataFrame) -> DataFrame:
    """Leaves by number of users, as counts and as shares of all leaves."""
    per = placements.groupBy(*[c for c in ("tree_id", "path") if c in placements.columns]).agg(F.count(F.lit(1)).alias("users"))
    counts = per.groupBy("users").agg(F.count(F.lit(1)).alias("leaves"))
    return counts.withColumn("share", F.col("leaves") / F.sum("leaves").over(Window.partitionBy()))  # one row per fill, at most capacity + a few


def hit_curve(outcome: DataFrame, hops: list[int]) -> DataFrame:
    """(max_hops, found, rate): share of all queries answered within each number of contacts."""
    limits = F.explode(F.array(*[F.lit(h) for h in hops])).alias("max_hops")
    total = outcome.agg(F.count(F.lit(1)).alias("total"))
    by_hop = outcome.filter("status = 'found'").groupBy("hops").agg(F.count(F.lit(1)).alias("n"))
    grid = outcome.sparkSession.range(1).select(limits)
    joined = grid.join(by_hop, F.col("hops") <= F.col("max_hops"), "left").groupBy("max_hops").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("found"))  # a few rows on both sides
    return joined.crossJoin(total).select("max_hops", "found", F.try_divide("found", "total").alias("rate"))


def message_count(outcome: DataFrame) -> DataFrame:
    return outcome.agg(F.count(F.lit(1)).alias("queries"), F.sum("hops").alias("messages"), F.max("hops").alias("most"), F.avg("hops").alias("mean"))


def work_count(trace: DataFrame, lists: DataFrame, holding: DataFrame) -> DataFrame:
    """(query_id, similarities, documents): local work along each walk, list sizes where it went on and documents looked at."""
    k = lists.groupBy("user_id").agg(F.count(F.lit(1)).alias("k"))
    d = holding.groupBy("user_id").agg(F.count_distinct("doc_id").alias("d"))
    met = trace.filter("status <> 'dead_end'").join(k, "user_id", "left").join(d, "user_id", "left")
    return met.groupBy("query_id").agg(F.sum(F.when(F.col("status") == "open", F.coalesce("k", F.lit(0))).otherwise(0)).alias("similarities"), F.sum(F.coalesce("d", F.lit(0))).alias("documents"))


def build_cost(placements: DataFrame, users: int, rounds: int, *, splits: int, capacity: int) -> DataFrame:
    """Messages of insertion (one per level and placement) and of the rounds (one per user and round), and members moved by splits."""
    return placements.agg(F.coalesce(F.sum(F.char_length("path")), F.lit(0)).alias("insertion")).select(
        "insertion", F.lit(rounds * users).cast("long").alias("expansion"), F.lit(splits * (capacity + 1)).cast("long").alias("reassigned"), (F.col("insertion") + F.lit(rounds * users)).alias("total")
    )


def trie_shape(nodes: DataFrame) -> DataFrame:
    """Per depth: splits, leaves, users on leaves, and 2-means steps."""
    return nodes.groupBy("depth").agg(
        F.count_if(F.col("kind") == "split").alias("splits"), F.count_if(F.col("kind") != "split").alias("leaves"), F.sum(F.when(F.col("kind") != "split", F.col("n_users")).otherwise(0)).alias("placements"), F.coalesce(F.sum("steps"), F.lit(0)).alias("steps")
    )


def degree_stats(edges: DataFrame) -> DataFrame:
    per = edges.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    return per.agg(F.count(F.lit(1)).alias("users"), F.avg("n").alias("mean"), F.min("n").alias("least"), F.percentile("n", 0.5).alias("median"), F.max("n").alias("most"))


def hop_histogram(dist: DataFrame) -> DataFrame:
    """(dist, pairs, share) with -1 for out of reach."""
    counts = dist.groupBy(F.coalesce("dist", F.lit(-1)).alias("dist")).agg(F.count(F.lit(1)).alias("pairs"))
    return counts.withColumn("share", F.col("pairs") / F.sum("pairs").over(Window.partitionBy()))  # a handful of rows


def lift(a: DataFrame, b: DataFrame, key: str, value: str) -> DataFrame:
    """Ratio of a measure of one method to another's at equal rounds or hops."""
    other = b.select(key, F.col(value).alias("__base"))
    return a.join(other, key).select(key, value, F.col("__base").alias("baseline"), F.try_divide(value, "__base").alias("lift"))


def technique_traits(spark) -> DataFrame:
    """Which traits each family of techniques has."""
    # The published table of traits.
    rows = [
        ("central trained index", True, False, False, False),
        ("decentralised trained index", True, False, True, False),
        ("hash ring", False, True, True, True),
        ("graph diffusion", True, False, True, True),
        ("semantic trie", True, True, True, True),
    ]
    return spark.createDataFrame(rows, "technique string, semantic boolean, predictive_cache boolean, distributed boolean, no_training boolean")
