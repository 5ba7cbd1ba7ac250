"""Reading and writing users' own logs, and the trie's tables as partitioned and bucketed files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ACCESS = "user_id bigint, doc_id string, ts timestamp, query string"
FORMATS = ("csv", "json", "orc", "parquet", "text")


def read_access(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = ACCESS, **options) -> DataFrame:
    """An access log with an explicit schema; text lines are user, document, time and query parted by tabs."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    if fmt == "text":
        parts = F.split("value", "\t")
        return spark.read.text(path).select(F.get(parts, F.lit(0)).try_cast("bigint").alias("user_id"), F.get(parts, F.lit(1)).alias("doc_id"), F.get(parts, F.lit(2)).try_cast("timestamp").alias("ts"), F.get(parts, F.lit(3)).alias("query"))
    return spark.read.schema(schema).options(**options).format(fmt).load(path)


def write_access(access: DataFrame, path: str, fmt: str = "parquet", **options) -> None:
    if fmt == "text":
        access = access.select(F.concat_ws("\t", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in ("user_id", "doc_id", "ts", "query")]).alias("value"))
    access.write.mode("overwrite").options(**options).format(fmt).save(path)


def write_placements(placements: DataFrame, path: str, prefix: int = 4) -> None:
    """Placements by path prefix, so that a search around a leaf prunes to few folders."""
    placements.withColumn("path_prefix", F.substring(F.concat("path", F.lit("----------------")), 1, prefix)).repartition("path_prefix").write.mode("overwrite").partitionBy("path_prefix").parquet(path)


def append_level(nodes: DataFrame, path: str, level: int) -> None:
    """Nodes of one depth; writing a level again replaces it, so a restarted build repeats nothing."""
    nodes.filter(F.col("depth") == level).drop("depth").write.mode("overwrite").parquet(f"{path}/depth={level}")


def save_bucketed(df: DataFrame, name: str, column: str = "user_id", buckets: int = 32) -> None:
    """A table bucketed by user: later joins and windows by user need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).saveAsTable(name)
