"""Ranks over a whole table without sending it to one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BUCKETS = 64


def global_rank(df: DataFrame, value: str, tie: str, *, descending: bool = False, out: str = "rank") -> DataFrame:
    """Add the 1-based position by (value, tie).

    Rows fall into value ranges cut at approximate quantiles; ranks inside a
    range are local, and a range's offset is the count before it.  Equal values
    stay in one range.  Null values come last.
    """
    cuts = df.agg(F.percentile_approx(F.col(value).cast("double"), [i / BUCKETS for i in range(1, BUCKETS)]).alias("c")).first()["c"] or []
    v = F.col(value).cast("double")
    bucket = F.size(F.filter(F.array(*[F.lit(c) for c in cuts]).cast("array<double>"), lambda c: c < v)) if cuts else F.lit(0)
    last = F.lit(BUCKETS + 1)
    bucket = F.when(v.isNull(), last).otherwise(F.lit(BUCKETS) - bucket if descending else bucket).cast("int")
    keyed = df.withColumn("__bucket", bucket)
    sizes = keyed.groupBy("__bucket").agg(F.count(F.lit(1)).alias("__n"))  # at most BUCKETS + 2 rows
    before = sizes.select("__bucket", F.coalesce(F.sum("__n").over(Window.orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"))
    order = F.col(value).desc_nulls_last() if descending else F.col(value).asc_nulls_last()
    local = F.row_number().over(Window.partitionBy("__bucket").orderBy(order, tie))
    return keyed.withColumn("__local", local).join(F.broadcast(before), "__bucket").withColumn(out, F.col("__before") + F.col("__local")).drop("__bucket", "__local", "__before")
