"""Decisions the optimizer cannot take, from counted sizes; and a look at executed plans."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class BuildPlan:
    """How a trie of ``users`` vectors is built: rows per finishing task, outer levels, bytes of centres on the widest level."""

    local_rows: int
    outer_levels: int
    centre_mb: float


def plan_build(users: int, dim: int, *, capacity: int = 50, mean_placements: float = 1.4, task_mb: int = 256) -> BuildPlan:
    """Rows that fit one finishing task (vectors plus working copies), and what that means for the outer loop."""
    row_bytes = 8 * dim * 4
    local = max(4 * capacity, int(task_mb * 1e6 / row_bytes))
    parts = max(1.0, users * mean_placements / local)
    levels = 0
    while 2**levels < 2 * parts and parts > 1:
        levels += 1
    return BuildPlan(local, levels, 2 ** max(0, levels - 1) * 2 * dim * 8 / 1e6)


def shuffled_bytes(spark) -> int:
    """Bytes that the session's tasks have written to shuffles so far: the difference over a step is its traffic."""
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(found.apply(i).totalShuffleWrite() for i in range(found.size()))


def executed_plan(df: DataFrame) -> str:
    """The formatted physical plan, for assertions on pushed filters, read schemas, joins and exchanges."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
