"""Reader of synthetic overlay graphs: ``spark.read.format("pa_graph").option("users", n).option("m", m)``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class PaGraphSource(DataSource):
    """Preferential-attachment edges over user numbers 0 to users - 1, one direction, loops left out."""

    @classmethod
    def name(cls) -> str:
        return "pa_graph"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema):
        return _PaReader(self.options)


class _PaReader(DataSourceReader):
    def __init__(self, options):
        self.users, self.m = int(options["users"]), int(options["m"])
        self.seed, self.parts = int(options.get("seed", 42)), int(options.get("partitions", 8))

    def partitions(self):
        edges = self.users * self.m
        return [_Range(edges * i // self.parts, edges * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, partition):
        from semtrie.operators.overlay import resolve_slot

        for e in range(partition.lo, partition.hi):
            src, dst = e // self.m, resolve_slot(2 * e + 1, self.seed) // self.m
            if src != dst:
                yield (src, dst)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PaGraphSource)
