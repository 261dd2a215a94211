"""Table functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult, OrderingColumn, PartitioningColumn, udtf
from pyspark.sql.types import IntegerType, LongType, StructType

from ..session import ship


class NoveltyTimeline:
    """`SELECT * FROM novelty_timeline(TABLE(t))` over a table with columns series, pos, v: adds s and nu.

    The table is partitioned by series and ordered by pos, so any number of series run side by side.
    """

    def __init__(self):
        self.best, self.nu = None, 0

    @staticmethod
    def analyze(rows: AnalyzeArgument) -> AnalyzeResult:
        schema = StructType([*rows.dataType.fields]).add("s", IntegerType()).add("nu", LongType())
        return AnalyzeResult(schema=schema, partitionBy=[PartitioningColumn("series")], orderBy=[OrderingColumn("pos")])

    def eval(self, row: Row) -> Iterator[tuple]:
        v, s = row["v"], None
        if v is not None:
            s = 1 if self.best is None or v > self.best else 0 if v == self.best else -1
            if s == 1:
                self.best, self.nu = v, self.nu + 1
        yield (*row, s, self.nu)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.udtf.register("novelty_timeline", udtf(NoveltyTimeline))
