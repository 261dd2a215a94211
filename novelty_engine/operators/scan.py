"""Order over a whole table without a single task: positions, running sums and ranks.

Rows are cut into ranges of the order and sorted inside each; a table with one row a range carries counts or sums from
range to range.  Only that small table ever meets in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut_lineage

_ROW_BITS = 33  # monotonically_increasing_id: partition above, place in the partition below


def ranged(df: DataFrame, *order: Column | str, rows_a_range: int = 2_000_000) -> DataFrame:
    """df plus `range_` and `place_` (from 0): ranges ascend with the order, places inside a range too.  Checkpointed."""
    held = cut_lineage(df)
    ranges = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-held.count() // rows_a_range))
    placed = held.repartitionByRange(ranges, *order).sortWithinPartitions(*order).withColumn("at_", F.monotonically_increasing_id())
    split = placed.withColumn("range_", F.shiftright("at_", _ROW_BITS)).withColumn("place_", F.col("at_").bitwiseAND(F.lit((1 << _ROW_BITS) - 1)))
    return cut_lineage(split.drop("at_"))


def _before(totals: DataFrame, value: str) -> DataFrame:
    """(range_, before_): sum of `value` over the ranges ahead; one row a range."""
    ahead = Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)
    return totals.select("range_", F.coalesce(F.sum(value).over(ahead), F.lit(0)).alias("before_"))


def numbered(df: DataFrame, *order: Column | str, name: str = "pos") -> DataFrame:
    """df plus its dense position from 1 in a total order."""
    rows = ranged(df, *order)
    sizes = rows.groupBy("range_").agg(F.count("*").alias("n_"))
    return rows.join(F.broadcast(_before(sizes, "n_")), "range_").withColumn(name, F.col("before_") + F.col("place_") + 1).drop("range_", "place_", "before_")


def running(df: DataFrame, order: Column | str, value: str, name: str) -> DataFrame:
    """df plus the sum of an integer `value` over the rows ahead; the order has no ties."""
    rows = ranged(df, order)
    offsets = F.broadcast(_before(rows.groupBy("range_").agg(F.sum(value).alias("n_")), "n_"))
    inside = Window.partitionBy("range_").orderBy("place_").rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("own_", F.coalesce(F.sum(value).over(inside), F.lit(0))).join(offsets, "range_").withColumn(name, F.col("before_") + F.col("own_")).drop("range_", "place_", "before_", "own_")


def ranks(df: DataFrame, value: str, name: str, descending: bool = True, average: bool = False) -> DataFrame:
    """df plus the rank of `value`: one more than the number of better rows, or the mean rank of ties.

    Ranks come from the counts of distinct values, so only those are put in order.
    """
    counts = df.groupBy(F.col(value).alias("v_")).agg(F.count("*").alias("c_"))
    order = F.col("v_").desc_nulls_last() if descending else F.col("v_").asc_nulls_last()
    placed = running(counts, order, "c_", "ahead_")
    rank = F.col("ahead_") + (F.col("c_") + 1) / 2 if average else (F.col("ahead_") + 1).cast("bigint")
    return df.join(placed.select("v_", rank.alias(name)), F.col(value).eqNullSafe(F.col("v_"))).drop("v_")


def neighbours(df: DataFrame, key: str, name: str) -> DataFrame:
    """(key, name): the next lower key, null for the lowest.  Keys are unique and not null."""
    rows = ranged(df.select(key), key)
    inside = rows.withColumn("below_", F.lag(key).over(Window.partitionBy("range_").orderBy("place_")))
    ends = rows.groupBy("range_").agg(F.max(key).alias("top_"))
    chain = ends.select("range_", F.max("top_").over(Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)).alias("last_"))
    return inside.join(F.broadcast(chain), "range_").select(key, F.coalesce("below_", "last_").alias(name))
