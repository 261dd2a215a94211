"""Sinks: bucketed tables, call log, graph text."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int = 64, mode: str = "overwrite") -> None:
    """A table whose joins and aggregations on `by` need no exchange."""
    df.write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def append_calls(calls: DataFrame, path: str) -> None:
    """Append to the call log, JSON lines."""
    calls.write.mode("append").json(path)


def dot_lines(forest: DataFrame, nodes: DataFrame, key: str = "pos", label: str = "value") -> DataFrame:
    """Lines of a DOT digraph, ordered by `place`: nodes, then edges.  The text stays distributed."""
    quoted = F.concat(F.lit('"'), F.regexp_replace(F.col(label), '"', "'"), F.lit('"'))
    rows = nodes.select(F.lit(1).alias("place"), F.concat(F.lit("  n"), F.col(key).cast("string"), F.lit(" [label="), quoted, F.lit("];")).alias("line"))
    edges = forest.select(F.lit(2).alias("place"), F.concat(F.lit("  n"), F.col("src").cast("string"), F.lit(" -> n"), F.col("dst").cast("string"), F.lit(" [weight="), F.col("sigma").cast("string"), F.lit("];")).alias("line"))
    spark = forest.sparkSession
    ends = spark.createDataFrame([(0, "digraph forest {"), (3, "}")], "place int, line string")
    return ends.unionByName(rows).unionByName(edges)


def graphml_lines(forest: DataFrame, nodes: DataFrame, key: str = "pos") -> DataFrame:
    """Lines of a GraphML document, ordered by `place`."""
    spark = forest.sparkSession
    ends = spark.createDataFrame([(0, '<graphml xmlns="http://graphml.graphdrawing.org/xmlns"><graph edgedefault="directed">'), (3, "</graph></graphml>")], "place int, line string")
    rows = nodes.select(F.lit(1).alias("place"), F.format_string('<node id="n%d"/>', F.col(key)).alias("line"))
    edges = forest.select(F.lit(2).alias("place"), F.format_string('<edge source="n%d" target="n%d"/>', "src", "dst").alias("line"))
    return ends.unionByName(rows).unionByName(edges)
