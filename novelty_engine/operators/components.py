"""Connected components on edge tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut_lineage, release, ship

#: Rows of edges or pointers in one partition, for tables that each round reads again.
PARTITION_ROWS = 1_000_000
#: Up to this many edges (16 bytes each) one task joins them; more go in distributed rounds.
ONE_TASK_EDGES = 1 << 20


def least_nodes(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component), sorted by node."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    a, b = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        one, two = label[a], label[b]
        live = one != two
        if not live.any():
            return nodes, nodes[label]
        a, b, one, two = a[live], b[live], one[live], two[live]
        np.minimum.at(label, np.maximum(one, two), np.minimum(one, two))
        while (further := label[label]).tobytes() != label.tobytes():
            label = further


def _in_one_task(edges: DataFrame) -> DataFrame:
    """(node, label) of edges(a, b) that fit into one task."""
    kind = edges.schema["a"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs = [(x.column("a").to_numpy(), x.column("b").to_numpy()) for x in batches if x.num_rows]
        if pairs:
            found = least_nodes(*(np.concatenate(x) for x in zip(*pairs)))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["node", "label"])

    ship(edges.sparkSession)
    return edges.coalesce(1).mapInArrow(run, f"node {kind}, label {kind}")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of `edges(a, b)` as (node, label): the least node reachable from each.

    Every node points to a smaller node of its component or to itself.  In each round a node and the node it points to
    take the least node that its neighbours' pointers point to, and pointers are followed one step.  Pointers only fall; when
    none has moved they are equal across every edge, so they are the least nodes.  Rounds grow with the logarithm of a
    component's width.  All of it stays distributed; a round is one job and the driver sees one test.

    Whole-numbered edges of at most ONE_TASK_EDGES rows are joined in one task instead: rounds over few rows cost as many
    tasks, shuffle files and log entries as rounds over many.
    """
    given = cut_lineage(edges.select("a", "b").where("a is not null and b is not null"))
    kinds = {f.dataType.simpleString() for f in given.schema.fields}
    if kinds in ({"bigint"}, {"int"}) and given.count() <= ONE_TASK_EDGES:
        return cut_lineage(_in_one_task(given))
    both = cut_lineage(given.union(given.select("b", "a")).distinct())
    parts = 8 + both.count() // PARTITION_ROWS
    both = both.coalesce(parts)
    points = cut_lineage(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("node")).alias("label")).coalesce(parts))
    for _ in range(max_rounds):
        further = points.join(points.select(F.col("node").alias("label"), F.col("label").alias("far")), "label").select("node", "label", "far")
        near = both.join(further.select(F.col("node").alias("b"), "far"), "b").groupBy(F.col("a").alias("node")).agg(F.min("far").alias("near"))
        offers = further.join(near, "node").select("node", "label", F.least("far", "near").alias("low"))
        taken = offers.select("node", "low", F.col("label").alias("old")).union(offers.select("label", "low", F.lit(None).cast(points.schema["label"].dataType)))
        points = cut_lineage(taken.groupBy("node").agg(F.min("low").alias("label"), F.max("old").alias("old")).coalesce(parts))
        if not points.where("label < old").limit(1).count():
            return points.select("node", "label")
        points = points.select("node", "label")
        release(edges.sparkSession)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
