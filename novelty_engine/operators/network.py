"""Networks of related items around targets."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship


def cap_neighbours(edges: DataFrame, parent: list[str], item: str = "item_id", by: str = "relevance", limit: int | None = 50) -> DataFrame:
    """At most `limit` neighbours of each parent: by relevance, newest first (`date`), or at random (`hash`); ties by id.

    The window limit is pushed below its shuffle, so a hub sends at most `limit` rows per task.
    """
    if limit is None:
        return edges
    first = {"relevance": F.desc("relevance"), "date": F.desc("pub_date"), "hash": F.xxhash64(item)}[by]
    rank = F.row_number().over(Window.partitionBy(*parent).orderBy(first, item))
    return edges.withColumn("rank_", rank).where(F.col("rank_") <= limit).drop("rank_")


def one_hop(links: DataFrame, targets: DataFrame, cap_refs: int | None = None, cap_cites: int | None = 50, by: str = "relevance") -> DataFrame:
    """References out of, and citations into, each target: (target_id, item_id, relation, layer, relevance)."""
    refs = targets.join(links, F.col("target_id") == F.col("src")).select("target_id", F.col("dst").alias("item_id"), "relevance")
    cites = targets.join(links, F.col("target_id") == F.col("dst")).select("target_id", F.col("src").alias("item_id"), "relevance")
    refs, cites = cap_neighbours(refs, ["target_id"], limit=cap_refs, by=by), cap_neighbours(cites, ["target_id"], limit=cap_cites, by=by)
    return refs.withColumn("relation", F.lit("reference")).unionByName(cites.withColumn("relation", F.lit("citation"))).withColumn("layer", F.lit(1)).select("target_id", "item_id", "relation", "layer", "relevance")


def layered_network(links: DataFrame, targets: DataFrame, depth: int = 2, cap_refs: int | None = None, cap_cites: int | None = 50) -> DataFrame:
    """References of references and citations of citations, never mixed; the least layer wins, then the reference; targets are left out."""
    layers = {"reference": [], "citation": []}
    for relation, start, end, cap in (("reference", "src", "dst", cap_refs), ("citation", "dst", "src", cap_cites)):
        front = targets.select("target_id", F.col("target_id").alias("from_"))
        for layer in range(1, depth + 1):
            step = front.join(links, F.col("from_") == F.col(start)).select("target_id", "from_", F.col(end).alias("item_id"), "relevance")
            step = cap_neighbours(step, ["target_id", "from_"], limit=cap).where("item_id <> target_id")
            reached = step.groupBy("target_id", "item_id").agg(F.max("relevance").alias("relevance"))
            layers[relation].append(reached.withColumn("relation", F.lit(relation)).withColumn("layer", F.lit(layer)))
            front = reached.select("target_id", F.col("item_id").alias("from_"))
    every = None
    for one in layers["reference"] + layers["citation"]:
        every = one if every is None else every.unionByName(one)
    best = F.min(F.struct("layer", (F.col("relation") == "citation").alias("is_citation"), (-F.col("relevance")).alias("minus")))
    return every.groupBy("target_id", "item_id").agg(best.alias("x")).select("target_id", "item_id", F.when(F.col("x.is_citation"), "citation").otherwise("reference").alias("relation"), F.col("x.layer").alias("layer"), (-F.col("x.minus")).alias("relevance"))


def restrict(network: DataFrame, relation: str | None = None, layer: int | None = None) -> DataFrame:
    out = network if relation is None else network.where(F.col("relation") == relation)
    return out if layer is None else out.where(F.col("layer") <= layer)


def require_body(network: DataFrame, items: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(kept, dropped): items without a body take no part."""
    bodied = items.where(F.trim(F.coalesce("body", F.lit(""))) != "").select("item_id")
    return network.join(bodied, "item_id", "left_semi"), network.join(bodied, "item_id", "left_anti")


def semantic_network(vectors: DataFrame, targets: DataFrame, top_k: int = 20, min_sim: float = 0.0, block: int = 2048) -> DataFrame:
    """Nearest vectors of each target instead of links: targets and vectors are dealt to blocks, each pair of blocks is one matrix
    product that keeps the `top_k` of each target (ties by id), and these meet in one small window a target."""
    ship(vectors.sparkSession)
    rows = vectors.select(F.col("item_id").cast("bigint").alias("id"), F.transform("vec", lambda x: x.cast("double")).alias("vec"))
    chosen = rows.join(targets.select(F.col("target_id").alias("id")).distinct(), "id")
    n_rows, n_targets = (max(1, -(-df.count() // block)) for df in (rows, chosen))
    own = lambda n: F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    dealt = rows.select("id", "vec", F.lit(False).alias("asks"), every(n_targets).alias("i"), own(n_rows).alias("j")).unionByName(chosen.select("id", "vec", F.lit(True).alias("asks"), own(n_targets).alias("i"), every(n_rows).alias("j")))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        group = group.sort_values("id", kind="stable")
        asks, has = group[group["asks"]], group[~group["asks"]]
        if not len(asks) or not len(has):
            return pd.DataFrame({"target_id": [], "item_id": [], "relevance": []})
        sim = np.round(np.stack(asks["vec"].to_numpy()) @ np.stack(has["vec"].to_numpy()).T, 6)
        ids, askers = has["id"].to_numpy(), asks["id"].to_numpy()
        sim[askers[:, None] == ids[None, :]] = -np.inf
        best = np.argsort(-sim, axis=1, kind="stable")[:, :top_k]
        out = pd.DataFrame({"target_id": np.repeat(askers, best.shape[1]), "item_id": ids[best].ravel(), "relevance": np.take_along_axis(sim, best, axis=1).ravel()})
        return out[out["relevance"] >= min_sim]

    near = dealt.groupBy("i", "j").applyInPandas(run, "target_id bigint, item_id bigint, relevance double")
    return cap_neighbours(near, ["target_id"], limit=top_k).select("target_id", "item_id", F.lit("similar").alias("relation"), F.lit(1).alias("layer"), "relevance")


def network_profile(network: DataFrame, items: DataFrame) -> DataFrame:
    """Size by target, relation, layer and year."""
    return network.join(items.select("item_id", "year"), "item_id").groupBy("target_id", "relation", "layer", "year").agg(F.count("*").alias("n"))


def most_linked(links: DataFrame, n: int) -> DataFrame:
    """The `n` items with most links in and out; ties by smaller id."""
    ends = links.select(F.col("src").alias("target_id")).union(links.select("dst"))
    return ends.groupBy("target_id").agg(F.count("*").alias("n_links")).orderBy(F.desc("n_links"), "target_id").limit(n)
