"""Evolution of one axis: similar values, density clusters, confidence graph, forest, lineages.

Nodes are winners with a position, a value and a date.  Every step is a join or an aggregate over the edges that can exist:
token pairs come from an inverted index with prefix filtering, vector pairs from blocks, low-overlap pairs of one cluster
from neighbours in time only (an exact pruning), and the forest from rounds in which every component picks its best edge.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from math import acos, ceil, log, pi

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import confidence, edge_score
from ..session import cut_lineage, ship
from .components import components


def jaccard_pairs(nodes: DataFrame, threshold: float, key: str = "pos", tokens: str = "tokens") -> DataFrame:
    """(a, b, sim) with a < b and Jaccard of distinct tokens at least `threshold` (sim rounded to 6 places).

    Tokens are ranked from rare to frequent; two sets that similar share a token among the first
    |x| - ceil(threshold |x|) + 1 of each, so only those prefixes are joined.
    """
    sets = nodes.select(F.col(key).alias("id"), F.array_distinct(tokens).alias("set")).where(F.size("set") > 0)
    counts = sets.select(F.explode("set").alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    ranked = sets.select("id", F.size("set").alias("size"), F.explode("set").alias("token")).join(counts, "token").withColumn("place", F.row_number().over(Window.partitionBy("id").orderBy("n", "token")))
    prefix = ranked.where(F.col("place") <= F.col("size") - F.ceil(F.col("size") * (threshold - 1e-9)) + 1).select("token", "id", "size")
    left, right = prefix.select("token", F.col("id").alias("a"), F.col("size").alias("size_a")), prefix.select("token", F.col("id").alias("b"), F.col("size").alias("size_b"))
    close = (F.col("size_a") >= (threshold - 1e-9) * F.col("size_b")) & (F.col("size_b") >= (threshold - 1e-9) * F.col("size_a"))
    candidates = left.join(right, "token").where((F.col("a") < F.col("b")) & close).select("a", "b").distinct()
    both = candidates.join(sets.select(F.col("id").alias("a"), F.col("set").alias("set_a")), "a").join(sets.select(F.col("id").alias("b"), F.col("set").alias("set_b")), "b")
    sim = F.round(F.size(F.array_intersect("set_a", "set_b")) / F.size(F.array_union("set_a", "set_b")), 6)
    return both.select("a", "b", sim.alias("sim")).where(F.col("sim") >= threshold)


def vector_pairs(vectors: DataFrame, threshold: float, key: str = "item_id", vec: str = "vec", metric: str = "cosine", block: int = 2048, within: str | None = None) -> DataFrame:
    """(a, b, sim) of all pairs within a threshold, exactly: vectors are dealt to blocks of about `block`, and each pair of blocks is one
    matrix product.  With `within` only pairs of one group are compared, every group in blocks of its own.

    Work grows with the square of a group, so it is for axes (winners), not corpora; `search_pairs` answers chosen
    queries beyond.  Euclidean distances are passed as negative similarity.
    """
    ship(vectors.sparkSession)
    plain = vectors.select(F.col(key).cast("bigint").alias("id"), F.transform(vec, lambda x: x.cast("double")).alias("vec"), (F.col(within) if within else F.lit(0)).alias("g"))
    sizes = plain.groupBy("g").agg(F.ceil(F.count("*") / F.lit(block)).cast("int").alias("blocks"))
    placed = plain.join(sizes, "g").withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    dealt = placed.withColumn("k", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("g", "id", "vec", "own", F.least("own", "k").alias("i"), F.greatest("own", "k").alias("j"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        group = group.sort_values("id", kind="stable")
        i, j = group["i"].iloc[0], group["j"].iloc[0]
        left, right = (group[group["own"] == k] for k in (i, j))
        if not len(left) or not len(right):
            return pd.DataFrame({"a": [], "b": [], "sim": []})
        x, y = np.stack(left["vec"].to_numpy()), np.stack(right["vec"].to_numpy())
        square_x, square_y = (x * x).sum(axis=1), (y * y).sum(axis=1)
        if metric == "cosine":
            with np.errstate(invalid="ignore", divide="ignore"):
                sim = (x @ y.T) / np.sqrt(square_x[:, None] * square_y[None, :])
        else:
            sim = -np.sqrt(np.maximum(0.0, square_x[:, None] + square_y[None, :] - 2 * (x @ y.T)))
        sim = np.round(sim, 6)
        p, q = np.nonzero(sim >= threshold)
        ids = left["id"].to_numpy()[p], right["id"].to_numpy()[q]
        keep = ids[0] < ids[1] if i == j else ids[0] != ids[1]
        return pd.DataFrame({"a": np.minimum(*ids)[keep], "b": np.maximum(*ids)[keep], "sim": sim[p, q][keep]})

    return dealt.groupBy("g", "i", "j").applyInPandas(run, "a bigint, b bigint, sim double")


Relater = Callable[[DataFrame, DataFrame], DataFrame]


def judged_pairs(judge: Callable[[Column, Column], Column], key: str = "pos", value: str = "value") -> Relater:
    """A relater: of candidate pairs(a, b) those whose two values `judge` calls related.  Any symmetric column expression will do,
    a pandas function over a model included."""

    def run(nodes: DataFrame, candidates: DataFrame) -> DataFrame:
        left, right = (nodes.select(F.col(key).alias(k), F.col(value).alias(f"{k}_value")) for k in "ab")
        return candidates.select("a", "b").join(left, "a").join(right, "b").where(judge(F.col("a_value"), F.col("b_value"))).select("a", "b")

    return run


def _searched(queries: DataFrame, vectors: DataFrame, key: str, vec: str, judge: Callable, schema: str, rows: int, block: int) -> DataFrame:
    """`judge(query ids, unit queries, item ids, unit items)` on every block of queries and shard of items; vectors travel as floats, pairs do not.

    A shard has about `rows` items (fewer while there are few shards), a block `block` queries: items are copied once a block, queries once a shard.
    """
    ship(vectors.sparkSession)
    plain = lambda df: df.where(F.col(vec).isNotNull()).select(F.col(key).cast("bigint").alias("id"), F.col(vec).cast("array<float>").alias("vec"))
    items, asked = plain(vectors), plain(queries)
    n = items.count()
    shards, blocks = max(-(-n // rows), min(24, -(-n // 2048)), 1), max(1, -(-asked.count() // block))
    place = lambda parts: F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    dealt = items.select("id", "vec", F.lit(False).alias("asks"), place(shards).alias("i"), every(blocks).alias("j")).unionByName(asked.select("id", "vec", F.lit(True).alias("asks"), every(shards).alias("i"), place(blocks).alias("j")))

    names = pa.schema([(name, pa.float64() if kind == "double" else pa.int64()) for name, kind in (x.split() for x in schema.split(", "))])

    def run(group: pa.Table) -> pa.Table:
        asks = group.column("asks").to_numpy()
        ids, column = group.column("id").to_numpy(), group.column("vec").combine_chunks()
        flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(ids), -1)
        with np.errstate(invalid="ignore", divide="ignore"):
            unit = flat / np.sqrt((flat * flat).sum(axis=1))[:, None]
        parts = [names.empty_table()]
        if asks.any() and not asks.all():
            who, asked_for, at = ids[asks], unit[asks], ids[~asks]
            found = judge(unit[~asks])
            for k in range(0, len(who), 256):
                parts.append(pa.table(found(who[k : k + 256], asked_for[k : k + 256], at), schema=names))
        return pa.concat_tables(parts)

    return dealt.groupBy("i", "j").applyInArrow(run, schema)


def _exact_hits(x: np.ndarray, y: np.ndarray, threshold: float) -> np.ndarray:
    """Marks of the pairs of unit vectors whose cosine, rounded to 6 places, is at least the threshold."""
    return x @ y.T >= threshold - 5e-7


class SignIndex:
    """Tables of items by the signs of hashed random projections.

    Two vectors at the threshold agree in one sign with p = 1 - angle / pi, so 1 - (1 - p**bits)**tables of their pairs are
    found; the number of tables follows from the recall asked for.  More bits suit higher thresholds.
    """

    def __init__(self, items: np.ndarray, threshold: float, recall: float = 0.97, bits: int = 5):
        agree = (1 - acos(max(-1.0, min(1.0, threshold))) / pi) ** bits
        self.tables = 1 if agree >= recall else ceil(log(1 - recall) / log(1 - agree))
        self.items, self.threshold, self.bits = items, threshold, bits
        self.planes = np.array([[1.0 if hash_bit(t, b, j) else -1.0 for j in range(items.shape[1])] for t in range(self.tables) for b in range(bits)])
        codes = self.codes(items)
        self.order = np.argsort(codes, axis=0, kind="stable")
        self.cuts = [np.searchsorted(codes[self.order[:, t], t], np.arange(2**bits + 1)) for t in range(self.tables)]

    def codes(self, x: np.ndarray) -> np.ndarray:
        """Bucket of each vector in each table."""
        signs = (x @ self.planes.T >= 0).reshape(len(x), self.tables, self.bits)
        return signs @ (1 << np.arange(self.bits))

    def hits(self, x: np.ndarray) -> np.ndarray:
        """Marks of the pairs within the threshold that share a bucket; every candidate is checked exactly."""
        out, codes = np.zeros((len(x), len(self.items)), bool), self.codes(x)
        for t in range(self.tables):
            for code in np.unique(codes[:, t]).tolist():
                asks = np.flatnonzero(codes[:, t] == code)
                bucket = self.order[self.cuts[t][code] : self.cuts[t][code + 1], t]
                p, q = np.nonzero(_exact_hits(x[asks], self.items[bucket], self.threshold))
                out[asks[p], bucket[q]] = True
        return out


def search_pairs(queries: DataFrame, vectors: DataFrame, threshold: float, key: str = "item_id", vec: str = "vec", approximate: bool = False, rows: int = 32768, block: int = 16384) -> DataFrame:
    """(query, item, sim) of all items within a threshold of a query, itself excepted: by brute force, or by a sign index over every row."""

    def judge(items: np.ndarray) -> Callable:
        find = SignIndex(items, threshold).hits if approximate else lambda x: _exact_hits(x, items, threshold)

        def found(who: np.ndarray, x: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
            p, q = np.nonzero(find(x) & (who[:, None] != at[None, :]))
            return [who[p], at[q], np.round((x[p] * items[q]).sum(axis=1), 6)]

        return found

    return _searched(queries, vectors, key, vec, judge, "query bigint, item bigint, sim double", rows, block)


def search_recall(queries: DataFrame, vectors: DataFrame, threshold: float, key: str = "item_id", vec: str = "vec", rows: int = 32768, block: int = 16384) -> DataFrame:
    """(n_exact, recall): of the pairs that `search_pairs` finds by brute force, the share that the sign index finds.

    Both searches run side by side in each shard and only their counts leave it.
    """

    def judge(items: np.ndarray) -> Callable:
        index = SignIndex(items, threshold)

        def found(who: np.ndarray, x: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
            exact = _exact_hits(x, items, threshold) & (who[:, None] != at[None, :])
            return [who, exact.sum(axis=1), (exact & index.hits(x)).sum(axis=1)]

        return found

    counts = _searched(queries, vectors, key, vec, judge, "query bigint, n_exact bigint, n_found bigint", rows, block)
    total = counts.agg(F.coalesce(F.sum("n_exact"), F.lit(0)).alias("n_exact"), F.sum("n_found").alias("n_found"))
    return total.select("n_exact", F.round(F.try_divide("n_found", "n_exact"), 6).alias("recall"))


def hash_bit(t: int, b: int, j: int) -> bool:
    x = (t * 1_000_003 + b * 10_007 + j * 101 + 12345) * 0x9E3779B97F4A7C15 & (1 << 64) - 1
    x = (x ^ x >> 29) * 0xBF58476D1CE4E5B9 & (1 << 64) - 1
    return bool(x >> 40 & 1)


def dbscan(nodes: DataFrame, pairs: DataFrame, min_pts: int, key: str = "pos") -> DataFrame:
    """(node, is_core, cluster): cluster is the least core node of its component, null for noise.

    A node counts itself among its neighbours; a border node joins the cluster with the least label among its core neighbours.
    """
    ids = nodes.select(F.col(key).alias("node")).distinct()
    once = cut_lineage(pairs.select("a", "b"))
    both = once.union(once.select(F.col("b").alias("a"), F.col("a").alias("b")))
    degree = both.groupBy(F.col("a").alias("node")).agg((F.count("*") + 1).alias("n"))
    core = cut_lineage(ids.join(degree, "node", "left").where(F.coalesce("n", F.lit(1)) >= min_pts).select("node"))
    inner = both.join(core.select(F.col("node").alias("a")), "a", "left_semi").join(core.select(F.col("node").alias("b")), "b", "left_semi")
    grouped = components(inner)
    labels = core.join(grouped, "node", "left").select("node", F.coalesce("label", "node").alias("label"))
    border = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
    out = ids.join(labels, "node", "left").join(border, "node", "left")
    return out.select("node", F.col("label").isNotNull().alias("is_core"), F.coalesce("label", "near").alias("cluster"))


def threshold_clusters(nodes: DataFrame, pairs: DataFrame, key: str = "pos") -> DataFrame:
    """Single-link alternative: components of the similarity graph."""
    return nodes.select(F.col(key).alias("node")).join(components(pairs), "node", "left").select("node", F.coalesce("label", "node").alias("cluster"))


def kmeans(vectors: DataFrame, k: int, seed: int = 1, vec: str = "vec") -> DataFrame:
    """k-means alternative."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = vectors.withColumn("features", array_to_vector(F.col(vec)))
    return KMeans(k=k, seed=seed).fit(rows).transform(rows).drop("features").withColumnRenamed("prediction", "cluster")


def confidence_graph(nodes: DataFrame, clusters: DataFrame, overlapping: DataFrame, related: DataFrame, prune: bool = False) -> DataFrame:
    """(src, dst, conf, gap) for pairs of confidence above 0, earlier to later.

    nodes(pos, period), clusters(node, cluster), overlapping(a, b) and related(a, b).  Same-cluster pairs come from a join within
    clusters; `prune` keeps, of those with low overlap, only neighbours in time, which never changes the forest.
    """
    labelled = nodes.select("pos", "period").join(clusters.select(F.col("node").alias("pos"), "cluster"), "pos")
    marks = overlapping.select("a", "b", F.lit(True).alias("high"), F.lit(False).alias("rel")).union(related.select("a", "b", F.lit(False), F.lit(True)))
    inside = labelled.where("cluster is not null")
    if prune:
        ahead = Window.partitionBy("cluster").orderBy("pos")
        mates = inside.select(F.col("pos").alias("a"), F.lead("pos").over(ahead).alias("b")).where("b is not null")
    else:
        mates = inside.select("cluster", F.col("pos").alias("a")).join(inside.select("cluster", F.col("pos").alias("b")), "cluster").where("a < b").select("a", "b")
    marks = marks.union(mates.select("a", "b", F.lit(False), F.lit(False)))
    pairs = marks.groupBy("a", "b").agg(F.bool_or("high").alias("high"), F.bool_or("rel").alias("rel"))
    ends = pairs.join(labelled.select(F.col("pos").alias("a"), F.col("cluster").alias("ca"), F.col("period").alias("pa")), "a").join(labelled.select(F.col("pos").alias("b"), F.col("cluster").alias("cb"), F.col("period").alias("pb")), "b")
    scored = ends.withColumn("conf", confidence(F.col("ca"), F.col("cb"), F.col("high"), F.col("rel"))).where("conf > 0")
    return scored.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("conf").cast("int").alias("conf"), (F.col("pb") - F.col("pa")).cast("int").alias("gap"))


def scored_edges(graph: DataFrame, gamma: float = 1.0, delta: float = 1.0) -> DataFrame:
    return graph.withColumn("sigma", F.round(edge_score(F.col("conf"), F.col("gap"), gamma, delta), 6))


def kruskal(edges: Iterable[tuple[float, int, int]]) -> list[int]:
    """Places of the chosen edges among (sigma, src, dst): best score, then smallest distance, source and destination."""
    rows = list(edges)
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for at in sorted(range(len(rows)), key=lambda i: (-rows[i][0], rows[i][2] - rows[i][1], rows[i][1], rows[i][2])):
        a, b = find(rows[at][1]), find(rows[at][2])
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append(at)
    return out


def temporal_forest(edges: DataFrame, engine: str = "auto", keys: list[str] | None = None, max_rounds: int = 40, most_edges: int = 4_000_000) -> DataFrame:
    """Maximum spanning forest of edges(src, dst, sigma); ties: smallest distance, source, destination, so it is unique.

    `auto`: `filter` up to `most_edges` edges, `boruvka` above.  `filter`: forests of slices, merged eightfold until one is left; an edge rejected in a slice is rejected everywhere, so a
    task holds at most eight forests, whose size is the number of winners and not of edges.  `boruvka`: rounds in which each
    component takes its best outgoing edge; for axes with too many winners for one task.  `kruskal`: one group.  With `keys`
    the last two make a forest for each value of the keys; nodes that are numbered apart need none.
    """
    if engine == "auto":
        edges = cut_lineage(edges)
        engine = "filter" if edges.count() <= most_edges else "boruvka"
    if engine == "boruvka":
        return _boruvka(edges, max_rounds)
    if engine == "filter":
        ship(edges.sparkSession)
        for slices in (64, 8, 1):
            slice_ = F.pmod(F.xxhash64("src", "dst"), F.lit(slices))
            edges = edges.withColumn("slice_", slice_).groupBy(*(keys or []), "slice_").applyInPandas(_group_kruskal(edges.columns), edges.schema)
        return edges
    if engine == "kruskal":
        ship(edges.sparkSession)
        grouped = edges.groupBy(*keys) if keys else edges.withColumn("all_", F.lit(1)).groupBy("all_")
        return grouped.applyInPandas(_group_kruskal(edges.columns), edges.schema)
    raise ValueError("engine is auto, boruvka, kruskal or filter")


def _group_kruskal(columns: list[str]):
    def run(group: pd.DataFrame) -> pd.DataFrame:
        return group.iloc[kruskal(zip(group["sigma"], group["src"], group["dst"]))][columns]

    return run


def _boruvka(edges: DataFrame, max_rounds: int) -> DataFrame:
    rest = cut_lineage(edges)
    ranks = F.struct((-F.col("sigma")).alias("o0"), (F.col("dst") - F.col("src")).alias("o1"), F.col("src").alias("o2"), F.col("dst").alias("o3"))
    live = cut_lineage(rest.select(ranks.alias("r"), F.col("src").alias("ca"), F.col("dst").alias("cb")))
    chosen = None
    for _ in range(max_rounds):
        if not live.limit(1).count():
            break
        best = live.select(F.col("ca").alias("c"), "r").union(live.select(F.col("cb").alias("c"), "r")).groupBy("c").agg(F.min("r").alias("r"))
        picked = cut_lineage(best.select("r").distinct())
        chosen = picked if chosen is None else cut_lineage(chosen.union(picked))
        joined = components(live.join(picked, "r", "left_semi").select(F.col("ca").alias("a"), F.col("cb").alias("b")))
        moved = live.join(joined.select(F.col("node").alias("ca"), F.col("label").alias("la")), "ca", "left").join(joined.select(F.col("node").alias("cb"), F.col("label").alias("lb")), "cb", "left")
        live = cut_lineage(moved.select("r", F.coalesce("la", "ca").alias("ca"), F.coalesce("lb", "cb").alias("cb")).where("ca <> cb"))
    if chosen is None:
        return rest
    kept = chosen.select(F.col("r.o2").alias("src"), F.col("r.o3").alias("dst"))
    return rest.join(kept, ["src", "dst"], "left_semi")


def arborescence(edges: DataFrame) -> DataFrame:
    """Alternative: the best incoming edge of each node only."""
    rank = F.row_number().over(Window.partitionBy("dst").orderBy(F.desc("sigma"), F.col("dst") - F.col("src"), "src"))
    return edges.withColumn("rank_", rank).where("rank_ = 1").drop("rank_")


def forest_roots(nodes: DataFrame, forest: DataFrame, key: str = "pos") -> DataFrame:
    """Nodes without an incoming forest edge, isolated ones included."""
    return nodes.join(forest.select(F.col("dst").alias(key)).distinct(), key, "left_anti")


def lineage(forest: DataFrame, roots: DataFrame, max_depth: int = 1000) -> DataFrame:
    """(root, node, depth): everything that descends from each root, at its least depth."""
    front = cut_lineage(roots.select(F.col("root").cast("bigint").alias("root"), F.col("root").cast("bigint").alias("node"), F.lit(0).alias("depth")))
    seen = front
    for depth in range(1, max_depth + 1):
        step = front.join(forest.select("src", "dst"), F.col("node") == F.col("src")).select("root", F.col("dst").alias("node"), F.lit(depth).alias("depth")).distinct()
        front = cut_lineage(step.join(seen.select("root", "node"), ["root", "node"], "left_anti"))
        if not front.limit(1).count():
            break
        seen = cut_lineage(seen.unionByName(front))
    return seen


def ancestry(forest: DataFrame, nodes: DataFrame, max_depth: int = 1000) -> DataFrame:
    """(root, node, depth) backwards: everything a node descends from."""
    return lineage(forest.select(F.col("dst").alias("src"), F.col("src").alias("dst")), nodes, max_depth)


def forest_events(nodes: DataFrame, forest: DataFrame, key: str = "pos") -> DataFrame:
    """Per node: in and out degree, and whether ideas emerge, diverge or converge there."""
    outs, ins = forest.groupBy(F.col("src").alias(key)).agg(F.count("*").alias("n_out")), forest.groupBy(F.col("dst").alias(key)).agg(F.count("*").alias("n_in"))
    rows = nodes.select(key).join(outs, key, "left").join(ins, key, "left").select(key, F.coalesce("n_in", F.lit(0)).alias("n_in"), F.coalesce("n_out", F.lit(0)).alias("n_out"))
    return rows.withColumn("emergence", F.col("n_in") == 0).withColumn("divergence", F.col("n_out") >= 2).withColumn("convergence", F.col("n_in") >= 2)


def level_counts(nodes: DataFrame, clusters: DataFrame, overlapping: DataFrame, related: DataFrame) -> DataFrame:
    """(conf, n): edges of the full confidence graph by level, without its pairs: those of level 4 are the pairs inside clusters
    less those of level 5."""
    listed = confidence_graph(nodes, clusters, overlapping, related, prune=True).where("conf <> 4").groupBy("conf").agg(F.count("*").alias("n"))
    inside = clusters.where("cluster is not null").groupBy("cluster").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).alias("pairs"))
    fives = listed.agg(F.coalesce(F.sum(F.when(F.col("conf") == 5, F.col("n"))), F.lit(0)).alias("fives"))
    four = inside.crossJoin(fives).select(F.lit(4).alias("conf"), (F.col("pairs") - F.col("fives")).alias("n")).where("n > 0")
    return listed.unionByName(four)


def forest_stats(nodes: DataFrame, forest: DataFrame, key: str = "pos") -> DataFrame:
    """One row: n_nodes, n_edges, n_components, n_roots, depth (most steps from the nearest root), total_sigma."""
    roots = cut_lineage(forest_roots(nodes, forest, key))
    n = nodes.select(key).distinct().agg(F.count("*").alias("n_nodes"))
    e = forest.agg(F.count("*").alias("n_edges"), F.round(F.coalesce(F.sum(F.col("sigma").cast("decimal(18,6)")).cast("double"), F.lit(0.0)), 6).alias("total_sigma"))
    depth = depths(forest, roots.select(F.col(key).alias("node"))).agg(F.coalesce(F.max("depth"), F.lit(0)).cast("bigint").alias("depth"))
    return n.crossJoin(e).crossJoin(roots.agg(F.count("*").alias("n_roots"))).crossJoin(depth).select("n_nodes", "n_edges", (F.col("n_nodes") - F.col("n_edges")).alias("n_components"), "n_roots", "depth", "total_sigma")


def depths(forest: DataFrame, roots: DataFrame, max_depth: int = 1000) -> DataFrame:
    """(node, depth): steps of each node from its nearest root."""
    front = cut_lineage(roots.select("node", F.lit(0).alias("depth")))
    seen = front
    for depth in range(1, max_depth + 1):
        step = front.join(forest.select("src", "dst"), F.col("node") == F.col("src")).select(F.col("dst").alias("node"), F.lit(depth).alias("depth")).distinct()
        front = cut_lineage(step.join(seen.select("node"), "node", "left_anti"))
        if not front.limit(1).count():
            return seen
        seen = cut_lineage(seen.unionByName(front))
    raise RuntimeError("the forest is deeper than the limit")


def cluster_terms(nodes: DataFrame, clusters: DataFrame, tokens: str = "tokens", top: int = 3, key: str = "pos") -> DataFrame:
    """Most frequent tokens of each cluster."""
    counts = nodes.join(clusters.where("cluster is not null").withColumnRenamed("node", key), key).select("cluster", F.explode(tokens).alias("token")).groupBy("cluster", "token").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("n"), "token"))
    return counts.withColumn("rank", rank).where(F.col("rank") <= top)


def project2d(vectors: DataFrame, method: str = "pca", key: str = "item_id", vec: str = "vec", max_points: int = 2000, seed: int = 1) -> DataFrame:
    """(key, x, y): PCA at any size, or t-SNE for at most `max_points` vectors (more is an error)."""
    if method == "pca":
        from pyspark.ml.feature import PCA
        from pyspark.ml.functions import array_to_vector, vector_to_array

        rows = vectors.select(key, array_to_vector(F.transform(vec, lambda v: v.cast("double"))).alias("features"))
        out = PCA(k=2, inputCol="features", outputCol="p").fit(rows).transform(rows).select(key, vector_to_array("p").alias("p"))
        return out.select(key, F.col("p")[0].alias("x"), F.col("p")[1].alias("y"))
    if vectors.count() > max_points:
        raise ValueError(f"t-SNE takes at most {max_points} points; use pca")
    ship(vectors.sparkSession)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        group = group.sort_values("id", kind="stable")
        y = tsne(np.stack(group["vec"].to_numpy()).astype(float), seed)
        return pd.DataFrame({"id": group["id"].to_numpy(), "x": y[:, 0], "y": y[:, 1]})

    out = vectors.select(F.lit(1).alias("one"), F.col(key).alias("id"), F.col(vec).alias("vec")).groupBy("one").applyInPandas(run, "id bigint, x double, y double")
    return out.withColumnRenamed("id", key)


def tsne(points, seed: int = 1, perplexity: float = 20.0, rounds: int = 250):
    """Exact t-SNE of a small array, fixed seed."""
    import numpy as np

    n = len(points)
    if n < 3:
        return np.zeros((n, 2))
    square = ((points[:, None, :] - points[None, :, :]) ** 2).sum(axis=2)
    target, p = np.log(min(perplexity, (n - 1) / 3)), np.zeros((n, n))
    for i in range(n):
        low, high, beta = 0.0, np.inf, 1.0
        for _ in range(40):
            row = np.exp(-(square[i] - square[i].min()) * beta)
            row[i] = 0
            total = row.sum()
            entropy = np.log(total) + beta * ((square[i] - square[i].min()) * row).sum() / total
            if abs(entropy - target) < 1e-4:
                break
            low, high = (beta, high) if entropy > target else (low, beta)
            beta = beta * 2 if high == np.inf else (low + high) / 2
        p[i] = row / total
    p = np.maximum((p + p.T) / (2 * n), 1e-12)
    y, speed = np.random.default_rng(seed).normal(scale=1e-4, size=(n, 2)), np.zeros((n, 2))
    for step in range(rounds):
        inverse = 1 / (1 + ((y[:, None, :] - y[None, :, :]) ** 2).sum(axis=2))
        np.fill_diagonal(inverse, 0)
        q = np.maximum(inverse / inverse.sum(), 1e-12)
        force = ((4 if step < 60 else 1) * p - q) * inverse
        slope = 4 * (np.diag(force.sum(axis=1)) - force) @ y
        speed = (0.5 if step < 60 else 0.8) * speed - 50 * slope
        y = y + speed
    return y - y.mean(axis=0)
