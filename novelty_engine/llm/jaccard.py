"""Jaccard self-join on word shingles by chosen paths.

Every text is a set of hashed shingles of `words` consecutive words (a shorter text is one shingle; a
text without words is the empty set and links to nothing).  Texts with equal sets form one class
and are represented once.  Then, for representatives:

1. *Paths.*  A set is embedded as `COORDINATES` minhash values.  In each of `runs` independent runs sets
   are split by the value of a sampled coordinate: sets that go to one bucket share a sampled
   token.  A bucket that is still large is split again on coordinates sampled from its own
   path, so a pair of similarity s stays together with probability about s per split and coordinate.
   Small buckets are compared by brute force; a large bucket that does not shrink, or is at the depth
   limit, consists of near copies and is compared by brute force too, in blocks.  Runs are repeated
   until the target recall: for a pair at the threshold s the chance to be missed is (1 - s)**runs
   for one split, and two coordinates are sampled on deeper ones.
2. *Candidates.*  Brute force inside a bucket compares minhash values and keeps a spanning set of
   the pairs that look similar enough (six standard errors under the threshold), not the pairs.
   Connected components of those give candidate clusters: every pair that any bucket brought
   together and that may reach the threshold lies inside one cluster.
3. *Verification.*  The shingle sets of cluster members are made again, from one text each, and all pairs
   of a cluster are compared exactly by a blocked matrix product; clusters over `BLOCK` members or
   `BLOCK_SHINGLES` shingles are cut into blocks and each pair of blocks is one piece of work, so no
   task holds a whole large cluster.  A set then travels once for each block of its cluster.
   Per set the number of linked documents is counted; pairs are never written out.

The result has one row per document: the class id is the least doc_id of its connected component of links,
`n_links` the number of other documents within the threshold (exact copies included).

Rows that repeat a doc_id are answered each; a null doc_id is joined like any other and its class id is
the least id that is not null, or null.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, log, sqrt

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Words, binary, bit_filter, components, cut_lineage, gram_hashes, release, ship, slices, table, whole_groups

COORDINATES = 64
#: Buckets up to this many sets are compared directly; larger ones split, at most DEPTH times.
SMALL, DEPTH, STUCK = 256, 5, 0.7
#: Sets in a block of a large bucket or cluster, and shingles in a block of a cluster.
BLOCK, BLOCK_SHINGLES = 2048, 2 << 20
RECALL = 1 - 1e-6
#: Sets (about 300 bytes) and paths (24) in one partition of a table that is read again.
PART_SETS, PART_PATHS = 100_000, 1_000_000


def shingles(texts: list[bytes], words: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's word n-grams."""
    found = Words(texts)
    grams = gram_hashes(found.hashes, words)
    return [np.unique(grams[a : a + n - words + 1]) if n >= words else np.array([xxhash.xxh3_64_intdigest(b" ".join(parts), seed=1)] if n else [], np.uint64) for a, n, parts in zip(found.first.tolist(), found.sizes.tolist(), found.split)]


def set_name(values: np.ndarray) -> int:
    """64-bit name of a set, 0 for the empty one."""
    return (xxhash.xxh3_64_intdigest(values.tobytes()) or 1) if len(values) else 0


_ODD = np.arange(1, 2 * COORDINATES + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
_SALT = ((_ODD ^ (_ODD >> np.uint64(29))) >> np.uint64(31)).astype(np.uint32) | np.uint32(1)


def minhash(sets: list[np.ndarray], chunk: int = 1 << 15) -> np.ndarray:
    """COORDINATES 32-bit minima of independently mixed hashes for each set (none of them empty)."""
    out = np.empty((len(sets), COORDINATES), np.uint32)
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    block = np.cumsum(sizes) // chunk
    cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(sets)]
    for a, b in zip(cuts, cuts[1:]):  # values that stay in the cache
        if a == b:
            continue
        flat = np.concatenate(sets[a:b])
        flat = (flat ^ (flat >> np.uint64(32))).astype(np.uint32)
        begins = np.cumsum(sizes[a:b]) - sizes[a:b]
        mixed, shifted = np.empty_like(flat), np.empty_like(flat)
        for i in range(COORDINATES):
            np.multiply(flat, _SALT[i], out=mixed)
            np.right_shift(mixed, np.uint32(15), out=shifted)
            np.bitwise_xor(mixed, shifted, out=mixed)
            np.multiply(mixed, _SALT[COORDINATES + i], out=mixed)
            out[a:b, i] = np.minimum.reduceat(mixed, begins)
    return out


def _sketches(docs: DataFrame, words: int) -> DataFrame:
    """(doc, cid, size, text_key, sig) for every row: cid names the set (0 for the empty one), sig is its minhash; columns named keep_* go along."""
    keep = [c for c in docs.columns if c.startswith("keep_")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t", 4 << 20):
            texts = [x or b"" for x in binary(batch.column("t"))]
            place = {text: i for i, text in enumerate(dict.fromkeys(texts))}
            sets = shingles(list(place), words)
            filled = [i for i, values in enumerate(sets) if len(values)]
            sigs = np.zeros((len(sets), COORDINATES), np.uint32)
            if filled:
                sigs[filled] = minhash([sets[i] for i in filled])
            at = np.array([place[text] for text in texts])
            sizes = np.array([len(values) for values in sets])[at]
            cids = np.array([set_name(values) for values in sets], np.uint64)[at]
            keys = np.array([xxhash.xxh3_64_intdigest(text) for text in place], np.uint64)[at]
            sig = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * COORDINATES), pa.array(sigs[at].view(np.int32).ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("d"), pa.array(cids.view(np.int64)), pa.array(sizes, pa.int64()), pa.array(keys.view(np.int64)), sig, *(batch.column(c) for c in keep)], ["doc", "cid", "size", "text_key", "sig", *keep])

    kept = "".join(f", {c} {docs.schema[c].dataType.simpleString()}" for c in keep)
    return docs.mapInArrow(run, f"doc bigint, cid bigint, size bigint, text_key bigint, sig array<int>{kept}")


def _runs(threshold: float, recall: float) -> int:
    return max(2, ceil(log(1 - recall) / log(1 - threshold)))


def _alike(threshold: float) -> int:
    """Least number of agreeing coordinates of a pair that may reach the threshold."""
    return max(1, int(COORDINATES * threshold - 6 * sqrt(COORDINATES * threshold * (1 - threshold))))


def _link_alike(sig: np.ndarray, least: int) -> np.ndarray:
    """First position of each row's component, rows being joined where `least` coordinates agree.

    Rows that hang together already are not compared again, so a group of near copies costs one pass.
    """
    label = np.arange(len(sig))
    for i in range(len(sig) - 1):
        rest = i + 1 + np.flatnonzero(label[i + 1 :] != label[i])
        if not len(rest):
            if (label == label[i]).all():
                break
            continue
        near = rest[(sig[rest] == sig[i]).sum(axis=1) >= least]
        if len(near):
            merged = np.unique(np.r_[label[i], label[near]])
            label[np.isin(label, merged)] = merged[0]
    return label


def _bucket_edges(rows: DataFrame, least: int) -> DataFrame:
    """Brute force inside each path: (a, b) joins each set to the first one that it hangs together with."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in whole_groups(batches, "path", None, 2048):
            paths, cids = part.column("path").to_numpy(), part.column("cid").to_numpy()
            sigs = part.column("sig").combine_chunks().flatten().to_numpy().reshape(-1, COORDINATES)
            begins = np.flatnonzero(np.r_[True, paths[1:] != paths[:-1]])
            left, right = [], []
            for a, b in zip(begins.tolist(), [*begins[1:].tolist(), len(paths)]):
                if b - a == 2:
                    if (sigs[a] == sigs[a + 1]).sum() >= least and cids[a] != cids[a + 1]:
                        left.append(cids[a : a + 1])
                        right.append(cids[a + 1 : a + 2])
                elif b - a > 2:
                    first = _link_alike(sigs[a:b], least)
                    moved = np.flatnonzero(first != np.arange(b - a))
                    left.append(cids[a:b][moved])
                    right.append(cids[a:b][first[moved]])
            if left and len(one := np.concatenate(left)):
                yield pa.RecordBatch.from_arrays([pa.array(one), pa.array(np.concatenate(right))], ["a", "b"])

    return rows.repartition("path").sortWithinPartitions("path").mapInArrow(run, "a bigint, b bigint")


def _tiles(blocks: Column, member: Column) -> Column:
    """Block pairs (i <= j) that a member's block takes part in, as structs(i, j, block)."""
    own = F.pmod(F.xxhash64(member, F.lit(77)), blocks).cast("int")
    return F.transform(F.sequence(F.lit(0), blocks - 1), lambda k: F.struct(F.least(own, k).alias("i"), F.greatest(own, k).alias("j"), own.alias("block")))


def candidate_edges(sets: DataFrame, threshold: float, recall: float) -> DataFrame:
    """Spanning edges of likely pairs among sets(cid, sig), by chosen paths."""
    least, runs = _alike(threshold), _runs(threshold, recall)

    def sampled(parent: Column, level: int, picks: int) -> Column:
        coordinate = lambda k: F.pmod(F.xxhash64(parent, F.lit(level), F.lit(k)), F.lit(COORDINATES)).cast("int")
        return F.array(*(F.xxhash64(parent, coordinate(k), F.element_at("sig", coordinate(k) + 1)) for k in range(picks)))

    if runs > COORDINATES:
        raise ValueError("the target recall needs more runs than there are coordinates")
    first = F.array(*(F.xxhash64(F.lit(r), F.element_at("sig", r + 1)) for r in range(runs)))  # another coordinate for each run
    parts = 8 + sets.count() * runs // PART_PATHS
    level = sets.select("cid", F.explode(F.array_distinct(first)).alias("path"), F.lit(0).cast("bigint").alias("parent_n"))
    compared = None
    for depth in range(DEPTH):
        sizes = level.groupBy("path").agg(F.count("*").alias("n")).where("n > 1")
        kept = cut_lineage(level.join(sizes, "path").coalesce(parts))
        stuck = (F.col("n") > SMALL) & ((F.col("n") > STUCK * F.col("parent_n")) & (F.col("parent_n") > 0) if depth + 1 < DEPTH else F.lit(True))
        small = kept.where(F.col("n") <= SMALL).select("path", "cid")
        blocks = kept.where(stuck).select("path", "cid", F.explode(_tiles(F.ceil(F.col("n") / F.lit(BLOCK)).cast("int"), F.col("cid"))).alias("x")).select(F.xxhash64("path", "x.i", "x.j").alias("path"), "cid")
        compared = small.union(blocks) if compared is None else compared.union(small).union(blocks)
        split = kept.where((F.col("n") > SMALL) & ~stuck)
        if depth + 1 == DEPTH or not split.limit(1).count():
            break
        release(sets.sparkSession)
        level = split.join(sets, "cid").select("cid", F.explode(F.array_distinct(sampled(F.col("path"), depth + 1, 2))).alias("new"), F.col("n").alias("parent_n")).select("cid", F.col("new").alias("path"), "parent_n").dropDuplicates(["cid", "path"])
    return _bucket_edges(compared.join(sets, "cid").select("path", "cid", "sig"), least).distinct()


def _exact(values: list[np.ndarray], block: np.ndarray, cross: bool, weight: np.ndarray, threshold: float) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """(linked weight of each set, spanning links) over all pairs, or over the pairs of two blocks."""
    n = len(values)
    left = np.flatnonzero(block == block.min()) if cross else np.arange(n)
    right = np.flatnonzero(block != block.min()) if cross else left
    sizes = np.array([len(v) for v in values])
    total = np.zeros(n)
    if not len(left) or not len(right):
        return total.astype(np.int64), []
    owner = np.repeat(np.arange(n), sizes)
    _, token, counts = np.unique(np.concatenate(values), return_inverse=True, return_counts=True)
    often = counts[token] > 1
    owner, token = owner[often], np.unique(token[often], return_inverse=True)[1]
    order = np.argsort(token, kind="stable")
    owner, token = owner[order], token[order]
    shared = np.zeros((len(left), len(right)), np.float32)
    width = 2048
    top = int(token[-1]) + 1 if len(token) else 0
    for start in range(0, top, width):
        a, b = np.searchsorted(token, [start, start + width])
        dense = np.zeros((n, min(width, top - start)), np.float32)
        dense[owner[a:b], token[a:b] - start] = 1
        shared += dense[left] @ dense[right].T
    union = (sizes[left][:, None] + sizes[right][None, :]).astype(np.float32) - shared
    linked = shared >= np.float32(threshold) * union - np.float32(1e-6) * union
    if cross:
        total[left] += linked @ weight[right].astype(np.float64)
        total[right] += linked.T @ weight[left].astype(np.float64)
    else:
        np.fill_diagonal(linked, False)
        total += linked @ weight.astype(np.float64)
    return total.round().astype(np.int64), _spanning(linked, left, right, n)


def _spanning(linked: np.ndarray, left: np.ndarray, right: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Links that reach every set of each component of a (left x right) matrix of links."""
    at_left, at_right = np.full(n, -1), np.full(n, -1)
    at_left[left], at_right[right] = np.arange(len(left)), np.arange(len(right))
    seen, pairs = np.zeros(n, bool), []
    for root in left[linked.any(axis=1)].tolist():
        if seen[root]:
            continue
        seen[root], front = True, [root]
        while front:
            x = front.pop()
            near = right[linked[at_left[x]]] if at_left[x] >= 0 else left[linked[:, at_right[x]]]
            for y in near[~seen[near]].tolist():
                seen[y] = True
                pairs.append((x, y))
                front.append(y)
    return pairs


def _verify(members: DataFrame, threshold: float) -> DataFrame:
    """members(tile, i, j, block, cid, copies, values) -> links counted per set and spanning links, as (cid, links, other)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in whole_groups(batches, "tile", "values", 4 << 20):
            tiles = part.column("tile").to_numpy()
            begins = np.flatnonzero(np.r_[True, tiles[1:] != tiles[:-1]]).tolist()
            cids, copies, block = part.column("cid").to_numpy(), part.column("copies").to_numpy(), part.column("block").to_numpy()
            cross = (part.column("i").to_numpy() != part.column("j").to_numpy())
            raw = part.column("values").to_pylist()
            one, links, other = [], [], []
            for a, b in zip(begins, [*begins[1:], len(tiles)]):
                if b - a < 2:
                    continue
                total, pairs = _exact([np.frombuffer(x, np.uint64) for x in raw[a:b]], block[a:b], bool(cross[a]), copies[a:b], threshold)
                for k in np.flatnonzero(total).tolist():
                    one.append(int(cids[a + k]))
                    links.append(int(total[k]))
                    other.append(None)
                for x, y in pairs:
                    one.append(int(cids[a + x]))
                    links.append(0)
                    other.append(int(cids[a + y]))
            yield pa.RecordBatch.from_arrays([pa.array(one, pa.int64()), pa.array(links, pa.int64()), pa.array(other, pa.int64())], ["cid", "links", "other"])

    return members.repartition("tile").sortWithinPartitions("tile").mapInArrow(run, "cid bigint, links bigint, other bigint")


def near_classes(df: DataFrame, key: str = "doc_id", text: str = "text", words: int = 5, threshold: float = 0.8, recall: float = RECALL) -> DataFrame:
    """(key, class_id, n_links) for every row."""
    return _near(df, key, text, words, threshold, recall).select(F.col("doc").alias(key), F.when(F.col("cid") == 0, F.col("doc")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"))


def near_groups(df: DataFrame, keep: dict[str, Column], text: str = "text", words: int = 5, threshold: float = 0.8, recall: float = RECALL) -> DataFrame:
    """(near_group, *keep) for every row: the group names the row's class whatever its ids are; null for a text without words."""
    named = _near(df, None, text, words, threshold, recall, keep)
    return named.select(F.when(F.col("cid") != 0, F.col("group")).alias("near_group"), *(F.col(f"keep_{i}").alias(c) for i, c in enumerate(keep)))


def _near(df: DataFrame, key: str | None, text: str, words: int, threshold: float, recall: float, keep: dict[str, Column] | None = None) -> DataFrame:
    """(doc, cid, class_id, n_links, group, keep_*) for every row."""
    ship(df.sparkSession)
    docs = df.select((F.col(key).cast("bigint") if key else F.lit(None).cast("bigint")).alias("d"), F.col(text).alias("t"), *(v.alias(f"keep_{i}") for i, v in enumerate((keep or {}).values())))
    sketches = cut_lineage(_sketches(docs, words))
    full = sketches.where("cid <> 0")
    classes = cut_lineage(full.groupBy("cid").agg(F.min("doc").alias("least"), F.count("*").alias("copies"), F.first("size").alias("size"), F.min("text_key").alias("text_key"), F.first("sig").alias("sig")))
    parts = 8 + classes.count() // PART_SETS
    classes = classes.coalesce(parts)
    clusters = components(candidate_edges(classes.select("cid", "sig"), threshold, recall)).withColumnRenamed("node", "cid")
    labelled = clusters.join(classes.select("cid", "copies", "size", "text_key"), "cid")
    blocks = F.greatest(F.ceil(F.count("*") / F.lit(BLOCK)), F.ceil(F.sum("size") / F.lit(BLOCK_SHINGLES))).cast("int")
    active = cut_lineage(labelled.join(labelled.groupBy("label").agg(blocks.alias("blocks")), "label").coalesce(parts))
    wanted = ship(df.sparkSession).sparkContext.broadcast(bit_filter(active, "text_key"))  # one text stands for each set

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t", 4 << 20):
            once = list(dict.fromkeys(x or b"" for x in binary(batch.column("t"))))
            keys = np.array([xxhash.xxh3_64_intdigest(x) for x in once], np.uint64)
            sets = [x for x in shingles([once[i] for i in np.flatnonzero(wanted.value.hits(keys)).tolist()], words) if len(x)]
            yield pa.RecordBatch.from_arrays([pa.array(np.array([set_name(x) for x in sets], np.uint64).view(np.int64)), pa.array([x.tobytes() for x in sets], pa.binary())], ["cid", "values"])

    sets = docs.select("t").mapInArrow(fetch, "cid bigint, values binary").groupBy("cid").agg(F.first("values").alias("values"))
    members = sets.join(active, "cid").select("cid", "copies", "values", "label", F.explode(_tiles(F.col("blocks"), F.col("cid"))).alias("x")).select(F.xxhash64("label", "x.i", "x.j").alias("tile"), "x.i", "x.j", "x.block", "cid", "copies", "values")
    verified = cut_lineage(_verify(members, threshold))
    links = verified.where("links > 0").groupBy("cid").agg(F.sum("links").alias("links"))
    release(df.sparkSession)
    joined = components(verified.where("other is not null").select(F.col("cid").alias("a"), F.col("other").alias("b")))
    named = joined.withColumnRenamed("node", "cid").join(classes.select("cid", "least"), "cid")
    ids = named.join(named.groupBy("label").agg(F.min("least").alias("class_id")), "label").select("cid", "class_id", "label")
    known = classes.select("cid", "least", "copies").join(ids, "cid", "left").join(links, "cid", "left").select("cid", F.coalesce("label", "cid").alias("group"), F.coalesce("class_id", "least").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    return sketches.drop("sig", "size", "text_key").join(known, "cid", "left")


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_classes(table(spark, sf_dir, "documents"))
