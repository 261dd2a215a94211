"""Conflict-constrained best-fit packing of documents into fixed-length bins.

Documents are dealt by row to shards of about `shard_rows` rows, repeated rows and null ids alike; each shard is packed on its own
with bounded memory, so a bin never crosses shards.  Inside a shard, documents longer than the
capacity first fill bins of their own; what remains is packed longest first.  Open bins are kept
by residual space and carry two bitmaps, one of sources and one of duplicate clusters.  A search
starts at the smallest residual that fits and goes on to its successors until it meets the
tightest bin whose bitmaps hold neither the document's source nor its cluster; if there is none, a
bin is opened.  Only ids, lengths, sources and clusters travel, never texts.

Every row is answered: a null or empty text counts one unit (its end mark), a null source is a
source of its own, and repeated rows are packed one by one.
"""

from __future__ import annotations

from bisect import bisect_left, insort

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, ship, table
from .jaccard import near_groups

CAPACITY, SHARD_ROWS = 2048, 4096


def best_fit(lengths: list[int], sources: list[int], clusters: list[int], capacity: int) -> list[tuple[int, int]]:
    """(bin, offset) of each item of at most `capacity`, given longest first.  Sources and clusters are small numbers."""
    room: dict[int, list[int]] = {}  # residual -> bins, oldest first
    residuals: list[int] = []  # sorted keys of room
    source_bits: list[int] = []
    cluster_bits: list[int] = []
    out = []
    for length, source, cluster in zip(lengths, sources, clusters):
        source_bit, cluster_bit = 1 << source, 1 << cluster
        at = bisect_left(residuals, length)
        chosen = -1
        while at < len(residuals) and chosen < 0:
            for place, candidate in enumerate(room[residuals[at]]):
                if not (source_bits[candidate] & source_bit or cluster_bits[candidate] & cluster_bit):
                    chosen = candidate
                    break
            else:
                at += 1
        if chosen < 0:
            chosen, residual = len(source_bits), capacity
            source_bits.append(0)
            cluster_bits.append(0)
        else:
            residual = residuals[at]
            room[residual].pop(place)
            if not room[residual]:
                del room[residual], residuals[at]
        source_bits[chosen] |= source_bit
        cluster_bits[chosen] |= cluster_bit
        out.append((chosen, capacity - residual))
        if left := residual - length:
            if left not in room:
                room[left] = []
                insort(residuals, left)
            insort(room[left], chosen)
    return out


def pack_shard(rows: pd.DataFrame, capacity: int) -> pd.DataFrame:
    """Bins of one shard: columns id, length, source, cluster in; id, piece, length, bin_no, bin_offset out."""
    rows = rows.sort_values(["length", "id", "cluster"], ascending=[False, True, True], kind="stable", na_position="first")
    whole = [(i, piece, capacity) for i, n in zip(rows["id"], rows["length"]) for piece in range(int(n) // capacity)]
    rest = rows[rows["length"] % capacity > 0]
    rest = rest.assign(piece=rest["length"] // capacity, length=rest["length"] % capacity).sort_values("length", ascending=False, kind="stable")
    placed = best_fit(rest["length"].tolist(), pd.factorize(rest["source"], use_na_sentinel=False)[0].tolist(), pd.factorize(rest["cluster"])[0].tolist(), capacity)
    out = [(i, p, n, bin_no, offset) for i, p, n, (bin_no, offset) in zip(rest["id"], rest["piece"], rest["length"], placed)]
    used = max((x[3] for x in out), default=-1) + 1
    out += [(i, p, n, used + k, 0) for k, (i, p, n) in enumerate(whole)]
    return pd.DataFrame(out, columns=["id", "piece", "length", "bin_no", "bin_offset"])


def units(text: str) -> Column:
    """Default length of a text: a unit for every four bytes of UTF-8 and one for its end."""
    return (F.floor(F.coalesce(F.octet_length(F.col(text)), F.lit(0)) / 4) + 1).cast("bigint")


def pack(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", length: Column | None = None, cluster: Column | None = None, capacity: int = CAPACITY, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(key, piece, n_units, shard, bin_no, bin_offset): one row per piece of each document.

    The default cluster is the text itself (exact copies); `pack_near` uses near-duplicate classes.
    """
    ship(df.sparkSession)
    small = cut_lineage(df.select(F.col(key).cast("bigint").alias("id"), (units(text) if length is None else length).alias("length"), F.col(source).cast("string").alias("source"), (F.xxhash64(F.coalesce(F.col(text), F.lit(""))) if cluster is None else cluster).alias("cluster"), F.monotonically_increasing_id().alias("row")))
    shards = max(1, -(-small.count() // shard_rows))
    dealt = small.select("id", "length", "source", "cluster", F.pmod(F.xxhash64("row"), F.lit(shards)).alias("shard"))

    def run(group: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows["id"] = rows["id"].astype("Int64")
        return pack_shard(rows, capacity).assign(shard=group[0])[["id", "piece", "length", "shard", "bin_no", "bin_offset"]]

    out = dealt.groupBy("shard").applyInPandas(run, "id bigint, piece bigint, length bigint, shard bigint, bin_no bigint, bin_offset bigint")
    return out.withColumnsRenamed({"id": key, "length": "n_units"})


def pack_near(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", **options) -> DataFrame:
    """`pack` with classes of near copies as clusters; a text without words has its exact copies only."""
    keep = {key: F.col(key), source: F.col(source), "length": units(text), "exact": F.xxhash64(F.coalesce(F.col(text), F.lit("")))}
    return pack(near_groups(df, keep, text), key, text, source, length=F.col("length"), cluster=F.coalesce("near_group", "exact"), **options)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_near(table(spark, sf_dir, "documents"))
