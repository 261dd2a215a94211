"""Helpers shared by the training-data operators.

Conventions that every operator of this subpackage keeps:

* only the columns named in an operator's arguments are read, so extra columns,
  whatever their names, never clash with the operator's own;
* a null text is an empty text, an empty table gives an empty result with the
  usual schema, and repeated rows are answered once each;
* what is broadcast has a fixed upper size that does not depend on the data.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import session
from ..operators.components import components  # noqa: F401  used by the operators
from ..session import cut_lineage, fresh_folder, release  # noqa: F401

#: Rows in one Arrow batch; texts are long, and a batch is held on both sides of the process border.
BATCH_ROWS = 2000


def ship(spark: SparkSession) -> SparkSession:
    """`session.ship`, and Arrow batches sized for texts unless the session has its own size."""
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return session.ship(spark)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def binary(column: pa.ChunkedArray | pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of a string column without decoding it."""
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def slices(batches: Iterable[pa.RecordBatch], text: str, limit: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """Cut batches so that one slice holds about `limit` bytes of the text column, or a single row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        block = np.cumsum(_lengths(batch.column(text))) // limit
        cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            yield batch.slice(a, b - a)


def _lengths(column: pa.Array) -> np.ndarray:
    import pyarrow.compute as pc

    if pa.types.is_list(column.type):
        return pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64) * 8
    return pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def whole_groups(batches: Iterable[pa.RecordBatch], key: str, weight: str | None, limit: int) -> Iterator[pa.Table]:
    """From batches sorted by `key`: tables of whole groups, each closed once `limit` weight has been gathered."""
    held: list[pa.RecordBatch] = []
    total = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        total += int(_lengths(batch.column(weight)).sum()) if weight else batch.num_rows
        if total < limit:
            continue
        table_ = pa.Table.from_batches(held).combine_chunks()
        keys = table_.column(key).to_numpy()
        last = int(np.searchsorted(keys, keys[-1], side="left"))
        if last:
            yield table_.slice(0, last)
        rest = table_.slice(last)
        held = rest.to_batches()
        total = (int(sum(_lengths(b.column(weight)).sum() for b in held)) if weight else rest.num_rows) if last else total // 2
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


class Words:
    """The words of many texts as one flat array of hashes: word k of text i stands at `first[i]` + k."""

    def __init__(self, texts: list[bytes]):
        self.split = [text.split() for text in texts]
        self.sizes = np.fromiter(map(len, self.split), np.int64, len(texts))
        self.end = np.cumsum(self.sizes)
        self.first = self.end - self.sizes
        self.hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, chain.from_iterable(self.split)), np.uint64, int(self.sizes.sum()))

    def owner(self) -> np.ndarray:
        """Text of each word."""
        return np.repeat(np.arange(len(self.sizes)), self.sizes)


_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB], np.uint64)  # odd multipliers


def gram_hashes(hashes: np.ndarray, gram: int) -> np.ndarray:
    """A well-mixed hash of every `gram` consecutive words."""
    n = max(0, len(hashes) - gram + 1)
    out = np.zeros(n, np.uint64)
    for k in range(gram):
        out *= np.uint64(0x9E3779B97F4A7C15)
        out += hashes[k : k + n] ^ _MIX[k % len(_MIX)]
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    return out ^ (out >> np.uint64(29))


FILTER_BITS = 27


class BitFilter:
    """A bitmap of fixed size (2**bits bits) over 64-bit hashes: no false negatives, so it only spares work.

    When the data outgrow it, it fills up and lets everything through; results never depend on it.
    """

    def __init__(self, words: np.ndarray, bits: int):
        self.words, self.bits = words, bits

    def hits(self, hashes: np.ndarray) -> np.ndarray:
        at = hashes.astype(np.uint64) & np.uint64((1 << self.bits) - 1)
        return ((self.words[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1)).astype(bool)


def bit_filter(hashes: DataFrame, column: str, bits: int = FILTER_BITS) -> BitFilter:
    """Build the bitmap with one aggregation; at most 2**(bits - 6) longs reach the driver."""
    at = F.col(column).bitwiseAND(F.lit((1 << bits) - 1))
    packed = (
        hashes.select(F.shiftright(at, 6).cast("int").alias("word"), F.expr(f"shiftleft(1L, cast({column} & 63 as int))").alias("bit"))
        .groupBy("word").agg(F.bit_or("bit").alias("bits"))
    )
    words = np.zeros(1 << (bits - 6), np.uint64)
    for batch in packed.toArrow().to_batches():
        words[batch.column("word").to_numpy()] = batch.column("bits").to_numpy().view(np.uint64)
    return BitFilter(words, bits)


def crc_fold(column: str, folds: int) -> Column:
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(folds))
