"""Byte-level BPE encoding and decoding by a two-tier lookup.

Tier one resolves a whole pre-token with a minimal perfect hash over the vocabulary (hash and
displace: one digest, one displacement, one comparison with the only key that could match).
Tier two merges the bytes of a pre-token that is not in the vocabulary: a heap holds the
mergeable neighbours of a doubly linked list of parts, so a pre-token of n bytes takes
O(n log n) even when it is very long.

Null and empty texts have no ids.  Ids are int32; `encode` keeps the input's key column and
returns one row per input row.  The vocabulary is read on the driver, its size is checked and
it is broadcast (at most `MAX_VOCABULARY` entries).
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame, SparkSession

from .common import slices

MAX_VOCABULARY = 1_000_000
#: Bytes of answers a worker remembers before it starts afresh, with the cost of an entry besides its text and ids.
MEMO_BYTES, ENTRY_BYTES = 128 << 20, 200


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}
    if len(ranks) > MAX_VOCABULARY:
        raise ValueError(f"{len(ranks)} tokens; at most {MAX_VOCABULARY} are broadcast")
    return ranks


class PerfectHash:
    """Minimal perfect hash: n keys on n slots, one displacement per bucket."""

    def __init__(self, keys: list[bytes]):
        n = self.n = len(keys)
        self.buckets = max(1, n // 4)
        low, high = self._digests(keys)
        bucket = (low % np.uint64(self.buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        counts = np.bincount(bucket, minlength=self.buckets)
        ends = np.cumsum(counts)
        self.shift = np.zeros(self.buckets, np.int64)
        taken = np.zeros(n, bool)
        slot_of = np.zeros(n, np.int64)
        tries = np.arange(512, dtype=np.uint64)[:, None]
        by_size = np.argsort(-counts, kind="stable")
        for b in by_size[counts[by_size] > 1].tolist():
            members = order[ends[b] - counts[b] : ends[b]]
            base = 0
            while True:
                slots = ((high[members] + (tries + np.uint64(base)) * (low[members] | np.uint64(1))) % np.uint64(n)).astype(np.int64)
                free = ~taken[slots].any(axis=1)
                ordered = np.sort(slots, axis=1)
                good = np.flatnonzero(free & (np.diff(ordered, axis=1) > 0).all(axis=1))
                if len(good):
                    self.shift[b], chosen = base + int(good[0]), slots[good[0]]
                    taken[chosen], slot_of[members] = True, chosen
                    break
                base += 512
        spare = iter(np.flatnonzero(~taken).tolist())
        for b in by_size[counts[by_size] == 1].tolist():  # a lone key takes any slot left, named outright
            slot = next(spare)
            self.shift[b], slot_of[order[ends[b] - 1]] = -1 - slot, slot
        self.key_at: list[bytes] = [b""] * n
        for key, slot in zip(keys, slot_of.tolist()):
            self.key_at[slot] = key

    @staticmethod
    def _digests(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        pairs = np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, keys)), ">u8").astype(np.uint64).reshape(-1, 2)
        return pairs[:, 0], pairs[:, 1]

    def slots(self, keys: list[bytes]) -> list[int]:
        """The one slot where each key can be; the caller compares with `key_at`."""
        if not self.n or not keys:
            return [0] * len(keys)
        low, high = self._digests(keys)
        shift = self.shift[(low % np.uint64(self.buckets)).astype(np.int64)]
        far = ((high + shift.astype(np.uint64) * (low | np.uint64(1))) % np.uint64(self.n)).astype(np.int64)
        return np.where(shift < 0, -1 - shift, far).tolist()


def merge_parts(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Lowest rank first, leftmost among equals, over a linked list of byte parts."""
    n = len(piece)
    end = list(range(1, n + 1))  # end[i]: where the part that starts at i stops; 0 when it has been swallowed
    back = list(range(-1, n - 1))  # start of the part before
    heap = [(rank, i, i + 2) for i in range(n - 1) if (rank := ranks.get(piece[i : i + 2])) is not None]
    heapify(heap)
    while heap:
        _, left, stop = heappop(heap)
        middle = end[left]
        if not middle or middle >= n or end[middle] != stop:
            continue
        end[left], end[middle] = stop, 0
        if stop < n:
            back[stop] = left
            if (rank := ranks.get(piece[left : end[stop]])) is not None:
                heappush(heap, (rank, left, end[stop]))
        before = back[left]
        if before >= 0 and (rank := ranks.get(piece[before:stop])) is not None:
            heappush(heap, (rank, before, stop))
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = end[i]
    return out


class TwoTier:
    """Encoder and decoder of one vocabulary; picklable, so it can be broadcast."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, pattern
        self.hash = PerfectHash(list(ranks))
        self.rank_at = [ranks[key].to_bytes(4, "little") for key in self.hash.key_at]
        self.token_of = {rank: token for token, rank in ranks.items()}
        self._memo: dict[str, bytes] = {}
        self._memo_bytes = 0
        self._find = None

    def __getstate__(self):
        return self.__dict__ | {"_memo": {}, "_memo_bytes": 0, "_find": None}

    def _learn(self, pieces: list[str]) -> None:
        raw = [piece.encode() for piece in pieces]
        for piece, key, slot in zip(pieces, raw, self.hash.slots(raw)):
            ids = self.rank_at[slot] if self.hash.key_at[slot] == key else np.array(merge_parts(key, self.ranks), "<u4").tobytes()
            self._memo[piece] = ids
            self._memo_bytes += len(key) + len(ids) + ENTRY_BYTES

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if self._find is None:
            self._find = regex.compile(self.pattern).findall
        pieces = self._find(text)
        if self._memo_bytes > MEMO_BYTES:
            self._memo.clear()
            self._memo_bytes = 0
        if new := set(pieces).difference(self._memo):
            self._learn(list(new))
        return b"".join(map(self._memo.__getitem__, pieces))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def two_tier(path: str, pattern: str) -> TwoTier:
    return TwoTier(read_ranks(path), pattern)


def encode(df: DataFrame, tokenizer: TwoTier, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, ids array<int>) for every row."""
    shared, kind = df.sparkSession.sparkContext.broadcast(tokenizer), df.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t"):
            ids = [np.frombuffer(shared.value.encode(t or ""), "<u4").astype(np.int32) for t in batch.column("t").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array(ids, pa.list_(pa.int32()))], ["k", "ids"])

    return df.selectExpr(f"`{key}` as k", f"`{text}` as t").mapInArrow(run, f"k {kind}, ids array<int>").withColumnRenamed("k", key)


def decode(df: DataFrame, tokenizer: TwoTier, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """(key, text_bytes binary): the bytes that the ids stand for; null ids give no bytes."""
    shared, kind = df.sparkSession.sparkContext.broadcast(tokenizer), df.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "i"):
            out = [shared.value.decode(np.array(x or [], "<u4").tobytes()) for x in batch.column("i").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array(out, pa.binary())], ["k", "text_bytes"])

    return df.selectExpr(f"`{key}` as k", f"`{ids}` as i").mapInArrow(run, f"k {kind}, text_bytes binary").withColumnRenamed("k", key)


def round_trip(df: DataFrame, tokenizer: TwoTier, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Encode, decode the ids again, and keep digests of both: no id list leaves the worker."""
    shared, kind = df.sparkSession.sparkContext.broadcast(tokenizer), df.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t"):
            counts, id_sums, text_sums = [], [], []
            for t in batch.column("t").to_pylist():
                ids = shared.value.encode(t or "")
                counts.append(len(ids) // 4)
                id_sums.append(hashlib.sha256(ids).hexdigest())
                text_sums.append(hashlib.sha256(shared.value.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array(counts, pa.int64()), pa.array(id_sums), pa.array(text_sums)], ["k", "n_tokens", "ids_sha256", "decoded_sha256"])

    return df.selectExpr(f"`{key}` as k", f"`{text}` as t").mapInArrow(run, f"k {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string").withColumnRenamed("k", key)


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .common import table

    return round_trip(table(spark, sf_dir, "documents"), two_tier(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN))
