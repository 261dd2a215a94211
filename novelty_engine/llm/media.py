"""Media columns: payloads cut into content-defined chunks, stored once, read back and verified.

A payload is held as a WAV object of 8-bit mono samples.  A rolling gear hash cuts its samples where
the top bits of the hash vanish (between MIN_CHUNK and MAX_CHUNK bytes), so equal content gives equal
chunks wherever it starts.  Each document keeps an ordered list of chunk digests.  Chunks whose digest
occurs in two places are stored once in a chunk table, deduplicated by a Spark aggregation; all
others are packed (zstandard) beside the one list that names them, which spares shuffling them.  Which digests are
shared is read off a bitmap of fixed size: a chunk taken for shared by mistake is merely stored
in the chunk table.  Reading joins the lists with the chunk table on digests, puts the chunks back in
order and checks every digest before the object is used.

`write_store` writes both tables to a folder, `read_store` rebuilds every object from them.  Null and
empty texts are a payload of 64 zero bytes; equal payloads have equal objects; repeated rows are
answered each.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import binary, bit_filter, fresh_folder, ship, slices, table

MIN_CHUNK, MAX_CHUNK, CUT_BITS = 256, 8192, 10
RATE = 8000


def _gear() -> np.ndarray:
    """256 well-mixed words from a counter."""
    x = np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((x ^ (x >> np.uint64(27))) >> np.uint64(32)).astype(np.uint32)


GEAR = _gear()


def cuts(payload: bytes) -> list[int]:
    """Ends of the chunks."""
    n = len(payload)
    if n <= MIN_CHUNK:
        return [n]
    h = GEAR[np.frombuffer(payload, np.uint8)]
    for step in (1, 2, 4, 8, 16):  # the hash of 32 bytes from hashes of 16, of 8, ...
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
    out, last = [], 0
    for end in (np.flatnonzero(h >> np.uint32(32 - CUT_BITS) == 0) + 1).tolist():
        while end - last > MAX_CHUNK:
            last += MAX_CHUNK
            out.append(last)
        if end - last >= MIN_CHUNK:
            out.append(end)
            last = end
    while n - last > MAX_CHUNK:
        last += MAX_CHUNK
        out.append(last)
    if last < n:
        out.append(n)
    return out


def chunks(payload: bytes) -> list[bytes]:
    ends = cuts(payload)
    return [payload[a:b] for a, b in zip([0, *ends], ends)]


def digest(chunk: bytes) -> bytes:
    return hashlib.sha256(chunk).digest()[:16]


def padded(text: bytes | None) -> bytes:
    raw = text or b""
    return raw + bytes(-len(raw) % 64 or (0 if raw else 64))


def header(samples: int) -> bytes:
    """RIFF header of 8-bit mono samples."""
    return b"RIFF" + struct.pack("<I", 36 + samples) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE, RATE, 1, 8) + b"data" + struct.pack("<I", samples)


def samples_of(wav: bytes) -> bytes:
    """The samples of such an object, by its own header."""
    if wav[:4] != b"RIFF" or wav[8:16] != b"WAVEfmt " or wav[36:40] != b"data":
        raise ValueError("not an object that this module stored")
    return wav[44 : 44 + struct.unpack_from("<I", wav, 40)[0]]


def features(payload: bytes) -> str:
    x = np.frombuffer(payload, np.uint8).astype(np.float64) - 128.0
    crossings = int(np.count_nonzero(np.diff(np.signbit(x))))
    spread = np.histogram(x, bins=8, range=(-128, 128))[0]
    return f"mean={x.mean():.4f};rms={np.sqrt((x * x).mean()):.4f};peak={np.abs(x).max():.0f};crossings={crossings};spread=" + "/".join(map(str, spread.tolist()))


def _halves(raw: list[bytes]) -> tuple[pa.Array, pa.Array]:
    pairs = np.frombuffer(b"".join(raw), "<i8").reshape(-1, 2)
    return pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())


def _payloads(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    for batch in slices(batches, "t"):
        yield batch, [x or b"" for x in binary(batch.column("t"))]


def write_store(df: DataFrame, folder: str, key: str = "doc_id", text: str = "text") -> None:
    """Write `folder`/lists (one row per input row) and `folder`/chunks (one row per shared chunk)."""
    sc = ship(df.sparkSession).sparkContext
    docs = df.select(F.col(key).alias("k"), F.col(text).alias("t"))

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, texts in _payloads(batches):
            found = [digest(c) for t in texts for c in chunks(padded(t))]
            yield pa.RecordBatch.from_arrays(list(_halves(found)), ["h0", "h1"])

    counts = docs.select("t").mapInArrow(digests, "h0 bigint, h1 bigint").groupBy("h0", "h1").agg(F.count("*").alias("n"))
    shared = sc.broadcast(bit_filter(counts.where("n > 1"), "h0"))

    def lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for batch, texts in _payloads(batches):
            rows: tuple[list, ...] = ([], [], [], [], [], [])
            for text in texts:
                parts = chunks(padded(text))
                names = [digest(c) for c in parts]
                apart = shared.value.hits(np.frombuffer(b"".join(names), "<u8")[::2]).tolist()
                values = (len(text), xxhash.xxh3_128_digest(text), names, [len(c) for c in parts], apart, pack(b"".join(c for c, a in zip(parts, apart) if not a)))
                for column, value in zip(rows, values):
                    column.append(value)
            sizes, contents, names, lengths, apart, packed = rows
            c0, c1 = _halves(contents)
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array(sizes, pa.int64()), c0, c1, pa.array(names, pa.list_(pa.binary())), pa.array(lengths, pa.list_(pa.int32())), pa.array(apart, pa.list_(pa.bool_())), pa.array(packed, pa.binary())], ["k", "n_bytes", "c0", "c1", "names", "lengths", "apart", "packed"])

    def taken(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for _, texts in _payloads(batches):
            once: dict[bytes, bytes] = {}
            for text in texts:
                for c in chunks(padded(text)):
                    once.setdefault(digest(c), c)
            names = list(once)
            if names:
                chosen = np.flatnonzero(shared.value.hits(np.frombuffer(b"".join(names), "<u8")[::2])).tolist()
                if chosen:
                    yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in chosen], pa.binary()), pa.array([pack(once[names[i]]) for i in chosen], pa.binary())], ["name", "chunk"])

    kind = df.schema[key].dataType.simpleString()
    docs.mapInArrow(lists, f"k {kind}, n_bytes bigint, c0 bigint, c1 bigint, names array<binary>, lengths array<int>, apart array<boolean>, packed binary").write.parquet(f"{folder}/lists")
    docs.select("t").mapInArrow(taken, "name binary, chunk binary").groupBy("name").agg(F.first("chunk").alias("chunk")).write.parquet(f"{folder}/chunks")


def read_store(spark: SparkSession, folder: str, use: Callable[[bytes, int], list], names: list[str], schema: str) -> DataFrame:
    """Rebuild and verify every object; `use(object, n_bytes)` gives the values of the columns `names`.

    The result has the stored key as `k` and then those columns, declared in `schema`.
    """
    ship(spark)
    lists, stored = spark.read.parquet(f"{folder}/lists"), spark.read.parquet(f"{folder}/chunks")
    shares = F.exists("apart", lambda a: a)
    content = ["n_bytes", "names", "lengths", "apart", "packed"]
    alone = lists.where(~shares).select("k", *content, F.lit(None).cast("array<struct<at:int,chunk:binary>>").alias("taken"))
    # Equal payloads have equal lists: those that name shared chunks are put together once for all their rows.
    whole = lists.where(shares).groupBy("c0", "c1").agg(F.first(F.struct(*content)).alias("x")).select("c0", "c1", "x.*")
    parts = lists.where(shares).select("c0", "c1", F.posexplode(F.arrays_zip("names", "apart")).alias("at", "x")).where("x.apart").select("c0", "c1", "at", F.col("x.names").alias("name")).distinct()
    gathered = parts.join(stored, "name").groupBy("c0", "c1").agg(F.collect_list(F.struct("at", "chunk")).alias("taken"))
    mixed = whole.join(gathered, ["c0", "c1"], "left").select(F.struct("c0", "c1").alias("k"), *content, "taken")
    types = {f.name: f.type for f in pa.schema([pa.field(n, t) for n, t in _arrow_types(schema)])}

    def rebuild(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in _by_size(batches):
            out: list[list] = [[] for _ in names]
            for row in batch.select([*content, "taken"]).to_pylist():
                taken, own, at, parts_ = {x["at"]: x["chunk"] for x in row["taken"] or ()}, unpack(row["packed"]), 0, []
                for i, (name, length, apart) in enumerate(zip(row["names"], row["lengths"], row["apart"])):
                    chunk = unpack(taken[i]) if apart else own[at : at + length]
                    at += 0 if apart else length
                    if digest(chunk) != name:
                        raise ValueError("a stored chunk does not match its digest")
                    parts_.append(chunk)
                payload = b"".join(parts_)
                for column, value in zip(out, use(header(len(payload)) + payload, row["n_bytes"])):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([batch.column("k"), *(pa.array(c, types[n]) for n, c in zip(names, out))], ["k", *names])

    kind = lists.schema["k"].dataType.simpleString()
    made = mixed.mapInArrow(rebuild, f"k struct<c0:bigint,c1:bigint>, {schema}").select("k.c0", "k.c1", *names)
    together = lists.where(shares).select("k", "c0", "c1").join(made, ["c0", "c1"]).select("k", *names)
    return alone.mapInArrow(rebuild, f"k {kind}, {schema}").union(together)


def _by_size(batches: Iterator[pa.RecordBatch], limit: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """Slices whose payloads have about `limit` bytes, or a single row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        block = np.cumsum(batch.column("n_bytes").to_numpy()) // limit
        cuts_ = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts_, cuts_[1:]):
            yield batch.slice(a, b - a)


def _arrow_types(schema: str) -> list[tuple[str, pa.DataType]]:
    known = {"bigint": pa.int64(), "string": pa.string(), "binary": pa.binary(), "double": pa.float64()}
    return [(name, known[kind]) for name, kind in (x.split() for x in schema.split(", "))]


def describe(wav: bytes, n_bytes: int) -> list:
    payload = samples_of(wav)
    return [n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(wav), hashlib.sha256(wav).hexdigest(), features(payload)]


REPORT = "n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string"


def op6_media_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = fresh_folder(spark, "media")
    write_store(table(spark, sf_dir, "documents"), folder)
    return read_store(spark, folder, describe, [x.split()[0] for x in REPORT.split(", ")], REPORT).withColumnRenamed("k", "doc_id")
