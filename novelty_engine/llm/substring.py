"""Removal of repeated word windows by super-k-mer partitioning.

A window is `width` consecutive words.  Its minimiser is the least hash among its word
`gram`-grams; equal windows have equal minimisers, so all copies of a window meet in one bucket.
Consecutive windows that share a minimiser travel as one packed string (their words joined by
single spaces), cut from a document once instead of once per window.  In its bucket the windows of
the packed strings are sorted where they lie, by digest; equal neighbours are compared byte by byte,
and a window whose least doc_id is smaller than the document's own covers words to remove.

Two things keep this whole and even at scale, and neither depends on the size of the data:

* one counting pass over minimisers (pre-aggregated before its shuffle) fills a bitmap of fixed
  size with those that occur in two documents; other windows cannot repeat and do not travel.
  A full bitmap only lets more through.
* a minimiser with more than HOT_RUNS runs (a second bitmap) is dealt out by digest instead.  Equal
  packed strings become one row with their least and greatest doc_id, so a group of copies counts
  once; of what is left, the windows that two strings hold (a third bitmap) are aggregated by 128-bit
  digest with partial sums before the shuffle, and joined back.  No task then holds more than
  HOT_RUNS runs of one minimiser, and a frequent phrase in ever new surroundings opens no windows.

Null or empty text has no words.  Rows with a null doc_id, or rows that repeat a doc_id, are
answered each; a null doc_id neither removes nor loses words, and equal doc_ids do not remove
from each other.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import FILTER_BITS, BitFilter, Words, binary, bit_filter, cut_lineage, gram_hashes, slices, table, whole_groups

GRAM = 4
RUN_WINDOWS = 64
HOT_RUNS = 256
#: Slots of the bitmap of windows that travel as one row.
PART_BITS = 17


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Least value of every `width` neighbours, by doubling."""
    have = 1
    while have * 2 <= width:
        values = np.minimum(values[:-have], values[have:])
        have *= 2
    return np.minimum(values[: len(values) - (width - have)], values[width - have :]) if have < width else values


def super_runs(words: Words, width: int, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, minimiser, first window, windows) of each maximal run, cut into at most RUN_WINDOWS windows."""
    total = len(words.hashes)
    if total < width:
        none = np.zeros(0, np.int64)
        return none, none.astype(np.uint64), none, none
    least = sliding_least(gram_hashes(words.hashes, gram), width - gram + 1)
    owner = words.owner()[: len(least)]
    inside = np.arange(len(least)) + width <= words.end[owner]  # windows that end in their own text
    same = (least[1:] == least[:-1]) & inside[1:] & inside[:-1]
    starts = np.flatnonzero(inside & ~np.r_[False, same])
    lengths = np.flatnonzero(inside & ~np.r_[same, False]) + 1 - starts
    if (lengths > RUN_WINDOWS).any():
        parts = -(-lengths // RUN_WINDOWS)
        within = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
        stops = np.repeat(starts + lengths, parts)
        starts = np.repeat(starts, parts) + within * RUN_WINDOWS
        lengths = np.minimum(stops - starts, RUN_WINDOWS)
    owner = owner[starts]
    return owner, least[starts], starts - words.first[owner], lengths


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, list[bytes]]]:
    """Ids and texts of the rows that have an id."""
    for batch in slices(batches, "t", 4 << 20):
        known = batch.filter(batch.column("d").is_valid())
        if known.num_rows:
            yield known.column("d").to_numpy(), [x or b"" for x in binary(known.column("t"))]


def _signed(values: np.ndarray) -> pa.Array:
    return pa.array(np.asarray(values, np.uint64).view(np.int64))


def _minimisers(df: DataFrame, width: int) -> DataFrame:
    """(mini, doc, runs), once for each text and minimiser."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in _documents(batches):
            owner, mini, _, _ = super_runs(Words(texts), width)
            order = np.lexsort((mini, owner))
            owner, mini = owner[order], mini[order]
            fresh = np.r_[True, (owner[1:] != owner[:-1]) | (mini[1:] != mini[:-1])][: len(mini)]
            heads = np.flatnonzero(fresh)
            yield pa.RecordBatch.from_arrays([_signed(mini[heads]), pa.array(ids[owner[heads]]), pa.array(np.diff(np.r_[heads, len(mini)]))], ["mini", "doc", "runs"])

    return df.mapInArrow(run, "mini bigint, doc bigint, runs bigint")


_RUNS = "mini bigint, h0 bigint, h1 bigint, doc bigint, row_key bigint, start int, stop int, packed binary"


def _packed(df: DataFrame, width: int, shared: BitFilter, hot: BitFilter, want_hot: bool) -> DataFrame:
    """Runs of shared minimisers with their packed strings; hot ones carry a string's digest, and the string once a batch."""
    sent = df.sparkSession.sparkContext.broadcast((shared, hot))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep, often = sent.value
        for ids, texts in _documents(batches):
            words = Words(texts)
            owner, mini, starts, lengths = super_runs(words, width)
            chosen = np.flatnonzero(keep.hits(mini) & (often.hits(mini) == want_hot))
            if not len(chosen):
                continue
            owner, mini, starts, lengths = owner[chosen], mini[chosen], starts[chosen], lengths[chosen]
            packed = [b" ".join(words.split[t][s : s + n + width - 1]) for t, s, n in zip(owner.tolist(), starts.tolist(), lengths.tolist())]
            halves = np.zeros((len(packed), 2), np.int64)
            if want_hot:
                names = [xxhash.xxh3_128_digest(x) for x in packed]
                halves = np.frombuffer(b"".join(names), "<i8").reshape(-1, 2)
                once = dict(zip(reversed(names), range(len(names) - 1, -1, -1)))
                packed = [x if once[name] == i else None for i, (name, x) in enumerate(zip(names, packed))]
            keys = {t: xxhash.xxh3_64_intdigest(texts[t]) for t in np.unique(owner).tolist()}
            yield pa.RecordBatch.from_arrays([
                _signed(mini), pa.array(halves[:, 0].copy()), pa.array(halves[:, 1].copy()), pa.array(ids[owner]), _signed([keys[t] for t in owner.tolist()]),
                pa.array(starts.astype(np.int32)), pa.array((starts + lengths + width - 1).astype(np.int32)), pa.array(packed, pa.binary()),
            ], _RUNS.replace(",", "").split()[::2])

    return df.mapInArrow(run, _RUNS)


_SPANS = "doc bigint, row_key bigint, lo int, hi int"


def _windows(packed: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(string, begin, end) of every window as places in its packed string."""
    row, begin, end = [], [], []
    for i, text in enumerate(packed):
        at = np.flatnonzero(np.frombuffer(text, np.uint8) == 32)
        heads, tails = np.r_[0, at + 1], np.r_[at, len(text)]
        n = len(heads) - width + 1
        row.append(np.full(n, i))
        begin.append(heads[:n])
        end.append(tails[width - 1 :])
    return np.concatenate(row), np.concatenate(begin), np.concatenate(end)


def _first_docs(doc: np.ndarray, packed: list[bytes], row: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Least doc of the strings that hold each window: sort by digest, then let the bytes of equal neighbours decide."""
    views = [memoryview(text) for text in packed]
    text = lambda i: views[row[i]][begin[i] : end[i]]
    digest = np.fromiter((xxhash.xxh3_64_intdigest(views[r][a:b]) for r, a, b in zip(row.tolist(), begin.tolist(), end.tolist())), np.uint64, len(row))
    order = np.lexsort((doc[row], digest))
    ordered = digest[order]
    fresh = np.r_[True, ordered[1:] != ordered[:-1]]
    for i in np.flatnonzero(~fresh).tolist():
        if text(order[i]) != text(order[i - 1]):  # two sequences under one digest
            order = np.array(sorted(range(len(row)), key=lambda k: (bytes(text(k)), doc[row[k]])))
            fresh = np.array([True] + [text(a) != text(b) for a, b in zip(order, order[1:])])
            break
    first = np.empty(len(row), np.int64)
    first[order] = doc[row][order][np.flatnonzero(fresh)][np.cumsum(fresh) - 1]
    return first


def _bucket_spans(packed: DataFrame, width: int) -> DataFrame:
    """Spans from buckets of at most HOT_RUNS runs a minimiser."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in whole_groups(batches, "mini", "packed", 3 << 20):
            mini, doc = rows.column("mini").to_numpy(), rows.column("doc").to_numpy()
            begins = np.flatnonzero(np.r_[True, mini[1:] != mini[:-1]])
            several = np.minimum.reduceat(doc, begins) < np.maximum.reduceat(doc, begins)
            kept = np.flatnonzero(np.repeat(several, np.diff(np.r_[begins, len(mini)])))
            if not len(kept):
                continue
            rows = rows.take(kept).combine_chunks()
            doc, texts = rows.column("doc").to_numpy(), rows.column("packed").to_pylist()
            row, begin, end = _windows(texts, width)
            again = np.flatnonzero(doc[row] > _first_docs(doc, texts, row, begin, end))
            if not len(again):
                continue
            counts = np.bincount(row, minlength=len(texts))
            place = rows.column("start").to_numpy()[row] + (np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts))
            cut = np.r_[True, (np.diff(again) > 1) | (np.diff(row[again]) > 0)]
            heads = np.flatnonzero(cut)
            tails = np.r_[heads[1:], len(again)] - 1
            owner = row[again[heads]]
            yield pa.RecordBatch.from_arrays([pa.array(doc[owner]), pa.array(rows.column("row_key").to_numpy()[owner]), pa.array(place[again[heads]].astype(np.int32)), pa.array((place[again[tails]] + width).astype(np.int32))], ["doc", "row_key", "lo", "hi"])

    return packed.select("mini", "doc", "row_key", "start", "packed").repartition("mini").sortWithinPartitions("mini").mapInArrow(run, _SPANS)


def _named_windows(packed: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """(string, 128-bit digest) of every window."""
    row, begin, end = _windows(packed, width)
    views = [memoryview(text) for text in packed]
    digests = b"".join([xxhash.xxh3_128_digest(views[r][a:b]) for r, a, b in zip(row.tolist(), begin.tolist(), end.tolist())])
    return row, np.frombuffer(digests, "<i8").reshape(-1, 2)


def _folded(codes: np.ndarray) -> np.ndarray:
    """One code (twice the slot, plus a mark) for each slot, in order; it has the mark if one of its codes had it or there were two."""
    codes = np.sort(codes)
    tails = np.flatnonzero(np.r_[codes[1:] >> 1 != codes[:-1] >> 1, True][: len(codes)])
    return codes[tails] | (np.diff(np.r_[-1, tails]) > 1).astype(codes.dtype)


def _windows_of_two(strings: DataFrame, width: int) -> BitFilter:
    """Bitmap of the windows that two of the distinct strings hold.

    Every task folds its windows to one code a slot and sends a part of the bitmap as one row; at most 2**FILTER_BITS bits reach the driver.
    """

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, most = [], 0, 1 << 20
        for batch in slices(batches, "packed", 1 << 20):
            row, names = _named_windows(batch.column("packed").to_pylist(), width)
            slot = names[:, 0] & ((1 << FILTER_BITS) - 1)
            once = np.unique(row << FILTER_BITS | slot) & ((1 << FILTER_BITS) - 1)  # a string counts once
            held.append(_folded(once.astype(np.uint32) << np.uint32(1)))
            size += len(held[-1])
            if size > most:
                held = [_folded(np.concatenate(held))]
                size, most = len(held[0]), max(most, 2 * len(held[0]))
        if held:
            codes = _folded(np.concatenate(held))
            part = codes >> np.uint32(PART_BITS + 1)
            heads = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
            yield pa.RecordBatch.from_arrays([pa.array(part[heads].astype(np.int32)), pa.array([x.tobytes() for x in np.split(codes, heads[1:])], pa.binary())], ["part", "codes"])

    def united(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, once, twice = None, np.zeros(1 << PART_BITS, bool), np.zeros(1 << PART_BITS, bool)
        bits = lambda: pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([np.packbits(twice, bitorder="little").tobytes()], pa.binary())], ["part", "bits"])
        for batch in batches:
            for part, packed in zip(batch.column("part").to_pylist(), batch.column("codes").to_pylist()):
                if part != at:
                    if at is not None:
                        yield bits()
                    at = part
                    once[:] = twice[:] = False
                codes = np.frombuffer(packed, np.uint32)
                slot = codes >> np.uint32(1) & np.uint32((1 << PART_BITS) - 1)
                twice[slot[(codes & np.uint32(1) > 0) | once[slot]]] = True
                once[slot] = True
        if at is not None:
            yield bits()

    parts = strings.select("packed").mapInArrow(seen, "part int, codes binary").repartition("part").sortWithinPartitions("part").mapInArrow(united, "part int, bits binary")
    words = np.zeros((1 << (FILTER_BITS - PART_BITS), 1 << (PART_BITS - 6)), np.uint64)
    for batch in parts.toArrow().to_batches():
        for part, packed in zip(batch.column("part").to_pylist(), batch.column("bits").to_pylist()):
            words[part] = np.frombuffer(packed, np.uint64)
    return BitFilter(words.reshape(-1), FILTER_BITS)


def _hot_spans(runs: DataFrame, width: int) -> DataFrame:
    """Spans under hot minimisers, from the distinct strings.

    A run whose string an earlier document has loses all its words.  The first document of a string loses the
    windows that an earlier document has in another string; a window that only one string holds needs no look.
    """
    name = ["h0", "h1"]
    runs = cut_lineage(runs)
    strings = cut_lineage(runs.groupBy(*name).agg(F.min("doc").alias("least"), F.max("doc").alias("most"), F.max("packed").alias("packed")))
    sent = strings.sparkSession.sparkContext.broadcast(_windows_of_two(strings, width))

    def opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "packed", 1 << 20):
            row, halves = _named_windows(batch.column("packed").to_pylist(), width)
            counts = np.bincount(row, minlength=batch.num_rows)
            place = np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)
            kept = np.flatnonzero(sent.value.hits(halves[:, 0].view(np.uint64)))
            halves, place, at = halves[kept], place[kept], pa.array(row[kept])
            yield pa.RecordBatch.from_arrays([pa.array(halves[:, 0].copy()), pa.array(halves[:, 1].copy()), *(batch.column(c).take(at) for c in (*name, "least")), pa.array(place.astype(np.int32))], ["w0", "w1", *name, "least", "place"])

    windows = strings.select(*name, "least", "packed").mapInArrow(opened, "w0 bigint, w1 bigint, h0 bigint, h1 bigint, least bigint, place int")
    first = windows.groupBy("w0", "w1").agg(F.min("least").alias("first_doc"), F.max("least").alias("last_doc")).where("first_doc < last_doc").drop("last_doc")
    earlier = windows.join(first, ["w0", "w1"]).where("least > first_doc").select(*name, F.col("least").alias("doc"), "place")
    partly = runs.select(*name, "doc", "row_key", "start").join(earlier, [*name, "doc"]).select("doc", "row_key", (F.col("start") + F.col("place")).alias("lo"), (F.col("start") + F.col("place") + width).alias("hi"))
    whole = runs.join(strings.where("least < most").select(*name, "least"), name).where("doc > least").select("doc", "row_key", F.col("start").alias("lo"), F.col("stop").alias("hi"))
    return whole.union(partly)


def repeated_spans(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = 50) -> DataFrame:
    """(doc, row_key, lo, hi): word ranges covered by windows that start in a document with a smaller id."""
    docs = df.selectExpr(f"cast(`{key}` as bigint) as d", f"`{text}` as t")
    counted = _minimisers(docs, width).groupBy("mini").agg(F.sum("runs").alias("runs"), F.min("doc").alias("lo"), F.max("doc").alias("hi"))
    twice = cut_lineage(counted.where("lo < hi").select("mini", "runs"))
    shared, hot = bit_filter(twice, "mini"), bit_filter(twice.where(F.col("runs") > HOT_RUNS), "mini")
    spans = _bucket_spans(_packed(docs, width, shared, hot, False), width)
    return spans.union(_hot_spans(_packed(docs, width, shared, hot, True), width)) if hot.words.any() else spans


def _keep(text: bytes, spans: list[tuple[int, int]]) -> tuple[list[bytes], int]:
    words = text.split()
    gone = np.zeros(len(words) + 1, np.int64)
    for lo, hi in spans:
        gone[lo] += 1
        gone[hi] -= 1
    covered = np.cumsum(gone[:-1]) > 0
    return [w for w, c in zip(words, covered.tolist()) if not c], len(words)


def _apply(df: DataFrame, width: int, finish, schema: str, columns: list[str]) -> DataFrame:
    """Call `finish(batch, kept words, n_words)` on every row of df(d, t, ...), with its spans where it has some."""
    spans = cut_lineage(repeated_spans(df, "d", "t", width).groupBy("doc", "row_key").agg(F.collect_list(F.struct("lo", "hi")).alias("spans")))
    touched = df.sparkSession.sparkContext.broadcast(bit_filter(spans.select(F.col("row_key").alias("h")), "h"))

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t"):
            keys = np.array([xxhash.xxh3_64_intdigest(x or b"") for x in binary(batch.column("t"))], np.uint64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(keys.view(np.int64))], [*batch.schema.names, "row_key"]).filter(pa.array(touched.value.hits(keys)))

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t"):
            texts = [x or b"" for x in binary(batch.column("t"))]
            keys = np.array([xxhash.xxh3_64_intdigest(x) for x in texts], np.uint64)
            free = np.flatnonzero(~touched.value.hits(keys))
            if len(free):
                words = [texts[i].split() for i in free.tolist()]
                yield finish(batch.take(pa.array(free)), words, [len(w) for w in words])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "t"):
            kept, totals = [], []
            for text, spans_ in zip(binary(batch.column("t")), batch.column("spans").to_pylist()):
                words, n = _keep(text or b"", [(s["lo"], s["hi"]) for s in spans_ or ()])
                kept.append(words)
                totals.append(n)
            yield finish(batch.select(columns), kept, totals)

    width_schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
    some = df.mapInArrow(keyed, f"{width_schema}, row_key bigint").join(spans.withColumnRenamed("row_key", "span_key"), (F.col("d") == F.col("doc")) & (F.col("row_key") == F.col("span_key")), "left").select(*columns, "spans")
    return df.mapInArrow(clean, schema).union(some.mapInArrow(cut, schema))


def removal_digests(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = 50) -> DataFrame:
    """doc_id, n_words, n_removed and the digest of the kept words, for every row."""

    def finish(batch: pa.RecordBatch, kept: list[list[bytes]], totals: list[int]) -> pa.RecordBatch:
        sums = [hashlib.sha256(b" ".join(words)).hexdigest() for words in kept]
        gone = [n - len(words) for n, words in zip(totals, kept)]
        return pa.RecordBatch.from_arrays([batch.column("d"), pa.array(totals, pa.int64()), pa.array(gone, pa.int64()), pa.array(sums, pa.string())], ["d", "n_words", "n_removed", "kept_sha256"])

    out = _apply(df.selectExpr(f"cast(`{key}` as bigint) as d", f"`{text}` as t"), width, finish, "d bigint, n_words bigint, n_removed bigint, kept_sha256 string", ["d", "t"])
    return out.withColumnRenamed("d", key)


def remove_repeats(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = 50, keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, text, *keep, n_removed): rows that lose words get their kept words joined by one space; other texts stay as they are."""
    extra = [f"x{i}" for i in range(len(keep))]

    def finish(batch: pa.RecordBatch, kept: list[list[bytes]], totals: list[int]) -> pa.RecordBatch:
        gone = [n - len(words) for n, words in zip(totals, kept)]
        texts = [old if not g else b" ".join(words).decode() for old, g, words in zip(batch.column("t").to_pylist(), gone, kept)]
        return pa.RecordBatch.from_arrays([batch.column("d"), pa.array(texts, pa.string()), *(batch.column(x) for x in extra), pa.array(gone, pa.int64())], ["d", "t", *extra, "n_removed"])

    rows = df.select(F.col(key).cast("bigint").alias("d"), F.col(text).alias("t"), *(F.col(c).alias(x) for c, x in zip(keep, extra)))
    types = "".join(f", {f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[2:])
    out = _apply(rows, width, finish, f"d bigint, t string{types}, n_removed bigint", ["d", "t", *extra])
    return out.withColumnsRenamed({"d": key, "t": text, **dict(zip(extra, keep))})


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removal_digests(table(spark, sf_dir, "documents"))


#: DuckDB: the same result by plain windows over word lists.
OP2_SQL = """
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents),
win AS (
  SELECT doc_id, p, array_to_string(ws[p:p + 49], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS p FROM w WHERE len(ws) >= 50)),
dup AS (SELECT doc_id, p FROM (SELECT doc_id, p, min(doc_id) OVER (PARTITION BY k) AS f FROM win) WHERE f < doc_id),
gone AS (SELECT DISTINCT doc_id, unnest(range(p, p + 50)) AS q FROM dup),
g AS (SELECT doc_id, list(q) AS qs FROM gone GROUP BY doc_id),
kept AS (
  SELECT w.doc_id, len(ws) AS n, ws, coalesce(qs, []) AS qs FROM w LEFT JOIN g USING (doc_id)),
pos AS (SELECT doc_id, unnest(ws) AS x, unnest(range(1, len(ws) + 1)) AS q FROM w),
txt AS (
  SELECT pos.doc_id, string_agg(x, ' ' ORDER BY pos.q) AS t FROM pos LEFT JOIN gone ON gone.doc_id = pos.doc_id AND gone.q = pos.q
  WHERE gone.q IS NULL GROUP BY pos.doc_id)
SELECT kept.doc_id, CAST(n AS BIGINT) AS n_words, CAST(len(qs) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM kept LEFT JOIN txt USING (doc_id)
"""
