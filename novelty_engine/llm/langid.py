"""Language identification by compression.

Each language has a zstandard raw-content dictionary cut from labelled text.  A text is
normalised (lower case, letter runs only, immediate repeats of a word dropped so that a text
cannot compress against itself) and its short blocks are compressed once with every
dictionary; the smallest total wins.  The score is the relative margin over the runner-up, and
a margin under `narrow` rejects the decision.

Training reads a bounded sample: of each language the labelled texts with the least hashes, whole,
at most `per_language` of them and as long as they fit into `dictionary_bytes` after normalising
(one that does not fit is passed over).  Both bounds are shared out when there are more than
`FULL_LANGUAGES` languages, so what is broadcast stays under FULL_LANGUAGES * dictionary_bytes.
Scoring reads whole texts.  A null text, or one without a letter, is `und` with score 0 and
rejected.  With no labelled rows every text is `und`; with one language its score is 1.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import groupby

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import crc_fold, ship, slices, table

FULL_LANGUAGES = 64
LEVEL, BLOCK = 3, 512
NARROW = 0.003
_LETTERS = re.compile(r"[^\W\d_]+")


def normalise(text: str) -> str:
    return " ".join([word for word, _ in groupby(_LETTERS.findall(text.lower()))])


def hash_sample(rows: DataFrame, by: str, per_group: int, sizes: dict, seed: int = 7) -> DataFrame:
    """The `per_group` rows of each value of `by` with the least hash of `id`, plus their `place`; rows are distinct.

    `sizes` has the number of rows of each value.  Hashes are even, so rows beyond a cut that holds `per_group` rows with
    eight standard errors to spare are left out before the window, which then meets about `per_group` rows of a value.
    """
    hashed = rows.withColumn("h_", F.xxhash64(F.col("id"), F.lit(seed)))
    share = {k: min(1.0, (per_group + 8 * per_group**0.5 + 32) / max(1, n)) for k, n in sizes.items()}
    cuts = [(k, int(-(2**63) + s * (2**64 - 1))) for k, s in share.items() if s < 1]
    if cuts:
        cut = F.create_map(*(F.lit(x) for pair in cuts for x in pair))
        hashed = hashed.where(F.coalesce(F.col("h_") <= F.try_element_at(cut, F.col(by)), F.lit(True)))
    order = Window.partitionBy(by).orderBy("h_", "id")
    return hashed.withColumn("place", F.row_number().over(order)).where(F.col("place") <= per_group).drop("h_")


def train(df: DataFrame, key: str, text: str, lang: str, usable: Column, per_language: int = 900, dictionary_bytes: int = 448 << 10) -> dict[str, bytes]:
    """Dictionary of each language, most frequent language in the sample first."""
    fits = F.octet_length(F.col(text)) <= dictionary_bytes
    labelled = df.where(usable & F.col(lang).isNotNull() & F.col(text).isNotNull() & fits)
    rows = labelled.select(F.col(key).alias("id"), F.col(lang).alias("lang")).distinct()
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).toLocalIterator()}
    parts_of_all = max(1, -(-len(sizes) // FULL_LANGUAGES))
    most, room = max(1, per_language // parts_of_all), dictionary_bytes // parts_of_all
    ids = hash_sample(rows, "lang", most, sizes)
    sample = labelled.select(F.col(key).alias("id"), F.col(lang).alias("lang"), F.col(text).alias("text")).join(F.broadcast(ids), ["id", "lang"]).orderBy("lang", "place", F.xxhash64("text"), "text")
    parts: dict[str, list[bytes]] = {}
    free: dict[str, int] = {}
    for row in sample.select("lang", "text").toLocalIterator():
        clean = normalise(row.text).encode()
        mine = parts.setdefault(row.lang, [])
        if clean and len(mine) < most and len(clean) < free.setdefault(row.lang, room):
            mine.append(clean)
            free[row.lang] -= len(clean) + 1
    order = sorted((k for k in parts if parts[k]), key=lambda k: (-len(parts[k]), k))
    return {k: b"\n".join(parts[k]) for k in order}


class Sizer:
    """Compressed size of a text under each dictionary."""

    def __init__(self, dictionaries: dict[str, bytes]):
        self.by = {}
        for lang, raw in dictionaries.items():
            content = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            content.precompute_compress(level=LEVEL)
            self.by[lang] = zstandard.ZstdCompressor(dict_data=content, write_checksum=False, write_content_size=False).compress

    def classify(self, text: str | None) -> tuple[str, float]:
        raw = normalise(text or "").encode()
        if not raw or not self.by:
            return "und", 0.0
        blocks = [raw[at : at + BLOCK] for at in range(0, len(raw), BLOCK)]
        sizes = [(sum(map(len, map(compress, blocks))), order, lang) for order, (lang, compress) in enumerate(self.by.items())]
        if len(sizes) == 1:
            return sizes[0][2], 1.0
        best, second = sorted(sizes)[:2]
        return best[2], (second[0] - best[0]) / second[0]


def identify(df: DataFrame, dictionaries: dict[str, bytes], key: str = "doc_id", text: str = "text", narrow: float = NARROW, keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, *keep, lang_pred, score, rejected) for every row."""
    shared = ship(df.sparkSession).sparkContext.broadcast(dictionaries)
    at = f"k{1 + keep.index(text)}" if text in keep else "t"
    kept = ", ".join(f"k{i} {df.schema[c].dataType.simpleString()}" for i, c in enumerate((key, *keep)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizer = Sizer(shared.value)
        for batch in slices(batches, at):
            found = [sizer.classify(t) for t in batch.column(at).to_pylist()]
            scores = [score for _, score in found]
            names = [n for n in batch.schema.names if n != "t"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array([lang for lang, _ in found], pa.string()), pa.array(scores, pa.float64()), pa.array([lang == "und" or score < narrow for lang, score in found], pa.bool_())], [*names, "lang_pred", "score", "rejected"])

    out = df.select(*(F.col(c).alias(f"k{i}") for i, c in enumerate((key, *keep))), *([] if text in keep else [F.col(text).alias("t")])).mapInArrow(run, f"{kept}, lang_pred string, score double, rejected boolean")
    return out.withColumnsRenamed({f"k{i}": c for i, c in enumerate((key, *keep))})


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = crc_fold("doc_id", 3) == 1
    dictionaries = train(docs, "doc_id", "text", "lang", ~held_out)
    return identify(docs, dictionaries).select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "rejected")


__all__ = ["Sizer", "hash_sample", "identify", "normalise", "op5_language_id", "train"]
