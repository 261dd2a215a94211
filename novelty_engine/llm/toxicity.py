"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Features are hashed character n-grams of the lower-cased whole text, valued by the logarithm of
one plus their count per thousand characters, so that long texts are not toxic merely by having
more of everything.  The log ratio of smoothed n-gram counts in the two classes scales each
feature; logistic regression (with L2 shrinkage) is then fitted on the scaled features.

Training reads a bounded sample: at most `per_class` labelled documents of each class with whole texts
of at most `most_bytes`, chosen by hash, and fits on the driver with arrays of 2**BITS entries.  Rows
that repeat an id train with its greatest label.  Scoring is one pass over all documents, however
long, with the broadcast weights (4 bytes * 2**BITS).  Null and empty texts get the score of the
intercept; so does every text when no labelled row exists (score 0).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_fold, ship, slices, table
from .langid import hash_sample

BITS = 20
SIZES = (5, 6, 7)
LEAST_RATIO, LEAST_TEXTS = 0.7, 4
_ODD = np.array([0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35, 0x27D4EB2F, 0x165667B1, 0xD3A2646D, 0x9E3779B9], np.uint32)


def grams(text: str, size: int) -> np.ndarray:
    """Hashed n-grams of a padded lower-cased text, by position."""
    chars = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    n = len(chars) - size + 1
    if n <= 0:
        return np.zeros(0, np.int32)
    out = chars[:n] * _ODD[0]
    for k in range(1, size):
        out = (out ^ (out >> np.uint32(15))) * _ODD[k] + chars[k : k + n]
    out ^= out >> np.uint32(13)
    out *= _ODD[size - 1]
    return (out >> np.uint32(32 - BITS)).astype(np.int32)


def padded(text: str | None) -> str:
    return f" {(text or '').lower()} "


def rates(text: str, useful: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(feature, count) of the useful features of a text."""
    found = [grams(text, size) for size in SIZES]
    return np.unique(np.concatenate([at if useful is None else at[useful[at]] for at in found]), return_counts=True)


def value(counts: np.ndarray, text: str) -> np.ndarray:
    return np.log1p(counts * (1000.0 / max(1, len(text))))


def fit(texts: list[str], toxic: np.ndarray, prior: float, rounds: int = 200, shrink: float = 1e-3) -> tuple[np.ndarray, float]:
    """(weight of each feature, intercept): naive Bayes ratios, then logistic regression on what they scale."""
    seen, counts = np.zeros(1 << BITS, np.int64), np.zeros((2, 1 << BITS))
    for text, y in zip(texts, toxic):
        names, times = rates(text)
        seen[names] += 1
        counts[y, names] += times
    totals = np.maximum(counts.sum(axis=1), 1.0)
    smooth = 2.0 * totals / totals[1]
    ratio = np.log((counts[1] + smooth[1]) / totals[1]) - np.log((counts[0] + smooth[0]) / totals[0])
    ratio[(np.abs(ratio) < LEAST_RATIO) | (seen < LEAST_TEXTS)] = 0
    useful = ratio != 0
    rows = [rates(text, useful) for text in texts]
    sizes = [len(names) for names, _ in rows]
    values = np.concatenate([value(times, text) for (_, times), text in zip(rows, texts)])
    names, flat = np.unique(np.concatenate([names for names, _ in rows]), return_inverse=True)
    owner = np.repeat(np.arange(len(rows)), sizes)
    scaled = values * ratio[names][flat]
    share = np.where(toxic == 1, prior * len(toxic) / max(1, (toxic == 1).sum()), (1 - prior) * len(toxic) / max(1, (toxic == 0).sum()))
    beta, bias = np.zeros(len(names)), np.log(prior / (1 - prior))
    grad_sq, bias_sq = np.full(len(names), 1e-8), 1e-8
    for _ in range(rounds):  # adaptive gradient steps
        margin = np.bincount(owner, weights=beta[flat] * scaled, minlength=len(rows)) + bias
        error = share * (1 / (1 + np.exp(-np.clip(margin, -30, 30))) - toxic) / len(rows)
        grad = np.bincount(flat, weights=error[owner] * scaled, minlength=len(names)) + shrink * beta
        grad_sq += grad * grad
        bias_sq += error.sum() ** 2
        beta -= 0.1 * grad / np.sqrt(grad_sq)
        bias -= 0.1 * error.sum() / np.sqrt(bias_sq)
    weights = np.zeros(1 << BITS, np.float32)
    weights[names] = beta * ratio[names]
    return weights, float(bias)


def train(docs: DataFrame, labels: DataFrame, usable: Column, key: str = "doc_id", text: str = "text", label: str = "toxic", per_class: int = 2500, most_bytes: int = 256 << 10) -> tuple[np.ndarray, float] | None:
    """Fit on a bounded hash sample; `usable` is a condition on the key column."""
    known = labels.where(usable & F.col(label).isin(0, 1)).groupBy(F.col(key).alias("id")).agg(F.max(label).cast("int").alias("y"))
    sizes = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return None
    chosen = hash_sample(known, "y", per_class, sizes).select("id", "y")
    short = F.coalesce(F.octet_length(F.col(text)), F.lit(0)) <= most_bytes
    rows = docs.where(short).select(F.col(key).alias("id"), F.col(text).alias("t")).join(F.broadcast(chosen), "id").distinct().orderBy(F.xxhash64("id"), F.xxhash64("t"))
    texts, toxic = [], []
    for row in rows.select("t", "y").toLocalIterator():
        texts.append(padded(row.t))
        toxic.append(row.y)
    prior = min(0.99, max(0.01, sizes.get(1, 0) / sum(sizes.values())))
    return fit(texts, np.array(toxic, np.int64), prior) if texts else None


def score(df: DataFrame, model: tuple[np.ndarray, float] | None, key: str = "doc_id", text: str = "text", cut: float = 0.3) -> DataFrame:
    """(key, score, predicted) for every row."""
    shared, kind = ship(df.sparkSession).sparkContext.broadcast(model), df.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, bias = shared.value or (np.zeros(1 << BITS, np.float32), -30.0)
        useful = weights != 0
        for batch in slices(batches, "t"):
            margins = np.full(batch.num_rows, bias)
            for i, t in enumerate(map(padded, batch.column("t").to_pylist())):
                names, times = rates(t, useful)
                margins[i] += (weights[names] * value(times, t)).sum()
            scores = 1 / (1 + np.exp(-np.clip(margins, -30, 30)))
            yield pa.RecordBatch.from_arrays([batch.column("k"), pa.array(scores), pa.array((scores >= cut).astype(np.int32))], ["k", "score", "predicted"])

    return df.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, f"k {kind}, score double, predicted int").withColumnRenamed("k", key)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = crc_fold("doc_id", 4) == 2
    model = train(docs, labels, ~held_out)
    return score(docs, model).select("doc_id", held_out.alias("held_out"), "score", "predicted")
