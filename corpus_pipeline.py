"""Corpus cleaning in five stages, each one of the training-data operators.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; `run` writes each
stage as Parquet in the shared folder and reads it again.  All but the last return the columns of
`documents`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from novelty_engine.llm import jaccard, langid, packing, secrets, substring
from novelty_engine.llm.common import crc_fold, cut_lineage, fresh_folder, ship
from novelty_engine.session import remove_folder

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _sized(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.length("text").cast("bigint")).select(*COLUMNS)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents whose language the classifier rejects: no letter, or too narrow a margin."""
    ship(spark)
    dictionaries = langid.train(docs, "doc_id", "text", "lang", crc_fold("doc_id", 3) != 1)
    return langid.identify(docs, dictionaries, keep=COLUMNS[1:]).where("not rejected").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each class of near copies: the least doc_id, rows without one last, then the least hash of the row.

    Rows are told apart by all their columns, so of rows that repeat an id, or have none, one stays as well; texts without
    words belong to no class and stay.
    """
    ship(spark)
    row = F.xxhash64(*COLUMNS)
    named = cut_lineage(jaccard.near_groups(docs, {"doc_id": F.col("doc_id"), "row": row}).where("near_group is not null"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row"))
    kept = cut_lineage(named.groupBy("near_group").agg(first.alias("x")).select("x.row").join(named.groupBy("row").agg(F.count("*").alias("n")), "row"))
    keyed = docs.select(*COLUMNS, row.alias("row"))
    wordless = keyed.where(~F.coalesce("text", F.lit("")).rlike(r"[^\x20\x09-\x0D]"))
    out = wordless.select(*COLUMNS).unionByName(keyed.join(kept.where("n = 1"), "row", "left_semi").select(*COLUMNS))
    if kept.where("n > 1").limit(1).count():
        out = out.unionByName(keyed.join(kept.where("n > 1"), "row", "left_semi").dropDuplicates(["row"]).select(*COLUMNS))
    return out


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove repeated windows; a document that loses all its words goes."""
    ship(spark)
    cut = substring.remove_repeats(docs, keep=("lang", "source"))
    return _sized(cut.where("n_removed = 0 or text <> ''"))


def secret_spans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replace secrets in the text."""
    return _sized(secrets.redact(docs, keep=("lang", "source")))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bins of the cleaned documents; what masking and cutting have made alike is kept apart again."""
    return packing.pack_near(docs)


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("secret_spans", secret_spans),
    ("packed", packed),
]

#: Compression sizes, sampled paths and sequential packing have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows.  A stage's folder goes when the next one has been written; the last one's stays, the result reads it."""
    docs, folder = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        before, folder = folder, fresh_folder(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(folder)
        docs = spark.read.parquet(folder)
        if before:
            remove_folder(spark, before)
    return docs
