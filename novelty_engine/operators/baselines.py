"""Baselines: citation counts, h-index, plain similarity, fixed axes, cumulative mean, extraction engines."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import words
from ..session import ship
from .scan import ranks


def rank_by_citations(links: DataFrame) -> DataFrame:
    counts = links.groupBy(F.col("dst").alias("item_id")).agg(F.count("*").alias("cites"))
    return ranks(counts, "cites", "cite_rank")


def h_index(links: DataFrame, items: DataFrame, by: str) -> DataFrame:
    """Largest h such that h items of a group have h citations each."""
    counts = items.select("item_id", by).join(links.groupBy(F.col("dst").alias("item_id")).agg(F.count("*").alias("cites")), "item_id", "left").withColumn("cites", F.coalesce("cites", F.lit(0)))
    ranked = counts.withColumn("place", F.row_number().over(Window.partitionBy(by).orderBy(F.desc("cites"), "item_id")))
    return ranked.groupBy(by).agg(F.coalesce(F.max(F.when(F.col("cites") >= F.col("place"), F.col("place"))), F.lit(0)).cast("bigint").alias("h"))


def similarity_search(vectors: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """Whole-item nearest neighbours by cosine, no axes."""
    from .network import semantic_network

    return semantic_network(vectors, queries.select("target_id"), top_k=k, min_sim=-1.0).select("target_id", "item_id", F.col("relevance").alias("sim"))


def rank_by_nu_bar(paced: DataFrame) -> DataFrame:
    """Rank by the cumulative mean, which favours late items; kept to show what marginal gains repair."""
    return paced.withColumn("nu_rank", F.rank().over(Window.partitionBy("target_id").orderBy(F.desc("nu_bar"))).cast("bigint"))


def newest_first_network(links: DataFrame, items: DataFrame, targets: DataFrame, limit: int = 50) -> DataFrame:
    """Citation cap by date instead of relevance."""
    from .network import cap_neighbours

    cites = targets.join(links, F.col("target_id") == F.col("dst")).select("target_id", F.col("src").alias("item_id"), "relevance").join(items.select("item_id", "pub_date"), "item_id")
    return cap_neighbours(cites, ["target_id"], by="date", limit=limit)


def pairwise_winners(items: DataFrame, axes: dict[str, int], key: str = "item_id", fixed: str | None = None) -> DataFrame:
    """(winner, loser) of every pair of a few items, each pair on an axis of its own: the one with the largest relative lead (ties by
    name), or on the `fixed` axis for all.  Pairs grow with the square of the items, so it is for sets of targets."""
    wide = items.select(F.col(key).alias("id"), *(F.col(a).cast("double").alias(a) for a in axes))
    a, b = wide.select([F.col(c).alias(f"a_{c}") for c in wide.columns]), wide.select([F.col(c).alias(f"b_{c}") for c in wide.columns])
    pairs = a.join(b, F.col("a_id") < F.col("b_id"))
    lead = lambda x: F.coalesce(F.try_divide((F.col(f"a_{x}") - F.col(f"b_{x}")) * axes[x], F.greatest(F.abs(F.col(f"a_{x}")), F.abs(F.col(f"b_{x}")))), F.lit(0.0))
    used = [fixed] if fixed else sorted(axes)
    best = F.array_sort(F.array(*(F.struct((-F.abs(lead(x))).alias("size"), F.lit(x).alias("axis"), lead(x).alias("lead")) for x in used)))[0]
    played = pairs.select("a_id", "b_id", best.alias("x")).where("x.lead <> 0")
    return played.select(F.when(F.col("x.lead") > 0, F.col("a_id")).otherwise(F.col("b_id")).alias("winner"), F.when(F.col("x.lead") > 0, F.col("b_id")).otherwise(F.col("a_id")).alias("loser"), F.col("x.axis").alias("axis"))


def intransitive_triples(wins: DataFrame) -> DataFrame:
    """One row: the number of triples in which a beats b, b beats c and c beats a.  No fixed numeric axis has one."""
    w = lambda x, y: wins.select(F.col("winner").alias(x), F.col("loser").alias(y))
    return w("a", "b").join(w("b", "c"), "b").join(w("c", "a"), ["c", "a"]).where("a < b and a < c").agg(F.count("*").alias("n_cycles"))


def _python_words(text: str | None) -> int:
    import re

    return len([x for x in re.split(r"[ \t\n\r\f]+", text or "") if x])


def extraction_engines() -> dict[str, Callable[[DataFrame], DataFrame]]:
    """The same extraction (number of words, number of lines) on several engines: (item_id, n_words, n_lines)."""

    def built_in(df: DataFrame) -> DataFrame:
        return df.select("item_id", F.size(words(F.col("body"))).cast("bigint").alias("n_words"), F.size(F.split("body", "\n")).cast("bigint").alias("n_lines"))

    def sql(df: DataFrame) -> DataFrame:
        return df.selectExpr("item_id", r"cast(size(filter(split(body, '[ \\t\\n\\r\\f]+'), x -> x <> '')) as bigint) as n_words", r"cast(size(split(body, '\\n')) as bigint) as n_lines")

    def pandas_engine(df: DataFrame) -> DataFrame:
        ship(df.sparkSession)

        @F.pandas_udf("bigint")
        def count_words(body: pd.Series) -> pd.Series:
            return body.map(_python_words)

        @F.pandas_udf("bigint")
        def count_lines(body: pd.Series) -> pd.Series:
            return body.str.count("\n") + 1

        return df.select("item_id", count_words("body").alias("n_words"), count_lines("body").alias("n_lines"))

    def map_engine(df: DataFrame) -> DataFrame:
        ship(df.sparkSession)

        def run(batches):
            for b in batches:
                yield pd.DataFrame({"item_id": b["item_id"], "n_words": b["body"].map(_python_words), "n_lines": b["body"].str.count("\n") + 1})

        return df.select("item_id", "body").mapInPandas(run, "item_id bigint, n_words bigint, n_lines bigint")

    def row_engine(df: DataFrame) -> DataFrame:
        ship(df.sparkSession)
        count = F.udf(_python_words, "bigint")
        lines = F.udf(lambda body: (body or "").count("\n") + 1, "bigint")
        return df.select("item_id", count("body").alias("n_words"), lines("body").alias("n_lines"))

    return {"built_in": built_in, "sql": sql, "pandas": pandas_engine, "map": map_engine, "row": row_engine}
