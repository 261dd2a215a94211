"""Verdicts of a target against related items."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import categorical_score, numeric_score

SCALES = ("ternary", "ternary_strict", "five", "binary")


def verdict(scale: str = "ternary", cut: float = 0.25, how: str = "exact", least: float = 0.5) -> Column:
    """Verdict on a claims row, positive when the target is ahead.

    ternary: +1, 0, -1, categorical axes never -1; ternary_strict: a different categorical value counts -1 when it sorts after
    the target's; five: half steps where a numeric lead is under `cut` of the larger value; binary: win or no win.
    `how` and `least` say which categorical values are equivalent.
    """
    numeric = numeric_score(F.col("t_num"), F.col("v_num"), F.col("direction"), F.col("tolerance"))
    categorical = categorical_score(F.col("t_txt"), F.col("v_txt"), how, least)
    if scale == "five":
        size = F.abs(F.col("t_num") - F.col("v_num")) / F.greatest(F.abs("t_num"), F.abs("v_num"))
        numeric = F.when((numeric == 0) | (size >= cut), numeric.cast("double")).otherwise(numeric * 0.5)
        return F.when(F.col("kind") == "numeric", numeric).otherwise(categorical.cast("double"))
    if scale == "ternary_strict":
        categorical = F.when((categorical == 1) & (F.col("v_txt") > F.col("t_txt")), -1).otherwise(categorical)
    out = F.when(F.col("kind") == "numeric", numeric).otherwise(categorical)
    return F.when(out.isNull(), out).when(out == 1, 1).otherwise(0) if scale == "binary" else out


def duels(claims: DataFrame, scale: str = "ternary", explain: bool = False, how: str = "exact", least: float = 0.5) -> DataFrame:
    """claims plus `s` (and `why`): the target plays each related item on each of its axes."""
    s = verdict(scale, how=how, least=least)
    if "t_unit" in claims.columns and "v_unit" in claims.columns:  # values in different units are not comparable
        s = F.when(F.col("t_unit") != F.col("v_unit"), F.lit(None)).otherwise(s)
    out = claims.withColumn("s", s)
    return out.withColumn("why", explanation()) if explain else out


def explanation() -> Column:
    shown = lambda n, t: F.coalesce(F.col(n).cast("decimal(20,6)").cast("string"), F.col(t), F.lit("none"))
    word = F.when(F.col("s") == 1, "ahead of").when(F.col("s") == 0, "level with").when(F.col("s") == -1, "behind").otherwise("not comparable with")
    return F.concat_ws(" ", F.col("axis"), shown("t_num", "t_txt"), word, shown("v_num", "v_txt"))


def score_matrix(verdicts: DataFrame, axes: list[str]) -> DataFrame:
    """Items by axes, for display."""
    return verdicts.groupBy("target_id", "item_id").pivot("axis", axes).agg(F.first("s"))


def group_tournament(items: DataFrame, group: str, numeric: dict[str, int], categorical: list[str], key: str = "item_id") -> DataFrame:
    """Every item plays all others of its group on every axis, without pairs: (group, item, axis, n_win, n_draw, n_loss).

    Verdicts depend on counts only, so rows are first reduced to distinct values per group with their counts;
    running sums over those give the items below and above.  A group of n items costs n log n.
    """
    out = None
    for axis, direction in numeric.items():
        counts = items.where(F.col(axis).isNotNull()).groupBy(group, axis).agg(F.count("*").alias("same"))
        w = f"(PARTITION BY {group} ORDER BY {axis} {'ASC' if direction > 0 else 'DESC'} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
        ranked = counts.select(group, axis, "same", F.coalesce(F.expr(f"sum(same) OVER {w}"), F.lit(0)).alias("below"), F.expr(f"sum(same) OVER (PARTITION BY {group})").alias("all_"))
        one = items.select(group, key, axis).join(ranked, [group, axis]).select(group, key, F.lit(axis).alias("axis"), F.col("below").cast("bigint").alias("n_win"), (F.col("same") - 1).cast("bigint").alias("n_draw"), (F.col("all_") - F.col("below") - F.col("same")).cast("bigint").alias("n_loss"))
        out = one if out is None else out.unionByName(one)
    for axis in categorical:
        present = items.where(F.col(axis).isNotNull())
        same = present.groupBy(group, axis).agg(F.count("*").alias("same"))
        every = same.groupBy(group).agg(F.sum("same").alias("all_"))
        one = items.select(group, key, axis).join(same.join(every, group), [group, axis]).select(group, key, F.lit(axis).alias("axis"), (F.col("all_") - F.col("same")).cast("bigint").alias("n_win"), (F.col("same") - 1).cast("bigint").alias("n_draw"), F.lit(0).cast("bigint").alias("n_loss"))
        out = one if out is None else out.unionByName(one)
    return out


def link_tournament(links: DataFrame, features: DataFrame) -> DataFrame:
    """Every item plays the items it cites: counts per (item, axis)."""
    mine = features.select(F.col("item_id").alias("src"), "axis", "kind", "direction", F.lit(0.0).alias("tolerance"), F.col("v_num").alias("t_num"), F.col("v_txt").alias("t_txt"))
    theirs = features.select(F.col("item_id").alias("dst"), "axis", "v_num", "v_txt")
    played = links.select("src", "dst").join(mine, "src").join(theirs, ["dst", "axis"]).withColumn("s", verdict())
    return played.groupBy(F.col("src").alias("item_id"), "axis").agg(F.count_if(F.col("s") == 1).alias("n_win"), F.count_if(F.col("s") == 0).alias("n_draw"), F.count_if(F.col("s") == -1).alias("n_loss"))
