"""Overall novelty score from verdict counts.

The score of an axis is P(win) + alpha P(draw) - P(loss); axes are weighted by their normalised win rates,
or alike when nothing was won.  With integer counts per axis everything else is arithmetic, so counts of
several views (whole network, references only, ...) come from one aggregation and counts of new items are
merged by addition.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import axis_score

WEIGHTINGS = ("win_rate", "uniform", "entropy")
VIEWS = {"all": "true", "reference": "relation = 'reference'", "citation": "relation = 'citation'", "layer1": "layer = 1"}


def axis_counts(verdicts: DataFrame, views: dict[str, str] | None = None) -> DataFrame:
    """(target_id, axis, view, n_win, n_draw, n_loss): all views in one pass."""
    views = {"all": "true"} if views is None else views
    counts = [F.count_if(F.expr(f"({where}) AND s = {s}")).alias(f"{name}|{label}") for name, where in views.items() for s, label in ((1, "n_win"), (0, "n_draw"), (-1, "n_loss"))]
    wide = verdicts.groupBy("target_id", "axis").agg(*counts)
    opened = F.explode(F.array(*(F.struct(F.lit(name).alias("view"), *(F.col(f"`{name}|{label}`").alias(label) for label in ("n_win", "n_draw", "n_loss"))) for name in views)))
    return wide.select("target_id", "axis", opened.alias("x")).select("target_id", "axis", "x.*")


def merge_counts(old: DataFrame, new: DataFrame) -> DataFrame:
    """Counts after more related items have been compared."""
    return old.unionByName(new).groupBy("target_id", "axis", "view").agg(*(F.sum(c).alias(c) for c in ("n_win", "n_draw", "n_loss")))


def proportions() -> dict[str, Column]:
    total = F.col("n_win") + F.col("n_draw") + F.col("n_loss")
    return {c: F.coalesce(F.try_divide(F.col(c), total), F.lit(0.0)) for c in ("n_win", "n_draw", "n_loss")}


def raw_weight(weighting: str) -> Column:
    p = proportions()
    if weighting == "win_rate":
        return p["n_win"]
    if weighting == "uniform":
        return F.lit(1.0)
    if weighting == "entropy":
        return sum((F.when(x > 0, -x * F.ln(x)).otherwise(0.0) for x in p.values()), F.lit(0.0))
    raise ValueError(f"weighting is one of {WEIGHTINGS}")


def overall_score(counts: DataFrame, alpha: float | Column = 0.5, weighting: str | DataFrame = "win_rate", by: list[str] | None = None) -> DataFrame:
    """(target_id, view, omega, n_axes): the weighted sum of axis scores.

    `weighting` is a rule or a table (target_id, axis, w) of given weights; axes it lacks weigh 0.
    """
    by = by or ["target_id", "view"]
    if isinstance(weighting, DataFrame):
        rows = counts.join(weighting, ["target_id", "axis"], "left").withColumn("raw", F.coalesce("w", F.lit(0.0)))
        rows = rows.withColumn("score", axis_score(F.col("n_win"), F.col("n_draw"), F.col("n_loss"), alpha))
        return rows.groupBy(*by).agg(F.round(F.sum(F.col("raw") * F.col("score")), 6).alias("omega"), F.count("*").alias("n_axes"))
    rows = counts.withColumn("raw", raw_weight(weighting)).withColumn("score", axis_score(F.col("n_win"), F.col("n_draw"), F.col("n_loss"), alpha))
    total = F.sum("raw")
    omega = F.when(total > 0, F.sum(F.col("raw") * F.col("score")) / total).otherwise(F.sum("score") / F.count("*"))
    return rows.groupBy(*by).agg(F.round(omega, 6).alias("omega"), F.count("*").alias("n_axes"))


def scaled_score(verdicts: DataFrame, alpha: float = 0.5, by: list[str] | None = None) -> DataFrame:
    """(target_id, omega, n) for verdicts on any scale: what is won less what is lost, draws at `alpha`, weighted by what is won.

    With verdicts -1, 0 and 1 this is `overall_score`.
    """
    by, s = by or ["target_id"], F.col("s").cast("double")
    axes = verdicts.groupBy(*by, "axis").agg(F.sum(F.greatest(s, F.lit(0.0))).alias("won"), F.sum(F.greatest(-s, F.lit(0.0))).alias("lost"), F.count_if(s == 0).alias("level"), F.count("s").alias("n"))
    rows = axes.select(*by, "n", F.coalesce(F.try_divide("won", "n"), F.lit(0.0)).alias("raw"), F.coalesce(F.try_divide(F.col("won") + alpha * F.col("level") - F.col("lost"), "n"), F.lit(0.0)).alias("score"))
    total = F.sum("raw")
    omega = F.when(total > 0, F.sum(F.col("raw") * F.col("score")) / total).otherwise(F.sum("score") / F.count("*"))
    return rows.groupBy(*by).agg(F.round(omega, 6).alias("omega"), F.sum("n").alias("n"))


def without_items(verdicts: DataFrame, alpha: float = 0.5) -> DataFrame:
    """(target_id, item_id, omega_without): the score when one related item is left out, from counts less that item's verdicts."""
    counts = axis_counts(verdicts).drop("view")
    items = verdicts.select("target_id", "item_id").distinct().join(counts, "target_id")
    own = verdicts.where("s is not null").select("target_id", "item_id", "axis", "s")
    left = items.join(own, ["target_id", "item_id", "axis"], "left").select("target_id", "item_id", "axis", *((F.col(c) - F.coalesce((F.col("s") == v).cast("bigint"), F.lit(0))).alias(c) for c, v in (("n_win", 1), ("n_draw", 0), ("n_loss", -1))))
    return overall_score(left, alpha, by=["target_id", "item_id"]).select("target_id", "item_id", F.col("omega").alias("omega_without"))


def axis_table(counts: DataFrame, alpha: float = 0.5) -> DataFrame:
    """Score, weight and contribution of each axis, with the score left when the axis is taken out."""
    from pyspark.sql import Window

    mine = Window.partitionBy("target_id", "view")
    rows = counts.withColumn("raw", raw_weight("win_rate")).withColumn("axis_score", axis_score(F.col("n_win"), F.col("n_draw"), F.col("n_loss"), alpha))
    rows = rows.withColumn("sum_raw", F.sum("raw").over(mine)).withColumn("m", F.count("*").over(mine)).withColumn("sum_weighted", F.sum(F.col("raw") * F.col("axis_score")).over(mine)).withColumn("sum_score", F.sum("axis_score").over(mine))
    weight = F.when(F.col("sum_raw") > 0, F.col("raw") / F.col("sum_raw")).otherwise(1 / F.col("m"))
    left = F.col("sum_raw") - F.col("raw")
    without = F.when(left > 1e-12, (F.col("sum_weighted") - F.col("raw") * F.col("axis_score")) / left).otherwise(F.try_divide(F.col("sum_score") - F.col("axis_score"), F.col("m") - 1))
    return rows.select("target_id", "view", "axis", "n_win", "n_draw", "n_loss", F.round("axis_score", 6).alias("axis_score"), F.round(weight, 6).alias("weight"), F.round(weight * F.col("axis_score"), 6).alias("contribution"), F.round(without, 6).alias("omega_without"))


def omega_sweep(counts: DataFrame, alphas: list[float], weightings: list[str]) -> DataFrame:
    """Scores for each alpha and weighting from the same counts."""
    spread = counts.withColumn("alpha", F.explode(F.array(*map(F.lit, alphas))))
    out = None
    for name in weightings:
        one = overall_score(spread, F.col("alpha"), name, ["target_id", "view", "alpha"]).withColumn("weighting", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out
