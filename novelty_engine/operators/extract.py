"""Axes of targets and the values of related items on them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import ship


def extract_axes(features: DataFrame, targets: DataFrame, tolerance: float = 0.0, only: list[str] | None = None) -> DataFrame:
    """Axes on which a target has a value, with that value: axes are the target's own.  `only` fixes the list in advance."""
    mine = features.join(targets.select("target_id"), features["item_id"] == F.col("target_id"), "inner")
    out = mine.select("target_id", "axis", "kind", "direction", F.lit(float(tolerance)).alias("tolerance"), F.col("v_num").alias("t_num"), F.col("v_txt").alias("t_txt"), F.lit("user" if only else "rule").alias("origin"))
    return out.where(F.col("axis").isin(only)) if only else out


def fill_claims(network: DataFrame, features: DataFrame, axes: DataFrame) -> DataFrame:
    """Values of related items on the axes of their target; null where an item has none.

    Features exist once per item; they are packed into one map a row before the join, so an item that
    serves many targets is read once and shuffled once.
    """
    packed = features.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("axis", F.struct("v_num", "v_txt")))).alias("values"))
    per = axes.groupBy("target_id").agg(F.collect_list(F.struct("axis", "kind", "direction", "tolerance", "t_num", "t_txt")).alias("axes"))
    joined = network.join(packed, "item_id", "left").join(per, "target_id")
    opened = joined.select("target_id", "item_id", "relation", "layer", "values", F.explode("axes").alias("x"))
    value = F.try_element_at("values", F.col("x.axis"))
    return opened.select("target_id", "item_id", "relation", "layer", "x.*", value["v_num"].alias("v_num"), value["v_txt"].alias("v_txt"))


def curate_axes(axes: DataFrame, edits: DataFrame, offered: DataFrame | None = None) -> DataFrame:
    """Apply a person's edits(op, axis, new_axis, kind, direction): remove, rename, retype, reorient, and add.

    `add` takes an axis of `offered`, rows like `axes` that were not chosen at first.  Weights are edited by `edited_weights`.
    """
    named = edits.select("op", F.col("axis").alias("edit_axis"), "new_axis", F.col("kind").alias("new_kind"), F.col("direction").alias("new_direction"))
    if offered is not None:
        added = offered.join(named.where("op = 'add'"), F.col("axis") == F.col("edit_axis"), "left_semi")
        axes = axes.unionByName(added.join(axes.select("target_id", "axis"), ["target_id", "axis"], "left_anti").select(*axes.columns))
    kept = axes.join(named.where("op = 'remove'"), F.col("axis") == F.col("edit_axis"), "left_anti")
    changed = kept.join(named.where("op = 'edit'"), F.col("axis") == F.col("edit_axis"), "left")
    names = [c for c in axes.columns if c not in ("axis", "kind", "direction")]
    return changed.select(*names, F.coalesce("new_axis", "axis").alias("axis"), F.coalesce("new_kind", "kind").alias("kind"), F.coalesce("new_direction", "direction").alias("direction")).select(*axes.columns)


def edited_weights(counts: DataFrame, edits: DataFrame) -> DataFrame:
    """(target_id, axis, w): win-rate weights times a person's factors (op `weight`), normalised again; for `overall_score`."""
    from .overall import raw_weight

    factors = edits.where("op = 'weight'").select("axis", F.col("weight").alias("factor"))
    raw = counts.join(factors, "axis", "left").select("target_id", "axis", (raw_weight("win_rate") * F.coalesce("factor", F.lit(1.0))).alias("raw"))
    total = raw.groupBy("target_id").agg(F.sum("raw").alias("total"), F.count("*").alias("m"))
    return raw.join(total, "target_id").select("target_id", "axis", F.when(F.col("total") > 0, F.col("raw") / F.col("total")).otherwise(1 / F.col("m")).alias("w"))


def infer_axis_types(values: DataFrame, min_numeric_share: float = 0.8) -> DataFrame:
    """(axis, kind): numeric when enough non-null values parse as numbers."""
    return values.where("value is not null").groupBy("axis").agg(F.avg(F.when(F.col("value").try_cast("double").isNotNull(), 1.0).otherwise(0.0)).alias("share")).select("axis", F.when(F.col("share") >= min_numeric_share, "numeric").otherwise("categorical").alias("kind"))


def parse_response(text: Column, axes: list[str]) -> Column:
    """Map of the known axes from a model's JSON answer; unknown keys are dropped, a broken answer is an empty map."""
    parsed = F.coalesce(F.from_json(text, "map<string,string>"), F.create_map().cast("map<string,string>"))
    return F.map_filter(parsed, lambda k, v: k.isin(axes) & v.isNotNull() & (v != ""))


def majority_vote(votes: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Most frequent value per key; a tie gives null."""
    counts = votes.where(F.col(value).isNotNull()).groupBy(*keys, value).agg(F.count("*").alias("n"))
    best = counts.groupBy(*keys).agg(F.max("n").alias("most"))
    top = counts.join(best, keys).where("n = most").groupBy(*keys).agg(F.count("*").alias("tied"), F.min(value).alias(value))
    return top.select(*keys, F.when(F.col("tied") == 1, F.col(value)).alias(value))


def model_extract(items: DataFrame, model: Callable[[list[str]], list[str]], axes: list[str], cache: DataFrame | None = None, body: str = "body") -> DataFrame:
    """(item_id, prompt_hash, answer map) by a plug-in model that answers batches of prompts with JSON.

    Prompts already answered in `cache(prompt_hash, answer)` are not asked again.  Append the result to the cache.
    """
    ship(items.sparkSession)
    asked = items.select("item_id", F.concat(F.lit("Give values for: " + ", ".join(axes) + "\n"), F.coalesce(F.col(body), F.lit(""))).alias("prompt")).withColumn("prompt_hash", F.sha2("prompt", 256))
    done = None
    if cache is not None:
        done = asked.join(cache, "prompt_hash").select("item_id", "prompt_hash", "answer")
        asked = asked.join(cache, "prompt_hash", "left_anti")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"item_id": batch["item_id"], "prompt_hash": batch["prompt_hash"], "raw": model(batch["prompt"].tolist())})

    fresh = asked.select("item_id", "prompt_hash", "prompt").mapInPandas(run, "item_id bigint, prompt_hash string, raw string").select("item_id", "prompt_hash", parse_response(F.col("raw"), axes).alias("answer"))
    return fresh if done is None else fresh.unionByName(done)
