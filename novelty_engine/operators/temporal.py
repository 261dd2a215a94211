"""Temporal scores: each item against the best state so far.

A series is a set of rows ordered by `pos`.  With no tolerance the verdict on a numeric axis compares a value with
the running best before it, and on a categorical axis only the first appearance of a value wins; both are
plain windows or aggregates.  With a tolerance or a fuzzy equivalence the outcome depends on earlier outcomes:
strict records are a superset of tolerant wins (an item that wins beats the state by more than the tolerance, and the state is
never further than the tolerance under any earlier value), so a window first cuts a series down to its few records and only
those are folded; fuzzy first appearances are the lexicographically first maximal independent set of the similarity
graph, found in rounds.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import numeric_score
from ..session import cut_lineage, ship


def timeline(network: DataFrame, items: DataFrame, targets: DataFrame) -> DataFrame:
    """(target_id, pos, item_id, pub_date, relation, is_target): related items and the target in date order, ties by id."""
    mine = targets.select("target_id", F.col("target_id").alias("item_id"), F.lit("target").alias("relation"), F.lit(True).alias("is_target"))
    every = network.select("target_id", "item_id", "relation", F.lit(False).alias("is_target")).unionByName(mine)
    dated = every.join(items.select("item_id", "pub_date"), "item_id").where("pub_date is not null")
    return dated.withColumn("pos", F.row_number().over(Window.partitionBy("target_id").orderBy("pub_date", "item_id")).cast("bigint"))


def present(value: Column) -> Column:
    """The value, null for NaN: what is not a number is missing and never becomes the best."""
    return F.nanvl(value.cast("double"), F.lit(None).cast("double"))


def numeric_advances(rows: DataFrame, keys: list[str], value: str, direction: Column | int = 1) -> DataFrame:
    """rows plus `s` and `nu`, tolerance 0: a strict record wins, the first value wins."""
    before = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    upto = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    v = present(F.col(value)) * direction
    best = F.max(v).over(before)
    s = F.when(v.isNull(), F.lit(None).cast("int")).when(best.isNull() | (v > best), 1).when(v == best, 0).otherwise(-1)
    return rows.withColumn("s", s).withColumn("nu", F.count_if(F.col("s") == 1).over(upto))


def categorical_advances(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """rows plus `s` and `nu`: the first appearance of a value wins, later ones draw."""
    first = F.min("pos").over(Window.partitionBy(*keys, value))
    s = F.when(F.col(value).isNull(), F.lit(None).cast("int")).when(first == F.col("pos"), 1).otherwise(0)
    upto = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return rows.withColumn("s", s).withColumn("nu", F.count_if(F.col("s") == 1).over(upto))


def first_appearances(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """(keys, value, pos): winners only, by one aggregation that spreads a hot axis over its values."""
    return rows.where(F.col(value).isNotNull()).groupBy(*keys, value).agg(F.min("pos").alias("pos"))


def bounded_first_appearances(rows: DataFrame, keys: list[str], value: str, bits: int = 16) -> DataFrame:
    """First appearances with a history of fixed size: a value is known by one of 2**bits hash slots.

    A new value whose slot is taken counts as known, so wins are a subset of the exact ones; `measures.recall_vs_exact`
    gives the share that is found.
    """
    slot = F.pmod(F.xxhash64(value), F.lit(1 << bits)).alias("slot")
    first = rows.where(F.col(value).isNotNull()).select(*keys, slot, "pos", value).groupBy(*keys, "slot").agg(F.min(F.struct("pos", value)).alias("x"))
    return first.select(*keys, F.col(f"x.{value}").alias(value), F.col("x.pos").alias("pos"))


def target_marker(paced: DataFrame) -> DataFrame:
    """Where each target stands in its own timeline, with its scores there."""
    return paced.where("is_target")


def fold(values: list[float], tolerance: float, direction: int = 1) -> list[int]:
    """Places of the winners of one series in order."""
    out, state = [], None
    for at, v in enumerate(values):
        if v is None or v != v:
            continue
        if state is None or (v - state) * direction > tolerance * max(abs(v), abs(state)):
            out.append(at)
            state = v
    return out


def tolerant_winners(rows: DataFrame, keys: list[str], value: str, tolerance: float, direction: int = 1) -> DataFrame:
    """(keys, pos, value) of wins by more than a relative tolerance: strict records by a window, then a fold over those.

    Exact for values of one sign; a series whose values differ in sign is folded whole.
    """
    ship(rows.sparkSession)
    known = rows.select(*keys, "pos", present(F.col(value)).alias("v")).where("v is not null")
    before = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    signs = Window.partitionBy(*keys)
    mixed = (F.min("v").over(signs) < 0) & (F.max("v").over(signs) > 0)
    best = F.max(F.col("v") * direction).over(before)
    records = known.withColumn("mixed", mixed).withColumn("best", best).where("mixed or best is null" + f" or v * {direction} > best").select(*keys, "pos", "v")
    schema = ", ".join(f"`{k}` {records.schema[k].dataType.simpleString()}" for k in keys)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("pos", kind="stable")
        return group.iloc[fold(group["v"].tolist(), tolerance, direction)][[*keys, "pos", "v"]]

    return records.groupBy(*keys).applyInPandas(run, f"{schema}, pos bigint, v double")


def with_state(rows: DataFrame, winners: DataFrame, keys: list[str], value: str, tolerance: float, direction: int = 1) -> DataFrame:
    """rows plus the state before each row (the last winner's value), its verdict and nu."""
    marked = rows.join(winners.select(*keys, "pos", F.col("v").alias("won")), [*keys, "pos"], "left")
    before = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    upto = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    state = F.last("won", ignorenulls=True).over(before)
    s = F.when(F.col("won").isNotNull(), 1).otherwise(F.least(F.lit(0), numeric_score(F.col(value), F.col("state"), direction, tolerance)))
    return marked.withColumn("state", state).withColumn("s", F.when(present(F.col(value)).isNull(), F.lit(None).cast("int")).otherwise(s)).withColumn("nu", F.count("won").over(upto)).drop("won")


def leaders(pairs: DataFrame, nodes: DataFrame, max_rounds: int = 100) -> DataFrame:
    """Positions that win under a fuzzy equivalence, from nodes(pos) and similar pairs(a, b) with a < b.

    In each round an undecided node without an earlier undecided neighbour wins and its neighbours lose.
    """
    undecided = cut_lineage(nodes.select("pos").distinct())
    live = cut_lineage(pairs.select("a", "b").distinct())
    won = None
    for _ in range(max_rounds):
        blocked = live.select(F.col("b").alias("pos")).distinct()
        now = cut_lineage(undecided.join(blocked, "pos", "left_anti"))
        won = now if won is None else cut_lineage(won.unionByName(now))
        lost = live.join(now, live["a"] == now["pos"]).select(F.col("b").alias("pos")).distinct()
        gone = now.unionByName(lost)
        undecided = cut_lineage(undecided.join(gone, "pos", "left_anti"))
        live = cut_lineage(live.join(undecided.withColumnRenamed("pos", "a"), "a", "left_semi").join(undecided.withColumnRenamed("pos", "b"), "b", "left_semi"))
        if not undecided.limit(1).count():
            return won
    raise RuntimeError("leaders did not settle")


def best_so_far_scan(rows: DataFrame, value: str, cut_rows: int = 1_000_000, keys: list[str] | None = None) -> DataFrame:
    """Strict records of very long series in two phases: positions are cut into ranges of `cut_rows`, each cut knows the best of
    the cuts before it (a row a series and cut), and windows run inside cuts only.  Same `s` as `numeric_advances`."""
    keys = keys or []
    cut = rows.withColumn("v_", present(F.col(value))).withColumn("cut_", F.floor(F.col("pos") / F.lit(cut_rows)).cast("bigint"))
    tops = cut.groupBy(*keys, "cut_").agg(F.max("v_").alias("top_"))
    earlier = Window.partitionBy(*keys).orderBy("cut_").rowsBetween(Window.unboundedPreceding, -1)
    offsets = tops.select(*keys, "cut_", F.max("top_").over(earlier).alias("offset_"))
    inside = Window.partitionBy(*keys, "cut_").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    joined = cut.withColumn("own_", F.max("v_").over(inside)).join(offsets, [*keys, "cut_"]).withColumn("best_", F.greatest("own_", "offset_"))
    s = F.when(F.col("v_").isNull(), F.lit(None).cast("int")).when(F.col("best_").isNull() | (F.col("v_") > F.col("best_")), 1).when(F.col("v_") == F.col("best_"), 0).otherwise(-1)
    return joined.select(*rows.columns, s.alias("s"))


def temporal_state(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Mergeable state of numeric series: (keys, best, nu, last_pos).  It is all that later rows need, so it may be stored."""
    done = numeric_advances(rows, keys, value)
    return done.groupBy(*keys).agg(F.max(present(F.col(value))).alias("best"), F.count_if(F.col("s") == 1).alias("nu"), F.max("pos").alias("last_pos"))


def continue_advances(state: DataFrame, rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """rows that come after a stored state plus `s` and `nu`, as if the series had been read whole."""
    before = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    upto = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    joined = rows.withColumn("v_", present(F.col(value))).join(state.select(*keys, F.col("best").alias("best_"), F.col("nu").alias("nu_")), keys, "left")
    best = F.greatest(F.max("v_").over(before), F.col("best_"))
    s = F.when(F.col("v_").isNull(), F.lit(None).cast("int")).when(best.isNull() | (F.col("v_") > best), 1).when(F.col("v_") == best, 0).otherwise(-1)
    return joined.withColumn("s", s).withColumn("nu", F.count_if(F.col("s") == 1).over(upto) + F.coalesce("nu_", F.lit(0))).select(*rows.columns, "s", "nu")


def merge_states(old: DataFrame, new: DataFrame, keys: list[str]) -> DataFrame:
    """State after the rows of `new`, whose counts continue those of `old` (from `continue_advances`)."""
    return old.unionByName(new).groupBy(*keys).agg(F.max("best").alias("best"), F.max("nu").alias("nu"), F.max("last_pos").alias("last_pos"))


def target_advances(line: DataFrame, claims: DataFrame, axes: DataFrame, values_too: bool = False) -> DataFrame:
    """(target_id, axis, pos, item_id, s, nu) for all rows of each target's timeline that have a value.

    `claims` holds the related items' values; the target's own come from `axes`.  `values_too` keeps the values.
    """
    own = axes.select("target_id", F.col("target_id").alias("item_id"), "axis", "kind", "direction", F.col("t_num").alias("v_num"), F.col("t_txt").alias("v_txt"))
    values = claims.select("target_id", "item_id", "axis", "kind", "direction", "v_num", "v_txt").unionByName(own).where("v_num is not null or v_txt is not null")
    placed = values.join(line.select("target_id", "item_id", "pos"), ["target_id", "item_id"])
    keys = ["target_id", "axis"]
    numeric = numeric_advances(placed.where("kind = 'numeric'"), keys, "v_num", F.col("direction"))
    categorical = categorical_advances(placed.where("kind = 'categorical'"), keys, "v_txt")
    return numeric.unionByName(categorical).select("target_id", "axis", "pos", "item_id", "kind", "s", "nu", *(["v_num", "v_txt"] if values_too else []))


def winners(advances: DataFrame, items: DataFrame) -> DataFrame:
    """(target_id, axis, pos, item_id, year, value): the advancing items of each axis with their values as text, from advances with values."""
    value = F.coalesce("v_txt", F.col("v_num").cast("decimal(20,6)").cast("string"))
    return advances.where("s = 1").select("target_id", "axis", "pos", "item_id", value.alias("value")).join(items.select("item_id", "year"), "item_id").select("target_id", "axis", "pos", "item_id", "year", "value")


def pace(line: DataFrame, advances: DataFrame, axes: DataFrame) -> DataFrame:
    """line plus n_won, nu_bar, d_nu_bar and log_nu: wins at a position over the number of axes, never an items x axes grid."""
    m = axes.groupBy("target_id").agg(F.count("*").alias("m"))
    wins = advances.where("s = 1").groupBy("target_id", "pos").agg(F.count("*").alias("won"))
    upto = Window.partitionBy("target_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = line.join(wins, ["target_id", "pos"], "left").join(m, "target_id").withColumn("n_won", F.coalesce("won", F.lit(0)).cast("bigint")).withColumn("total", F.sum("n_won").over(upto))
    return rows.select(*line.columns, "n_won", F.round(F.col("total") / F.col("m"), 6).alias("nu_bar"), F.round(F.col("n_won") / F.col("m"), 6).alias("d_nu_bar"), F.round(F.log1p(F.col("total") / F.col("m")), 6).alias("log_nu"))


def spells(paced: DataFrame, flat: int = 5) -> DataFrame:
    """Runs of positions without and with advances: (target_id, moving, first_pos, last_pos, n, gain); flat runs from `flat` long."""
    order = Window.partitionBy("target_id").orderBy("pos")
    marked = paced.withColumn("moving", F.col("n_won") > 0).withColumn("island", F.sum(F.when(F.lag("moving").over(order) == F.col("moving"), 0).otherwise(1)).over(order))
    runs = marked.groupBy("target_id", "island", "moving").agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.count("*").alias("n"), F.round(F.sum("d_nu_bar"), 6).alias("gain"))
    return runs.where(F.col("moving") | (F.col("n") >= flat)).drop("island")


def densify(line: DataFrame, advances: DataFrame, axes: DataFrame) -> DataFrame:
    """Full (target, axis, pos) grid with nu carried forward, for plots only."""
    grid = line.select("target_id", "pos").join(axes.select("target_id", "axis"), "target_id")
    upto = Window.partitionBy("target_id", "axis").orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    joined = grid.join(advances.select("target_id", "axis", "pos", "s", F.col("nu").alias("here")), ["target_id", "axis", "pos"], "left")
    return joined.select("target_id", "axis", "pos", "s", F.coalesce(F.last("here", ignorenulls=True).over(upto), F.lit(0)).cast("bigint").alias("nu"))


def annotated_advances(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """numeric_advances with the state before each row and a sentence."""
    before = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    done = numeric_advances(rows, keys, value).withColumn("state", F.max(present(F.col(value))).over(before))
    shown = lambda c: F.coalesce(F.col(c).cast("decimal(20,6)").cast("string"), F.lit("nothing"))
    word = F.when(F.col("s") == 1, "advance").when(F.col("s") == 0, "level").when(F.col("s") == -1, "behind").otherwise("no verdict")
    return done.withColumn("note", F.concat(shown(value), F.lit(" after "), shown("state"), F.lit(": "), word))


def iterate(values: Iterator[float], tolerance: float = 0.0) -> Iterator[int]:
    """Verdicts of one series in order; the plain form that windows and streams are tested against."""
    state = None
    for v in values:
        if v is None or v != v:
            yield None
        elif state is None or v - state > tolerance * max(abs(v), abs(state)):
            state = v
            yield 1
        else:
            yield 0 if abs(v - state) <= tolerance * max(abs(v), abs(state)) else -1
