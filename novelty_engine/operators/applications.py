"""What users do with duels, paces and forests."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .scan import ranks


def radar(verdicts: DataFrame, target_id: int, items: list[int] | None = None) -> DataFrame:
    """(axis, item_id, s) of one target, for a radar chart."""
    rows = verdicts.where(F.col("target_id") == target_id)
    return (rows.where(F.col("item_id").isin(items)) if items else rows).select("axis", "item_id", "s")


def profile_classes(verdicts: DataFrame) -> DataFrame:
    """(target_id, item_id, profile, n_members): items of a target whose verdicts are all alike; the profile is named by its least item.

    A profile is three bitmaps, of axes won, level and lost (60 axes to a long), as `won`, `level` and `lost`.
    """
    places = verdicts.select("target_id", "axis").distinct().withColumn("at", F.row_number().over(Window.partitionBy("target_id").orderBy("axis")) - 1)
    words = F.lit(0).cast("bigint")
    known = verdicts.where("s is not null").join(places, ["target_id", "axis"])
    bit = F.expr("shiftleft(1L, at % 60)")
    parts = known.groupBy("target_id", "item_id", F.floor(F.col("at") / 60).alias("word")).agg(*(F.coalesce(F.bit_or(F.when(F.col("s") == v, bit)), words).alias(c) for c, v in (("won", 1), ("level", 0), ("lost", -1))))
    whole = parts.groupBy("target_id", "item_id").agg(F.sort_array(F.collect_list(F.struct("word", "won", "level", "lost"))).alias("bits"))
    kinds = whole.groupBy("target_id", "bits").agg(F.min("item_id").alias("profile"), F.count("*").alias("n_members"))
    return whole.join(kinds, ["target_id", "bits"]).select("target_id", "item_id", "profile", "n_members", "bits")


def similar_profiles(verdicts: DataFrame, top_k: int = 5) -> DataFrame:
    """The `top_k` pairs of each target's related items whose verdicts agree most: (target_id, a, b, shared, similarity).

    Only classes of equal profiles are compared, by counting bits.  A pair of items ranks no better than the best pair of its two
    classes, so the best `top_k` pairs of classes, a class of several items being a pair with itself, hold all that is asked
    for, and of each class the first `top_k` + 1 items.
    """
    classes = profile_classes(verdicts)
    kinds = classes.groupBy("target_id", "profile", "n_members").agg(F.first("bits").alias("bits"))
    first = classes.withColumn("place", F.row_number().over(Window.partitionBy("target_id", "profile").orderBy("item_id"))).where(F.col("place") <= top_k + 1).groupBy("target_id", "profile").agg(F.sort_array(F.collect_list("item_id")).alias("items"))
    a, b = (kinds.select("target_id", F.col("profile").alias(f"p{n}"), F.col("bits").alias(f"bits_{n}"), F.col("n_members").alias(f"n_{n}")) for n in "ab")
    total = lambda x: F.aggregate(x, F.lit(0), lambda s, v: s + v)
    match = lambda test: F.flatten(F.transform("bits_a", lambda x: F.transform(F.filter("bits_b", lambda y: y["word"] == x["word"]), lambda y: test(x, y))))
    seen = lambda x: x["won"].bitwiseOR(x["level"]).bitwiseOR(x["lost"])
    shared = total(match(lambda x, y: F.bit_count(seen(x).bitwiseAND(seen(y)))))
    agree = total(match(lambda x, y: F.bit_count(x["won"].bitwiseAND(y["won"])) + F.bit_count(x["level"].bitwiseAND(y["level"])) + F.bit_count(x["lost"].bitwiseAND(y["lost"]))))
    pairs = a.join(b, "target_id").where("pa < pb or pa = pb and n_a > 1").select("target_id", "pa", "pb", shared.cast("bigint").alias("shared"), agree.alias("agree")).where("shared > 0")
    scored = pairs.withColumn("similarity", F.round(F.col("agree") / F.col("shared"), 6)).drop("agree")
    held = scored.join(first.select("target_id", F.col("profile").alias("pa"), F.col("items").alias("xs")), ["target_id", "pa"]).join(first.select("target_id", F.col("profile").alias("pb"), F.col("items").alias("ys")), ["target_id", "pb"])
    second = F.when(F.col("pa") == F.col("pb"), F.element_at("xs", 2)).otherwise(F.col("pb"))
    by_class = Window.partitionBy("target_id").orderBy(F.desc("similarity"), F.desc("shared"), "pa", second)
    best = held.withColumn("rank", F.row_number().over(by_class)).where(F.col("rank") <= top_k)
    opened = best.select("target_id", "shared", "similarity", F.explode("xs").alias("x"), "ys", (F.col("pa") == F.col("pb")).alias("same")).select("target_id", "shared", "similarity", "x", F.explode("ys").alias("y"), "same").where("not same and x <> y or x < y")
    ordered = opened.select("target_id", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "shared", "similarity")
    rank = F.row_number().over(Window.partitionBy("target_id").orderBy(F.desc("similarity"), F.desc("shared"), "a", "b"))
    return ordered.withColumn("rank", rank).where(F.col("rank") <= top_k).drop("rank")


def stalled_ideas(nodes: DataFrame, forest: DataFrame, min_age: int, now: int | None = None, key: str = "pos") -> DataFrame:
    """Winners without successors whose last activity is at least `min_age` periods old."""
    latest = nodes.agg(F.max("period").alias("now_")) if now is None else nodes.agg(F.lit(now).alias("now_"))
    leaves = nodes.join(forest.select(F.col("src").alias(key)).distinct(), key, "left_anti")
    return leaves.crossJoin(F.broadcast(latest)).withColumn("idle", (F.col("now_") - F.col("period")).cast("int")).where(F.col("idle") >= min_age).drop("now_")


def influence_by_novelty(paced: DataFrame) -> DataFrame:
    """Items by their largest marginal gain: (item_id, gain, novelty_rank)."""
    gains = paced.groupBy("item_id").agg(F.max("d_nu_bar").alias("gain"))
    return ranks(gains, "gain", "novelty_rank")


def portfolio(paced: DataFrame, items: DataFrame, dimensions: list[str]) -> DataFrame:
    """Cube of the mean number of axes advanced per item, with counts and grouping_id."""
    joined = paced.join(items, "item_id")
    return joined.cube(*dimensions).agg(F.count("*").alias("n"), F.round(F.sum("n_won") / F.count("*"), 6).alias("mean_won"), F.grouping_id().alias("level"))


def trends(paced: DataFrame, items: DataFrame, by: str) -> DataFrame:
    """Slope of marginal novelty over years."""
    return paced.join(items.select("item_id", "year", by), "item_id").groupBy(by).agg(F.regr_slope("d_nu_bar", F.col("year").cast("double")).alias("slope"), F.count("*").alias("n"))


def knowledge_graph(features: DataFrame) -> DataFrame:
    """Item-value bipartite edges of categorical axes: (item_id, axis, value)."""
    return features.where("v_txt is not null").select("item_id", "axis", F.col("v_txt").alias("value"))


def associated_values(graph: DataFrame, axis_a: str, axis_b: str, least_support: int = 1) -> DataFrame:
    """(value_a, value_b, support, confidence, lift) of two axes of the same item; swap the axes to trace back."""
    a, b = graph.where(F.col("axis") == axis_a).select("item_id", F.col("value").alias("value_a")), graph.where(F.col("axis") == axis_b).select("item_id", F.col("value").alias("value_b"))
    both = a.join(b, "item_id").groupBy("value_a", "value_b").agg(F.count("*").alias("support"))
    na, nb = a.groupBy("value_a").agg(F.count("*").alias("na")), b.groupBy("value_b").agg(F.count("*").alias("nb"))
    n = graph.agg(F.count_distinct("item_id").alias("n"))
    rows = both.where(F.col("support") >= least_support).join(na, "value_a").join(nb, "value_b").crossJoin(F.broadcast(n))
    return rows.select("value_a", "value_b", "support", F.round(F.col("support") / F.col("na"), 6).alias("confidence"), F.round(F.col("support") * F.col("n") / (F.col("na") * F.col("nb")), 6).alias("lift"))


def bridges(values: DataFrame, links: DataFrame) -> DataFrame:
    """(value, item_id, n_members, n_linked, n_bridges): for every item and value, how many of the others that have the value it is
    linked to and how many it is not, from values(item_id, value).

    Items of a value that are not linked are all its pairs less the links inside it, so the result is as long as `values`
    however frequent a value is; `bridge_partners` names the partners of chosen items.
    """
    known = values.where("value is not null").distinct()
    linked = links.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).where("a <> b").distinct()
    ends = known.select(F.col("item_id").alias("a"), "value").join(linked, "a").join(known.select(F.col("item_id").alias("b"), "value"), ["b", "value"])
    inside = ends.select("value", F.explode(F.array("a", "b")).alias("item_id")).groupBy("value", "item_id").agg(F.count("*").alias("n_linked"))
    sizes = known.groupBy("value").agg(F.count("*").alias("n_members"))
    rows = known.join(sizes, "value").join(inside, ["value", "item_id"], "left").withColumn("n_linked", F.coalesce("n_linked", F.lit(0)))
    return rows.select("value", "item_id", "n_members", "n_linked", (F.col("n_members") - 1 - F.col("n_linked")).alias("n_bridges"))


def bridge_partners(values: DataFrame, links: DataFrame, items: DataFrame) -> DataFrame:
    """(item_a, item_b, n_shared): all items that share values with the given items(item_id) but no link."""
    known = values.where("value is not null").distinct()
    asked = known.join(items.select("item_id").distinct(), "item_id").select(F.col("item_id").alias("item_a"), "value")
    pairs = asked.join(known.select(F.col("item_id").alias("item_b"), "value"), "value").where("item_a <> item_b").groupBy("item_a", "item_b").agg(F.count("*").alias("n_shared"))
    both = links.select(F.col("src").alias("item_a"), F.col("dst").alias("item_b")).union(links.select("dst", "src"))
    return pairs.join(both, ["item_a", "item_b"], "left_anti")


def shortlist(verdicts: DataFrame, axes: list[str], top_k: int = 10) -> DataFrame:
    """Related items that the target does not beat on chosen axes: the prior work to read first."""
    rows = verdicts.where(F.col("axis").isin(axes) & F.col("s").isNotNull()).groupBy("target_id", "item_id").agg(F.count_if(F.col("s") <= 0).alias("held"), F.count("*").alias("compared"))
    rank = F.row_number().over(Window.partitionBy("target_id").orderBy(F.desc("held"), F.desc("compared"), "item_id"))
    return rows.withColumn("rank", rank.cast("bigint")).where(F.col("rank") <= top_k)


def first_seen(features: DataFrame, items: DataFrame, axis: str) -> DataFrame:
    """(value, item_id, pub_date) of the first item with each value of an axis."""
    rows = features.where((F.col("axis") == axis) & F.col("v_txt").isNotNull()).join(items.select("item_id", "pub_date"), "item_id")
    return rows.groupBy(F.col("v_txt").alias("value")).agg(F.min(F.struct("pub_date", "item_id")).alias("x")).select("value", "x.item_id", "x.pub_date")


def recurring_values(claims: DataFrame, top_k: int = 5) -> DataFrame:
    """Most frequent values of each target's network and categorical axis."""
    counts = claims.where("v_txt is not null").groupBy("target_id", "axis", "v_txt").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("target_id", "axis").orderBy(F.desc("n"), "v_txt"))
    return counts.withColumn("rank", rank.cast("bigint")).where(F.col("rank") <= top_k)


def materialise(df: DataFrame, path: str, by: str | None = None, buckets: int = 64, mode: str = "overwrite") -> None:
    """Write a relation for later queries, partitioned by a hash bucket of `by` so that one key reads one folder."""
    if by is None:
        df.write.mode(mode).parquet(path)
    else:
        df.withColumn("bucket", F.pmod(F.xxhash64(by), F.lit(buckets)).cast("int")).repartition("bucket").write.mode(mode).partitionBy("bucket").parquet(path)


def open_store(spark: SparkSession, path: str, by: str | None = None, value=None, buckets: int = 64) -> DataFrame:
    """Read it again; with `by` and `value` only that bucket is read."""
    df = spark.read.parquet(path)
    if by is None or value is None:
        return df
    bucket = F.pmod(F.xxhash64(F.lit(value).cast(df.schema[by].dataType)), F.lit(buckets)).cast("int")
    at = spark.range(1).select(bucket.alias("b")).first()[0]
    return df.where((F.col("bucket") == at) & (F.col(by) == value)).drop("bucket")


def direct_classify(paced: DataFrame, seminal: float = 0.3) -> DataFrame:
    """The simpler alternative: label items by thresholds on their gain, without a graph."""
    return paced.withColumn("label", F.when(F.col("d_nu_bar") >= seminal, "seminal").when(F.col("d_nu_bar") > 0, "incremental").otherwise("none"))
