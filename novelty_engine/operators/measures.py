"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import cut_lineage
from .scan import ranks, running


def time_extractors(items: DataFrame, engines: dict[str, Callable[[DataFrame], DataFrame]]) -> dict[str, float]:
    """Mean seconds per body of each engine, measured around a write to nowhere."""
    n, out = max(1, items.count()), {}
    for name, run in engines.items():
        start = time.perf_counter()
        run(items).write.format("noop").mode("overwrite").save()
        out[name] = (time.perf_counter() - start) / n
    return out


class StageTimer:
    """Seconds by stage; `rows` is appended to the call log."""

    def __init__(self):
        self.rows: list[tuple[str, int, int, float]] = []

    def run(self, stage: str, df: DataFrame | Callable[[], DataFrame], calls: Callable[[int], int] = lambda rows: rows) -> DataFrame:
        """Work a stage out, hold its rows for the next one, and note rows, calls (from the rows) and seconds."""
        start = time.perf_counter()
        held = cut_lineage(df() if callable(df) else df)
        seconds = time.perf_counter() - start
        rows = held.count()
        self.rows.append((stage, int(calls(rows)), rows, seconds))
        return held

    def log(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows or [("", 0, 0, 0.0)], "stage string, calls bigint, rows bigint, seconds double").where("stage <> ''")


def call_model(sizes: DataFrame) -> DataFrame:
    """Calls per stage from sizes(target_id, n, m, pairs): one for the axes, one per related item, one per duel,
    one per item and axis of the timeline, one per pair that a cluster does not already link."""
    stages = {"axes": F.lit(1), "values": F.col("n"), "overall": F.col("n") * F.col("m"), "temporal": (F.col("n") + 1) * F.col("m"), "graph": F.col("pairs")}
    return sizes.select("target_id", F.explode(F.array(*(F.struct(F.lit(k).alias("stage"), v.cast("bigint").alias("calls")) for k, v in stages.items()))).alias("x")).select("target_id", "x.*")


def stability(a: DataFrame, b: DataFrame, keys: list[str], values: list[str]) -> DataFrame:
    """One row: cells of both runs and the share that is identical."""
    right = b.select(*keys, *(F.col(v).alias(f"{v}_b") for v in values), F.lit(1).alias("in_b"))
    joined = a.select(*keys, *values, F.lit(1).alias("in_a")).join(right, keys, "full")
    same = F.lit(True)
    for v in values:
        same = same & F.col(v).eqNullSafe(F.col(f"{v}_b"))
    same = same & F.col("in_a").eqNullSafe(F.col("in_b"))
    return joined.agg(F.count("*").alias("cells"), F.round(F.avg(F.when(same, 1.0).otherwise(0.0)), 6).alias("agree_share"))


def auc(rows: DataFrame, score: str, label: str) -> DataFrame:
    """Area under the ROC curve from rank sums; ties count half.  Ranks come from counts of distinct scores."""
    counts = rows.where(F.col(score).isNotNull() & F.col(label).isNotNull()).groupBy(score).agg(F.count_if(F.col(label) == 1).alias("p"), F.count_if(F.col(label) == 0).alias("n"))
    placed = running(counts, score, "n", "below")
    won = placed.select("p", "n", (F.col("p") * (2 * F.col("below") + F.col("n"))).alias("twice"))
    return won.agg(F.round(F.try_divide(F.sum("twice"), 2 * F.sum("p") * F.sum("n")), 6).alias("auc"))


def precision_at_k(rows: DataFrame, score: str, label: str, key: str, k: int) -> DataFrame:
    top = rows.where(F.col(label).isNotNull() & F.col(score).isNotNull()).orderBy(F.desc(score), key).limit(k)
    return top.agg(F.round(F.avg(F.col(label).cast("double")), 6).alias("p_at_k"))


def average_ranks(rows: DataFrame, value: str, name: str) -> DataFrame:
    """Adds the average rank of a value, ties shared: from counts of distinct values, as a double."""
    return ranks(rows, value, name, descending=False, average=True)


def spearman(rows: DataFrame, a: str, b: str) -> DataFrame:
    ranked = average_ranks(average_ranks(rows.where(F.col(a).isNotNull() & F.col(b).isNotNull()), a, "rank_a"), b, "rank_b")
    return ranked.agg(F.round(F.corr("rank_a", "rank_b"), 6).alias("rho"))


def rank_agreement(rows: DataFrame, a: str, b: str, key: str, k: int) -> DataFrame:
    """Spearman's rho and the overlap of the top `k` of both."""
    tops = [rows.orderBy(F.desc(c), key).limit(k).select(key) for c in (a, b)]
    both = tops[0].join(tops[1], key).agg(F.round(F.count("*") / F.lit(k), 6).alias("overlap"))
    return spearman(rows, a, b).crossJoin(both)


def uncertain(rows: DataFrame, key: str, value: str, errs: int, calls: Iterable[int]) -> DataFrame:
    """An extractor's answers over several calls: `errs` in a hundred are wrong, chosen by a digest of the row's key and the call."""
    at = lambda call: F.conv(F.substring(F.md5(F.concat_ws("|", F.col(key).cast("string"), F.lit(str(call)))), 1, 8), 16, 10).cast("bigint")
    answer = lambda call: F.when(at(call) % 100 < errs, F.concat(F.lit("wrong "), (at(call) % 7).cast("string"))).otherwise(F.col(value))
    return rows.select(key, F.explode(F.array(*(answer(c) for c in calls))).alias(value))


def noisy(claims: DataFrame, noise: float, seed: int = 3) -> DataFrame:
    """Values shaken by up to `noise` of their size, the same way every time."""
    digest = F.substring(F.md5(F.concat_ws("|", "target_id", "item_id", "axis", F.lit(seed))), 1, 8)
    unit = (F.conv(digest, 16, 10).cast("bigint") % 2001).cast("double") / 1000.0 - 1.0
    return claims.withColumn("v_num", F.col("v_num") * (1 + noise * unit))


def flip_rate(before: DataFrame, after: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Share of verdicts that change between two runs, overall or for each `by`."""
    keys = ["target_id", "item_id", "axis"]
    joined = before.select(*keys, F.col("s").alias("s0")).join(after.select(*keys, F.col("s").alias("s1")), keys).where("s0 is not null")
    grouped = joined.groupBy(*by) if by else joined
    return grouped.agg(F.count("*").alias("n"), F.round(F.avg(F.when(F.col("s0") != F.col("s1"), 1.0).otherwise(0.0)), 6).alias("flips"))


def cluster_quality(labelled: DataFrame, cluster: str = "cluster", label: str = "label") -> DataFrame:
    """Adjusted Rand index, purity and noise share of clusters against labels; noise is left out of the first two."""
    cells = labelled.where(F.col(cluster).isNotNull()).groupBy(cluster, label).agg(F.count("*").alias("n"))
    pairs = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2)
    a = cells.groupBy(cluster).agg(F.sum("n").alias("n"), F.max("n").alias("top")).agg(pairs("n").alias("a"), F.sum("n").alias("total"), F.sum("top").alias("top"))
    b = cells.groupBy(label).agg(F.sum("n").alias("n")).agg(pairs("n").alias("b"))
    both = cells.agg(pairs("n").alias("ab"))
    noise = labelled.agg(F.round(F.avg(F.when(F.col(cluster).isNull(), 1.0).otherwise(0.0)), 6).alias("noise_share"))
    expected = F.col("a") * F.col("b") / (F.col("total") * (F.col("total") - 1) / 2)
    ari = F.try_divide(F.col("ab") - expected, (F.col("a") + F.col("b")) / 2 - expected)
    return a.crossJoin(b).crossJoin(both).crossJoin(noise).select(F.round(ari, 6).alias("ari"), F.round(F.col("top") / F.col("total"), 6).alias("purity"), "noise_share")


def year_balance(network: DataFrame, items: DataFrame, by: list[str]) -> DataFrame:
    """Entropy of the years of capped citers and their span."""
    counts = network.join(items.select("item_id", "year"), "item_id").groupBy(*by, "year").agg(F.count("*").alias("n"))
    total = Window.partitionBy(*by)
    p = F.col("n") / F.sum("n").over(total)
    return counts.withColumn("h", -p * F.ln(p)).groupBy(*by).agg(F.round(F.sum("h"), 6).alias("year_entropy"), (F.max("year") - F.min("year")).cast("bigint").alias("span"), F.sum("n").alias("n_items"))


def coverage(verdicts: DataFrame) -> DataFrame:
    """Share of missing, winning, level and losing verdicts per axis."""
    n = F.count("*")
    share = lambda c: F.round(F.count_if(c) / n, 6)
    return verdicts.groupBy("axis").agg(n.alias("n"), share(F.col("s").isNull()).alias("missing"), share(F.col("s") == 1).alias("win"), share(F.col("s") == 0).alias("draw"), share(F.col("s") == -1).alias("loss"))


def recall_vs_exact(found: DataFrame, exact: DataFrame, keys: list[str]) -> DataFrame:
    """Recall of an approximate set of rows."""
    hit = exact.select(*keys).distinct().join(found.select(*keys).distinct().withColumn("hit", F.lit(1.0)), keys, "left")
    return hit.agg(F.count("*").alias("n_exact"), F.round(F.avg(F.coalesce("hit", F.lit(0.0))), 6).alias("recall"))


def sketch_counts(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Distinct values by a mergeable HLL sketch beside the exact count: the categorical nu at scale."""
    return rows.groupBy(*keys).agg(F.hll_sketch_estimate(F.hll_sketch_agg(value)).alias("estimate"), F.count_distinct(value).alias("exact"))


def plan_shape(df: DataFrame) -> dict[str, int]:
    """Counts of the physical operators that matter at scale."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {name: text.count(name) for name in ("Exchange", "BroadcastExchange", "CartesianProduct", "BroadcastNestedLoopJoin", "SortMergeJoin", "BatchEvalPython", "ArrowEvalPython", "MapInPandas", "FlatMapGroupsInPandas")}


def run_costs(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """(measure, value): operators of a query's plan, and the jobs, stages, shuffled rows, shuffled and spilled bytes of its run."""
    store = spark.sparkContext._jsc.sc().statusStore()
    stages = lambda: {(s.stageId(), s.attemptId()): s for s in (lambda seq: [seq.apply(i) for i in range(seq.size())])(store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None))}
    before = set(stages())
    df = make()
    df.write.format("noop").mode("overwrite").save()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    ran = [s for k, s in stages().items() if k not in before]
    total = lambda name: sum(getattr(s, name)() for s in ran)
    rows = {"stages": len(ran), "shuffle_rows": total("shuffleWriteRecords"), "shuffle_bytes": total("shuffleWriteBytes"), "spilled_bytes": total("diskBytesSpilled")} | {f"plan {k}": v for k, v in plan_shape(df).items()}
    return spark.createDataFrame(list(rows.items()), "measure string, value bigint")
