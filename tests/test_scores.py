"""Overall and temporal scores by hand, invariants, and equal answers of different engines."""

import random

import pytest
from pyspark.sql import functions as F

from novelty_engine.operators import compare, evolution, extract, measures, network, overall, temporal
from novelty_engine.operators.components import components

COUNTS = "target_id bigint, axis string, view string, n_win bigint, n_draw bigint, n_loss bigint"


def omega(spark, rows, **options):
    df = spark.createDataFrame([(1, a, "all", *x) for a, x in rows.items()], COUNTS)
    return overall.overall_score(df, **options).first().omega


def test_omega_by_hand(spark):
    assert omega(spark, {"a": (6, 2, 2), "b": (3, 1, 0), "c": (0, 4, 1), "d": (0, 0, 0)}) == 0.708333


def test_omega_extremes(spark):
    assert omega(spark, {"a": (5, 0, 0), "b": (9, 0, 0)}) == 1
    assert omega(spark, {"a": (0, 5, 0)}, alpha=0.25) == 0.25
    assert omega(spark, {"a": (0, 0, 5), "b": (0, 0, 2)}) == -1
    assert omega(spark, {"a": (0, 0, 0)}) == 0


def test_omega_properties(spark):
    rng = random.Random(4)
    for _ in range(4):
        rows = {k: (rng.randrange(6), rng.randrange(6), rng.randrange(6)) for k in "abc"}
        values = [omega(spark, rows, alpha=a) for a in (0.0, 0.5, 1.0)]
        assert values == sorted(values) and all(-1 <= v <= 1 for v in values)
        assert omega(spark, {k: tuple(2 * x for x in v) for k, v in rows.items()}) == values[1]


def test_given_weights_and_uniform(spark):
    w = spark.createDataFrame([(1, "a", 1.0)], "target_id bigint, axis string, w double")
    rows = {"a": (1, 1, 0), "b": (0, 0, 1)}
    assert omega(spark, rows, weighting=w) == 0.75 and omega(spark, rows, weighting="uniform") == -0.125


def test_leave_one_axis_out(spark):
    df = spark.createDataFrame([(1, "a", "all", 6, 2, 2), (1, "b", "all", 3, 1, 0)], COUNTS)
    out = {r.axis: r.omega_without for r in overall.axis_table(df).collect()}
    assert out == {"a": 0.875, "b": 0.5}


def series(spark, values):
    kind = "double" if any(isinstance(v, float) for v in values) else "string"
    return spark.createDataFrame([("k", i + 1, v) for i, v in enumerate(values)], f"series string, pos bigint, v {kind}")


def test_numeric_series(spark):
    out = temporal.numeric_advances(series(spark, [3.0, 1.0, None, 3.0, 5.0, 4.0]), ["series"], "v").orderBy("pos").collect()
    assert [r.s for r in out] == [1, -1, None, 0, 1, -1] and [r.nu for r in out] == [1, 1, 1, 1, 2, 2]


def test_categorical_series(spark):
    rows = series(spark, ["a", "b", "a", None, "B", "c"]).withColumn("v", F.lower("v"))
    out = temporal.categorical_advances(rows, ["series"], "v").orderBy("pos").collect()
    assert [r.s for r in out] == [1, 1, 0, None, 0, 1] and [r.nu for r in out] == [1, 2, 2, 2, 2, 3]


def test_tolerance(spark):
    rows = series(spark, [100.0, 104.0, 108.0])
    won = temporal.tolerant_winners(rows, ["series"], "v", 0.05)
    assert sorted(r.pos for r in won.collect()) == [1, 3]


def test_tolerant_wins_equal_the_plain_fold(spark):
    rng = random.Random(2)
    values = [[round(rng.uniform(1, 100), 1) for _ in range(40)] for _ in range(6)] + [[round(rng.uniform(-50, 50), 1) for _ in range(40)]]
    df = spark.createDataFrame([(k, i + 1, v) for k, one in enumerate(values) for i, v in enumerate(one)], "series int, pos bigint, v double")
    got = {(r.series, r.pos) for r in temporal.tolerant_winners(df, ["series"], "v", 0.1).collect()}
    assert got == {(k, i + 1) for k, one in enumerate(values) for i in temporal.fold(one, 0.1)}
    assert [i for i, s in enumerate(temporal.iterate(values[0])) if s == 1] == temporal.fold(values[0], 0.0)


def test_two_phase_scan_equals_window(spark):
    rng = random.Random(1)
    rows = spark.createDataFrame([("k", i + 1, float(rng.randrange(50)) if i % 7 else None) for i in range(300)], "series string, pos bigint, v double")
    a = {(r.pos, r.s) for r in temporal.numeric_advances(rows, ["series"], "v").collect()}
    assert a == {(r.pos, r.s) for r in temporal.best_so_far_scan(rows, "v", 8).collect()}


def test_fuzzy_leaders_equal_the_fold(spark):
    rng = random.Random(8)
    n = 25
    pairs = [(a, b) for a in range(n) for b in range(a + 1, n) if rng.random() < 0.15]
    won, near = [], set(pairs)
    for x in range(n):
        if not any((y, x) in near for y in won):
            won.append(x)
    got = temporal.leaders(spark.createDataFrame(pairs, "a bigint, b bigint"), spark.range(n).withColumnRenamed("id", "pos"))
    assert sorted(r.pos for r in got.collect()) == won


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (103, 101)], "a bigint, b bigint")
    got = {r.node: r.label for r in components(edges).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[103] == 100 and components(edges.limit(0)).count() == 0


def test_components_of_random_graphs(spark):
    rng = random.Random(31)
    rows = [(g * 1000 + rng.randrange(80), g * 1000 + rng.randrange(80)) for g in range(6) for _ in range(20 + 12 * g)] + [(9000 + i, 9000 + i) for i in range(2)] + [(None, 3)]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in rows[:-1]:
        low, high = sorted((find(a), find(b)))
        root[high] = low
    got = {r.node: r.label for r in components(spark.createDataFrame(rows, "a bigint, b bigint")).collect()}
    assert got == {x: find(x) for x in root}


@pytest.mark.parametrize("most", [0, 1 << 20])
def test_components_in_one_task_or_in_rounds(spark, monkeypatch, most):
    monkeypatch.setattr("novelty_engine.operators.components.ONE_TASK_EDGES", most)
    rng = random.Random(5)
    low = -(1 << 62)
    rows = [(low + i, low + i + 1) for i in range(300)] + [(rng.randrange(1000), rng.randrange(1000)) for _ in range(700)] + [(5000, 5000 + i) for i in range(50)] + [(7, None)]
    label = {x: x for pair in rows[:-1] for x in pair}
    moved = True
    while moved:
        moved = False
        for a, b in rows[:-1]:
            least = min(label[a], label[b])
            moved |= label[a] != least or label[b] != least
            label[a] = label[b] = least
    assert {r.node: r.label for r in components(spark.createDataFrame(rows, "a bigint, b bigint")).collect()} == label


def test_components_of_few_edges_take_few_tasks(spark):
    """However many shuffle partitions the session has."""
    spark.conf.set("spark.sql.shuffle.partitions", "50")
    spark.sparkContext.setJobGroup("few-edges", "")
    try:
        got = components(spark.range(0, 200, 1, 4).selectExpr("id as a", "id + 1 as b")).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
        spark.sparkContext.setJobGroup(None, None)
    assert len(got) == 201 and {r.label for r in got} == {0}
    status = spark.sparkContext.statusTracker()
    stages = {s for job in status.getJobIdsForGroup("few-edges") for s in status.getJobInfo(job).stageIds}
    assert stages and sum(info.numCompletedTasks for s in stages if (info := status.getStageInfo(s))) < 50


EDGES = "src bigint, dst bigint, sigma double"


@pytest.mark.parametrize("engine", ["kruskal", "filter", "boruvka"])
def test_forest_engines_agree(spark, engine):
    rng = random.Random(5)
    rows = [(a, b, float(rng.randrange(4))) for a in range(14) for b in range(a + 1, 14) if rng.random() < 0.35]
    want = {rows[i][:2] for i in evolution.kruskal((s, a, b) for a, b, s in rows)}
    got = evolution.temporal_forest(spark.createDataFrame(rows, EDGES), engine)
    assert {(r.src, r.dst) for r in got.collect()} == want


def test_forest_shape(spark):
    nodes = spark.createDataFrame([(i,) for i in range(1, 6)], "pos bigint")
    forest = spark.createDataFrame([(1, 3, 2.0), (2, 3, 1.0), (3, 4, 1.0)], EDGES)
    assert sorted(r.pos for r in evolution.forest_roots(nodes, forest).collect()) == [1, 2, 5]
    s = evolution.forest_stats(nodes, forest).first()
    assert (s.n_nodes, s.n_edges, s.n_components, s.n_roots, s.total_sigma) == (5, 3, 2, 3, 4.0)
    line = evolution.lineage(forest, spark.createDataFrame([(1,)], "root bigint"))
    assert {(r.node, r.depth) for r in line.collect()} == {(1, 0), (3, 1), (4, 2)}
    back = evolution.ancestry(forest, spark.createDataFrame([(4,)], "root bigint"))
    assert {r.node for r in back.collect()} == {1, 2, 3, 4}


def test_pruned_graph_has_the_same_forest(spark):
    rng = random.Random(9)
    nodes = spark.createDataFrame([(i, 10 + i // 4) for i in range(16)], "pos bigint, period int")
    clusters = spark.createDataFrame([(i, rng.choice([0, 1, None])) for i in range(16)], "node bigint, cluster bigint")
    pairs = [(a, b) for a in range(16) for b in range(a + 1, 16)]
    high, rel = (spark.createDataFrame(rng.sample(pairs, k), "a bigint, b bigint") for k in (12, 25))
    forests = []
    for prune in (False, True):
        graph = evolution.confidence_graph(nodes, clusters, high, rel, prune)
        forests.append({(r.src, r.dst) for r in evolution.temporal_forest(evolution.scored_edges(graph), "kruskal").collect()})
    assert forests[0] == forests[1]


def test_dbscan_border_and_noise(spark):
    nodes = spark.createDataFrame([(i,) for i in range(9)], "pos bigint")
    pairs = spark.createDataFrame([(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (4, 5), (4, 6), (5, 6)], "a bigint, b bigint")
    got = {r.node: (r.is_core, r.cluster) for r in evolution.dbscan(nodes, pairs, 4).collect()}
    assert got[2] == (True, 2) and got[4] == (True, 4) and got[3] == (False, 2) and got[7] == (False, None)


def test_group_tournament_counts(spark):
    rng = random.Random(3)
    rows = [(i, i % 2, rng.randrange(4), rng.choice("ab")) for i in range(20)]
    df = spark.createDataFrame(rows, "item_id bigint, g int, v int, c string")
    got = {(r.item_id, r.axis): (r.n_win, r.n_draw, r.n_loss) for r in compare.group_tournament(df, "g", {"v": -1}, ["c"]).collect()}
    for i, g, v, c in rows:
        others = [x for x in rows if x[1] == g and x[0] != i]
        assert got[i, "v"] == (sum(x[2] > v for x in others), sum(x[2] == v for x in others), sum(x[2] < v for x in others))
        assert got[i, "c"] == (sum(x[3] != c for x in others), sum(x[3] == c for x in others), 0)


def test_network_layers_and_caps(spark):
    links = spark.createDataFrame([(5, 3, 1.0), (5, 4, 2.0), (4, 1, 1.0), (6, 5, 1.0), (7, 5, 3.0), (8, 7, 1.0), (8, 5, 1.0)], "src bigint, dst bigint, relevance double")
    targets = spark.createDataFrame([(5,)], "target_id bigint")
    got = {(r.item_id, r.relation, r.layer) for r in network.layered_network(links, targets, 2, cap_cites=2).collect()}
    assert got == {(3, "reference", 1), (4, "reference", 1), (1, "reference", 2), (6, "citation", 1), (7, "citation", 1), (8, "citation", 2)}
    deeper, flat = (network.layered_network(links, targets, d) for d in (2, 1))
    assert flat.select("item_id").exceptAll(deeper.select("item_id")).count() == 0


def test_curation_and_parsing(spark):
    axes = spark.createDataFrame([(1, "a", "numeric", 1), (1, "b", "numeric", 1)], "target_id bigint, axis string, kind string, direction int")
    edits = spark.createDataFrame([("remove", "a", None, None, None), ("edit", "b", "c", None, -1)], "op string, axis string, new_axis string, kind string, direction int")
    assert [(r.axis, r.direction) for r in extract.curate_axes(axes, edits).collect()] == [("c", -1)]
    parsed = spark.createDataFrame([('{"a": "1", "x": "2", "b": ""}',), ("broken",), (None,)], "t string").select(extract.parse_response(F.col("t"), ["a", "b"]).alias("m")).collect()
    assert [r.m for r in parsed] == [{"a": "1"}, {}, {}]


def test_model_plug_in_asks_once(spark):
    items = spark.createDataFrame([(1, "x"), (2, "y")], "item_id bigint, body string")
    model = lambda prompts: ['{"a": "%d"}' % len(p) for p in prompts]
    first = extract.model_extract(items, model, ["a"])
    again = extract.model_extract(items, lambda p: 1 / 0, ["a"], cache=first.select("prompt_hash", "answer"))
    assert sorted(r.answer["a"] for r in again.collect()) == sorted(r.answer["a"] for r in first.collect())


def test_measures(spark):
    rows = spark.createDataFrame([(i, float(s), y) for i, (s, y) in enumerate([(3, 1), (2, 0), (2, 1), (1, 0)])], "id bigint, s double, y int")
    assert measures.auc(rows, "s", "y").first().auc == 0.875
    assert measures.precision_at_k(rows, "s", "y", "id", 2).first().p_at_k == 0.5
    assert measures.spearman(rows.withColumn("t", -F.col("s")), "s", "t").first().rho == -1.0
    same = measures.stability(rows, rows, ["id"], ["s"]).first()
    assert (same.cells, same.agree_share) == (4, 1.0)


def test_empty_inputs(spark):
    empty = spark.createDataFrame([], "series string, pos bigint, v double")
    assert temporal.numeric_advances(empty, ["series"], "v").count() == 0
    assert temporal.tolerant_winners(empty, ["series"], "v", 0.1).count() == 0
    assert evolution.dbscan(empty.select("pos"), spark.createDataFrame([], "a bigint, b bigint"), 3).count() == 0
    assert evolution.temporal_forest(spark.createDataFrame([], EDGES)).count() == 0


def test_units_must_agree(spark):
    schema = "kind string, direction int, tolerance double, t_num double, v_num double, t_txt string, v_txt string, t_unit string, v_unit string"
    rows = [("numeric", 1, 0.0, 2.0, 1.0, None, None, "ms", "ms"), ("numeric", 1, 0.0, 2.0, 1.0, None, None, "ms", "%")]
    assert [r.s for r in compare.duels(spark.createDataFrame(rows, schema)).collect()] == [1, None]


def test_bounded_history_is_a_subset(spark):
    rows = series(spark, [f"v{i % 40}" for i in range(80)])
    exact = {(r.v, r.pos) for r in temporal.first_appearances(rows, ["series"], "v").collect()}
    bounded = {(r.v, r.pos) for r in temporal.bounded_first_appearances(rows, ["series"], "v", 4).collect()}
    assert bounded <= exact and 0 < len(bounded) <= 16


def test_nan_is_missing(spark):
    nan = float("nan")
    rows = series(spark, [1.0, nan, 5.0, None, 9.0, 5.0])
    want = [1, None, 1, None, 1, -1]
    assert [r.s for r in temporal.numeric_advances(rows, ["series"], "v").orderBy("pos").collect()] == want
    assert [r.s for r in temporal.best_so_far_scan(rows, "v", 2, ["series"]).orderBy("pos").collect()] == want
    assert list(temporal.iterate([1.0, nan, 5.0, None, 9.0, 5.0])) == want
    won = temporal.tolerant_winners(rows, ["series"], "v", 0.0)
    assert sorted(r.pos for r in won.collect()) == [1, 3, 5]
    assert [r.s for r in temporal.with_state(rows, won, ["series"], "v", 0.0).orderBy("pos").collect()] == want


def test_state_is_continued_and_merged(spark):
    rng = random.Random(12)
    rows = spark.createDataFrame([(k, i, float(rng.randrange(40)) if i % 5 else None) for k in "ab" for i in range(1, 60)] + [("c", 50, 1.0)], "series string, pos bigint, v double")
    keys, whole = ["series"], temporal.numeric_advances(rows, ["series"], "v")
    old = temporal.temporal_state(rows.where("pos <= 30"), keys, "v")
    later = temporal.continue_advances(old, rows.where("pos > 30"), keys, "v")
    assert sorted(map(tuple, later.collect()), key=str) == sorted(map(tuple, whole.where("pos > 30").collect()), key=str)
    new = later.groupBy("series").agg(F.max("v").alias("best"), F.max("nu").alias("nu"), F.max("pos").alias("last_pos"))
    assert sorted(map(tuple, temporal.merge_states(old, new, keys).collect())) == sorted(map(tuple, temporal.temporal_state(rows, keys, "v").collect()))


def test_similar_profiles_equal_all_pairs(spark):
    from novelty_engine.operators import applications

    rng = random.Random(13)
    axes = [f"a{i:02d}" for i in range(70)]
    rows = []
    for item in range(24):
        seed = random.Random(item % 9)
        rows += [(t, item, a, seed.choice([1, 0, -1, None])) for t in (1, 2) for a in axes[: 6 if t == 1 else 70]]
    df = spark.createDataFrame(rows, "target_id bigint, item_id bigint, axis string, s int")
    profile = {}
    for t, i, a, s in rows:
        profile.setdefault((t, i), {}).update({a: s} if s is not None else {})
    want = []
    for t in (1, 2):
        pairs = []
        for a in range(24):
            for b in range(a + 1, 24):
                p, q = profile[t, a], profile[t, b]
                both = p.keys() & q.keys()
                if both:
                    pairs.append((-round(sum(p[x] == q[x] for x in both) / len(both), 6), -len(both), a, b))
        want += [(t, a, b, -n, -s) for s, n, a, b in sorted(pairs)[:7]]
    assert sorted(map(tuple, applications.similar_profiles(df, 7).collect())) == sorted(want)
    classes = {(r.target_id, r.item_id): (r.profile, r.n_members) for r in applications.profile_classes(df).collect()}
    for (t, i), (least, n) in classes.items():
        same = [j for j in range(24) if profile[t, j] == profile[t, i]]
        assert (least, n) == (min(same), len(same))


def test_curation_adds_and_weighs(spark):
    schema = "target_id bigint, axis string, kind string, direction int"
    axes, offered = spark.createDataFrame([(1, "a", "numeric", 1)], schema), spark.createDataFrame([(1, "a", "numeric", 1), (1, "b", "numeric", 1), (1, "c", "numeric", 1)], schema)
    edits = spark.createDataFrame([("add", "b", None, None, None, None), ("edit", "b", None, None, -1, None), ("weight", "a", None, None, None, 3.0)], "op string, axis string, new_axis string, kind string, direction int, weight double")
    assert sorted((r.axis, r.direction) for r in extract.curate_axes(axes, edits, offered).collect()) == [("a", 1), ("b", -1)]
    counts = spark.createDataFrame([(1, "a", "all", 1, 1, 0), (1, "b", "all", 1, 0, 1)], COUNTS)
    assert {r.axis: r.w for r in extract.edited_weights(counts, edits).collect()} == {"a": 0.75, "b": 0.25}


def test_scales_agree_on_ternary_verdicts(spark):
    rng = random.Random(15)
    rows = [(t, i, a, rng.choice([1, 0, -1, None])) for t in range(3) for i in range(9) for a in "xyz"]
    df = spark.createDataFrame(rows, "target_id bigint, item_id bigint, axis string, s int")
    plain = {r.target_id: r.omega for r in overall.overall_score(overall.axis_counts(df)).collect()}
    assert plain == {r.target_id: r.omega for r in overall.scaled_score(df).collect()}
    for r in overall.without_items(df).where("item_id = 4").collect():
        rest = df.where((F.col("target_id") == r.target_id) & (F.col("item_id") != 4))
        assert overall.overall_score(overall.axis_counts(rest)).first().omega == r.omega_without


def test_equivalence_rules(spark):
    from novelty_engine.functions import categorical_score

    df = spark.createDataFrame([("large brass widget", "brass widget large", "larger brass wodget")], "a string, b string, c string")
    r = df.select(*(categorical_score(F.col("a"), F.col(x), how, 0.6).alias(f"{how}_{x}") for how in ("exact", "jaccard", "edit", "cosine") for x in "bc")).first()
    assert (r.exact_b, r.exact_c, r.jaccard_b, r.jaccard_c, r.edit_b, r.edit_c, r.cosine_b, r.cosine_c) == (1, 1, 0, 1, 1, 0, 0, 0)


def test_tsne_parts_two_heaps():
    import numpy as np

    rng = np.random.default_rng(3)
    points = np.concatenate([rng.normal(0, 0.1, (20, 5)), rng.normal(5, 0.1, (20, 5))])
    y = evolution.tsne(points)
    inside = max(np.linalg.norm(y[:20] - y[:20].mean(axis=0), axis=1).mean(), np.linalg.norm(y[20:] - y[20:].mean(axis=0), axis=1).mean())
    assert np.linalg.norm(y[:20].mean(axis=0) - y[20:].mean(axis=0)) > 2 * inside


def test_stage_timer_and_costs(spark):
    timer = measures.StageTimer()
    timer.run("one", spark.range(7), calls=lambda rows: 2 * rows)
    assert [(r.stage, r.calls, r.rows) for r in timer.log(spark).collect()] == [("one", 14, 7)]
    costs = {r.measure: r.value for r in measures.run_costs(spark, lambda: spark.range(100).groupBy((F.col("id") % 3).alias("k")).count()).collect()}
    assert costs["stages"] >= 1 and costs["shuffle_rows"] > 0 and costs["plan Exchange"] >= 1
