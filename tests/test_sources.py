"""Readers, item feed, stores, streaming."""

import json
from datetime import datetime, timedelta

from novelty_engine import sources, streaming
from novelty_engine.operators import applications, baselines
from novelty_engine.sources import feed


def test_item_feed(spark, tmp_path):
    (tmp_path / "a.jsonl").write_text("\n".join(json.dumps(x) for x in [{"item_id": 1, "title": "t", "year": 2001}, {"item_id": 2, "body": "b"}]))
    feed.register(spark)
    rows = spark.read.format("item_feed").option("path", str(tmp_path)).load().orderBy("item_id").collect()
    assert [(r.item_id, r.title, r.body, r.year) for r in rows] == [(1, "t", None, 2001), (2, None, "b", None)]


def test_items_fall_back_to_the_year(spark):
    df = spark.createDataFrame([(1, "x", "2001-05-03", 2001), (2, "y", None, 1999), (3, "z", None, None)], "id int, t string, d string, y int")
    got = {r.item_id: str(r.pub_date) for r in sources.items_from(df, "id", "t", "d", "y").collect()}
    assert got == {1: "2001-05-03", 2: "1999-01-01"}


def test_formats(spark, tmp_path):
    df = spark.createDataFrame([(1, "a")], "item_id bigint, body string")
    for fmt in ("parquet", "json", "orc", "csv"):
        path = str(tmp_path / fmt)
        df.write.format(fmt).option("header", True).save(path)
        assert sources.read_items(spark, path, fmt, df.schema, header=True).collect()[0].body == "a"


def test_store_reads_one_bucket(spark, tmp_path):
    df = spark.range(200).withColumnRenamed("id", "target_id")
    applications.materialise(df, str(tmp_path / "s"), "target_id", 8)
    one = applications.open_store(spark, str(tmp_path / "s"), "target_id", 77, 8)
    assert [r.target_id for r in one.collect()] == [77] and applications.open_store(spark, str(tmp_path / "s")).count() == 200


def test_passages_equal_plain_search(spark, sf):
    docs, passages = sources.load(spark, sf, "documents"), sources.load(spark, sf, "benchmark")
    got = {(r.item_id, r.passage_id) for r in sources.contained_passages(docs, passages).collect()}
    texts = {r.item_id: r.text for r in passages.collect()}
    assert got == {(d.doc_id, p) for d in docs.collect() for p, t in texts.items() if t in d.text}


def test_passages_in_any_number(spark, sf):
    docs, passages = sources.load(spark, sf, "documents"), sources.load(spark, sf, "benchmark").union(spark.createDataFrame([(9001, "the")], "item_id bigint, text string"))
    few, many = ({(r.item_id, r.passage_id) for r in sources.contained_passages(docs, passages, most=n).collect()} for n in (2000, 7))
    assert few == many and {p for _, p in many} > {9001}


def test_targets_in_blocks(spark):
    from novelty_engine.operators import network

    vectors = spark.createDataFrame([(i, [float(i % 7), float(i % 5), 1.0]) for i in range(60)], "item_id bigint, vec array<double>")
    targets = spark.range(0, 60, 3).withColumnRenamed("id", "target_id")
    one, blocks = (sorted(map(tuple, network.semantic_network(vectors, targets, 5, block=n).collect())) for n in (100, 7))
    rows = {r.item_id: r.vec for r in vectors.collect()}
    want = []
    for t in range(0, 60, 3):
        near = sorted((-round(sum(a * b for a, b in zip(rows[t], v)), 6), i) for i, v in rows.items() if i != t)[:5]
        want += [(t, i, "similar", 1, -s) for s, i in near]
    assert one == blocks == sorted(want)


def test_pairwise_axes_are_intransitive(spark):
    items = spark.createDataFrame([(1, 1.0, 10.0, 5.0), (2, 5.0, 1.0, 10.0), (3, 10.0, 5.0, 1.0)], "item_id bigint, x double, y double, z double")
    axes = {"x": 1, "y": 1, "z": 1}
    assert baselines.intransitive_triples(baselines.pairwise_winners(items, axes)).first().n_cycles == 1
    assert baselines.intransitive_triples(baselines.pairwise_winners(items, axes, fixed="y")).first().n_cycles == 0


def chain_by_hand(rows):
    """(src, dst) -> relevance from (group, member): cite the member before and the first."""
    groups, out = {}, {}
    for g, m in sorted(set(rows)):
        members = groups.setdefault(g, [])
        for cited in {members[-1], members[0]} if members else ():
            out[m, cited] = out.get((m, cited), 0) + 1.0
        members.append(m)
    return out


def test_links_through_lines_of_any_frequency(spark):
    common, rare = "c" * 40, "r" * 45
    docs = spark.createDataFrame([(i, f"{common}\n{rare}\n{rare}" if i % 40 == 0 else common) for i in range(120)] + [(500, None), (501, "short")], "doc_id bigint, text string").repartition(7)
    got = {(r.src, r.dst): r.relevance for r in sources.document_links(docs).collect()}
    assert got == chain_by_hand([(common, i) for i in range(120)] + [(rare, i) for i in range(0, 120, 40)])
    assert sources.document_links(docs.limit(0)).count() == 0


def test_chain_links_equal_the_plain_chain(spark):
    import random

    rng = random.Random(2)
    rows = list({(rng.randrange(12), rng.randrange(60)) for _ in range(300)})
    df = spark.createDataFrame(rows, "g int, m bigint").repartition(6)
    assert {(r.src, r.dst): r.relevance for r in sources.chain_links(df, ["g"], ["m"], "m").collect()} == chain_by_hand(rows)


def test_bridges_of_values_of_any_frequency(spark):
    pairs = [(i, "mit") for i in range(60)] + [(3, "passage"), (7, "passage"), (9, None)]
    values = spark.createDataFrame(pairs, "item_id bigint, value string")
    links = spark.createDataFrame([(2, 1), (59, 0), (7, 3), (1, 2)], "src bigint, dst bigint")
    linked = {(2, 1), (59, 0), (7, 3)}
    got = {(r.value, r.item_id): (r.n_members, r.n_linked, r.n_bridges) for r in applications.bridges(values, links).collect()}
    for (value, item), counts in got.items():
        others = [j for j, v in pairs if v == value and j != item]
        n = sum((max(item, j), min(item, j)) in linked for j in others)
        assert counts == (len(others) + 1, n, len(others) - n)
    assert len(got) == 62
    partners = applications.bridge_partners(values, links, spark.createDataFrame([(3,), (2,)], "item_id bigint")).collect()
    want = {(i, j): 1 for i in (2, 3) for j in range(60) if i != j and (max(i, j), min(i, j)) not in linked}
    assert {(r.item_a, r.item_b): r.n_shared for r in partners} == want


def test_stream_orders_and_counts(spark, tmp_path):
    start = datetime(2024, 1, 1)
    rows = [("k", i, start + timedelta(hours=h), v) for i, (h, v) in enumerate([(0, 1.0), (3, 5.0), (1, 3.0), (2, 2.0), (4, None), (5, 5.0), (6, 9.0)])]
    schema = "series string, id bigint, ts timestamp, v double"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in" / "a"))
    spark.createDataFrame([("k", -1, start + timedelta(days=30), None)], schema).write.parquet(str(tmp_path / "in" / "b"))
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    streaming.run_to_end(streaming.stream_advances(stream, "series", "id", "ts", "v"), str(tmp_path / "out"), str(tmp_path / "state"))
    got = spark.read.parquet(str(tmp_path / "out")).where("row_id >= 0").orderBy("ts").collect()
    assert [(r.row_id, r.s, r.nu) for r in got] == [(0, 1, 1), (2, 1, 2), (3, -1, 2), (1, 1, 3), (4, None, 3), (5, 0, 3), (6, 1, 4)]


def test_stream_windows(spark, tmp_path):
    start = datetime(2024, 1, 1)
    rows = [("k", i, start + timedelta(hours=i)) for i in range(6)] + [("k", 99, start + timedelta(days=40))]
    schema = "k string, id bigint, ts timestamp"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).parquet(str(tmp_path / "in"))
    streaming.run_to_end(streaming.windowed_counts(stream, "ts", "k", "3 hours"), str(tmp_path / "a"), str(tmp_path / "as"))
    streaming.run_to_end(streaming.session_counts(stream, "ts", "k"), str(tmp_path / "b"), str(tmp_path / "bs"))
    assert sorted(r.n for r in spark.read.parquet(str(tmp_path / "a")).collect()) == [3, 3]
    assert sorted(r.n for r in spark.read.parquet(str(tmp_path / "b")).collect()) in ([6], [1, 1, 1, 1, 1, 1])


def test_engine_does_not_collect():
    from pathlib import Path

    for file in (Path(sources.__file__).parents[1] / "operators").glob("*.py"):
        assert ".collect()" not in file.read_text() and "toPandas" not in file.read_text()
