"""Table functions, sinks and the SQL surface."""

from novelty_engine import sinks
from novelty_engine.functions import tables
from novelty_engine.operators import temporal


def test_table_function_equals_windows(spark):
    rows = spark.createDataFrame([(k, i + 1, float(v)) for k in ("a", "b") for i, v in enumerate([3, 1, 3, 5, 4])], "series string, pos bigint, v double")
    tables.register(spark)
    rows.createOrReplaceTempView("novelty_rows")
    got = {(r.series, r.pos, r.s, r.nu) for r in spark.sql("SELECT * FROM novelty_timeline(TABLE(novelty_rows))").collect()}
    assert got == {(r.series, r.pos, r.s, r.nu) for r in temporal.numeric_advances(rows, ["series"], "v").collect()}


def test_bucketed_join_has_no_exchange(spark):
    for name in ("bucket_a", "bucket_b"):
        sinks.write_bucketed(spark.range(100).withColumnRenamed("id", "item_id"), name, "item_id", 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        joined = spark.table("bucket_a").join(spark.table("bucket_b"), "item_id")
        assert joined.count() == 100 and "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_graph_text(spark, tmp_path):
    nodes = spark.createDataFrame([(1, 'a "b"'), (2, "c")], "pos bigint, value string")
    forest = spark.createDataFrame([(1, 2, 2.5)], "src bigint, dst bigint, sigma double")
    lines = [r.line for r in sinks.dot_lines(forest, nodes).orderBy("place", "line").collect()]
    assert lines[0].startswith("digraph") and "  n1 -> n2 [weight=2.5];" in lines and lines[-1] == "}"
    assert sinks.graphml_lines(forest, nodes).count() == 5
    calls = spark.createDataFrame([("axes", 0.5)], "stage string, seconds double")
    for _ in range(2):
        sinks.append_calls(calls, str(tmp_path / "calls"))
    assert spark.read.json(str(tmp_path / "calls")).count() == 2
