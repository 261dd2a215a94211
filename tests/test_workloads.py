"""Every workload with SQL gives the SQL's rows on the smallest tables; plans keep their shape."""

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry_points
from novelty_engine.operators import evolution, measures
from novelty_engine.plans import workloads
from novelty_engine.plans.oracles import SQL

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET timezone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_sql(spark, duck, sf, name):
    df = workloads.QUERIES[name](spark, sf)
    relation = duck.sql(SQL[name])
    assert sorted(df.columns) == sorted(relation.columns)
    order = sorted(df.columns)
    at = [relation.columns.index(c) for c in order]
    key = lambda row: tuple(str(x) for x in row)
    assert sorted(key(r[c] for c in order) for r in df.collect()) == sorted(key(r[i] for i in at) for r in relation.fetchall())


@pytest.mark.parametrize("name", sorted(set(workloads.QUERIES) - set(SQL)))
def test_runs_without_sql(spark, sf, name):
    assert workloads.QUERIES[name](spark, sf).count() > 0


def test_contract(spark):
    assert set(SQL) <= set(workloads.QUERIES) <= set(entry_points.queries())
    assert entry_points.entry(spark).count() == 20


def test_recall_of_approximate_pairs(spark, sf):
    assert workloads.y14_lsh_recall(spark, sf).first().recall >= 0.9


def test_recall_counts_pairs_and_shuffles_none(spark, sf):
    """Queries against all rows, as plain loops count them; no join of pairs, and a null or zero vector matches nothing."""
    vectors = workloads._vectors(spark, sf)
    rows = {r.item_id: np.array(r.vec, np.float32).astype(float) for r in vectors.collect()}
    unit = {k: v / np.linalg.norm(v) for k, v in rows.items()}
    want = {(q, k): round(float(unit[q] @ unit[k]), 6) for q in unit if q % 100 == 0 for k in unit if k != q and round(float(unit[q] @ unit[k]), 6) >= 0.33}
    df = workloads.y14_lsh_recall(spark, sf)
    assert df.columns == ["n_exact", "recall"] and df.first().n_exact == len(want)
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()
    odd = vectors.select("item_id", "vec").union(spark.createDataFrame([(9000, None), (9100, [0.0] * 64)], "item_id bigint, vec array<double>"))
    queries = odd.where("item_id % 100 = 0")
    exact, found = ({(r.query, r.item): r.sim for r in evolution.search_pairs(queries, odd, 0.33, approximate=how, rows=100, block=2).collect()} for how in (False, True))
    assert exact == pytest.approx(want, abs=2e-6) and set(found) <= set(exact) and len(found) >= 0.9 * len(exact)


def test_plan_shapes(spark, sf):
    duel_plan = measures.plan_shape(workloads.documents(spark, sf).duels)
    assert duel_plan["CartesianProduct"] == duel_plan["BroadcastNestedLoopJoin"] == 0
    assert not any(duel_plan[k] for k in ("BatchEvalPython", "ArrowEvalPython", "MapInPandas", "FlatMapGroupsInPandas"))
    lines = workloads.w07_records_by_brand(spark, sf)
    scan = lines._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in scan and "o_totalprice" not in scan
