"""Order without a single task equals plain windows."""

import random

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from novelty_engine import session
from novelty_engine.operators import scan


@pytest.fixture
def rows(spark):
    rng = random.Random(11)
    return spark.createDataFrame([(i * 3, float(rng.randrange(20)) if i % 9 else None) for i in range(200)], "id bigint, v double").repartition(5)


def test_positions_and_sums(spark, rows):
    got = {r.id: r.pos for r in scan.numbered(rows, F.desc("v"), "id").collect()}
    assert got == {r.id: r.p for r in rows.withColumn("p", F.row_number().over(Window.orderBy(F.desc("v"), "id"))).collect()}
    sums = {r.id: r.ahead for r in scan.running(rows.withColumn("n", F.col("id") % 7), "id", "n", "ahead").collect()}
    assert sums == {3 * i: sum(3 * j % 7 for j in range(i)) for i in range(200)}
    assert scan.numbered(rows.limit(0), "id").count() == 0


@pytest.mark.parametrize("descending", [True, False])
def test_ranks(spark, rows, descending):
    order = F.col("v").desc_nulls_last() if descending else F.col("v").asc_nulls_last()
    want = {r.id: r.r for r in rows.withColumn("r", F.rank().over(Window.orderBy(order))).collect()}
    assert {r.id: r.r for r in scan.ranks(rows, "v", "r", descending).collect()} == want
    ties = {v: sum(x == v for x in want.values()) for v in want.values()}
    assert {r.id: r.r for r in scan.ranks(rows, "v", "r", descending, average=True).collect()} == {i: v + (ties[v] - 1) / 2 for i, v in want.items()}


def test_neighbours(spark, rows):
    got = {r.id: r.below for r in scan.neighbours(rows, "id", "below").collect()}
    assert got == {3 * i: 3 * i - 3 if i else None for i in range(200)}


def test_shared_folder_is_never_local_on_a_cluster(spark, tmp_path):
    class Context:
        master, folder = "spark://host:7077", None

        def getCheckpointDir(self):
            return self.folder

        def setCheckpointDir(self, folder):
            self.folder = folder

    class Session:
        sparkContext = Context()
        conf = {}

    with pytest.raises(RuntimeError):
        session.shared_folder(Session)
    folder = tmp_path / "gone"
    folder.mkdir()
    session.remove_folder(spark, str(folder))
    assert not folder.exists()
