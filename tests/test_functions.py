"""Worked examples of verdicts, quantities, overlap, confidence and edge scores."""

from pyspark.sql import functions as F

from novelty_engine import functions as fn


def one(spark, column, **values):
    schema = ", ".join(f"{k} {t}" for k, (t, _) in values.items()) or "x int"
    row = tuple(v for _, v in values.values()) or (1,)
    return spark.createDataFrame([row], schema).select(column.alias("r")).first().r


def test_numeric_score_examples(spark):
    n = lambda t, v, d=1, tol=0.0: one(spark, fn.numeric_score(F.col("t"), F.col("v"), d, tol), t=("double", t), v=("double", v))
    assert n(28.4, 26.54) == 1 and n(41.8, 38.94) == 1
    assert n(1.0, 2.0) == -1 and n(1.0, 2.0, -1) == 1 and n(2.0, 2.0) == 0
    assert n(None, 2.0) is None and n(2.0, None) is None and n(float("nan"), 1.0) is None
    assert n(0.0, -0.0) == 0 and n(105.0, 100.0, 1, 0.05) == 0 and n(106.0, 100.0, 1, 0.05) == 1


def test_categorical_score_is_never_a_loss(spark):
    c = lambda t, v: one(spark, fn.categorical_score(F.col("t"), F.col("v")), t=("string", t), v=("string", v))
    assert c("B, b", "b B") == 0 and c("a", "b") == 1 and c("b", "a") == 1 and c(None, "a") is None


def test_parse_quantity(spark):
    q = lambda x: one(spark, fn.parse_quantity(F.col("x")), x=("string", x))
    assert q("28.4 points on a task").value == 28.4
    assert q("Over 2 times").value == 2.0 and q("12% of it").unit == "%" and q("3k items").value == 3000 and q("none") is None and q(None) is None


def test_confidence_levels_first_match(spark):
    rows = [(1, 1, True, True, 5), (1, 1, False, True, 4), (1, 2, True, True, 3), (1, None, False, True, 2), (None, None, False, True, 1), (1, 2, True, False, 0), (None, None, True, False, 0)]
    df = spark.createDataFrame(rows, "a int, b int, high boolean, rel boolean, want int")
    got = df.select("want", fn.confidence(F.col("a"), F.col("b"), F.col("high"), F.col("rel")).alias("got")).collect()
    assert all(r.want == r.got for r in got)


def test_edge_scores(spark):
    e = lambda g, d: one(spark, fn.edge_score(F.col("c"), F.col("g"), g, d), c=("int", 4), g=("int", 1))
    assert [e(1, 1), e(2, 1), e(1, 0), e(0, 1)] == [2.0, 8.0, 4.0, 0.5]


def test_overlap_and_edit(spark):
    a = F.array(*map(F.lit, "abc")), F.array(*map(F.lit, "bcd"))
    assert one(spark, fn.overlap(*a)) == 0.5
    assert abs(one(spark, fn.overlap(*a, "dice")) - 2 / 3) < 1e-12 and abs(one(spark, fn.overlap(*a, "overlap")) - 2 / 3) < 1e-12
    assert one(spark, fn.edit_similarity(F.lit("abcd"), F.lit("abcf"))) == 0.75


def test_text_vectors_are_unit_length(spark):
    v = one(spark, fn.embed_text(F.lit("Large brass widget")))
    assert len(v) == 64 and abs(sum(x * x for x in v) - 1) < 1e-9


def test_sql_functions(spark):
    fn.register(spark)
    r = spark.sql("SELECT numeric_score(2D, 1D, 1, 0D) a, normalise_value(' A-b ') b, axis_score(6L, 2L, 2L, 0.5D) c, edge_score(4, 1, 1D, 1D) d, novelty_step(1, 4L) e").first()
    assert (r.a, r.b, r.c, r.d, r.e) == (1, "a b", 0.5, 2.0, 5)
