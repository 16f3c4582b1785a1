import pytest
from pyspark.sql import functions as F

from hopjoin.functions import names, sql, strings
from hopjoin.plans import graph


@pytest.fixture(scope="module")
def known(spark):
    return sql.register_functions(spark)


def test_scalars_equal_the_column_forms(spark, known):
    df = spark.createDataFrame([("b a", "a  b"), ("almond tea", "tea almnd"), ("", ""), (None, "x"), (" x ", "x")], "a string, b string")
    df.createOrReplaceTempView("sql_pairs")
    got = spark.sql("SELECT token_sort_ratio(a, b) AS r, gestalt_ratio(a, b) AS g, token_sort(a) AS s FROM sql_pairs").collect()
    want = df.select(strings.token_sort_ratio(F.col("a"), F.col("b")).alias("r"), names.gestalt_ratio(F.col("a"), F.col("b")).alias("g"), strings.token_sort(F.col("a")).alias("s")).collect()
    assert got == want and got[0].r == 1.0 and got[3].r is None


def test_weights_equal_the_graph_forms(spark, known):
    df = spark.createDataFrame([(0.81,), (1.0,), (0.0,), (None,)], "s double")
    df.createOrReplaceTempView("sql_overlaps")
    got = spark.sql("SELECT edge_weight(s) AS w, retained(edge_weight(s)) AS k FROM sql_overlaps").collect()
    want = df.select(graph.edge_weight(F.col("s")).alias("w")).collect()
    for g, w in zip(got, want):
        assert g.w == (pytest.approx(w.w) if w.w is not None else None)
    assert got[0].k == pytest.approx(0.81)


def test_table_functions(spark, known):
    hops = spark.sql("SELECT p, hop, left_node, right_node FROM VALUES ('a>b>c'), ('a'), (''), (NULL) AS v(p), LATERAL path_hops(p) ORDER BY hop").collect()
    assert [tuple(r) for r in hops] == [("a>b>c", 1, "a", "b"), ("a>b>c", 2, "b", "c")]
    grams = spark.sql("SELECT v, pos, gram FROM VALUES ('abcd'), ('x'), (NULL) AS t(v), LATERAL grams_of(v, 3) ORDER BY v, pos").collect()
    assert [tuple(r) for r in grams] == [("abcd", 1, "abc"), ("abcd", 2, "bcd"), ("x", 1, "x")]


def test_grouped_score(spark, known):
    got = spark.sql("SELECT k, value_score_of(b, w) AS s FROM VALUES ('p', 1D, 3D), ('p', 0.5D, 1D), ('q', 0D, 0D) AS t(k, b, w) GROUP BY k ORDER BY k").collect()
    assert [tuple(r) for r in got] == [("p", 0.875), ("q", 0.0)]
