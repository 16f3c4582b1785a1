import pytest
from pyspark.sql import functions as F

from hopjoin.operators import measures
from hopjoin.plans import graph


def make(spark, edges):
    rows = [(f"{a}~{b}~{kind}", kind, a, ["k"], b, ["k"], s) for a, b, s, kind in edges]
    e = spark.createDataFrame(rows, "edge_id string, kind string, left_node string, left_columns array<string>, right_node string, right_columns array<string>, overlap double")
    return graph.build(e, None)


CASES = [
    ([("A", "B", 0.25, "fk"), ("A", "C", 0.9, "fk"), ("B", "C", 0.9, "fk")], ["A", "C", "B"], 0.81),
    ([("A", "B", 0.9, "fk"), ("A", "C", 0.9, "fk"), ("B", "C", 0.9, "fk")], ["A", "B"], 0.9),
    ([("A", "B", 0.81, "fk"), ("A", "C", 0.9, "fk"), ("B", "C", 0.9, "fk")], ["A", "B"], 0.81),
    ([("A", "B", 1.0, "fk"), ("A", "C", 1.0, "fk"), ("B", "C", 1.0, "fk")], ["A", "B"], 1.0),
]


@pytest.mark.parametrize("edges,nodes,kept", CASES)
def test_paths(spark, edges, nodes, kept):
    g = make(spark, edges)
    p = graph.shortest_path(g, "A", "B")
    assert measures.path_equal(p, nodes) and not measures.path_equal(p, nodes[::-1]) and p.retained == pytest.approx(kept, abs=1e-6)
    r = graph.paths_sql(g.edges, "A", 3).where("target = 'B'").first()
    assert r.nodes == nodes and r.total_weight == pytest.approx(p.total_weight)
    f = graph.all_pairs(g.edges, 3, ["A"]).where("target = 'B'").first()
    assert f.total_weight == pytest.approx(p.total_weight, abs=1e-6) and f.hops == len(p.hops)


def test_frontiers_equal_the_driver(spark):
    """Chains longer than any hop limit, a shortcut that weighs more, and a part of its own."""
    chain = [(f"n{i:02d}", f"n{i + 1:02d}", 0.9, "fk") for i in range(12)] + [("n00", "n12", 0.2, "fk"), ("x", "y", 0.5, "fk")]
    g = make(spark, chain)
    rows = lambda **o: sorted((r.source, r.target, r.hops, round(r.total_weight, 6)) for r in graph.all_pairs(g.edges, **o).collect())
    local, joined = rows(sources=["n00", "x"]), rows(sources=["n00", "x"], local_edges=0)
    assert local == joined and ("n00", "n12", 12, round(12 * graph.weight(0.9), 6)) in local and len(local) == 15
    assert rows(max_hops=3, sources=["n00"]) == rows(max_hops=3, sources=["n00"], local_edges=0)
    assert len(rows()) == 13 * 13 + 4


def test_parallel_edges_and_kinds(spark):
    g = make(spark, [("A", "B", 0.5, "fuzzy"), ("A", "B", 0.8, "fk")])
    assert graph.shortest_path(g, "A", "B").hops[0].kind == "fk"
    assert graph.shortest_path(g, "A", "B", kinds=("fuzzy",)).hops[0].overlap == 0.5


def test_limits(spark):
    g = make(spark, [("A", "B", 1.0, "fk"), ("C", "D", 0.0, "fk")])
    assert graph.shortest_path(g, "A", "B").total_weight == 0.0
    assert graph.shortest_path(g, "C", "D").total_weight == pytest.approx(29.9, abs=0.01)
    assert graph.shortest_path(g, "A", "A").hops == () and graph.shortest_path(g, "A", "A").retained == 1
    with pytest.raises(graph.NoJoinPath):
        graph.shortest_path(g, "A", "C")


def test_k_paths_and_hops(spark):
    g = make(spark, [("A", "B", 0.25, "fk"), ("A", "C", 0.9, "fk"), ("B", "C", 0.9, "fk")])
    assert [p.nodes for p in graph.k_paths(g, "A", "B", 5)] == [["A", "C", "B"], ["A", "B"]]
    assert graph.fewest_hops(g, "A", "B").nodes == ["A", "B"]
    assert '"A" -- "B"' in graph.to_dot(g)


def test_weights(spark):
    df = spark.createDataFrame([(1.0,), (0.5,), (0.0,)], "s double").select(graph.edge_weight(F.col("s")).alias("w"))
    assert [round(r.w, 3) for r in df.collect()] == [0.0, 1.0, 29.897]
