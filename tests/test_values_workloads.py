import math

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from hopjoin import workloads
from hopjoin.functions import names, strings
from hopjoin.operators import baselines, block, catalog, execute, measures, overlap, relational, values
from hopjoin.plans import discover, graph, planner
from hopjoin.plans.config import DiscoveryConfig, TableRef

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: one query per family; all of them are compared by the driver
SOME = ("fk_overlap", "trigram_cosine", "noise_people", "best_match_places", "value_score_parts", "assign_one_to_one", "match_quality", "path_recursive", "composite_match", "bed_paths", "op_lateral_best", "embedding_topk", "affine_cosine", "external_embedder", "false_friends", "fk_edges", "column_catalog", "column_pairs", "discovered_names", "blocked_names", "op_band", "op_asof", "sliding_counts", "scenario_people")


def norm(v):
    return round(v, 5) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", SOME)
def test_against_duckdb(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    a = workloads.QUERIES[name](spark, sf)
    rel = con.sql(workloads.oracles()[name])
    assert sorted(a.columns) == sorted(rel.columns)
    cols = sorted(a.columns)
    left = sorted(tuple(map(norm, r)) for r in a.select(*cols).collect())
    at = [rel.columns.index(c) for c in cols]
    assert [tuple(map(str, r)) for r in left] == sorted(tuple(str(norm(r[i])) for i in at) for r in rel.fetchall())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_value_score_counts_duplicates(spark):
    x = values.dictionary(spark.createDataFrame([("a",), ("a",), ("b",), (None,)], "v string"), "v")
    y = values.dictionary(spark.createDataFrame([("a",)], "v string"), "v")
    r = values.value_scores(x, y).first()
    assert r.lr == pytest.approx(2 / 3) and r.rl == 1.0 and r.n_left == 3
    assert values.value_scores(x, y, weighted=False).first().lr == pytest.approx(0.5)
    assert values.value_scores(x.limit(0), y).first().lr == 0.0


def test_jaccard_edges(spark):
    a = spark.createDataFrame([(1,), (2,), (3,), (3,), (None,)], "k int")
    b = spark.createDataFrame([(2,), (3,), (4,)], "k int")
    assert overlap.jaccard(a, b, ["k"], ["k"]).first().overlap == 0.5
    assert overlap.jaccard(a.limit(0), b.limit(0), ["k"], ["k"]).first().overlap == 0.0


@pytest.fixture(scope="module")
def some_people(spark, sf):
    x, y = workloads.people(spark, sf)
    return x.orderBy("v").limit(80), y.orderBy("v").limit(80)


def brute(x, y):
    ratio = lambda a, b: 2 * strings.lcs_length(a, b) / (len(a) + len(b)) if a or b else 1.0
    ys = [(r.v, r.s) for r in y.collect()]
    return {(r.v, v): ratio(r.s, s) for r in x.collect() for v, s in ys}


def test_ways_agree(some_people):
    x, y = some_people
    want = {k: v for k, v in brute(x, y).items() if v > 0.75}
    rows = lambda way: {(r.x, r.y): r.sim for r in values.scored_pairs(x, y, min_score=0.75, way=way).collect()}
    assert rows("brute") == pytest.approx(want) and rows("bounded") == pytest.approx(want)
    assert len(set(rows("lsh")) & set(want)) >= 0.9 * len(want)


@pytest.mark.parametrize("size", [3, 17, 2000])
def test_blocks_find_the_best(some_people, size):
    x, y = some_people
    all_pairs = brute(x, y)
    got = {r.x: (r.y, round(r.sim, 9)) for r in block.best_pairs(x, y, block=size).collect()}
    want = {}
    for (a, b), sim in sorted(all_pairs.items()):
        if a not in want or round(sim, 9) > want[a][1]:
            want[a] = (b, round(sim, 9))
    assert got == want
    above = {(r.x, r.y) for r in block.pairs_above(x, y, 0.7, block=size).collect()}
    assert above == {k for k, v in all_pairs.items() if v > 0.7}
    assert 80 <= measures.comparisons(x, y).first().compared < 80 * 80 / 4


def greedy(pairs, bar):
    xs, ys, out = set(), set(), set()
    for (x, y), sim in sorted(pairs.items(), key=lambda r: (-r[1], "" if r[1] >= 1 else block.tie_key(*r[0]), r[0])):
        if sim > bar and x not in xs and y not in ys:
            xs.add(x), ys.add(y), out.add((x, y))
    return out


def test_greedy_reference(some_people):
    x, y = some_people
    got = {(r.x, r.y) for r in values.assign_one_to_one(values.scored_pairs(x, y), 0.5).collect()}
    assert got == greedy(brute(x, y), 0.5)


def test_equal_scores_settle_in_few_rounds(spark):
    labels = spark.createDataFrame([(f"N_{i:03d}",) for i in range(30)], "v string")
    x, y = values.dictionary(labels, "v"), values.dictionary(labels.select((F.concat("v", F.lit("x"))).alias("v")), "v")
    got = values.assign_one_to_one(values.scored_pairs(x, y), 0.5, max_rounds=25)
    assert got.count() == 30 and got.select("x").distinct().count() == got.select("y").distinct().count() == 30
    with pytest.raises(RuntimeError):
        values.assign_one_to_one(values.scored_pairs(x, y), 0.5, max_rounds=0)


@pytest.mark.parametrize("local", [300_000, 0])
def test_edge_scores_do_not_depend_on_size(spark, some_people, monkeypatch, local):
    monkeypatch.setattr(planner, "LOCAL_PAIRS", local)
    monkeypatch.setattr(block, "BLOCK", 2000 if local else 9)
    x, y = some_people
    side = lambda d, s: d.select(F.lit("e").alias("edge_id"), F.lit(s).alias("side"), "v", "cnt", F.lit(False).alias("plain"))
    long = side(x, "l").union(side(y, "r"))
    scores, found = planner.edge_scores(long, spark.createDataFrame([("e",)], "edge_id string"), DiscoveryConfig(min_score=0.6))
    all_pairs = brute(x, y)
    one = greedy(all_pairs, 0.6)
    r = scores.first()
    best = {}
    for (a, _), sim in all_pairs.items():
        best[a] = max(best.get(a, 0), sim)
    assert r.value_score_lr == pytest.approx(sum(best.values()) / 80) and r.overlap_fuzzy == pytest.approx(len(one) / (160 - len(one)))
    assert {(m.x, m.y) for m in found.of("e", True, "one_to_one", 0.6).collect()} == one
    assert {(m.y, m.x) for m in found.of("e", False, "one_to_one", 0.6).collect()} == one


def test_path_over_tables_of_one_name(spark):
    """Two databases with a table of one name, and a key inside a struct."""
    a = spark.createDataFrame([(1, "Ada Abbott"), (2, "Bruno Barros")], "id int, who string")
    b = spark.createDataFrame([(("Abbott Ada", 7),), (("Bruno Baros", 8),)], "s struct<who: string, n: int>")
    refs = [TableRef("x", "people", a), TableRef("y", "people", b)]
    fk = spark.createDataFrame([], "db string, src_table string, src_columns array<string>, dst_table string, dst_columns array<string>")
    g = discover.discover(spark, refs, fk, DiscoveryConfig(name_threshold=0.2, overlap="fuzzy"))
    hop = graph.shortest_path(g, "x.people", "y.people").hops[0]
    assert hop.to_columns == ("s.who",) and hop.overlap == 1.0
    rows = discover.join_tables(g, "x.people", "y.people").collect()
    assert sorted((r["x__people__id"], r["y__people__s.n"]) for r in rows) == [(1, 7), (2, 8)]
    back = discover.join_tables(g, "y.people", "x.people", ["x__people__id"], cfg=DiscoveryConfig(assignment="mutual")).collect()
    assert sorted(r["x__people__id"] for r in back) == [1, 2]


def test_long_texts_and_numbers_meet_by_equality(spark):
    a = spark.createDataFrame([("x" * 300, 1.5), ("y", 2.5)], "note string, price double")
    b = spark.createDataFrame([("x" * 300, 1.5), ("z", 3.5)], "note string, price double")
    edges, _ = discover.fuzzy_edges(spark, [TableRef("p", "a", a), TableRef("q", "b", b)], DiscoveryConfig(value_threshold=0.4))
    assert {r.edge_id: (r.value_score_lr, r.overlap_fuzzy) for r in edges.collect()} == {"p.a(note)~q.b(note)": (0.5, 1 / 3), "p.a(price)~q.b(price)": (0.5, 1 / 3)}


def test_sample_estimates_the_score(spark, sf):
    c = spark.read.parquet(f"{sf}/customer.parquet")
    x, y = workloads.people(spark, sf)
    whole = values.value_scores(x, y).first().lr
    r = values.value_score_sampled(workloads.fx.customer_named(c), "person_name", "c_custkey", y, eps=0.2).first()
    assert r.n_left < 150 and abs(r.lr - whole) <= r.half_width == 0.2


def test_natural_join_refuses_cross_product(spark):
    a, b = spark.range(2).toDF("a"), spark.range(2).toDF("b")
    with pytest.raises(ValueError):
        baselines.natural_join(a, b)


def test_reflect_flattens(spark):
    df = spark.createDataFrame([(1, (2, "x"))], "a int, s struct<b: bigint, c: string>")
    assert [r.column for r in catalog.reflect(spark, [TableRef("d", "t", df)]).orderBy("ordinal").collect()] == ["a", "s.b", "s.c"]


def test_fk_hop_has_no_cartesian(spark, sf):
    a, b = spark.read.parquet(f"{sf}/orders.parquet"), spark.read.parquet(f"{sf}/customer.parquet")
    plan = execute.fk_hop(a, b, ["o_custkey"], ["c_custkey"])._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_surviving_rows_follow_the_orders_and_never_fan_out(spark, sf, tmp_path):
    """A line whose order has no customer does not survive, whatever its supplier's nation; one key meets many rows without a product."""
    for t in TABLES:
        if t not in ("lineitem", "orders"):
            (tmp_path / f"{t}.parquet").symlink_to(f"{sf}/{t}.parquet")
    orders = spark.read.parquet(f"{sf}/orders.parquet").withColumn("o_custkey", F.when(F.col("o_orderkey") % 4 == 0, F.lit(None).cast("bigint")).otherwise(F.col("o_custkey")))
    orders.write.parquet(f"{tmp_path}/orders.parquet")
    spark.read.parquet(f"{sf}/lineitem.parquet").withColumn("l_orderkey", F.when(F.col("l_linenumber") == 7, F.lit(None).cast("bigint")).otherwise(F.col("l_orderkey"))).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    con.execute(f"CREATE VIEW customer AS SELECT * FROM '{sf}/customer.parquet'")
    got = workloads.QUERIES["path_actual_retained"](spark, str(tmp_path))
    want = con.sql(workloads.oracles()["path_actual_retained"]).fetchall()[0]
    assert tuple(got.select("source_rows", "surviving", "fraction").first()) == tuple(want) and 0 < want[1] < want[0]
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("LeftSemi") == 2 and "s_nationkey" not in plan


@pytest.mark.parametrize("load", [100_000_000, 7])
def test_band_join_is_whole_and_dealt_to_all_tasks(spark, monkeypatch, load):
    monkeypatch.setattr(relational, "BAND_PAIRS", load)
    vals = [0.49999999999999994, 1.0, 1.5, 1.75, -0.2, None, float("nan"), float("inf"), 9.0] + [3.0] * 12
    a = spark.createDataFrame([(i, v) for i, v in enumerate(vals)], "i int, u double").coalesce(1)
    b = a.select(F.col("i").alias("j"), F.col("u").alias("v"))
    got = relational.band_join(a, b, "u", "v", 0.5)
    want = sorted((i, j) for i, u in enumerate(vals) for j, v in enumerate(vals) if u is not None and v is not None and abs(u - v) <= 0.5)
    assert sorted((r.i, r.j) for r in got.collect()) == want and (0, 1) in want
    assert got.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    if load == 7:  # one value's 144 pairs are dealt further
        assert got.where("u = 3").select(F.spark_partition_id()).distinct().count() > 1


def test_encoder_pairs_compare_six_decimals(spark, tmp_path):
    """A cosine of 0.2999997 counts as 0.3, one of 0.2999993 does not."""
    near = lambda c: [c, (1 - c * c) ** 0.5]
    rows = [(20, [1.0, 0.0]), (1, near(0.2999997)), (2, near(0.2999993)), (3, near(0.3000002))]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    want = sorted(con.sql(workloads.oracles()["encoder_pairs"]).fetchall())
    assert sorted(map(tuple, workloads.QUERIES["encoder_pairs"](spark, str(tmp_path)).collect())) == want == [(20, 1, 0.3), (20, 3, 0.3)]


def native_pairs(x, y, threshold):
    """Every row of x(a, u) beside every row of y(b, w), its cosine taken pair by pair."""
    both = x.crossJoin(y).withColumn("cosine", names.cosine(F.col("u"), F.col("w")))
    return both.where(F.round("cosine", 6) >= threshold).select("a", "b", "cosine")


def test_encoder_pairs_joins_blocks_not_rows(spark, sf):
    got = workloads.QUERIES["encoder_pairs"](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    want = native_pairs(e.where("vec_id % 20 = 0").selectExpr("vec_id a", "embedding u"), e.selectExpr("vec_id b", "embedding w"), 0.3).where("a <> b")
    assert got.columns == ["a", "b", "cosine"]
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.withColumn("cosine", F.round("cosine", 4)).collect())) != []


@pytest.mark.parametrize("threshold", [0.3, 0.0, -1.0])
@pytest.mark.parametrize("rows", [7, 8_192])
def test_encoder_pairs_of_odd_vectors(spark, monkeypatch, rows, threshold):
    """Blocks change no pair and no bit: null, empty, ragged, zero, huge, tiny vectors, nulls, NaN and infinity in them, ids twice or missing."""
    monkeypatch.setattr(baselines, "VECTOR_BLOCK", rows)
    nan, inf = float("nan"), float("inf")
    odd = [None, [], [], [0.0, 0.0], [1.0], [1.0, 2.0, 3.0], [None, 1.0], [nan, 1.0], [inf, 1.0], [1e200, 1e200], [1e-170, 1e-170], [1e-150, 1e-155], [0.3, -0.7], [3e150, 1.0], [-0.3, 0.7]]
    vectors = odd + [[math.cos(i), math.sin(i)] for i in range(20)]
    x = spark.createDataFrame([*enumerate(vectors), (3, [1.0, 0.5]), (None, [0.5, 1.0])], "a int, u array<double>")
    y = x.selectExpr("'n' || a AS b", "u AS w")
    bits = lambda df: sorted(map(repr, df.collect()))
    got = bits(baselines.encoder_pairs(x, y, "u", "w", threshold))
    assert got == bits(native_pairs(x, y, threshold)) and len(got) > 100
    assert bits(baselines.encoder_pairs(x.limit(0), y, "u", "w", threshold)) == [] == bits(baselines.encoder_pairs(x, y.limit(0), "u", "w", threshold))


def scans(df, table):
    """Whether Spark scans the table for the query."""
    return f"{table}.parquet" in " ".join(df.inputFiles())


def test_affine_cosine_reads_the_parts(spark, sf):
    got = workloads.QUERIES["affine_cosine"](spark, sf)
    assert scans(got, "part") and got.count() == spark.read.parquet(f"{sf}/part.parquet").select("p_name").distinct().count() ** 2


def test_external_embedder_reads_the_customers(spark, sf):
    got = workloads.QUERIES["external_embedder"](spark, sf)
    assert scans(got, "customer") and got.where("a = b and semantic_sim < 1").count() == 0 < got.where("semantic_sim < 1").count()


def test_false_friends_overlap_in_the_tables(spark, sf):
    got = workloads.QUERIES["false_friends"](spark, sf)
    assert scans(got, "customer") and scans(got, "embeddings")
    rows = got.collect()
    assert len(rows) == 3 and all(r.overlap > 0.1 and not r.passes for r in rows if r.a == "c_custkey")


def test_fk_edges_read_the_tables(spark, sf):
    got = workloads.QUERIES["fk_edges"](spark, sf)
    assert scans(got, "lineitem") and got.count() == 7 and got.where("n_common > 0").count() == 7


def observed(monkeypatch):
    """Tables that catalog.observe is asked to read."""
    seen, read = [], catalog.observe
    monkeypatch.setattr(catalog, "observe", lambda spark, tables: seen.extend(r.table for r in tables) or read(spark, tables))
    return seen


def test_observe_counts_values(spark):
    df = spark.createDataFrame([(1, (2, None), None, "u"), (None, (3, None), None, "v")], "a int, s struct<b: bigint, c: string>, d double, `e.f` string")
    rows = catalog.observe(spark, [TableRef("d", "t", df), TableRef("d", "empty", df.limit(0))])
    key = ["db", "table", "column", "type", "family", "ordinal"]
    declared = catalog.reflect(spark, [TableRef("d", "t", df), TableRef("d", "empty", df)])
    assert sorted(map(tuple, rows.select(*key).collect())) == sorted(map(tuple, declared.collect()))
    assert {r.column: r.n_values for r in rows.where("table = 't'").collect()} == {"a": 1, "s.b": 2, "s.c": 0, "d": 0, "e.f": 2}


def test_column_catalog_reads_the_tables(spark, sf, monkeypatch):
    seen = observed(monkeypatch)
    assert workloads.QUERIES["column_catalog"](spark, sf).count() == 63 and {"lineitem", "documents"} <= set(seen)


def test_column_pairs_read_the_tables(spark, sf, monkeypatch):
    seen = observed(monkeypatch)
    assert workloads.QUERIES["column_pairs"](spark, sf).count() == 4 and {"lineitem", "documents"} <= set(seen)


@pytest.mark.parametrize("name", ["discovered_names", "blocked_names"])
def test_names_are_those_of_tables_read(spark, sf, monkeypatch, name):
    seen = observed(monkeypatch)
    assert workloads.QUERIES[name](spark, sf).count() == 7 and {"lineitem", "documents", "resident_registry"} <= set(seen)


def test_projection_reaches_the_scan(spark, sf):
    df = relational.project(spark.read.parquet(f"{sf}/orders.parquet"), {"k": "o_orderkey"})
    assert "ReadSchema: struct<o_orderkey:bigint>" in df._jdf.queryExecution().toString()


def test_judge(spark):
    pairs = spark.createDataFrame([("Old Mill", "Mill Old"), ("Old Mill", "New Barn")], "x string, y string")
    assert [r.verdict for r in baselines.judge_pairs(pairs).orderBy(F.desc("y")).collect()] == [False, True]


def test_epsilon_and_modes():
    with pytest.raises(ValueError):
        DiscoveryConfig(overlap="other")
