"""The whole discovery (keys, names, values, overlap, graph) and joining along a path."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hopjoin.functions import names
from hopjoin.operators import catalog, execute, overlap, values
from hopjoin.operators.storage import materialize
from hopjoin.plans import graph, planner
from hopjoin.plans.config import DiscoveryConfig, TableRef


def fk_edges_with_overlap(tables: list[TableRef], manifest: DataFrame) -> DataFrame:
    edges = catalog.fk_edges(manifest)
    frames = {t.node: t.df for t in tables}
    rows = [r for r in edges.collect() if r.left_node in frames and r.right_node in frames]  # declared keys: metadata
    if not rows:
        return edges.limit(0).withColumn("overlap", F.lit(0.0))
    wanted = sorted({(n, tuple(c)) for r in rows for n, c in ((r.left_node, r.left_columns), (r.right_node, r.right_columns))})
    vals = materialize(overlap.value_table(frames, [(n, list(c)) for n, c in wanted]))
    spark = manifest.sparkSession
    pairs = spark.createDataFrame([(r.edge_id, overlap.col_id(r.left_node, r.left_columns), overlap.col_id(r.right_node, r.right_columns)) for r in rows], "edge_id string, left_id string, right_id string")
    found = overlap.jaccard_all(vals, pairs)
    return edges.join(found, "edge_id").withColumns({"overlap_exact": F.col("overlap")}).drop("n_common", "n_left", "n_right")


EDGE_SCHEMA = "edge_id string, kind string, left_node string, left_columns array<string>, right_node string, right_columns array<string>, name_sim double, semantic_sim double, token_overlap double, total_score double"
MEASURED = ("value_score_lr", "value_score_rl", "overlap_exact", "overlap_fuzzy", "overlap")


def fuzzy_edges(spark: SparkSession, tables: list[TableRef], cfg: DiscoveryConfig) -> tuple[DataFrame, planner.EdgeMatches | None]:
    """Fuzzy edges above both thresholds with what validation matched, all candidate pairs in one job keyed by pair.

    Every column is profiled once, in one scan of its table.  Strings meet in the LCS; columns of other families, and of
    texts with a value beyond cfg.long_text characters, are compared by equality of their values.
    """
    cand = names.candidates(catalog.reflect(spark, tables), cfg)
    rows = cand.collect()  # driver round trip: which columns to read is a planning decision; one row per candidate column pair
    frames = {t.node: t.df for t in tables}
    listed, sides = [], []
    for r in rows:
        left, right = (f"{r.db_a}.{r.table_a}", r.column_a), (f"{r.db_b}.{r.table_b}", r.column_b)
        if left[0] > right[0]:
            left, right = right, left
        ids = [overlap.col_id(n, [c]) for n, c in (left, right)]
        eid = "~".join(ids)
        listed.append((eid, "fuzzy", left[0], [left[1]], right[0], [right[1]], r.name_sim, r.semantic_sim, r.token_overlap, r.total_score))
        fuzzy = cfg.cast_to_string or {r.family_a, r.family_b} == {"string"}
        sides += [(eid, "l", ids[0], not fuzzy), (eid, "r", ids[1], not fuzzy)]
    edges = spark.createDataFrame(listed, EDGE_SCHEMA)
    if not listed:
        return edges.withColumns({c: F.lit(None).cast("double") for c in MEASURED}), None
    wanted = sorted({(n, (c[0],)) for e in listed for n, c in ((e[2], e[3]), (e[4], e[5]))})
    profile = materialize(overlap.value_rows(frames, [(n, list(c)) for n, c in wanted]).groupBy("col_id", "v").agg(F.count(F.lit(1)).alias("cnt")))
    longest = profile.groupBy("col_id").agg(F.max(F.length("v")).alias("longest"))
    sides = F.broadcast(spark.createDataFrame(sides, "edge_id string, side string, col_id string, plain boolean"))  # two rows per candidate column pair
    long = profile.join(F.broadcast(longest), "col_id").join(sides, "col_id")
    plain = F.max(F.col("longest")).over(Window.partitionBy("edge_id")) > cfg.long_text
    kinds = longest.join(sides, "col_id").select("edge_id", "side", (F.col("plain") | plain).alias("by_equality"))
    long = long.join(F.broadcast(kinds), ["edge_id", "side"]).select("edge_id", "side", "v", "cnt", F.col("by_equality").alias("plain"))
    scored, found = planner.edge_scores(long, edges.select("edge_id"), cfg)
    lr, rl = F.coalesce("value_score_lr", F.lit(0.0)), F.coalesce("value_score_rl", F.lit(0.0))
    out = edges.join(scored, "edge_id", "left").withColumns({"value_score_lr": lr, "value_score_rl": rl})
    out = out.where(values.directed(F.col("value_score_lr"), F.col("value_score_rl"), cfg.direction) > cfg.value_threshold)
    s = {"exact": F.col("overlap_exact"), "fuzzy": F.coalesce("overlap_fuzzy", "overlap_exact"), "value_score": values.directed(F.col("value_score_lr"), F.col("value_score_rl"), cfg.direction)}[cfg.overlap]
    return out.withColumn("overlap", s), found


def discover(spark: SparkSession, tables: list[TableRef], manifest: DataFrame, cfg: DiscoveryConfig = None) -> graph.JoinGraph:
    """The weighted join graph of the tables; its edge table is written once."""
    cfg = cfg or DiscoveryConfig()
    fk = fk_edges_with_overlap(tables, manifest)
    fuzzy, found = fuzzy_edges(spark, tables, cfg) if "fuzzy" in cfg.kinds else (None, None)
    g = graph.build(fk, fuzzy, tables, cfg.epsilon, cfg.log_base)
    g.found = found
    g.edges = materialize(g.edges)
    return g


def join_tables(g: graph.JoinGraph, source: str, target: str, select: list[str] | None = None, how: str = "inner", cfg: DiscoveryConfig = None, max_hops: int | None = None) -> DataFrame:
    """Best path between two tables, run: columns are table__column, one score per fuzzy hop and their product."""
    cfg = cfg or DiscoveryConfig()
    return execute.run_path(g, graph.shortest_path(g, source, target, cfg.kinds, max_hops), select, how, cfg)
