"""Accuracy and work measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopjoin.operators import block


def _safe(a, b):
    return F.coalesce(a / F.nullif(b, F.lit(0)), F.lit(0.0))


def match_quality(matches: DataFrame, truth: DataFrame) -> DataFrame:
    """matches(x, y) against truth(x, y): matched, right_count, precision, recall, f1."""
    right = matches.select("x", "y").distinct().join(truth.select("x", "y").distinct(), ["x", "y"])
    n = matches.select("x", "y").distinct().agg(F.count(F.lit(1)).alias("matched")).crossJoin(right.agg(F.count(F.lit(1)).alias("right_count"))).crossJoin(truth.select("x", "y").distinct().agg(F.count(F.lit(1)).alias("true_count")))
    n = n.withColumns({"precision": _safe(F.col("right_count"), F.col("matched")), "recall": _safe(F.col("right_count"), F.col("true_count"))})
    return n.withColumn("f1", _safe(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


def edge_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Edges (edge_id) against the known joinable ones: found, true_found, precision, recall."""
    f, t = found.select("edge_id").distinct(), truth.select("edge_id").distinct()
    n = f.agg(F.count(F.lit(1)).alias("found")).crossJoin(f.join(t, "edge_id").agg(F.count(F.lit(1)).alias("true_found"))).crossJoin(t.agg(F.count(F.lit(1)).alias("true_count")))
    return n.withColumns({"precision": _safe(F.col("true_found"), F.col("found")), "recall": _safe(F.col("true_found"), F.col("true_count"))})


def path_equal(path, nodes: list[str]) -> bool:
    return path.nodes == list(nodes)


def actual_retained(source: DataFrame, key: str, joined: DataFrame, joined_key: str) -> DataFrame:
    """Source rows with at least one output row, over all source rows: audits the estimate."""
    alive = source.join(joined.select(F.col(joined_key).alias("__k")).distinct(), source[key] == F.col("__k"), "left_semi")
    return source.agg(F.count(F.lit(1)).alias("source_rows")).crossJoin(alive.agg(F.count(F.lit(1)).alias("surviving"))).withColumn("fraction", _safe(F.col("surviving"), F.col("source_rows")))


def retained_rows(source: DataFrame, alive: DataFrame) -> DataFrame:
    """The same where alive holds the surviving source rows themselves."""
    return source.agg(F.count(F.lit(1)).alias("source_rows")).crossJoin(alive.agg(F.count(F.lit(1)).alias("surviving"))).withColumn("fraction", _safe(F.col("surviving"), F.col("source_rows")))


def work(x: DataFrame, y: DataFrame, t: float) -> DataFrame:
    """(bound, pairs_kept) of two dictionaries: pairs left after each bound at row threshold t, counted inside one plan."""
    pairs = x.select(F.col("s").alias("a")).crossJoin(y.select(F.col("s").alias("b")))
    a, b = F.col("a"), F.col("b")
    n = pairs.agg(F.count(F.lit(1)).alias("all"), F.count_if(block.length_bound(a, b, t)).alias("length"), F.count_if(block.bag_bound(a, b) >= t - 1e-9).alias("bag"), F.count_if(block.levenshtein_bound(a, b, t)).alias("levenshtein"))
    return n.select(F.explode(F.map_from_arrays(F.array(*[F.lit(c) for c in n.columns]), F.array(*n.columns))).alias("bound", "pairs_kept"))


def comparisons(x: DataFrame, y: DataFrame, floor: float | None = None) -> DataFrame:
    """One row: pairs there are, and pairs whose similarity the block comparison computed - with a floor for all pairs above it, else for the best of each x."""
    n = x.agg(F.count(F.lit(1)).alias("a")).crossJoin(y.agg(F.count(F.lit(1)).alias("b")))
    return n.select((F.col("a") * F.col("b")).alias("pairs")).crossJoin(block.compared(x, y, floor))


def sketch_error(exact: DataFrame, estimate: DataFrame) -> DataFrame:
    return exact.select("edge_id", F.col("overlap").alias("exact")).join(estimate.select("edge_id", F.col("overlap").alias("estimate")), "edge_id").withColumn("error", F.abs(F.col("exact") - F.col("estimate")))


def recall_of(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of truth pairs (x, y) that pairs has."""
    hit = truth.join(pairs.select("x", "y").distinct(), ["x", "y"], "left_semi")
    return truth.agg(F.count(F.lit(1)).alias("true_pairs")).crossJoin(hit.agg(F.count(F.lit(1)).alias("found"))).withColumn("recall", _safe(F.col("found"), F.col("true_pairs")))
