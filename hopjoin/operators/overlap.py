"""Column overlap: exact, all edges at once, sketched, and fuzzy."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def key_of(columns: list[str]) -> Column:
    """One comparable value of a column list; null when any part is null."""
    parts = [F.col(c).cast("string") for c in columns]
    if len(parts) == 1:
        return parts[0]
    return F.when(reduce(lambda x, y: x & y, [p.isNotNull() for p in parts]), F.to_json(F.struct(*[p.alias(f"c{i}") for i, p in enumerate(parts)])))


def jaccard(x: DataFrame, y: DataFrame, x_columns: list[str], y_columns: list[str]) -> DataFrame:
    """(n_common, n_left, n_right, overlap) of two column sets: one shuffle of values, no join; two empty sets give 0."""
    both = x.select(key_of(x_columns).alias("v"), F.lit(True).alias("l"), F.lit(False).alias("r")).unionAll(y.select(key_of(y_columns).alias("v"), F.lit(False).alias("l"), F.lit(True).alias("r")))
    sides = both.where("v is not null").groupBy("v").agg(F.bool_or("l").alias("l"), F.bool_or("r").alias("r"))
    n = sides.agg(F.count_if(F.col("l") & F.col("r")).alias("n_common"), F.count_if("l").alias("n_left"), F.count_if("r").alias("n_right"))
    return n.select("*", ratio().alias("overlap"))


def ratio() -> Column:
    union = F.col("n_left") + F.col("n_right") - F.col("n_common")
    return F.coalesce(F.col("n_common") / F.nullif(union, F.lit(0)), F.lit(0.0))


def value_rows(frames: dict[str, DataFrame], wanted: list[tuple[str, list[str]]]) -> DataFrame:
    """(col_id, v), nulls left out, of the wanted (node, columns) pairs: each table is scanned once, reading only those columns."""
    by_node: dict[str, list[list[str]]] = {}
    for node, cols in wanted:
        by_node.setdefault(node, []).append(cols)
    parts = []
    for node, lists in by_node.items():
        cells = F.array(*[F.struct(F.lit(col_id(node, c)).alias("col_id"), key_of(c).alias("v")) for c in lists])
        parts.append(frames[node].select(F.explode(cells).alias("x")).select("x.col_id", "x.v").where("v is not null"))
    return reduce(DataFrame.unionAll, parts)


def value_table(frames: dict[str, DataFrame], wanted: list[tuple[str, list[str]]]) -> DataFrame:
    """Distinct (col_id, v) of the wanted (node, columns) pairs."""
    return value_rows(frames, wanted).distinct()


def col_id(node: str, columns: list[str]) -> str:
    return f"{node}({','.join(columns)})"


def jaccard_all(values: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(edge_id, left_id, right_id) -> n_common, n_left, n_right, overlap, all edges in one job.

    A value's set of columns is at most the number of profiled columns, and few sets differ; each column of a set looks up
    the pairs it leads.
    """
    sizes = values.groupBy("col_id").agg(F.count(F.lit(1)).alias("n"))
    sets = values.groupBy("v").agg(F.sort_array(F.collect_set("col_id")).alias("cols")).groupBy("cols").agg(F.count(F.lit(1)).alias("n"))  # few distinct sets
    led = sets.select(F.explode("cols").alias("left_id"), "cols", "n").join(pairs, "left_id").where(F.array_contains("cols", F.col("right_id")))
    common = led.groupBy("edge_id").agg(F.sum("n").alias("n_common"))
    side = lambda c, out: sizes.select(F.col("col_id").alias(c), F.col("n").alias(out))
    out = pairs.join(side("left_id", "n_left"), "left_id", "left").join(side("right_id", "n_right"), "right_id", "left").join(common, "edge_id", "left")
    zero = F.lit(0).cast("long")
    out = out.select("edge_id", *[F.coalesce(c, zero).alias(c) for c in ("n_common", "n_left", "n_right")])
    return out.select("*", ratio().alias("overlap"))


def jaccard_theta(values: DataFrame, pairs: DataFrame, lg_k: int = 12) -> DataFrame:
    """Estimated overlap from one theta sketch per column: KB per column whatever its size."""
    sketches = values.groupBy("col_id").agg(F.expr(f"theta_sketch_agg(v, {lg_k})").alias("s"))
    side = lambda c, out: sketches.select(F.col("col_id").alias(c), F.col("s").alias(out))
    out = pairs.join(side("left_id", "sl"), "left_id").join(side("right_id", "sr"), "right_id")
    common, union = F.expr("theta_sketch_estimate(theta_intersection(sl, sr))"), F.expr(f"theta_sketch_estimate(theta_union(sl, sr, {lg_k}))")
    return out.select("edge_id", F.coalesce(common / F.nullif(union, F.lit(0)), F.lit(0.0)).alias("overlap"))


def jaccard_fuzzy(matches: DataFrame, n_left: int | Column, n_right: int | Column) -> DataFrame:
    """Overlap whose intersection is the number of one-to-one matches(x, y)."""
    m = F.count(F.lit(1))
    left, right = (F.lit(c) if isinstance(c, int) else c for c in (n_left, n_right))
    return matches.agg(m.alias("matched"), F.coalesce(m / F.nullif(left + right - m, F.lit(0)), F.lit(0.0)).alias("overlap"))
