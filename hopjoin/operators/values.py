"""Row-level validation: best match per value, value score, exact-hit shortcut, sampling, early rejection, assignments."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hopjoin.functions.strings import lcs_sql, lcs_udf, ratio_from_lcs, token_sort
from hopjoin.operators import block
from hopjoin.operators.storage import materialize


def dictionary(df: DataFrame, column: str, normalize: str | None = None) -> DataFrame:
    """(v, cnt, s): distinct non-null values, their counts, and their token-sorted form (made once per value)."""
    v = F.col(column).cast("string")
    return df.where(v.isNotNull()).groupBy(v.alias("v")).agg(F.count(F.lit(1)).alias("cnt")).withColumn("s", token_sort(F.col("v"), normalize))


def scored_pairs(x: DataFrame, y: DataFrame, min_score: float | None = None, native: bool = False, way: str = "brute") -> DataFrame:
    """(x, cx, y, cy, sim) of two dictionaries; with min_score only pairs above it.

    way="brute" pairs all, "bounded" (needs min_score) compares blocks behind the character-bag bound - both exact -, "lsh"
    joins on MinHash bands (lossy: its recall is measured, nothing is decided on it).
    """
    if way == "bounded":
        if min_score is None:
            raise ValueError("bounded pairs need min_score")
        return with_counts(block.pairs_above(x, y, min_score), x, y).select("x", "cx", "y", "cy", "sim")
    a = x.select(F.col("v").alias("x"), F.col("cnt").alias("cx"), F.col("s").alias("sx"))
    b = y.select(F.col("v").alias("y"), F.col("cnt").alias("cy"), F.col("s").alias("sy"))
    pairs = block.lsh_pairs(a, b) if way == "lsh" else a.crossJoin(b)
    if min_score is not None:
        pairs = pairs.where(block.bounds(F.col("sx"), F.col("sy"), min_score))
    lcs = lcs_sql(F.col("sx"), F.col("sy")) if native else lcs_udf(F.col("sx"), F.col("sy"))
    out = pairs.withColumn("lcs", lcs).withColumn("sim", ratio_from_lcs(F.col("lcs"), F.col("sx"), F.col("sy"))).select("x", "cx", "y", "cy", "sim")
    return out if min_score is None else out.where(F.col("sim") > min_score)


def with_counts(pairs: DataFrame, x: DataFrame, y: DataFrame) -> DataFrame:
    """pairs(x, y, ...) with the dictionaries' counts cx and cy."""
    return pairs.join(x.select(F.col("v").alias("x"), F.col("cnt").alias("cx")), "x").join(y.select(F.col("v").alias("y"), F.col("cnt").alias("cy")), "y")


def _first(score: str, name: str) -> Column:
    """Largest score, ties to the least name."""
    return F.min(F.struct((-F.col(score)).alias("m"), F.col(name).alias("n")))


def best_match(x: DataFrame, y: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """(x, best_y, sim) per distinct x, exact.  Values that hit exactly leave early: only the rest meets the whole dictionary."""
    if pairs is not None:
        return pairs.groupBy("x").agg(_first("sim", "y").alias("b")).select("x", F.col("b.n").alias("best_y"), (-F.col("b.m")).alias("sim"))
    hits = x.select(F.col("v").alias("x"), "s").join(y.groupBy("s").agg(F.min("v").alias("best_y")), "s").select("x", "best_y", F.lit(1.0).alias("sim"))
    rest = x.join(y.select("s"), "s", "left_anti")
    return hits.union(block.best_pairs(rest, y).select("x", F.col("y").alias("best_y"), "sim"))


def value_scores(x: DataFrame, y: DataFrame, weighted: bool = True, pairs: DataFrame | None = None) -> DataFrame:
    """lr, rl, n_left, n_right: mean over rows of x of the best similarity to y, and the other way.

    No row on one side gives score 0.  `pairs` is a pair table that is there anyway.
    """
    turned = pairs.select(F.col("y").alias("x"), F.col("x").alias("y"), "sim") if pairs is not None else None

    def mean(a, b, given):
        best = a.join(best_match(a, b, given).select(F.col("x").alias("v"), "sim"), "v", "left").withColumn("m", F.coalesce("sim", F.lit(0.0)))
        return best.agg(F.coalesce((F.sum(F.col("cnt") * F.col("m")) / F.sum("cnt")) if weighted else F.avg("m"), F.lit(0.0)), F.coalesce(F.sum("cnt") if weighted else F.count("v"), F.lit(0)).cast("long"))

    return mean(x, y, pairs).toDF("lr", "n_left").crossJoin(mean(y, x, turned).toDF("rl", "n_right")).select("lr", "rl", "n_left", "n_right")


def directed(lr: Column, rl: Column, direction: str) -> Column:
    """One number from the two directed scores."""
    return {"left": lr, "right": rl, "min": F.least(lr, rl), "max": F.greatest(lr, rl), "mean": (lr + rl) / 2}[direction]


def value_score_sampled(df: DataFrame, column: str, key: str, y: DataFrame, eps: float = 0.01, delta: float = 0.05) -> DataFrame:
    """lr and its half-width on a hashed sample of x rows of Hoeffding size ln(2/delta)/(2 eps^2); y is never sampled (it would bias the maxima down)."""
    need = math.ceil(math.log(2 / delta) / (2 * eps * eps))
    total = df.where(F.col(column).isNotNull()).count()
    share = min(1.0, need / max(1, total))
    draw = F.conv(F.substring(F.md5(F.col(key).cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    picked = df.where(draw < int(share * (1 << 32))) if share < 1 else df
    x = dictionary(picked, column)
    best = x.join(best_match(x, y).select(F.col("x").alias("v"), "sim"), "v", "left").withColumn("m", F.coalesce("sim", F.lit(0.0)))
    return best.agg(F.coalesce(F.sum(F.col("cnt") * F.col("m")) / F.sum("cnt"), F.lit(0.0)).alias("lr"), F.coalesce(F.sum("cnt"), F.lit(0)).alias("n_left"), F.lit(0.0 if share == 1 else eps).alias("half_width"))


def can_pass(x: DataFrame, y: DataFrame, threshold: float) -> DataFrame:
    """(bound, possible): an upper bound of the value score from character bags only; False means the pair can be dropped unseen."""
    best = x.join(block.best_bounds(x, y).withColumnRenamed("x", "v"), "v", "left").withColumn("m", F.coalesce("bound", F.lit(0.0)))
    bound = F.coalesce(F.sum(F.col("cnt") * F.col("m")) / F.sum("cnt"), F.lit(0.0))
    return best.agg(bound.alias("bound"), (bound > threshold).alias("possible"))


# --- assignments: which y a row is joined with ---------------------------------------------------------------------------


def assign_best(pairs: DataFrame, min_score: float) -> DataFrame:
    """argmax per x, ties to the least y."""
    return pairs.where(F.col("sim") > min_score).groupBy("x").agg(_first("sim", "y").alias("b")).select("x", F.col("b.n").alias("y"), (-F.col("b.m")).alias("sim"))


def assign_mutual(pairs: DataFrame, min_score: float) -> DataFrame:
    """Pairs that are best in both directions."""
    ok = pairs.where(F.col("sim") > min_score)
    by_x, by_y = Window.partitionBy("x").orderBy(F.desc("sim"), "y"), Window.partitionBy("y").orderBy(F.desc("sim"), "x")
    return ok.withColumn("rx", F.row_number().over(by_x)).withColumn("ry", F.row_number().over(by_y)).where("rx = 1 and ry = 1").select("x", "y", "sim")


def tie_order() -> Column:
    """Order among equal scores: pairs of one sorted form by name, others by a digest of the pair, so that rounds stay few."""
    return F.when(F.col("sim") >= 1.0, F.lit("")).otherwise(F.md5(F.concat_ws("|", "x", "y").cast("binary")))


def assign_one_to_one(pairs: DataFrame, min_score: float, keys: list[str] | None = None, max_rounds: int = 1000) -> DataFrame:
    """Greedy one-to-one by (score desc, tie order, x, y), as rounds of locally greatest pairs under that total order.

    A pair that is first for both its x and its y among what is left is taken by the greedy too.  Values of one sorted form
    (score 1: every x of the form pairs with every y of it) are settled at once, by rank.  Rounds are written out, so lineage
    and lost executors are no concern; rounds that do not settle are an error, never a partial result.
    """
    keys = keys or []
    left = materialize(pairs.where(F.col("sim") > min_score).select(*keys, "x", "y", "sim"))
    ones = left.where("sim >= 1")
    form = ones.groupBy(*keys, "x").agg(F.min("y").alias("form"))
    ones = ones.join(form, [*keys, "x"])
    rank = lambda c: ones.select(*keys, "form", c).distinct().withColumn("i", F.row_number().over(Window.partitionBy(*keys, "form").orderBy(c)))
    taken = materialize(rank("x").join(rank("y"), [*keys, "form", "i"]).select(*keys, "x", "y", F.lit(1.0).alias("sim")))
    drop = lambda rest, now: rest.join(now.select(*keys, "x"), [*keys, "x"], "left_anti").join(now.select(*keys, "y"), [*keys, "y"], "left_anti").select(*keys, "x", "y", "sim")
    left = materialize(drop(left, taken))
    order = [F.desc("sim"), "tie", "x", "y"]
    by_x, by_y = Window.partitionBy(*keys, "x").orderBy(*order), Window.partitionBy(*keys, "y").orderBy(*order)
    for _ in range(max_rounds):
        if not left.limit(1).count():
            return taken
        ranked = left.withColumn("tie", tie_order()).withColumn("rx", F.row_number().over(by_x)).withColumn("ry", F.row_number().over(by_y))
        now = materialize(ranked.where("rx = 1 and ry = 1").select(*keys, "x", "y", "sim"))
        taken = taken.union(now)
        left = materialize(drop(left, now))
    raise RuntimeError("the one-to-one assignment did not settle")


ASSIGNMENTS = {"best": assign_best, "mutual": assign_mutual, "one_to_one": assign_one_to_one}
