"""The batched scoring of all candidate edges: exact at every size, whatever the number of values."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopjoin.functions.strings import token_sort
from hopjoin.operators import block
from hopjoin.operators.storage import materialize
from hopjoin.plans.config import DiscoveryConfig

#: left-over pairs of one edge that a single task may finish
LOCAL_PAIRS = 300_000


@dataclass
class EdgeMatches:
    """Tables that validation leaves behind: best(edge_id, side, x, y, sim) of every value, one(edge_id, x, y, sim), one-to-one."""

    best: DataFrame
    one: DataFrame

    def of(self, edge_id: str, forward: bool, assignment: str, min_score: float) -> DataFrame:
        """(x, y, sim) of one edge for a join from its left side (forward) or its right side."""
        side, back = ("l", "r") if forward else ("r", "l")
        mine = lambda s: self.best.where((F.col("edge_id") == edge_id) & (F.col("side") == s) & (F.col("sim") > min_score)).select("x", "y", "sim")
        if assignment == "best":
            return mine(side)
        if assignment == "mutual":
            return mine(side).join(mine(back).select(F.col("y").alias("x"), F.col("x").alias("y")), ["x", "y"]).select("x", "y", "sim")
        one = self.one.where(F.col("edge_id") == edge_id)
        return one.select("x", "y", "sim") if forward else one.select(F.col("y").alias("x"), F.col("x").alias("y"), "sim")


def _finish(min_score: float):
    """The greedy assignment of what is left of one edge, in one task; plain values match their equals only."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        sides = [[t.column(c).to_pylist() for c in ("v", "s")] for t in (left, right)]
        some = left if left.num_rows else right
        if some.column("plain")[0].as_py():
            pairs = [(v, v, 1.0, None) for v in set(sides[0][0]) & set(sides[1][0])]
        else:
            pairs = list(block._compare(*sides[0], *sides[1], min_score, "above")) if left.num_rows and right.num_rows else []
        tie = lambda r: "" if r[2] >= 1 else block.tie_key(r[0], r[1])
        xs, ys, out = set(), set(), []
        for x, y, sim, _ in sorted(pairs, key=lambda r: (-r[2], tie(r), r[0], r[1])):
            if x not in xs and y not in ys:
                xs.add(x), ys.add(y), out.append((x, y, sim))
        edge = some.column("edge_id")[0].as_py()
        return pa.table([pa.array([edge] * len(out), pa.string()), *[pa.array([r[i] for r in out], t) for i, t in enumerate((pa.string(), pa.string(), pa.float64()))]], names=["edge_id", "x", "y", "sim"])

    return run


def _finished(left: DataFrame, right: DataFrame, min_score: float) -> DataFrame:
    pick = lambda d: d.select("edge_id", "v", "s", "plain").groupBy("edge_id")
    return pick(left).cogroup(pick(right)).applyInArrow(_finish(min_score), "edge_id string, x string, y string, sim double")


def one_to_one(left: DataFrame, right: DataFrame, min_score: float, most: int | None = None, max_rounds: int = 1000) -> DataFrame:
    """left(edge_id, v, s, plain), right -> the greedy one-to-one matches (edge_id, x, y, sim) above min_score, per edge.

    most: a bound of the pairs of any edge, if one is known; edges that are all small are finished at once, one task each.

    Values of one sorted form pair up by rank; plain values (compared by equality) end there.  Rounds of mutually best
    pairs follow until the rest of every edge is small enough for one task, which finishes it: the same greedy throughout.
    """
    if most is not None and most <= LOCAL_PAIRS:
        return materialize(_finished(left, right, min_score))
    ranked = lambda d, c: d.select("edge_id", "s", F.col("v").alias(c), F.row_number().over(Window.partitionBy("edge_id", "s").orderBy("v")).alias("i"))
    taken = materialize(ranked(left, "x").join(ranked(right, "y"), ["edge_id", "s", "i"]).select("edge_id", "x", "y", F.lit(1.0).alias("sim")))
    rest = lambda d, now, c: materialize(d.where("not plain").join(now.select("edge_id", F.col(c).alias("v")), ["edge_id", "v"], "left_anti").select("edge_id", "v", "s", "plain"))
    left, right = rest(left, taken, "x"), rest(right, taken, "y")
    for _ in range(max_rounds):
        size = lambda d, c: d.groupBy("edge_id").agg(F.count(F.lit(1)).alias(c))
        most = size(left, "n").join(size(right, "m"), "edge_id").agg(F.max(F.col("n") * F.col("m"))).first()[0] or 0
        if most <= LOCAL_PAIRS:
            return materialize(taken.unionByName(_finished(left, right, min_score)))
        there = block.best_pairs(left, right, ["edge_id"], min_score).select("edge_id", "x", F.col("tied").alias("y"), "sim")
        back = block.best_pairs(right, left, ["edge_id"], min_score).select("edge_id", F.col("x").alias("y"), F.col("tied").alias("x"))
        now = materialize(there.join(back, ["edge_id", "x", "y"]).select("edge_id", "x", "y", "sim"))
        if not now.limit(1).count():
            return taken
        taken = taken.unionByName(now)
        left, right = rest(left, now, "x"), rest(right, now, "y")
    raise RuntimeError("the one-to-one assignment did not settle")


def edge_scores(long: DataFrame, edges: DataFrame, cfg: DiscoveryConfig) -> tuple[DataFrame, EdgeMatches]:
    """long(edge_id, side, v, cnt, plain) -> value_score_lr, value_score_rl, overlap_exact, overlap_fuzzy per edge, all edges in one job.

    Values of one sorted form score 1 by an equi-join and never meet a dictionary; the others are compared with all values of
    the other side, block by block (plain ones - not strings, or too long for a character comparison - score 0 then).
    """
    s = F.when(F.col("plain"), F.col("v")).otherwise(token_sort(F.col("v"), cfg.normalize))
    d = materialize(long.withColumn("s", s))
    flipped = F.when(F.col("side") == "l", "r").otherwise("l").alias("side")
    forms = d.groupBy("edge_id", flipped, "s").agg(F.min("v").alias("y"))
    looked = d.join(forms, ["edge_id", "side", "s"], "left")
    hits = looked.where("y is not null").select("edge_id", "side", F.col("v").alias("x"), "cnt", "y", F.lit(1.0).alias("sim"))
    rest = looked.where("y is null").select("edge_id", "side", "v", "s", "cnt", "plain")
    of = lambda x: F.count_if(F.col("side") == x)
    counts = d.groupBy("edge_id").agg(of("l").alias("l"), of("r").alias("r"), F.bool_or("plain").alias("plain")).collect()  # one row per column pair
    bounds = [(r.edge_id, s_, n, m) for r in counts if not r.plain for s_, n, m in (("l", r.l, r.r), ("r", r.r, r.l))]
    met = block.best_pairs(rest.where("not plain"), d.where("not plain").select("edge_id", flipped, "v", "s"), ["edge_id", "side"], counts=bounds)
    others = rest.withColumnRenamed("v", "x").join(met.select("edge_id", "side", "x", "y", "sim"), ["edge_id", "side", "x"], "left").select("edge_id", "side", "x", "cnt", "y", F.coalesce("sim", F.lit(0.0)).alias("sim"))
    best = materialize(hits.unionByName(others))
    mean = lambda x: F.sum(F.when(F.col("side") == x, F.col("cnt") * F.col("sim"))) / F.nullif(F.sum(F.when(F.col("side") == x, F.col("cnt"))), F.lit(0))
    score = best.groupBy("edge_id").agg(mean("l").alias("value_score_lr"), mean("r").alias("value_score_rl"))
    sides = d.groupBy("edge_id", "v").agg(F.bool_or(F.col("side") == "l").alias("l"), F.bool_or(F.col("side") == "r").alias("r"))
    sizes = sides.groupBy("edge_id").agg(F.count_if("l").alias("n_l"), F.count_if("r").alias("n_r"), F.count_if(F.col("l") & F.col("r")).alias("n_both"), F.count(F.lit(1)).alias("n_any"))
    pick = lambda x: d.where(F.col("side") == x).select("edge_id", "v", "s", "plain")
    one = one_to_one(pick("l"), pick("r"), cfg.min_score, max((r.l * r.r for r in counts), default=0))
    matched = one.groupBy("edge_id").agg(F.count(F.lit(1)).alias("m"))
    m = F.coalesce("m", F.lit(0))
    overlaps = sizes.join(matched, "edge_id", "left").select("edge_id", (F.col("n_both") / F.nullif(F.col("n_any"), F.lit(0))).alias("overlap_exact"), F.coalesce(m / F.nullif(F.col("n_l") + F.col("n_r") - m, F.lit(0)), F.lit(0.0)).alias("overlap_fuzzy"))
    return edges.join(score, "edge_id", "left").join(overlaps, "edge_id", "left"), EdgeMatches(best.drop("cnt"), one)
