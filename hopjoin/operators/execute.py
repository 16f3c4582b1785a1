"""Running a join path as DataFrame joins: declared-key hops, fuzzy hops with scores, composite keys."""

from __future__ import annotations

import itertools
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hopjoin.functions.strings import token_sort
from hopjoin.operators import block, values
from hopjoin.operators.catalog import flat_columns
from hopjoin.operators.storage import materialize
from hopjoin.plans.config import DiscoveryConfig


def labels(nodes: list[str]) -> dict[str, str]:
    """Node -> prefix of its columns: the table's name, or db__table where several nodes have tables of one name."""
    tables = [n.rsplit(".", 1)[-1] for n in set(nodes)]
    return {n: n.replace(".", "__") if tables.count(n.rsplit(".", 1)[-1]) > 1 else n.rsplit(".", 1)[-1] for n in nodes}


def qualify(df: DataFrame, label: str) -> DataFrame:
    """Columns renamed to label__column, unambiguous on long chains; struct fields become label__struct.field."""
    plain = set(df.columns)
    return df.select(*[F.col(f"`{c}`" if c in plain else c).alias(f"{label}__{c}") for c, _ in flat_columns(df.schema)])


def fk_hop(rows: DataFrame, right: DataFrame, left_on: list[str], right_on: list[str], how: str = "inner") -> DataFrame:
    cond = reduce(lambda x, y: x & y, [rows[f"`{a}`"] == right[f"`{b}`"] for a, b in zip(left_on, right_on)])
    return rows.join(right, cond, how)


def match_table(left: DataFrame, right: DataFrame, left_on: str, right_on: str, cfg: DiscoveryConfig, pairs: DataFrame | None = None) -> DataFrame:
    """(x, y, sim): the assignment on distinct values; filters of the rows never move below it."""
    x, y = values.dictionary(left, f"`{left_on}`", cfg.normalize), values.dictionary(right, f"`{right_on}`", cfg.normalize)
    if cfg.assignment == "best" and pairs is None:
        return values.best_match(x, y).where(F.col("sim") > cfg.min_score).select("x", F.col("best_y").alias("y"), "sim")
    if pairs is None:
        pairs = materialize(values.scored_pairs(x, y, min_score=cfg.min_score, way="bounded"))
    return values.ASSIGNMENTS[cfg.assignment](pairs, cfg.min_score)


def fuzzy_hop(rows: DataFrame, right: DataFrame, left_on: str, right_on: str, cfg: DiscoveryConfig, how: str = "inner", score: str = "fuzzy_score", matches: DataFrame | None = None) -> DataFrame:
    """rows joined to right through the match table of distinct values; adds the score."""
    m = match_table(rows, right, left_on, right_on, cfg) if matches is None else matches
    m = m.select(F.col("x").alias("__x"), F.col("y").alias("__y"), F.col("sim").alias(score))
    step = rows.join(m, F.col(f"`{left_on}`").cast("string") == F.col("__x"), how)
    return step.join(right, F.col("__y") == F.col(f"`{right_on}`").cast("string"), how).drop("__x", "__y")


def run_path(g, path, select: list[str] | None = None, how: str = "inner", cfg: DiscoveryConfig = None) -> DataFrame:
    """All hops of a path, left-deep; fuzzy hop i adds fuzzy_score_i (the only one: fuzzy_score), and path_score is their product.

    The matches that validation left in the graph are joined again, not made again.
    """
    cfg = cfg or DiscoveryConfig()
    label = labels(path.nodes)
    rows = qualify(g.tables[path.source].df, label[path.source])
    n_fuzzy, scores = sum(h.kind == "fuzzy" for h in path.hops), []
    name = lambda node, c: f"{label[node]}__{c}"
    for h in path.hops:
        right = qualify(g.tables[h.to_node].df, label[h.to_node])
        a, b = [name(h.from_node, c) for c in h.from_columns], [name(h.to_node, c) for c in h.to_columns]
        if h.kind == "fk":
            rows = fk_hop(rows, right, a, b, how)
        else:
            scores.append("fuzzy_score" if n_fuzzy == 1 else f"fuzzy_score_{len(scores) + 1}")
            rows = fuzzy_hop(rows, right, a[0], b[0], cfg, how, scores[-1], g.matches_of(h, cfg))
    if scores:
        rows = rows.withColumn("path_score", reduce(lambda x, y: x * y, [F.col(s) for s in scores]))
    picked = [F.col(f"`{c}`") for c in select or ()]
    return rows.select(*picked, *scores, "path_score") if picked and scores else rows.select(*picked) if picked else rows


def surviving_rows(g, path) -> DataFrame:
    """Rows of the source with at least one output row on a path of declared keys: semi-joins from the far end, so no hop fans out."""
    if any(h.kind != "fk" for h in path.hops):
        raise ValueError("only declared keys; run the path for fuzzy hops")
    label = labels(path.nodes)
    rows = qualify(g.tables[path.nodes[-1]].df, label[path.nodes[-1]])
    for h in reversed(path.hops):
        left = qualify(g.tables[h.from_node].df, label[h.from_node])
        rows = fk_hop(left, rows, [f"{label[h.from_node]}__{c}" for c in h.from_columns], [f"{label[h.to_node]}__{c}" for c in h.to_columns], "left_semi")
    return rows


def composite_key(columns: list[str], sep: str = " ") -> Column:
    """Several columns as one value (nulls left out), e.g. the parts of an address against a full address."""
    return F.concat_ws(sep, *[F.col(c).cast("string") for c in columns])


def group_candidates(left: DataFrame, columns: list[str], right: DataFrame, right_on: str, max_size: int = 3) -> DataFrame:
    """(columns, value_score): column groups of left, in the given order, scored against one column of right - all groups in one job.

    The best of them are the branches that composite_match joins on.
    """
    groups = [list(g) for n in range(1, max_size + 1) for g in itertools.combinations(columns, n)]
    made = F.explode(F.array(*[F.struct(F.array(*[F.lit(c) for c in g]).alias("columns"), composite_key(g).alias("v")) for g in groups]))
    name = F.array_join("columns", ",").alias("grp")
    x = left.select(made.alias("g")).select("g.columns", "g.v").groupBy("columns", "v").agg(F.count(F.lit(1)).alias("cnt")).select(name, "columns", "v", "cnt", token_sort(F.col("v")).alias("s"))
    x = materialize(x)
    y = values.dictionary(right, right_on).select("v", "s", F.explode(F.array(*[F.lit(",".join(g)) for g in groups])).alias("grp"))
    best = block.best_pairs(x, y, ["grp"])
    return x.join(best.select("grp", F.col("x").alias("v"), "sim"), ["grp", "v"], "left").groupBy("columns").agg((F.sum(F.col("cnt") * F.coalesce("sim", F.lit(0.0))) / F.sum("cnt")).alias("value_score"))


def composite_match(left: DataFrame, groups: list[list[str]], right: DataFrame, right_on: str, keys: list[str], min_score: float = 0.5) -> DataFrame:
    """Many-to-many intermediate join: every column group (branch) is matched and the best branch kept per row of left.

    Gives keys, branch, combined, best, sim.
    """
    y = values.dictionary(right, right_on)
    out = None
    for i, g in enumerate(groups):
        rows = left.select(*keys, composite_key(g).alias("combined"), F.lit(i).alias("branch"))
        m = values.best_match(values.dictionary(rows, "combined"), y).where(F.col("sim") > min_score)
        one = rows.join(m, rows["combined"] == m["x"]).select(*keys, "branch", "combined", F.col("best_y").alias("best"), "sim")
        out = one if out is None else out.union(one)
    best = out.groupBy(*keys).agg(F.min(F.struct((-F.col("sim")).alias("m"), "branch", "combined", "best")).alias("b"))
    return best.select(*keys, "b.branch", "b.combined", "b.best", (-F.col("b.m")).alias("sim"))


def to_local(df: DataFrame, limit: int = 10_000):
    """At most `limit` rows as a pandas frame."""
    return df.limit(limit).toPandas()
