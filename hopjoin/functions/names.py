"""Column-name similarity: gestalt matching, token overlap, embedding cosine, their weighted total and its gate."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hopjoin.plans.config import DiscoveryConfig


def _longest_block(a: str, b: str, alo: int, ahi: int, blo: int, bhi: int, where: dict[str, list[int]]) -> tuple[int, int, int]:
    """First longest common block of a[alo:ahi] and b[blo:bhi]: start in a, start in b, length."""
    best = (alo, blo, 0)
    runs: dict[int, int] = {}
    for i in range(alo, ahi):
        fresh = {}
        for j in where.get(a[i], ()):
            if blo <= j < bhi:
                k = fresh[j] = runs.get(j - 1, 0) + 1
                if k > best[2]:
                    best = (i - k + 1, j - k + 1, k)
        runs = fresh
    return best


def gestalt(a: str, b: str) -> float:
    """2 * matched / total length, matched being the longest common block plus what matches on either side of it."""
    if not a and not b:
        return 1.0
    where: dict[str, list[int]] = {}
    for j, ch in enumerate(b):
        where.setdefault(ch, []).append(j)
    todo, matched = [(0, len(a), 0, len(b))], 0
    while todo:
        alo, ahi, blo, bhi = todo.pop()
        i, j, k = _longest_block(a, b, alo, ahi, blo, bhi, where)
        if k:
            matched += k
            todo += [(alo, i, blo, j), (i + k, ahi, j + k, bhi)]
    return 2 * matched / (len(a) + len(b))


def _gestalt_series(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else gestalt(x, y) for x, y in zip(a, b)], dtype="float64")


def gestalt_ratio(a: Column, b: Column) -> Column:
    """Depends on the order of its arguments: call it in canonical order."""
    return F.pandas_udf(_gestalt_series, T.DoubleType())(a, b)


def name_tokens(c: Column) -> Column:
    """Lower-case tokens at underscores, blanks, other marks and camel-case boundaries."""
    parted = F.regexp_replace(c, r"([a-z0-9])([A-Z])", "$1_$2")
    return F.array_distinct(F.filter(F.split(F.lower(parted), r"[^a-z0-9]+"), lambda t: t != ""))


def token_overlap(a: Column, b: Column, kind: str = "jaccard") -> Column:
    x, y = name_tokens(a), name_tokens(b)
    common = F.size(F.array_intersect(x, y)).cast("double")
    below = {"jaccard": F.size(F.array_union(x, y)), "containment": F.least(F.size(x), F.size(y)), "dice": (F.size(x) + F.size(y)) / 2}
    if kind not in below:
        raise ValueError(f"unknown token overlap {kind!r}")
    return F.coalesce(common / F.nullif(below[kind].cast("double"), F.lit(0.0)), F.lit(0.0))


def canonical(c: Column, lexicon: dict[str, str] | None) -> Column:
    """The name with each token replaced by its concept."""
    tokens = F.filter(F.split(F.lower(F.regexp_replace(c, r"([a-z0-9])([A-Z])", "$1_$2")), r"[^a-z0-9]+"), lambda t: t != "")
    if lexicon:
        table = F.create_map(*[F.lit(x) for kv in sorted(lexicon.items()) for x in kv])
        tokens = F.transform(tokens, lambda t: F.coalesce(F.try_element_at(table, t), t))
    return F.array_join(tokens, "_")


class TrigramEmbedder:
    """Built-in embedder: character trigram counts of the name; the cosine of two names is a join on trigrams."""

    lexicon: dict[str, str] | None = None

    def similarities(self, pairs: DataFrame) -> DataFrame:
        """pairs(a, b) -> distinct (a, b, cos)."""
        both = pairs.select("a", "b").distinct()
        names = both.select(F.col("a").alias("name")).union(both.select(F.col("b").alias("name"))).distinct()
        name = canonical(F.col("name"), self.lexicon)
        grams = F.transform(F.sequence(F.lit(1), F.greatest(F.length(name) - 2, F.lit(1))), lambda i: F.substring(name, i, F.lit(3)))
        counts = names.select("name", F.explode(grams).alias("gram")).groupBy("name", "gram").agg(F.count(F.lit(1)).cast("double").alias("n"))
        norms = counts.groupBy("name").agg(F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("norm"))
        side = lambda x: counts.join(norms, "name").select(F.col("name").alias(x), "gram", F.col("n").alias(f"n_{x}"), F.col("norm").alias(f"norm_{x}"))
        dots = both.join(side("a"), "a").join(side("b"), ["b", "gram"]).groupBy("a", "b").agg((F.sum(F.col("n_a") * F.col("n_b")) / (F.first("norm_a") * F.first("norm_b"))).alias("cos"))
        return both.join(dots, ["a", "b"], "left").select("a", "b", F.coalesce("cos", F.lit(0.0)).alias("cos"))


class LexiconEmbedder(TrigramEmbedder):
    """Trigrams after a user-supplied token -> concept map."""

    def __init__(self, lexicon: dict[str, str]):
        self.lexicon = dict(lexicon)


class UdfEmbedder:
    """External embedder: fn takes a list of names and gives a list of vectors; each name is embedded once."""

    def __init__(self, fn: Callable[[list[str]], list[list[float]]]):
        self.fn = fn

    def similarities(self, pairs: DataFrame) -> DataFrame:
        fn = self.fn

        def embed(frames):
            for pdf in frames:
                yield pd.DataFrame({"name": pdf["name"], "v": [list(map(float, v)) for v in fn(list(pdf["name"]))]})

        both = pairs.select("a", "b").distinct()
        names = both.select(F.col("a").alias("name")).union(both.select(F.col("b").alias("name"))).distinct()
        vectors = names.mapInPandas(embed, "name string, v array<double>")
        x, y = vectors.select(F.col("name").alias("a"), F.col("v").alias("u")), vectors.select(F.col("name").alias("b"), F.col("v").alias("w"))
        return both.join(x, "a").join(y, "b").select("a", "b", cosine(F.col("u"), F.col("w")).alias("cos"))


def cosine(u: Column, w: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, t: s + t)
    return F.coalesce(dot(u, w) / F.nullif(F.sqrt(dot(u, u)) * F.sqrt(dot(w, w)), F.lit(0.0)), F.lit(0.0))


def semantic_sim(pairs: DataFrame, embedder, mode: str = "clip") -> DataFrame:
    """(a, b, semantic_sim) in [0, 1]."""
    cos = F.col("cos")
    return embedder.similarities(pairs).select("a", "b", ((1 + cos) / 2 if mode == "affine" else F.greatest(F.lit(0.0), F.least(cos, F.lit(1.0)))).alias("semantic_sim"))


def column_pairs(columns: DataFrame, scope: str = "cross", same_family: bool = True) -> DataFrame:
    """Pairs of columns (metadata: a nested-loop join of K rows with itself), first side before the second by (db, table, column)."""
    side = lambda x: columns.select(*[F.col(c).alias(f"{c}_{x}") for c in ("db", "table", "column", "family")])
    key = lambda x: F.struct(f"db_{x}", f"table_{x}", f"column_{x}")
    a, b = side("a"), side("b")
    cond = key("a") < key("b")
    cond = cond & (F.col("db_a") != F.col("db_b") if scope == "cross" else (F.col("db_a") != F.col("db_b")) | (F.col("table_a") != F.col("table_b")))
    if same_family:
        cond = cond & (F.col("family_a") == F.col("family_b"))
    return a.join(b, cond).withColumn("a", F.col("column_a")).withColumn("b", F.col("column_b"))


def blocked_pairs(columns: DataFrame, lexicon: dict[str, str] | None = None, scope: str = "cross") -> DataFrame:
    """Only pairs that share a token, a concept or a trigram: for lakes with very many columns."""
    name = F.col("column")
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.length(name) - 2, F.lit(1))), lambda i: F.concat(F.lit("3:"), F.substring(F.lower(name), i, F.lit(3))))
    tokens = F.transform(F.split(canonical(name, lexicon), "_"), lambda t: F.concat(F.lit("t:"), t))
    keyed = columns.withColumn("block", F.explode(F.array_distinct(F.concat(grams, tokens))))
    side = lambda x: keyed.select("block", *[F.col(c).alias(f"{c}_{x}") for c in ("db", "table", "column", "family")])
    key = lambda x: F.struct(f"db_{x}", f"table_{x}", f"column_{x}")
    both = side("a").join(side("b"), "block").where((key("a") < key("b")) & (F.col("family_a") == F.col("family_b")))
    if scope == "cross":
        both = both.where("db_a <> db_b")
    return both.drop("block").distinct().withColumn("a", F.col("column_a")).withColumn("b", F.col("column_b"))


def total_score(pairs: DataFrame, cfg: DiscoveryConfig) -> DataFrame:
    """pairs with name_sim, token_overlap, semantic_sim and total_score."""
    names = pairs.select("a", "b").distinct()
    scored = names.withColumn("name_sim", gestalt_ratio(F.col("a"), F.col("b"))).withColumn("token_overlap", token_overlap(F.col("a"), F.col("b"), cfg.token_kind))
    scored = scored.join(semantic_sim(names, cfg.embedder, cfg.semantic_mode), ["a", "b"])
    total = cfg.alpha * F.col("name_sim") + cfg.beta * F.col("semantic_sim") + cfg.gamma * F.col("token_overlap")
    return pairs.join(scored.withColumn("total_score", total), ["a", "b"])


def candidates(columns: DataFrame, cfg: DiscoveryConfig) -> DataFrame:
    """Column pairs whose total score is above the name threshold (strict)."""
    pairs = blocked_pairs(columns, cfg.embedder.lexicon if isinstance(cfg.embedder, TrigramEmbedder) else None, cfg.scope) if cfg.blocking else column_pairs(columns, cfg.scope, not cfg.cast_to_string)
    return total_score(pairs, cfg).where(F.col("total_score") > cfg.name_threshold)
