"""Deterministic noise: every choice is arithmetic on a key, so that truth is known and SQL can repeat it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def drop_chars(c: Column, key: Column, n: int = 1, at: int = 2, spread: int = 3) -> Column:
    """n characters removed at 1-based position at + key mod spread."""
    pos = F.lit(at) + F.pmod(key, F.lit(spread)).cast("int")
    return F.concat(F.substr(c, F.lit(1), pos - 1), F.substr(c, pos + n, F.length(c)))


def reverse_parts(c: Column) -> Column:
    return F.array_join(F.reverse(F.split(c, " ")), " ")


def synonyms(c: Column, mapping: dict[str, str]) -> Column:
    """Each word replaced by its entry."""
    if not mapping:
        return c
    table = F.create_map(*[F.lit(x) for kv in mapping.items() for x in kv])
    return F.array_join(F.transform(F.split(c, " "), lambda w: F.coalesce(F.try_element_at(table, w), w)), " ")


def suffix(c: Column, key: Column, choices: list[str]) -> Column:
    pick = F.element_at(F.array(*[F.lit(x) for x in choices]), F.pmod(key, F.lit(len(choices))).cast("int") + 1)
    return F.concat(c, F.lit(" "), pick)


def choose(key: Column, plan: list[Column]) -> Column:
    """plan[key mod len(plan)]."""
    out = plan[-1]
    for i in range(len(plan) - 2, -1, -1):
        out = F.when(F.pmod(key, F.lit(len(plan))) == i, plan[i]).otherwise(out)
    return out


def fuzzify(df: DataFrame, column: str, key: Column, plan: list[Column], out: str, rate: int = 1, of: int = 1) -> DataFrame:
    """df with `out`: plan applied where key mod `of` < `rate`, the clean value elsewhere."""
    return df.withColumn(out, F.when(F.pmod(key, F.lit(of)) < rate, choose(key, plan)).otherwise(F.col(column)))


def hashed(key: Column, seed: int) -> Column:
    """32 bits of a digest of seed and key: the same under any partitioning, and in any engine that has MD5."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")


def fuzzify_random(df: DataFrame, column: str, key: Column, plan: list[Column], out: str, rate: float, seed: int) -> DataFrame:
    """The same with hashed randomness instead of rand()."""
    draw, kind = hashed(key, seed) / float(1 << 32), F.pmod(hashed(key, seed + 1), F.lit(len(plan)))
    return df.withColumn(out, F.when(draw < rate, choose(kind, plan)).otherwise(F.col(column)))
