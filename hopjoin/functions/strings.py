"""String measures in [0, 1]: token-sorted ratio (native and Arrow forms) and the alternatives a tuned fuzzy join chooses from."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    return F.element_at(F.transform(F.array(value), body), 1)


def token_sort(c: Column, normalize: str | None = None) -> Column:
    """Tokens of a string in code point order, joined by one blank; normalize="lower_alnum" folds case and marks first."""
    if normalize == "lower_alnum":
        c = F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " ")
    elif normalize is not None:
        raise ValueError(f"unknown normalisation {normalize!r}")
    tokens = F.filter(F.split(c, r"\s+"), lambda t: t != "")
    return F.array_join(F.array_sort(tokens), " ")


def lcs_sql(a: Column, b: Column) -> Column:
    """Length of the longest common subsequence, as nested folds over one row of the usual table (native, short strings)."""
    chars = lambda c: F.array_remove(F.split(c, ""), "")

    def table(y: Column) -> Column:
        def row(prev: Column, x: Column) -> Column:
            def cell(acc: Column, j: Column) -> Column:
                hit = F.get(y, j - 1) == x
                return F.concat(acc, F.array(F.when(hit, F.get(prev, j - 1) + 1).otherwise(F.greatest(F.get(prev, j), F.get(acc, j - 1)))))

            return F.aggregate(F.sequence(F.lit(1), F.size(y)), F.array(F.lit(0)), cell)

        return F.when(F.size(y) == 0, 0).otherwise(F.aggregate(chars(a), F.array_repeat(F.lit(0), F.size(y) + 1), row, lambda r: F.get(r, F.size(y))))

    return F.when(a.isNull() | b.isNull(), None).otherwise(_let(chars(b), table))


def lcs_length(a: str, b: str) -> int:
    """The same length by one machine word (of any width) per character of a."""
    where: dict[str, int] = {}
    for i, ch in enumerate(b):
        where[ch] = where.get(ch, 0) | 1 << i
    full = (1 << len(b)) - 1
    state = full
    for ch in a:
        u = state & where.get(ch, 0)
        state = ((state + u) | (state - u)) & full
    return len(b) - state.bit_count()


def _lcs_series(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else lcs_length(x, y) for x, y in zip(a, b)], dtype="Int32")


def lcs_udf(a: Column, b: Column) -> Column:
    """Arrow form for volume; equal to lcs_sql."""
    return F.pandas_udf(_lcs_series, T.IntegerType())(a, b)


def ratio_from_lcs(lcs: Column, a: Column, b: Column) -> Column:
    """2 * LCS / (|a| + |b|); two empty strings are equal."""
    total = F.length(a) + F.length(b)
    return F.when(total == 0, F.lit(1.0)).otherwise(2.0 * lcs / F.nullif(total, F.lit(0)))


def indel_ratio(a: Column, b: Column, native: bool = False) -> Column:
    """Plain (unsorted) insert/delete similarity."""
    return ratio_from_lcs(lcs_sql(a, b) if native else lcs_udf(a, b), a, b)


def token_sort_ratio(a: Column, b: Column, normalize: str | None = None, native: bool = False) -> Column:
    return indel_ratio(token_sort(a, normalize), token_sort(b, normalize), native)


def levenshtein_ratio(a: Column, b: Column) -> Column:
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, F.lit(1.0)).otherwise(1.0 - F.levenshtein(a, b) / F.nullif(longest, F.lit(0)))


def _jaccard(x: Column, y: Column) -> Column:
    union = F.size(F.array_union(x, y))
    return F.when(union == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(x, y)) / F.nullif(union, F.lit(0)))


def token_jaccard(a: Column, b: Column) -> Column:
    words = lambda c: F.array_distinct(F.filter(F.split(F.lower(c), r"\s+"), lambda t: t != ""))
    return _jaccard(words(a), words(b))


def qgrams(c: Column, q: int = 3) -> Column:
    """Distinct q-grams of a string (the whole string if shorter)."""
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.length(c) - q + 1, F.lit(1))), lambda i: F.substring(c, i, F.lit(q)))
    return F.array_distinct(grams)


def qgram_jaccard(a: Column, b: Column, q: int = 3) -> Column:
    return _jaccard(qgrams(a, q), qgrams(b, q))


def soundex_equal(a: Column, b: Column) -> Column:
    return (F.soundex(a) == F.soundex(b)).cast("double")


MEASURES: dict[str, Callable[[Column, Column], Column]] = {
    "token_sort": token_sort_ratio,
    "plain": indel_ratio,
    "levenshtein": levenshtein_ratio,
    "token_jaccard": token_jaccard,
    "qgram_jaccard": qgram_jaccard,
    "soundex": soundex_equal,
}
