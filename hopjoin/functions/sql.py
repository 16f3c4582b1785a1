"""The methods as SQL functions: scalar measures, table functions and a grouped aggregate for a session's SQL strings.

Native forms (`edge_weight`, `retained`, `token_sort`, `grams_of`) are SQL functions that Catalyst inlines; the LCS and the
gestalt matcher are Arrow functions.  A null argument gives null, a table function of a null gives no rows.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hopjoin.functions import names, strings


def _token_sort_ratio(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x: str, y: str) -> float:
        x, y = (" ".join(sorted(s.split())) for s in (x, y))
        return 2 * strings.lcs_length(x, y) / (len(x) + len(y)) if x or y else 1.0

    return pd.Series([None if x is None or y is None else one(x, y) for x, y in zip(a, b)], dtype="float64")


def _value_score(best: pd.Series, weight: pd.Series) -> float:
    total = weight.sum()
    return float((best * weight).sum() / total) if total else 0.0


class PathHops:
    """path_hops('a>b>c') gives (1, a, b), (2, b, c); a single table has no hop."""

    def eval(self, path: str):
        nodes = path.split(">") if path else []
        for i in range(1, len(nodes)):
            yield i, nodes[i - 1], nodes[i]


#: SQL functions that the optimizer inlines; the epsilon and base are those of graph.edge_weight.
NATIVE = {
    "edge_weight": "(overlap DOUBLE) RETURNS DOUBLE RETURN greatest(0D, -log2(overlap + 1e-9))",
    "retained": "(total DOUBLE) RETURNS DOUBLE RETURN pow(2D, -total)",
    "token_sort": r"(value STRING) RETURNS STRING RETURN array_join(array_sort(filter(split(value, '\\s+'), w -> w <> '')), ' ')",
    "grams_of": "(value STRING, q INT) RETURNS TABLE (pos INT, gram STRING) RETURN SELECT i, substr(value, i, q) FROM explode(if(value IS NULL, NULL, sequence(1, greatest(length(value) - q + 1, 1)))) AS e(i)",
}


def register_functions(spark: SparkSession) -> list[str]:
    """Makes the functions known to spark.sql and returns their names; registering again replaces them."""
    for name, body in NATIVE.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("token_sort_ratio", F.pandas_udf(_token_sort_ratio, T.DoubleType()))
    spark.udf.register("gestalt_ratio", F.pandas_udf(names._gestalt_series, T.DoubleType()))
    spark.udf.register("value_score_of", F.pandas_udf(_value_score, T.DoubleType()))
    spark.udtf.register("path_hops", F.udtf(PathHops, returnType="hop int, left_node string, right_node string"))
    return [*NATIVE, "token_sort_ratio", "gestalt_ratio", "value_score_of", "path_hops"]
