"""Thin, tested wrappers of the relational operators that users of the discovery need around it."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: queries of a nearest-row search that meet the rows together
QUERY_BLOCK = 4096
ROW_BLOCK = 20_000
#: pairs of a band join that one task compares
BAND_PAIRS = 100_000_000


def project(df: DataFrame, mapping: dict[str, Column | str]) -> DataFrame:
    return df.select(*[(F.col(c) if isinstance(c, str) else c).alias(k) for k, c in mapping.items()])


def where(df: DataFrame, predicate: Column | str) -> DataFrame:
    return df.where(predicate)


def equi_join(a: DataFrame, b: DataFrame, on: list[tuple[str, str]], how: str = "inner", strategy: str | None = None) -> DataFrame:
    """strategy: broadcast (check the size of b first), merge, shuffle_hash; none leaves it to the optimizer."""
    right = b.hint(strategy) if strategy else b
    return a.join(right, reduce(lambda x, y: x & y, [a[p] == b[q] for p, q in on]), how)


def semi(a: DataFrame, b: DataFrame, on: list[tuple[str, str]]) -> DataFrame:
    return equi_join(a, b, on, "left_semi")


def anti(a: DataFrame, b: DataFrame, on: list[tuple[str, str]]) -> DataFrame:
    return equi_join(a, b, on, "left_anti")


def theta_join(a: DataFrame, b: DataFrame, cond: Column) -> DataFrame:
    return a.join(b, cond)


def band_join(a: DataFrame, b: DataFrame, col_a: str, col_b: str, width: float) -> DataFrame:
    """|a - b| <= width as an equi-join on buckets and an exact filter.

    The pairs of a bucket are known from its two counts: they set the number of tasks, and a bucket of more than BAND_PAIRS is
    dealt further (rows of a parted, rows of b copied), so neither small files nor frequent values leave the work to a few tasks.
    """
    bucket = lambda c: F.floor(c / width)
    far = 1.000001 * width  # what rounding lets through lies in these buckets, too
    x = a.withColumn("__b", bucket(F.col(col_a)))
    y = b.withColumn("__b", F.explode(F.sequence(bucket(F.col(col_b) - far), bucket(F.col(col_b) + far))))
    met = x.where("__b is not null").groupBy("__b").agg(F.count(F.lit(1)).alias("n")).join(y.groupBy("__b").agg(F.count(F.lit(1)).alias("m")), "__b").select("__b", (F.col("n").cast("double") * F.col("m")).alias("pairs"))
    tasks = max(a.sparkSession.sparkContext.defaultParallelism, int((met.agg(F.sum("pairs")).first()[0] or 0) // BAND_PAIRS) + 1)  # driver round trip: one number
    large = F.broadcast(met.where(F.col("pairs") > BAND_PAIRS).select("__b", F.ceil(F.col("pairs") / BAND_PAIRS).cast("int").alias("__k")))
    x = x.join(large, "__b", "left").withColumn("__p", F.coalesce(F.pmod(F.xxhash64(*a.columns), F.col("__k")).cast("int"), F.lit(0))).drop("__k").repartition(tasks, "__b", "__p")
    y = y.join(large, "__b", "left").withColumn("__p", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("__k"), F.lit(1)) - 1))).drop("__k").repartition(tasks, "__b", "__p")
    return x.join(y.hint("merge"), ["__b", "__p"]).where(F.abs(F.col(col_a) - F.col(col_b)) <= width).drop("__b", "__p")


def interval_join(a: DataFrame, b: DataFrame, by: list[tuple[str, str]], ts_a: str, ts_b: str, seconds: int) -> DataFrame:
    """Rows of b within `seconds` after a row of a with the same key, by time buckets."""
    x = a.withColumn("__t", F.explode(F.array(*[F.floor(F.unix_timestamp(F.col(ts_a).cast("timestamp")) / seconds) + i for i in (0, 1)])))
    y = b.withColumn("__t", F.floor(F.unix_timestamp(F.col(ts_b).cast("timestamp")) / seconds))
    cond = reduce(lambda p, q: p & q, [x[p] == y[q] for p, q in by]) & (x["__t"] == y["__t"])
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    late = micros(ts_b) - micros(ts_a)
    return x.join(y, cond).where((late >= 0) & (late <= seconds * 1_000_000)).drop("__t")


def asof_join(a: DataFrame, b: DataFrame, by: str, ts: str, value: str, out: str) -> DataFrame:
    """Each row of a with the last earlier value of b under the same key (strictly earlier): one shuffle and one sort."""
    both = a.select("*", F.lit(None).cast(b.schema[value].dataType).alias("__v"), F.lit(0).alias("__side")).unionByName(b.select(by, ts, F.col(value).alias("__v"), F.lit(1).alias("__side")), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(out, F.last("__v", ignorenulls=True).over(w)).where("__side = 0").drop("__v", "__side")


def aggregate(df: DataFrame, keys: list[str], aggs: dict[str, Column]) -> DataFrame:
    return df.groupBy(*keys).agg(*[c.alias(k) for k, c in aggs.items()])


def grouping(df: DataFrame, keys: list[str], aggs: dict[str, Column], mode: str = "cube", sets: list[list[str]] | None = None) -> DataFrame:
    grouped = df.cube(*keys) if mode == "cube" else df.rollup(*keys) if mode == "rollup" else df.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(k) for k in keys])
    return grouped.agg(*[c.alias(k) for k, c in aggs.items()])


def distinct_count(df: DataFrame, column: str, approx: bool = False) -> DataFrame:
    return df.agg((F.approx_count_distinct(column) if approx else F.count_distinct(F.col(column))).alias("n"))


def rank_top_k(df: DataFrame, keys: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col("rank") <= k)


def ranks(df: DataFrame, keys: list[str], order: list[Column], tiles: int) -> DataFrame:
    """df with rank, dense_rank and ntile under one ordering."""
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumns({"rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "ntile": F.ntile(tiles).over(w)})


def lateral_best(left: DataFrame, right: DataFrame, score: Callable[[Column, Column], Column], left_on: str, right_on: str, k: int = 1) -> DataFrame:
    """Each row of left beside its k best rows of right (a small dictionary) as a lateral join: ties to the least right value."""
    mine = right.withColumn("score", score(F.col(left_on).outer(), F.col(right_on)))
    return left.lateralJoin(mine.orderBy(F.desc("score"), right_on).limit(k))


def approximate(df: DataFrame, value: str, item: str, k: int = 3, accuracy: int = 10_000) -> DataFrame:
    """One row of approximate aggregates: distinct items (HLL sketch), the k most frequent items, median and 90th percentile of a value."""
    return df.agg(
        F.hll_sketch_estimate(F.hll_sketch_agg(item, 14)).alias("n_items"),
        F.expr(f"transform(approx_top_k({item}, {k}), t -> t.item)").alias("top"),
        F.percentile_approx(value, [0.5, 0.9], accuracy).alias("quantiles"),
    )


def running(df: DataFrame, keys: list[str], order: list, expr: Column, out: str, frame: tuple[int, int] | None = None) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumn(out, expr.over(w.rowsBetween(*(frame or (Window.unboundedPreceding, Window.currentRow)))))


def lag_lead(df: DataFrame, keys: list[str], order: list, column: str, n: int, out: str) -> DataFrame:
    """n > 0 looks back, n < 0 ahead."""
    return df.withColumn(out, (F.lag(column, n) if n > 0 else F.lead(column, -n)).over(Window.partitionBy(*keys).orderBy(*order)))


def top_k(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    return df.orderBy(*order).limit(k)


def set_op(a: DataFrame, b: DataFrame, kind: str, keep_all: bool = False) -> DataFrame:
    if kind == "union":
        return a.unionAll(b) if keep_all else a.unionAll(b).distinct()
    return {("intersect", False): a.intersect, ("intersect", True): a.intersectAll, ("except", False): a.subtract, ("except", True): a.exceptAll}[kind, keep_all](b)


def normalise_text(c: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(F.translate(c, ".,;:!?", "      ")), " +", " "))


def json_fields(df: DataFrame, column: str, schema: str) -> DataFrame:
    return df.select("*", F.from_json(column, schema).alias("__j")).select(*df.columns, "__j.*")


def url_parts(df: DataFrame, column: str) -> DataFrame:
    return df.select("*", *[F.try_parse_url(F.col(column), F.lit(p)).alias(p.lower()) for p in ("HOST", "PATH", "QUERY")])


def explode_tokens(df: DataFrame, column: str, keys: list[str]) -> DataFrame:
    return df.select(*keys, F.explode(F.split(F.trim(F.col(column)), r"\s+")).alias("token"))


def vector_top_k(df: DataFrame, queries: DataFrame, key: str, vector: str, k: int) -> DataFrame:
    """The k nearest rows by cosine for a stated query set; ties to the least key.

    Queries are dealt to blocks of QUERY_BLOCK, each block meets the rows one Arrow batch at a time as a matrix product, and
    only the best k of a batch leave it.
    """
    q = queries.select(F.col(key).alias("q"), F.col(vector).alias("u"))
    n = max(1, -(-q.count() // QUERY_BLOCK))
    packed = q.withColumn("b", F.pmod(F.xxhash64("q"), F.lit(n)).cast("int")).groupBy("b").agg(F.collect_list(F.struct("q", "u")).alias("z")).select("b", "z.q", "z.u")
    spread = df.select(F.col(key).alias("neighbour"), F.col(vector).alias("w")).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    kind = dict(df.dtypes)[key]

    def unit(m):
        return m / np.maximum(np.sqrt((m * m).sum(1, keepdims=True)), 1e-300)

    def run(left: pa.Table, right: pa.Table):
        if not left.num_rows or not right.num_rows:
            return pa.table([pa.array([], t) for t in (left.schema.field("q").type.value_type if left.num_rows else pa.int64(), right.schema.field("neighbour").type, pa.float64())], names=["q", "neighbour", "cosine"])
        names = np.concatenate([np.array(x) for x in left.column("q").to_pylist()])
        u = unit(np.array([v for x in left.column("u").to_pylist() for v in x], float))
        near = np.array(right.column("neighbour").to_pylist())
        w = unit(np.array(right.column("w").to_pylist(), float))
        out = []
        for at in range(0, len(names), 64):
            cos = np.round(u[at : at + 64] @ w.T, 6)
            for i, row in enumerate(cos):
                row = np.where(near == names[at + i], -np.inf, row)
                edge = np.partition(row, -min(k, len(row)))[-min(k, len(row))]
                some = np.flatnonzero((row >= edge) & np.isfinite(row))
                for j in some[np.lexsort((near[some], -row[some]))][:k]:
                    out.append((names[at + i], near[j], row[j]))
        return pa.table([pa.array([r[i] for r in out]) for i in range(3)], names=["q", "neighbour", "cosine"]).cast(pa.schema([("q", right.schema.field("neighbour").type), ("neighbour", right.schema.field("neighbour").type), ("cosine", pa.float64())]))

    # the rows that meet a block are dealt further: a task holds about ROW_BLOCK of them, and small tables still use all cores
    parts = max(-(-df.count() // ROW_BLOCK), df.sparkSession.sparkContext.defaultParallelism // n, 1)
    spread = spread.withColumn("p", F.pmod(F.xxhash64("neighbour"), F.lit(parts)).cast("int"))
    copies = packed.withColumn("p", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    found = copies.groupBy("b", "p").cogroup(spread.groupBy("b", "p")).applyInArrow(run, f"q {kind}, neighbour {kind}, cosine double")
    return rank_top_k(found, ["q"], [F.desc("cosine"), F.col("neighbour")], k)
