"""Table reflection and declared-key edges."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hopjoin.operators.storage import materialize
from hopjoin.plans.config import TableRef

FAMILIES = (("integral", (T.ByteType, T.ShortType, T.IntegerType, T.LongType)), ("fractional", (T.FloatType, T.DoubleType, T.DecimalType)), ("temporal", (T.DateType, T.TimestampType, T.TimestampNTZType)), ("boolean", (T.BooleanType,)), ("binary", (T.BinaryType,)), ("string", (T.StringType,)))


def family(kind: T.DataType) -> str:
    return next((name for name, kinds in FAMILIES if isinstance(kind, kinds)), "other")


def flat_columns(schema: T.StructType) -> list[tuple[str, T.DataType]]:
    """(column, type) of all columns, the fields of structs as struct.field."""

    def flat(fields, prefix=""):
        for f in fields:
            if isinstance(f.dataType, T.StructType):
                yield from flat(f.dataType.fields, f"{prefix}{f.name}.")
            else:
                yield f"{prefix}{f.name}", f.dataType

    return list(flat(schema.fields))


def reflect(spark: SparkSession, tables: list[TableRef]) -> DataFrame:
    """columns(db, table, column, type, family, ordinal) from schemas alone; struct fields are flattened, maps and arrays are `other`."""
    rows = [(r.db, r.table, c, k.simpleString(), family(k), i) for r in tables for i, (c, k) in enumerate(flat_columns(r.df.schema))]
    return spark.createDataFrame(rows, "db string, table string, column string, type string, family string, ordinal int")


def observe(spark: SparkSession, tables: list[TableRef]) -> DataFrame:
    """reflect from the rows, with n_values: one scan a table counts every column's values and tells the family of those it finds.

    A column without values keeps its declared family.
    """
    parts = []
    for r in tables:
        plain, cells, row = set(r.df.columns), [], []
        for i, (c, k) in enumerate(flat_columns(r.df.schema)):
            col = F.col(f"`{c}`" if c in plain else c)
            cells += [F.max(F.when(col.isNotNull(), F.lit(family(k)))).alias(f"f{i}"), F.count(col).alias(f"n{i}")]
            row.append(F.struct(F.lit(r.db).alias("db"), F.lit(r.table).alias("table"), F.lit(c).alias("column"), F.lit(k.simpleString()).alias("type"), F.coalesce(f"f{i}", F.lit(family(k))).alias("family"), F.lit(i).alias("ordinal"), F.col(f"n{i}").alias("n_values")))
        if cells:
            parts.append(r.df.agg(*cells).select(F.explode(F.array(*row)).alias("x")).select("x.*"))
    return materialize(reduce(DataFrame.unionAll, parts))


def fk_edges(manifest: DataFrame) -> DataFrame:
    """Edges in canonical node order: (edge_id, kind, left_node, left_columns, right_node, right_columns)."""
    src, dst = F.concat_ws(".", "db", "src_table"), F.concat_ws(".", "db", "dst_table")
    swap = src > dst
    pick = lambda a, b: F.when(swap, b).otherwise(a)
    e = manifest.select(F.lit("fk").alias("kind"), pick(src, dst).alias("left_node"), pick(F.col("src_columns"), F.col("dst_columns")).alias("left_columns"), pick(dst, src).alias("right_node"), pick(F.col("dst_columns"), F.col("src_columns")).alias("right_columns"))
    return e.select(edge_id().alias("edge_id"), "*")


def edge_id():
    side = lambda x: F.concat(F.col(f"{x}_node"), F.lit("("), F.array_join(f"{x}_columns", ","), F.lit(")"))
    return F.concat(side("left"), F.lit("~"), side("right"))


def fk_orphans(src: DataFrame, dst: DataFrame, src_columns: list[str], dst_columns: list[str]) -> DataFrame:
    """orphans: rows of src whose complete key has no partner in dst."""
    keys = dst.select(*[F.col(c).alias(f"__k{i}") for i, c in enumerate(dst_columns)]).distinct()
    cond = reduce(lambda x, y: x & y, [F.col(c) == F.col(f"__k{i}") for i, c in enumerate(src_columns)])
    present = src.where(reduce(lambda x, y: x & y, [F.col(c).isNotNull() for c in src_columns]))
    return present.join(keys, cond, "left_anti").agg(F.count(F.lit(1)).alias("orphans"))


def infer_fk(tables: list[TableRef], min_containment: float = 1.0) -> DataFrame:
    """Proposed keys by inclusion: (src_node, src_column, dst_node, dst_column, containment) where a column's values are found in a
    unique column of another table of the same database.  One scan a table and one shuffle over distinct values."""
    parts = []
    for r in tables:
        cells = [F.struct(F.lit(c).alias("column"), F.lit(family(k)).alias("family"), F.col(c).cast("string").alias("v")) for c, k in flat_columns(r.df.schema) if family(k) in ("integral", "string")]
        if cells:
            parts.append(r.df.select(F.lit(r.db).alias("db"), F.lit(r.node).alias("node"), F.explode(F.array(*cells)).alias("x")).select("db", "node", "x.*").where("v is not null"))
    long = reduce(DataFrame.unionByName, parts).groupBy("db", "family", "node", "column", "v").agg(F.count(F.lit(1)).alias("n"))
    long = materialize(long)
    profile = long.groupBy("db", "family", "node", "column").agg(F.count(F.lit(1)).alias("d"), F.max("n").alias("most"))
    # values found in the same columns are counted together: pairs of columns are made once per distinct set, not once per value
    sets = long.groupBy("db", "family", "v").agg(F.sort_array(F.collect_set(F.struct("node", "column"))).alias("cols")).groupBy("db", "family", "cols").agg(F.count(F.lit(1)).alias("k"))
    pairs = sets.select("db", "family", "k", F.explode("cols").alias("x"), "cols").select("db", "family", "k", "x", F.explode("cols").alias("y")).where("x.node <> y.node")
    common = pairs.groupBy("db", "family", F.col("x.node").alias("src_node"), F.col("x.column").alias("src_column"), F.col("y.node").alias("dst_node"), F.col("y.column").alias("dst_column")).agg(F.sum("k").alias("common"))
    src = profile.select("db", "family", F.col("node").alias("src_node"), F.col("column").alias("src_column"), F.col("d").alias("src_d"))
    dst = profile.where("most = 1").select("db", "family", F.col("node").alias("dst_node"), F.col("column").alias("dst_column"))
    out = common.join(src, ["db", "family", "src_node", "src_column"]).join(dst, ["db", "family", "dst_node", "dst_column"])
    return out.withColumn("containment", F.col("common") / F.col("src_d")).where(F.col("containment") >= min_containment).select("src_node", "src_column", "dst_node", "dst_column", "containment")
