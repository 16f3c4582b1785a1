"""Sources and sinks: any Spark format, JDBC key metadata, a Python data source of table metadata, and stored graphs."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """spark.read of csv, json, orc, text, parquet or jdbc; give a schema where the format has none."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path) if fmt != "jdbc" else reader.option("url", path).load()


def write_any(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite", **options) -> None:
    writer = df.write.format(fmt).options(**options).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, name: str, column: str, buckets: int) -> None:
    """A catalog table bucketed by value, so that later equi-joins on it need no exchange."""
    df.write.bucketBy(buckets, column).sortBy(column).mode("overwrite").saveAsTable(name)


def save_graph(edges: DataFrame, path: str) -> None:
    edges.write.partitionBy("kind").mode("overwrite").parquet(path)


def load_graph(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


#: Metadata queries on the source's own catalog, by dialect.
FK_QUERIES = {
    "postgresql": """SELECT tc.table_name AS src_table, string_agg(kcu.column_name, ',' ORDER BY kcu.ordinal_position) AS src_columns,
        max(ccu.table_name) AS dst_table, string_agg(ccu.column_name, ',' ORDER BY kcu.ordinal_position) AS dst_columns
        FROM information_schema.table_constraints tc
        JOIN information_schema.key_column_usage kcu ON kcu.constraint_name = tc.constraint_name
        JOIN information_schema.key_column_usage ccu ON ccu.constraint_name = (SELECT rc.unique_constraint_name FROM information_schema.referential_constraints rc
            WHERE rc.constraint_name = tc.constraint_name) AND ccu.ordinal_position = kcu.position_in_unique_constraint
        WHERE tc.constraint_type = 'FOREIGN KEY' GROUP BY tc.table_name, tc.constraint_name""",
    "mysql": """SELECT table_name AS src_table, group_concat(column_name ORDER BY ordinal_position) AS src_columns,
        max(referenced_table_name) AS dst_table, group_concat(referenced_column_name ORDER BY ordinal_position) AS dst_columns
        FROM information_schema.key_column_usage WHERE referenced_table_name IS NOT NULL GROUP BY table_name, constraint_name""",
}


def jdbc_foreign_keys(spark: SparkSession, url: str, dialect: str, db: str, **options) -> DataFrame:
    """fk_manifest rows read from a live database's own catalog."""
    if dialect not in FK_QUERIES:
        raise ValueError(f"no key query for {dialect!r}; have {sorted(FK_QUERIES)}")
    rows = spark.read.format("jdbc").options(url=url, query=FK_QUERIES[dialect], **options).load()
    return rows.selectExpr(f"'{db}' AS db", "src_table", "split(src_columns, ',') AS src_columns", "dst_table", "split(dst_columns, ',') AS dst_columns")


class _MetadataReader(DataSourceReader):
    def __init__(self, rows):
        self.rows = rows

    def read(self, partition):
        yield from self.rows


class TableMetadataSource(DataSource):
    """spark.read.format("table_metadata").option("schema:<db>.<table>", df.schema.json()): one row per column, no data read."""

    @classmethod
    def name(cls):
        return "table_metadata"

    def schema(self):
        return "db string, table string, column string, type string, ordinal int"

    def reader(self, schema):
        from pyspark.sql.types import StructType

        rows = []
        for key, text in sorted(self.options.items()):
            if key.startswith("schema:"):
                db, name = key[7:].split(".", 1)
                rows += [(db, name, f.name, f.dataType.simpleString(), i) for i, f in enumerate(StructType.fromJson(json.loads(text)).fields)]
        return _MetadataReader(rows)
