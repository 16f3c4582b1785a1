import pytest
from pyspark.sql import functions as F

from hopjoin.plans.config import DiscoveryConfig
from hopjoin.sources import fixtures, io
from hopjoin.streaming import stream


def test_stream_equals_batch(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartition(1).sortWithinPartitions("ts").write.parquet(f"{tmp_path}/e")
    s = stream.read_events(spark, f"{tmp_path}/e", e.schema)
    got = stream.run_available(stream.window_counts(s), "w1", "complete").collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, stream.window_counts(e).collect()))


def test_profile_counts_full_windows(spark):
    """Windows at, just beyond and far beyond the size of a sketch, and one with no value."""
    sizes = {0: 0, 1: 4096, 2: 4097, 3: 30_000}
    parts = [spark.range(n).select((F.timestamp_seconds(F.lit(h * 3600) + F.col("id") % 3600)).alias("ts"), (F.col("id") * 7 + h).alias("user_id")) for h, n in sizes.items()]
    e = parts[1].union(parts[2]).union(parts[3]).union(parts[3]).union(spark.range(3).select(F.timestamp_seconds(F.lit(0)).alias("ts"), F.lit(None).cast("bigint").alias("user_id")))
    got = {r.start.timestamp() // 3600: r.n for r in stream.profile_counts(e).select(F.col("start"), "n").collect()}
    first = min(got)
    assert {h - first: n for h, n in got.items()} == sizes


def test_first_seen(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e.coalesce(1).write.parquet(f"{tmp_path}/e")
    s = stream.read_events(spark, f"{tmp_path}/e", e.schema)
    got = stream.run_available(stream.first_seen(s.select("ts", "user_id"), watermark="3650 days"), "w2")
    assert got.count() == e.select("user_id").distinct().count()


def test_first_seen_stateful(spark, sf, tmp_path):
    """A value is told when it appears and again when an earlier time of it arrives late; nothing is dropped."""
    t = lambda m: f"2024-01-01 10:{m:02d}:00"
    for i, rows in enumerate(([(1, t(30)), (2, t(31)), (None, t(1))], [(1, t(40)), (3, t(2))], [(1, t(5)), (2, t(50))])):
        spark.createDataFrame(rows, "user_id int, at string").select("user_id", F.col("at").cast("timestamp").alias("ts")).coalesce(1).write.parquet(f"{tmp_path}/s/{i}")
    s = stream.read_events(spark, f"{tmp_path}/s/*", "user_id int, ts timestamp")
    got = stream.run_available(stream.first_seen_stateful(s), "w3", "update").collect()
    last = {}
    for r in got:
        last[r.value] = min(last.get(r.value, r.first_ts), r.first_ts)
    assert {k: v.minute for k, v in last.items()} == {1: 5, 2: 31, 3: 2} and len(got) >= 3


def test_streams_join_within_an_interval(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).where("user_id < 4")
    sides = {"click": "a", "purchase": "b"}
    for kind, n in sides.items():
        e.where(F.col("event_type") == kind).select("user_id", "ts", F.col("event_id").alias(n)).coalesce(1).write.parquet(f"{tmp_path}/{n}")
    stream_of = lambda n: stream.read_events(spark, f"{tmp_path}/{n}", f"user_id bigint, ts timestamp, {n} bigint")
    got = {(r.a, r.b) for r in stream.run_available(stream.interval_join(stream_of("a"), stream_of("b"), within="6 hours", watermark="3650 days"), "w4").collect()}
    rows = e.collect()
    want = {(x.event_id, y.event_id) for x in rows for y in rows if x.event_type == "click" and y.event_type == "purchase" and x.user_id == y.user_id and 0 <= (y.ts - x.ts).total_seconds() <= 6 * 3600}
    assert got == want


def test_match_batch(spark, sf, tmp_path):
    c = spark.read.parquet(f"{sf}/customer.parquet").where("c_custkey < 40")
    fixtures.customer_named(c).select("c_custkey", "person_name").write.parquet(f"{tmp_path}/c")
    s = spark.readStream.schema("c_custkey bigint, person_name string").parquet(f"{tmp_path}/c")
    seen = []
    fn = stream.match_batch(fixtures.resident_registry(c), "person_name", "resident_name", DiscoveryConfig(min_score=0.6), lambda df, e: seen.append(df.count()))
    s.writeStream.foreachBatch(fn).trigger(availableNow=True).start().awaitTermination()
    assert sum(seen) >= 32


@pytest.mark.parametrize("fmt,schema,options", [("csv", "n_nationkey int, n_name string, n_regionkey int", {"header": "true"}), ("json", None, {}), ("orc", None, {}), ("parquet", None, {})])
def test_formats(spark, sf, tmp_path, fmt, schema, options):
    n = spark.read.parquet(f"{sf}/nation.parquet")
    io.write_any(n, f"{tmp_path}/{fmt}", fmt, **options)
    assert io.read_any(spark, f"{tmp_path}/{fmt}", fmt, schema, **options).count() == 25


def test_metadata_source_and_jdbc_text(spark):
    spark.dataSource.register(io.TableMetadataSource)
    df = spark.read.format("table_metadata").option("schema:db.t", spark.createDataFrame([], "a int, b string").schema.json()).load()
    assert [tuple(r) for r in df.orderBy("ordinal").collect()] == [("db", "t", "a", "int", 0), ("db", "t", "b", "string", 1)]
    assert "FOREIGN KEY" in io.FK_QUERIES["postgresql"]
    with pytest.raises(ValueError):
        io.jdbc_foreign_keys(spark, "jdbc:x", "none", "d")


def test_graph_round_trip(spark, tmp_path):
    e = spark.createDataFrame([("e1", "fk", 0.5), ("e2", "fuzzy", 0.1)], "edge_id string, kind string, overlap double")
    io.save_graph(e, f"{tmp_path}/g")
    assert io.load_graph(spark, f"{tmp_path}/g").where("kind = 'fk'").count() == 1
