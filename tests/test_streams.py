import datetime
import time

from pyspark.sql import functions as F

from trilist.operators import exact
from trilist.sources.graphs import edges_of, load
from trilist.streaming import edges as stream


def drain(query):
    try:
        query.processAllAvailable()
    finally:
        query.stop()


def test_incremental_triangles_equal_batch(spark, sf, tmp_path):
    e = edges_of(spark, sf, "halfyear").withColumn("g", F.lit(1).cast("long")).select("g", "u", "v")
    for part in range(3):
        e.filter(F.expr(f"(u + v) % 3 = {part}")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(0.05)
    source = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = stream.incremental_triangles(source).writeStream.format("memory").queryName("inc").outputMode("append").option("checkpointLocation", str(tmp_path / "cp")).start()
    drain(q)
    assert sorted(map(tuple, spark.sql("SELECT a, b, c FROM inc").collect())) == sorted(map(tuple, exact.triangles(e).collect()))


def test_window_counts_equal_batch_and_late_rows_drop(spark, sf, tmp_path):
    events = load(spark, sf, "events")
    events.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    q = stream.stream_window_counts(stream.read_stream(spark, str(tmp_path / "in")), "1 day").writeStream.format("memory").queryName("win").outputMode("complete").option("checkpointLocation", str(tmp_path / "cp")).start()
    drain(q)
    want = events.groupBy(F.window("ts", "1 day").start.alias("start"), "event_type").agg(F.count("*").alias("events"))
    assert sorted(map(tuple, spark.table("win").collect())) == sorted(map(tuple, want.collect()))


def feed(spark, tmp_path, batches, schema):
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(0.05)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def run(df, tmp_path, name, mode):
    drain(df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).start())
    return df.sparkSession.table(name)


def at(hour, minute=0):
    return datetime.datetime(2024, 1, 1, hour, minute)


EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def test_late_row_is_dropped_in_append_and_update_mode(spark, tmp_path):
    batches = [[(1, at(1), 1, "x", 0.0, "")], [(2, at(9), 2, "x", 0.0, "")], [(5, at(9, 30), 2, "x", 0.0, "")], [(3, at(1, 5), 3, "x", 0.0, "")], [(4, at(23), 4, "x", 0.0, "")]]
    source = feed(spark, tmp_path, batches, EVENT)
    got = run(stream.stream_window_counts(source, "1 hour"), tmp_path, "late_append", "append").collect()
    assert {(r.start, r.events) for r in got} == {(at(1), 1), (at(9), 2)}
    source = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = run(stream.stream_window_counts(source, "1 hour"), tmp_path, "late_update", "update").collect()
    assert {(r.start, r.events) for r in got} == {(at(1), 1), (at(9), 1), (at(9), 2), (at(23), 1)}


def test_stream_edges_equal_batch(spark, sf, tmp_path):
    events = load(spark, sf, "events")
    day = events.filter("ts < '2024-01-08'").orderBy("ts").coalesce(1)
    day.write.parquet(str(tmp_path / "in"))
    spark.createDataFrame([(-1, datetime.datetime(2025, 1, 1), -1, "end", 0.0, "")], EVENT).write.mode("append").parquet(str(tmp_path / "in"))
    got = run(stream.stream_edges(stream.read_stream(spark, str(tmp_path / "in")), "1 hour"), tmp_path, "edges_append", "append").distinct()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, stream.window_edges(day, "1 hour").collect())) != []


def test_repeated_edges_go_within_the_watermark(spark, tmp_path):
    source = feed(spark, tmp_path, [[(at(1), 1, 2), (at(1), 2, 1), (at(1), 3, 3)], [(at(1, 30), 1, 2), (at(1, 30), 2, 3)]], "ts timestamp, u long, v long")
    got = run(stream.distinct_edges(source), tmp_path, "distinct", "append").collect()
    assert sorted((r.u, r.v) for r in got) == [(1, 2), (2, 3)]


def test_window_edges_are_made_once_and_not_shuffled(spark, monkeypatch):
    """Users of one window in several types: as the plain join gives them, without an exchange of edges."""
    from trilist.streaming import edges as stream

    monkeypatch.setattr(stream, "BLOCK", 4)
    events = spark.range(300).selectExpr("timestamp_seconds(3600 * (id % 2) + id) AS ts", "id * 7 % 40 AS user_id", "element_at(array('a', 'b', 'c', NULL), cast(id * 5 % 11 % 4 + 1 AS int)) AS event_type")
    df = stream.window_edges(events, "1 hour")
    m = stream.window_members(events, "1 hour")
    want = m.withColumnRenamed("user_id", "u").join(m.withColumnRenamed("user_id", "v"), ["start", "event_type"]).filter("u < v").select("start", "u", "v").distinct()
    got = sorted(map(tuple, df.collect()))
    assert got and got == sorted(map(tuple, want.collect()))
    last = df._jdf.queryExecution().optimizedPlan().toString().splitlines()
    assert not any(w in line for line in last[: next(i for i, x in enumerate(last) if "Join" in x)] for w in ("Aggregate", "Repartition", "Deduplicate"))
