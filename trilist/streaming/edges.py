"""Graphs in time: windowed co-activity edges, and triangles of an edge stream with state."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK = 256
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_stream(spark: SparkSession, path: str) -> DataFrame:
    """Parquet files of events as a stream."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(path)


def window_members(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, event_type, user_id), distinct: who was active with whom."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.select(w.start.alias("start"), "event_type", "user_id").distinct()


def window_edges(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, u, v): users active in the same window with the same event type.

    A window's users fall into blocks of one set of types each, and blocks whose types overlap meet. So each edge is made once, and
    only users are shuffled.
    """
    users = window_members(events, size, slide).dropna().groupBy("start", "user_id").agg(F.array_sort(F.collect_set("event_type")).alias("types"))
    sizes = users.groupBy("start", "types").agg(F.count("*").alias("w"))
    b = F.struct("types", F.pmod(F.xxhash64("user_id"), F.ceil(F.col("w") / BLOCK)).alias("b")).alias("k")
    spark = events.sparkSession
    parts = max(8 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    blocks = users.join(sizes, ["start", "types"]).select("start", b, "user_id").groupBy("start", "k").agg(F.collect_list("user_id").alias("us")).repartition(parts, "start")
    x, y = (blocks.select("start", F.col("k").alias(f"k{c}"), F.col("us").alias(f"u{c}")) for c in "xy")
    met = x.join(y, "start").filter((F.col("kx") <= F.col("ky")) & F.arrays_overlap("kx.types", "ky.types")).withColumn("same", F.col("kx") == F.col("ky"))
    pairs = met.select("start", "same", "uy", F.explode("ux").alias("p")).select("start", "same", "p", F.explode("uy").alias("q")).filter("NOT same OR p < q")
    return pairs.select("start", F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v"))


def window_triangles(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, triangles) of each window's graph."""
    e = window_edges(events, size, slide)
    ab, ac, bc = (e.select("start", F.col("u").alias(x), F.col("v").alias(y)) for x, y in ("ab", "ac", "bc"))
    return ab.join(ac, ["start", "a"]).filter("b < c").join(bc, ["start", "b", "c"], "left_semi").groupBy("start").agg(F.count("*").alias("triangles"))


def session_users(events: DataFrame, gap: str) -> DataFrame:
    """(event_type, start, finish, users): sessions of each event type."""
    s = events.groupBy(F.session_window("ts", gap).alias("w"), "event_type").agg(F.count_distinct("user_id").alias("users"))
    return s.select("event_type", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "users")


def user_sessions(events: DataFrame, gap: str) -> DataFrame:
    """(user_id, start, finish, events)."""
    s = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "events")


def stream_window_counts(events: DataFrame, size: str, late: str = "1 hour") -> DataFrame:
    """(start, event_type, events) with a watermark: rows later than that are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("events")).select(F.col("w.start").alias("start"), "event_type", "events")


def stream_edges(events: DataFrame, size: str, late: str = "1 hour") -> DataFrame:
    """(start, u, v) on a stream: users active in one tumbling window with one event type, each edge once, when its window is complete.

    Rows later than the watermark are dropped. A window's users are gathered by (window, type) first and paired when it closes, so
    state holds users, not pairs.
    """
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.array_sort(F.collect_set("user_id")).alias("users"))
    pairs = F.flatten(F.transform("users", lambda u: F.transform(F.filter("users", lambda v: v > u), lambda v: F.struct(u.alias("u"), v.alias("v")))))
    return w.select(F.col("w.start").alias("start"), F.explode(pairs).alias("e")).select("start", "e.u", "e.v")


def distinct_edges(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """A stream of edges (ts, u, v), repeats within the watermark dropped, whatever the order of the ends."""
    same = edges.select("ts", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).filter("u <> v")
    return same.withWatermark("ts", late).dropDuplicatesWithinWatermark(["u", "v"])


def incremental_triangles(edges: DataFrame) -> DataFrame:
    """Triangles (g, a, b, c) of a stream of edges (g, u, v), each once, when its last edge arrives; state is g's adjacency."""

    def step(key, frames: Iterator, state) -> Iterator:
        import pandas as pd

        near: dict[int, set[int]] = {}
        for v, *others in state.get[0] if state.exists else []:
            near[v] = set(others)
        out = []
        for pdf in frames:
            for u, v in zip(pdf["u"].tolist(), pdf["v"].tolist()):
                if v in near.get(u, set()):
                    continue
                out += [(key[0], *sorted((u, v, w))) for w in near.get(u, set()) & near.get(v, set())]
                near.setdefault(u, set()).add(v)
                near.setdefault(v, set()).add(u)
        state.update(([[v, *sorted(s)] for v, s in near.items()],))
        yield pd.DataFrame(out, columns=["g", "a", "b", "c"]).astype("int64")

    return edges.groupBy("g").applyInPandasWithState(step, "g long, a long, b long, c long", "near array<array<bigint>>", "append", "NoTimeout")
