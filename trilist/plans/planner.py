"""Choose an exact triangle plan from degree statistics; joins that stand hubs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.operators.exact import degrees, oriented, triangles, triple, tripartition
from trilist.sources.graphs import arcs

ROW_BYTES = 24


def statistics(edges: DataFrame) -> DataFrame:
    """(edges, vertices, max_degree, wedges, forward_wedges): the last two are rows of the undirected and the oriented wedge join."""
    d = degrees(edges).agg(F.count("*").alias("vertices"), F.coalesce(F.max("degree"), F.lit(0)).alias("max_degree"), F.coalesce(F.sum(F.col("degree") * (F.col("degree") - 1) / 2), F.lit(0)).cast("long").alias("wedges"))
    f = oriented(edges).groupBy("lo").agg(F.count("*").alias("k")).agg(F.coalesce(F.sum(F.col("k") * (F.col("k") - 1) / 2), F.lit(0)).cast("long").alias("forward_wedges"))
    return d.join(F.broadcast(f)).join(F.broadcast(edges.agg(F.count("*").alias("edges")))).select("edges", "vertices", "max_degree", "wedges", "forward_wedges")


def choose(edges: int, forward_wedges: int, task_bytes: int = 256 << 20) -> tuple[str, int]:
    """('forward', 0), or ('tripartition', parts) where the wedges are more rows than shipping each edge parts times."""
    parts = max(1, math.ceil(math.sqrt(6 * edges * ROW_BYTES / task_bytes)))
    return ("tripartition", parts) if edges * parts * 3 < forward_wedges and parts > 1 else ("forward", 0)


def plan_triangles(edges: DataFrame, task_bytes: int = 256 << 20) -> DataFrame:
    s = statistics(edges).first()
    kind, parts = choose(s.edges, s.forward_wedges, task_bytes)
    return tripartition(edges, parts) if kind == "tripartition" else triangles(edges)


def salted_wedges(edges: DataFrame, salts: int = 16) -> DataFrame:
    """(src, u, v) with u < v neighbours of src: one side is spread over salts, the other repeated for each."""
    a = arcs(edges)
    left = a.select("src", F.col("dst").alias("u"), F.pmod(F.xxhash64("dst"), F.lit(salts)).cast("int").alias("salt"))
    right = a.select("src", F.col("dst").alias("v"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    return left.join(right, ["src", "salt"]).filter("u < v").select("src", "u", "v")


def salted_triangles(edges: DataFrame, salts: int = 16) -> DataFrame:
    closed = salted_wedges(edges, salts).join(edges, ["u", "v"], "left_semi")
    return closed.select(*triple("src", "u", "v")).distinct()


def range_buckets(edges: DataFrame, bounds: list[int]) -> DataFrame:
    """(bucket, edges) by ranges of u: a range join with a short list of bounds."""
    rows = [(i, lo, hi) for i, (lo, hi) in enumerate(zip(bounds, bounds[1:]))]
    ranges = edges.sparkSession.createDataFrame(rows, "bucket int, lo long, hi long")
    return edges.join(F.broadcast(ranges), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).groupBy("bucket").agg(F.count("*").alias("edges"))
