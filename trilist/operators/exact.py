"""Exact listing, supports, heavy and light triangles: the ground truth that the randomized methods are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.plans.session import cut
from trilist.sources.graphs import arcs

PAIRS = (("a", "b"), ("a", "c"), ("b", "c"))


def degrees(edges: DataFrame) -> DataFrame:
    return arcs(edges).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))


def triple(*columns: str) -> list:
    """The sorted triple (a, b, c) of three columns."""
    s = F.array_sort(F.array(*columns))
    return [s[i].alias(n) for i, n in enumerate("abc")]


def oriented(edges: DataFrame) -> DataFrame:
    """Each edge from the end of lower (degree, id) to the other, so that no vertex has more than sqrt(2m) outgoing ones."""
    d = degrees(edges)
    both = edges.join(d.select(F.col("v").alias("u"), F.col("degree").alias("du")), "u").join(d.select("v", F.col("degree").alias("dv")), "v")
    up = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    return both.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("lo"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("hi"))


def triangles(edges: DataFrame, hint: str | None = None) -> DataFrame:
    """All triangles (a < b < c): wedges at the lowest vertex in degree order, closed by a semi join; O(m^1.5) wedges."""
    o = oriented(edges)
    right = o.select("lo", F.col("hi").alias("h2"))
    wedges = o.join(right.hint(hint) if hint else right, "lo").filter("hi < h2")
    closed = wedges.join(edges.select(F.col("u").alias("hi"), F.col("v").alias("h2")), ["hi", "h2"], "left_semi")
    return closed.select(*triple("lo", "hi", "h2"))


def two_hop(edges: DataFrame) -> DataFrame:
    """Every vertex ships its whole neighbour list: OUT (node, a, b, c) at each vertex that can close a triangle."""
    a = arcs(edges)
    heard = a.select(F.col("src").alias("k"), F.col("dst").alias("j")).join(a.select(F.col("src").alias("j"), F.col("dst").alias("l")), "j").filter("l <> k")
    return heard.join(a.select(F.col("src").alias("k"), F.col("dst").alias("l")), ["k", "l"], "left_semi").select(F.col("k").alias("node"), *triple("j", "k", "l")).distinct()


def edge_support(edges: DataFrame) -> DataFrame:
    """(u, v, support): triangles on each edge, 0 included."""
    t = triangles(edges).select(F.explode(F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in PAIRS))).alias("e")).select("e.u", "e.v")
    return edges.join(t.groupBy("u", "v").agg(F.count("*").alias("support")), ["u", "v"], "left").select("u", "v", F.coalesce("support", F.lit(0)).alias("support"))


def pair_support(edges: DataFrame) -> DataFrame:
    """(u, v, support) for all pairs with a common neighbour, adjacent or not."""
    a = arcs(edges)
    w = a.select("src", F.col("dst").alias("u")).join(a.select("src", F.col("dst").alias("v")), "src").filter("u < v")
    return w.groupBy("u", "v").agg(F.count("*").alias("support"))


def classify(edges: DataFrame, threshold: float) -> DataFrame:
    """(a, b, c, max_support, is_heavy): heavy if an edge has support of the threshold or more."""
    t, s = triangles(edges), edge_support(edges)
    for x, y in PAIRS:
        t = t.join(s.select(F.col("u").alias(x), F.col("v").alias(y), F.col("support").alias(f"s_{x}{y}")), [x, y])
    top = F.greatest("s_ab", "s_ac", "s_bc")
    return t.select("a", "b", "c", top.alias("max_support"), (top >= threshold).alias("is_heavy"))


def local_listing(edges: DataFrame) -> DataFrame:
    """OUT with each triangle at all three of its vertices."""
    return triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("node"), "a", "b", "c")


def in_triangles(edges: DataFrame) -> DataFrame:
    return triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("v")).distinct()


def triangle_free_vertices(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    return vertices.join(in_triangles(edges), "v", "left_anti")


def triangle_free_edges(edges: DataFrame) -> DataFrame:
    return edge_support(edges).filter("support = 0").select("u", "v")


def centralised(edges: DataFrame) -> DataFrame:
    """Everything at one node, as the unlimited-bandwidth baseline has it: one task, so only for graphs that fit there."""

    def run(batches):
        import pandas as pd

        frames = list(batches)
        pairs = pd.concat(frames).itertuples(index=False) if frames else []
        near: dict[int, set[int]] = {}
        for u, v in pairs:
            near.setdefault(u, set()).add(v)
        found = [(a, b, c) for a, up in near.items() for b in up for c in up & near.get(b, set())]
        yield pd.DataFrame(found, columns=["a", "b", "c"], dtype="int64")

    return edges.coalesce(1).mapInPandas(run, "a long, b long, c long")


def local_kernel(pdf):
    """Triangles among the edges (u < v) of one group: for grouped maps."""
    import pandas as pd

    near: dict[int, set[int]] = {}
    for u, v in zip(pdf["u"], pdf["v"]):
        near.setdefault(u, set()).add(v)
    found = [(a, b, c) for a, up in near.items() for b in up for c in up & near.get(b, set())]
    return pd.DataFrame(found, columns=["a", "b", "c"], dtype="int64")


def tripartition(edges: DataFrame, parts: int, seed: int = 0) -> DataFrame:
    """One pass over reducers, each with three groups of vertices and the edges between them; no triangle twice.

    Vertices fall into parts by a coin; each edge goes to the reducers of all group triples that hold its two groups
    (about parts of them), and a reducer keeps the triangles whose sorted groups are its own key.
    """
    from trilist.functions.coins import coin, tag

    g = lambda c: coin(seed, tag("part"), c) % parts
    keyed = edges.select("u", "v", F.array(g("u"), g("v")).alias("p"))
    keys = keyed.select("u", "v", F.explode(F.transform(F.sequence(F.lit(0), F.lit(parts - 1)).cast("array<bigint>"), lambda x: F.array_sort(F.concat("p", F.array(x))))).alias("key"))

    def run(pdf):
        return local_kernel(pdf).assign(key=pdf["key"].iloc[0])

    found = keys.select("u", "v", F.array_join("key", "-").alias("key")).groupBy("key").applyInPandas(run, "a long, b long, c long, key string")
    own = F.array_join(F.array_sort(F.array(g("a"), g("b"), g("c"))), "-")
    return found.filter(own == F.col("key")).select("a", "b", "c")


def tripartition_keys(edges: DataFrame, parts: int, seed: int = 0) -> DataFrame:
    """Edges per reducer: (key, edges)."""
    from trilist.functions.coins import coin, tag

    g = lambda c: coin(seed, tag("part"), c) % parts
    p = F.array(g("u"), g("v"))
    keys = edges.select(p.alias("p")).select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(parts - 1)).cast("array<bigint>"), lambda x: F.array_sort(F.concat("p", F.array(x))))).alias("k"))
    return keys.groupBy(F.array_join("k", "-").alias("key")).agg(F.count("*").alias("edges"))


def algebraic_support(edges: DataFrame) -> DataFrame:
    """(A^2 masked by A): for each edge the product of its ends' rows, as the size of their intersection; no walk is ever a row."""
    rows = arcs(edges).groupBy("src").agg(F.collect_list("dst").alias("row"))
    left = edges.join(rows.select(F.col("src").alias("u"), F.col("row").alias("x")), "u")
    both = left.join(rows.select(F.col("src").alias("v"), F.col("row").alias("y")), "v")
    return both.select("u", "v", F.size(F.array_intersect("x", "y")).cast("long").alias("support"))


def spread_listing(edges: DataFrame, salts: int = 8) -> DataFrame:
    """Degree-bounded listing: each vertex's pairs of outgoing neighbours are spread evenly over reducers, by a hash of one end."""
    o = oriented(edges)
    left = o.withColumn("salt", F.pmod(F.xxhash64("hi"), F.lit(salts)).cast("int"))
    right = o.select("lo", F.col("hi").alias("h2"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    pairs = left.join(right, ["lo", "salt"]).filter("hi < h2")
    return pairs.join(edges.select(F.col("u").alias("hi"), F.col("v").alias("h2")), ["hi", "h2"], "left_semi").select(*triple("lo", "hi", "h2"))


def algebraic_count(edges: DataFrame) -> DataFrame:
    """trace(A^3) / 6 as a sum of supports."""
    return algebraic_support(edges).agg((F.coalesce(F.sum("support"), F.lit(0)) / 3).cast("long").alias("triangles"))


def bfs(edges: DataFrame, root: int) -> DataFrame:
    """(v, depth) by joins, one round per level; a driver loop over frontiers in memory-bounded tables."""
    spark = edges.sparkSession
    a = arcs(edges)
    frontier = spark.createDataFrame([(root,)], "v long")
    seen, depth = frontier.withColumn("depth", F.lit(0)), 0
    while True:
        depth += 1
        step = cut(frontier.join(a, frontier.v == a.src).select(F.col("dst").alias("v")).distinct().join(seen.select("v"), "v", "left_anti"))
        if step.isEmpty():
            return seen
        seen, frontier = cut(seen.union(step.withColumn("depth", F.lit(depth)))), step
