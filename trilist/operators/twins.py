"""Exact listing and supports of graphs whose edges join the members of groups, by classes of twins.

Vertices in the same groups have the same closed neighbourhood. They form a class; the graph of the classes, weighted with their
sizes, has all degrees, supports and counts, and edges or triangles are written out of it in blocks at the very end, each once and
without a shuffle. A clique of d members so costs d rows until then, not d squared or d cubed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trilist.operators import exact
from trilist.sources.graphs import arcs

BLOCK = 256


@dataclass(frozen=True)
class Twins:
    """members (v, k): the class of each vertex, named by its smallest member; links (x, y): adjacent classes x < y (each is adjacent to itself)."""

    members: DataFrame
    links: DataFrame

    @property
    def sizes(self) -> DataFrame:
        return self.members.groupBy("k").agg(F.count("*").alias("w"))


def of_groups(rows: DataFrame, groups: list[str]) -> Twins:
    """From (m, *groups), one row for each member of a group."""
    g = F.array_sort(F.collect_set(F.struct(*groups))).alias("gs")
    signed = rows.dropna().groupBy("m").agg(g)
    classes = signed.groupBy("gs").agg(F.min("m").alias("k"))
    members = signed.join(classes, "gs").select(F.col("m").alias("v"), "k")
    held = classes.select("k", F.explode("gs").alias("g"))
    links = held.withColumnRenamed("k", "x").join(held.withColumnRenamed("k", "y"), "g").filter("x < y").select("x", "y").distinct()
    return Twins(members, links)


def closed_rows(t: Twins) -> DataFrame:
    """(k, z, w): the classes z of k's closed neighbourhood and their sizes."""
    near = arcs(t.links.select(F.col("x").alias("u"), F.col("y").alias("v"))).select(F.col("src").alias("k"), F.col("dst").alias("z"))
    own = t.sizes.select("k", F.col("k").alias("z"))
    return near.unionByName(own).join(t.sizes.select(F.col("k").alias("z"), "w"), "z").select("k", "z", "w")


def pairs(t: Twins) -> DataFrame:
    """(x, y, edges, support): adjacent classes x <= y, the edges between their members and the support that each of these has.

    The masked product of the weighted class matrix: the sizes of the common closed neighbourhood, less the two ends.
    """
    rows = closed_rows(t)
    row = rows.groupBy("k").agg(F.collect_list(F.struct("z", "w")).alias("row"))
    sized = row.join(t.sizes, "k")
    left, right = (sized.select(F.col("k").alias(c), F.col("row").alias(f"r{c}"), F.col("w").alias(f"w{c}")) for c in "xy")
    met = rows.select(F.col("k").alias("x"), F.col("z").alias("y")).filter("x <= y").join(left, "x").join(right, "y")
    common = F.aggregate(F.array_intersect("rx", "ry"), F.lit(0).cast("long"), lambda s, e: s + e["w"])
    edges = F.when(F.col("x") < F.col("y"), F.col("wx") * F.col("wy")).otherwise(F.expr("wx * (wx - 1) div 2"))
    return met.select("x", "y", edges.alias("edges"), (common - 2).alias("support")).filter("edges > 0")


def count(t: Twins) -> DataFrame:
    """trace(A^3) / 6 as a sum of supports over class pairs."""
    return pairs(t).agg(F.expr("coalesce(sum(edges * support), 0) div 3").alias("triangles"))


def degrees(t: Twins) -> DataFrame:
    """(v, degree), isolated vertices left out."""
    d = closed_rows(t).groupBy("k").agg((F.sum("w") - 1).alias("degree")).filter("degree > 0")
    return t.members.join(d, "k").select("v", "degree")


def per_vertex(t: Twins) -> DataFrame:
    """(v, triangles) of the vertices in triangles."""
    p = pairs(t)
    both = p.select(F.col("x").alias("k"), F.col("y").alias("z"), "support").unionByName(p.filter("x < y").select(F.col("y").alias("k"), F.col("x").alias("z"), "support"))
    near = closed_rows(t).select("k", "z", F.when(F.col("k") == F.col("z"), F.col("w") - 1).otherwise(F.col("w")).alias("c"))
    sums = both.join(near, ["k", "z"]).groupBy("k").agg(F.expr("sum(c * support) div 2").alias("triangles")).filter("triangles > 0")
    return t.members.join(sums, "k").select("v", "triangles")


def triples(t: Twins, lister=exact.triangles) -> DataFrame:
    """(x, y, z, triangles): classes x <= y <= z with triangles among their members; three different classes come from the lister."""
    far = lister(t.links.select(F.col("x").alias("u"), F.col("y").alias("v"))).select(F.col("a").alias("x"), F.col("b").alias("y"), F.col("c").alias("z"))
    near = t.links.select(F.explode(F.array(F.struct("x", F.col("x").alias("y"), F.col("y").alias("z")), F.struct("x", "y", F.col("y").alias("z")))).alias("t")).select("t.*")
    out = far.unionByName(near).unionByName(t.sizes.select(F.col("k").alias("x"), F.col("k").alias("y"), F.col("k").alias("z")))
    for c in "xyz":
        out = out.join(t.sizes.select(F.col("k").alias(c), F.col("w").alias(f"w{c}")), c)
    number = F.expr("CASE WHEN x = z THEN wx * (wx - 1) div 2 * (wx - 2) div 3 WHEN x = y THEN wx * (wx - 1) div 2 * wz WHEN y = z THEN wy * (wy - 1) div 2 * wx ELSE wx * wy * wz END")
    return out.select("x", "y", "z", number.alias("triangles")).filter("triangles > 0")


def classify(t: Twins, threshold: float) -> DataFrame:
    """(x, y, z, triangles, max_support, is_heavy) of class triples."""
    out, s = triples(t), pairs(t).select("x", "y", "support")
    for i, j in ("xy", "xz", "yz"):
        out = out.join(s.select(F.col("x").alias(i), F.col("y").alias(j), F.col("support").alias(f"s_{i}{j}")), [i, j])
    top = F.greatest("s_xy", "s_xz", "s_yz")
    return out.select("x", "y", "z", "triangles", top.alias("max_support"), (top >= threshold).alias("is_heavy"))


def blocks(t: Twins) -> DataFrame:
    """(k, b, vs): the members of each class in blocks of about BLOCK."""
    b = F.pmod(F.xxhash64("v"), F.ceil(F.col("w") / BLOCK)).cast("int").alias("b")
    return t.members.join(t.sizes, "k").select("k", b, "v").groupBy("k", "b").agg(F.array_sort(F.collect_list("v")).alias("vs"))


def meet(t: Twins, rows: DataFrame, names: str) -> DataFrame:
    """Each row of classes (x, y[, z]) for all blocks of their members, no combination twice; spread evenly over tasks."""
    bs = blocks(t)
    for c in names:
        rows = rows.join(bs.select(F.col("k").alias(c), F.col("b").alias(f"b{c}"), F.col("vs").alias(f"v{c}")), c)
    for i, j in zip(names, names[1:]):
        rows = rows.filter((F.col(i) < F.col(j)) | (F.col(f"b{i}") <= F.col(f"b{j}")))
    sc = rows.sparkSession.sparkContext
    return rows.repartition(max(8 * sc.defaultParallelism, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))), *names, *(f"b{c}" for c in names))


def in_order(i: str, j: str) -> Column:
    """Two members of one block count once."""
    return (F.col(i) != F.col(j)) | (F.col(f"b{i}") != F.col(f"b{j}")) | (F.col(f"m{i}") < F.col(f"m{j}"))


def edges(t: Twins, rows: DataFrame, *extra: str) -> DataFrame:
    """(u, v, *extra) for all edges between the classes (x, y) of the rows."""
    far = meet(t, rows.select("x", "y", *extra), "xy").withColumn("mx", F.explode("vx")).withColumn("my", F.explode("vy")).filter(in_order("x", "y"))
    return far.select(F.least("mx", "my").alias("u"), F.greatest("mx", "my").alias("v"), *extra)


def edge_support(t: Twins) -> DataFrame:
    return edges(t, pairs(t), "support")


def same(i: str, j: str) -> Column:
    """Whether the blocks of two classes are one."""
    return (F.col(i) == F.col(j)) & (F.col(f"b{i}") == F.col(f"b{j}"))


def triangles(t: Twins, rows: DataFrame, *extra: str) -> DataFrame:
    """(a, b, c, *extra) for all triangles of the classes (x, y, z) of the rows.

    Generated code keeps all that it makes of one row before it hands on the first. The filter, which is not part of such code, ends it
    between the second and the third member, so that a task holds the triangles of one edge and a block, not those of three blocks.
    """
    out = meet(t, rows.select("x", "y", "z", *extra), "xyz")
    out = out.select("vy", "vz", F.explode("vx").alias("mx"), same("x", "y").alias("xy"), same("y", "z").alias("yz"), *extra)
    out = out.select("mx", "vz", "yz", F.explode(F.filter("vy", lambda m: ~F.col("xy") | (m > F.col("mx")))).alias("my"), *extra)
    # blocks are sorted: in one and the same, the third member stands behind the second
    third = F.when(F.col("yz"), F.slice("vz", F.array_position("vz", F.col("my")).cast("int") + 1, F.size("vz"))).otherwise(F.col("vz"))
    out = out.select(F.least("mx", "my").alias("lo"), F.greatest("mx", "my").alias("hi"), F.explode(third).alias("mz"), *extra)
    middle = F.greatest("lo", F.least("hi", "mz"))
    return out.select(F.least("lo", "mz").alias("a"), middle.alias("b"), F.greatest("hi", "mz").alias("c"), *extra)


def top_edges(t: Twins, k: int) -> DataFrame:
    """The k best edges (u, v, support) of each u < v, by support and then v: no block gives more than its k first for each u."""
    p = pairs(t).select("x", "y", "support")
    both = p.unionByName(p.filter("x < y").select(F.col("y").alias("x"), F.col("x").alias("y"), "support"))
    bs = blocks(t)
    ends = bs.select(F.col("k").alias("y"), F.col("vs").alias("vy"))
    met = both.join(bs.select(F.col("k").alias("x"), F.col("b").alias("bx"), F.col("vs").alias("vx")), "x").join(ends, "y")
    met = met.repartition(8 * met.sparkSession.sparkContext.defaultParallelism, "x", "bx", F.element_at("vy", 1))
    best = met.withColumn("u", F.explode("vx")).select("u", "support", F.explode(F.slice(F.filter("vy", lambda v: v > F.col("u")), 1, k)).alias("v"))
    # keyed by u, the few best are a small aggregate and not a sort of all edges
    kept = best.groupBy("u").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("support")).alias("s"), "v"))), 1, k).alias("best"))
    return kept.select("u", F.explode("best").alias("e")).select("u", "e.v", (-F.col("e.s")).alias("support"))
