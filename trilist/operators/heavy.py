"""Triangles on edges of high support: neighbour sampling and hash-filtered exchange.

Both return OUT (node, a, b, c) and have a ledger of what the message-passing model would send: rounds (most words on one
directed edge), words in total, and senders that stay silent over their cap.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.coins import PRIME, below, coefficient, coin, poly_hash, tag
from trilist.functions.params import Params
from trilist.operators.exact import triple
from trilist.sources.graphs import arcs


def neighbour_samples(edges: DataFrame, p: Params, seed: int, rep: int = 0, cap: int | None = None) -> DataFrame:
    """(j, l, size, speaks): each vertex keeps its neighbours by independent coins; over the cap it stays silent."""
    kept = arcs(edges).filter(coin(seed, rep, tag("s"), "src", "dst") < below(p.sample_probability)).select(F.col("src").alias("j"), F.col("dst").alias("l"))
    sizes = kept.groupBy("j").agg(F.count("*").alias("size"))
    return kept.join(sizes, "j").withColumn("speaks", F.col("size") <= (p.sample_cap if cap is None else cap))


def heavy_sample(edges: DataFrame, p: Params, seed: int, rep: int = 0, cap: int | None = None) -> DataFrame:
    """Samples go to all neighbours k, which report the sampled l they are adjacent to."""
    told = neighbour_samples(edges, p, seed, rep, cap).filter("speaks").select("j", "l")
    a = arcs(edges)
    heard = told.join(a.select(F.col("src").alias("j"), F.col("dst").alias("k")), "j").filter("k <> l")
    return heard.join(a.select(F.col("src").alias("k"), F.col("dst").alias("l")), ["k", "l"], "left_semi").select(F.col("k").alias("node"), *triple("j", "k", "l")).distinct()


def sample_ledger(edges: DataFrame, p: Params, seed: int, rep: int = 0, cap: int | None = None) -> DataFrame:
    s = neighbour_samples(edges, p, seed, rep, cap).select("j", "size", "speaks").distinct()
    d = arcs(edges).groupBy(F.col("src").alias("j")).agg(F.count("*").alias("degree"))
    loud = F.col("speaks")
    return s.join(d, "j").agg(
        F.coalesce(F.max(F.when(loud, F.col("size"))), F.lit(0)).cast("long").alias("rounds"),
        F.coalesce(F.sum(F.when(loud, F.col("size") * F.col("degree"))), F.lit(0)).cast("long").alias("words"),
        F.count_if(~loud).alias("silent"),
    ).select(F.lit("heavy_sample").alias("method"), F.lit("sample").alias("phase"), "rounds", "words", "silent")


def draw_hashes(vertices: DataFrame, seed: int, rep: int = 0) -> DataFrame:
    """HASHES (node, c0, c1, c2): a degree-2 polynomial for each vertex, a pure function of its id."""
    return vertices.select(F.col("v").alias("node"), *(coefficient(seed, rep, "v", k).alias(f"c{k}") for k in range(3)))


def hash_messages(edges: DataFrame, p: Params, seed: int, rep: int = 0, buckets: int | None = None, cap: int | None = None) -> DataFrame:
    """(j, a, l, size, speaks): j owes a the edges {j, l} with h_a(l) = 0, unless there are more than the cap.

    Coefficients are computed from the id on a's arcs before the join, so the bucket filter is part of the join.
    """
    b, most = buckets or p.buckets, cap if cap is not None else p.bucket_cap
    own = arcs(edges)
    asks = draw_hashes(own.select(F.col("src").alias("v")).distinct(), seed, rep).join(own, F.col("node") == F.col("src")).select(F.col("src").alias("a"), F.col("dst").alias("j"), "c0", "c1", "c2")
    owed = asks.join(own.select(F.col("src").alias("j"), F.col("dst").alias("l")), "j").filter(poly_hash("l", "c0", "c1", "c2", b) == 0).select("j", "a", "l")
    sizes = owed.groupBy("j", "a").agg(F.count("*").alias("size"))
    return owed.join(sizes, ["j", "a"]).withColumn("speaks", F.col("size") <= most)


def heavy_hash(edges: DataFrame, p: Params, seed: int, rep: int = 0, buckets: int | None = None, cap: int | None = None) -> DataFrame:
    """Each vertex lists the triangles inside the edges it received; it need not be on them."""
    sent = hash_messages(edges, p, seed, rep, buckets, cap).filter("speaks")
    got = sent.select(F.col("a").alias("node"), F.least("j", "l").alias("u"), F.greatest("j", "l").alias("v")).distinct()
    return local_triangles(got)


def local_triangles(got: DataFrame) -> DataFrame:
    """Triangles among the edges (u < v) that each node holds."""
    ab = got.select("node", F.col("u").alias("a"), F.col("v").alias("b"))
    ac = got.select("node", F.col("u").alias("a"), F.col("v").alias("c"))
    bc = got.select("node", F.col("u").alias("b"), F.col("v").alias("c"))
    return ab.join(ac, ["node", "a"]).filter("b < c").join(bc, ["node", "b", "c"], "left_semi").select("node", "a", "b", "c")


def hash_ledger(edges: DataFrame, p: Params, seed: int, rep: int = 0, buckets: int | None = None, cap: int | None = None) -> DataFrame:
    """Two phases: three words of coefficients on every arc, then the filtered edges."""
    m = hash_messages(edges, p, seed, rep, buckets, cap).select("j", "a", "size", "speaks").distinct()
    loud = F.col("speaks")
    second = m.agg(F.coalesce(F.max(F.when(loud, F.col("size"))), F.lit(0)).cast("long").alias("rounds"), F.coalesce(F.sum(F.when(loud, F.col("size"))), F.lit(0)).cast("long").alias("words"), F.count_if(~loud).alias("silent"))
    first = arcs(edges).agg(F.lit(3).cast("long").alias("rounds"), (3 * F.count("*")).cast("long").alias("words"), F.lit(0).cast("long").alias("silent"))
    name = F.lit("heavy_hash").alias("method")
    return first.select(name, F.lit("hashes").alias("phase"), "*").unionByName(second.select(name, F.lit("edges").alias("phase"), "*"))


def received_words(edges: DataFrame, p: Params, seed: int) -> DataFrame:
    """(node, words) that each vertex receives in the filtered exchange."""
    m = hash_messages(edges, p, seed).filter("speaks")
    return m.groupBy(F.col("a").alias("node")).agg(F.count("*").alias("words"))


def repeated(df: DataFrame, reps: int, first: int = 0) -> DataFrame:
    return df.withColumn("rep", F.explode(F.sequence(F.lit(first), F.lit(reps - 1))))


def sample_passes(edges: DataFrame, p: Params, seed: int, reps: int, first: int = 0) -> DataFrame:
    """(rep, node, a, b, c): passes first to reps - 1 of heavy_sample as one plan, with the coins of the single passes."""
    a = arcs(edges)
    kept = repeated(a, reps, first).filter(coin(seed, "rep", tag("s"), "src", "dst") < below(p.sample_probability)).select("rep", F.col("src").alias("j"), F.col("dst").alias("l"))
    loud = kept.groupBy("rep", "j").agg(F.count("*").alias("size")).filter(F.col("size") <= p.sample_cap).select("rep", "j")
    heard = kept.join(loud, ["rep", "j"]).join(a.select(F.col("src").alias("j"), F.col("dst").alias("k")), "j").filter("k <> l")
    return heard.join(a.select(F.col("src").alias("k"), F.col("dst").alias("l")), ["k", "l"], "left_semi").select("rep", F.col("k").alias("node"), *triple("j", "k", "l")).distinct()


def hash_passes(edges: DataFrame, p: Params, seed: int, reps: int) -> DataFrame:
    """(rep, node, a, b, c): the first reps passes of heavy_hash as one plan, with the coins of the single passes."""
    own = arcs(edges)
    drawn = repeated(own.select(F.col("src").alias("a")).distinct(), reps)
    drawn = drawn.select("rep", "a", *(F.pmod(coin(seed, "rep", tag("h"), "a", k), F.lit(PRIME)).alias(f"c{k}") for k in range(3)))
    asks = drawn.join(own.select(F.col("src").alias("a"), F.col("dst").alias("j")), "a")
    owed = asks.join(own.select(F.col("src").alias("j"), F.col("dst").alias("l")), "j").filter(poly_hash("l", "c0", "c1", "c2", p.buckets) == 0).select("rep", "j", "a", "l")
    loud = owed.groupBy("rep", "j", "a").agg(F.count("*").alias("size")).filter(F.col("size") <= p.bucket_cap).select("rep", "j", "a")
    got = owed.join(loud, ["rep", "j", "a"]).select(F.struct("rep", "a").alias("node"), F.least("j", "l").alias("u"), F.greatest("j", "l").alias("v")).distinct()
    return local_triangles(got).select("node.rep", F.col("node.a").alias("node"), "a", "b", "c")
