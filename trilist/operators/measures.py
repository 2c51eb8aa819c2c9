"""Accuracy, cost and lower-bound measures."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.coins import poly_hash
from trilist.functions.params import BOUNDS, Params
from trilist.operators.exact import PAIRS, classify, pair_support, triangles
from trilist.operators.heavy import draw_hashes
from trilist.operators.light import blocked_pairs, sample_x
from trilist.plans.session import cut

ROOT = math.sqrt(2) / 3
TAIL = 1 / 15 - 1 / 32


def recall(out: DataFrame, edges: DataFrame, threshold: float) -> DataFrame:
    """(class, total, found) for heavy, light and all triangles, and wrong: outputs that are no triangle (always 0)."""
    truth = classify(edges, threshold)
    got = out.select("a", "b", "c").distinct().withColumn("hit", F.lit(1))
    both = truth.join(got, ["a", "b", "c"], "full")
    kinds = F.explode(F.array(F.when(F.col("is_heavy"), "heavy").when(~F.col("is_heavy"), "light"), F.lit("all")))
    rows = both.withColumn("class", kinds).filter("class IS NOT NULL")
    return rows.groupBy("class").agg(F.count_if(F.col("is_heavy").isNotNull()).alias("total"), F.count_if((F.col("hit") == 1) & F.col("is_heavy").isNotNull()).alias("found"), F.count_if(F.col("is_heavy").isNull()).alias("wrong"))


def covered_edges(out: DataFrame) -> DataFrame:
    """(node, triangles, edges): distinct edges under each node's output."""
    e = out.select("node", "a", "b", "c", F.explode(F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in PAIRS))).alias("e"))
    return e.groupBy("node").agg(F.count_distinct("a", "b", "c").alias("triangles"), F.count_distinct("e").alias("edges"))


def edge_bound_check(out: DataFrame) -> DataFrame:
    """t triangles need (sqrt 2 / 3) t^(2/3) edges."""
    bound = F.lit(ROOT) * F.pow(F.col("triangles"), F.lit(2 / 3))
    return covered_edges(out).select("node", "triangles", "edges", F.round(bound, 6).alias("bound"), (F.col("edges") >= bound).alias("ok"))


def information(out: DataFrame, n: int) -> DataFrame:
    """(node, input_bits, revealed_bits): a node starts with n - 1 bits and its output reveals one bit per covered edge."""
    return covered_edges(out).select("node", F.lit(n - 1).cast("long").alias("input_bits"), F.col("edges").alias("revealed_bits"))


def busiest(out: DataFrame) -> DataFrame:
    sizes = out.groupBy("node").agg(F.count("*").alias("triangles"))
    return sizes.agg(F.max_by("node", F.struct(F.col("triangles"), -F.col("node"))).alias("node"), F.max("triangles").alias("triangles"))


def duplication(out: DataFrame) -> DataFrame:
    """(times, triangles): how many triangles are output by how many nodes."""
    return out.groupBy("a", "b", "c").agg(F.count("*").alias("times")).groupBy("times").agg(F.count("*").alias("triangles"))


def round_bounds(rows: DataFrame) -> DataFrame:
    """All bounds with constants 1 for rows (n, d): size and largest degree."""
    cols = F.explode(F.array(*(F.struct(F.lit(name).alias("bound"), F.round(F.expr(sql), 6).alias("rounds")) for name, sql in BOUNDS.items())))
    return rows.select("n", "d", cols.alias("x")).select("n", "d", "x.*")


def listing_bound(sizes: DataFrame) -> DataFrame:
    """Information bound of the busiest node, transcript bits beyond its own input, rounds, for each size n."""
    n = F.col("n").cast("double")
    rows = sizes.select("n").withColumn("triples", n * (n - 1) * (n - 2) / 6)
    bits = F.lit(ROOT) * F.pow(F.col("triples") / (16 * n), F.lit(2 / 3)) * F.lit(TAIL)
    out = rows.withColumn("information", bits).withColumn("transcript", F.greatest(F.lit(0.0), bits - (n - 1)))
    return out.select("n", F.round("information", 4).alias("information"), F.round("transcript", 4).alias("transcript"), F.round(F.col("transcript") / ((n - 1) * F.ceil(F.log2(n))), 9).alias("rounds"))


def local_bound(sizes: DataFrame) -> DataFrame:
    """The same for local listing: a sixteenth of all pairs, times the tail; and the exact expected number C(n-1, 2) / 8."""
    n = F.col("n").cast("double")
    rows = sizes.select("n").withColumn("information", n * (n - 1) / 32 * F.lit(TAIL))
    out = rows.withColumn("transcript", F.greatest(F.lit(0.0), F.col("information") - (n - 1)))
    return out.select("n", F.round("information", 4).alias("information"), F.round("transcript", 4).alias("transcript"), F.round(F.col("transcript") / ((n - 1) * F.ceil(F.log2(n))), 9).alias("rounds"), ((n - 1) * (n - 2) / 16).alias("expected_local"))


def coin_expectations(sizes: DataFrame) -> DataFrame:
    """Pairs, triples and the expected triangles of the fair coin graph for each size n."""
    n = F.col("n")
    return sizes.select("n", F.expr("n * (n - 1) div 2").alias("pairs"), F.expr("n * (n - 1) * (n - 2) div 6").alias("triples"), (n * (n - 1) * (n - 2) / 48).alias("expected_triangles"))


def coin_tiles(vertices: DataFrame, seeds: list[int], blocks: int) -> DataFrame:
    """(seed, i, j, rows, columns, bits): the fair coin graph's adjacency between blocks i <= j of vertices, its coins thrown where the tile is made."""
    b = vertices.groupBy(F.pmod(F.xxhash64("v"), F.lit(blocks)).cast("int").alias("b")).agg(F.array_sort(F.collect_list("v")).alias("vs"))
    met = b.select(F.col("b").alias("i"), F.col("vs").alias("x")).join(b.select(F.col("b").alias("j"), F.col("vs").alias("y")), F.col("i") <= F.col("j"))
    tasks = met.withColumn("seed", F.explode(F.array(*map(F.lit, seeds)).cast("array<bigint>"))).repartition(8 * vertices.sparkSession.sparkContext.defaultParallelism, "i", "j", "seed")

    def throw(batches):
        from hashlib import md5

        import numpy as np
        import pandas as pd

        for pdf in batches:
            for t in pdf.itertuples(index=False):
                x, y = t.x.tolist(), t.y.tolist()
                # the first bit of the digest is that of coin(): 0 means below 2^31
                hit = np.array([[u != v and md5(f"{t.seed}:{min(u, v)}:{max(u, v)}".encode()).digest()[0] < 128 for v in y] for u in x], dtype=bool)
                yield pd.DataFrame({"seed": [t.seed], "i": [t.i], "j": [t.j], "rows": [len(x)], "columns": [len(y)], "bits": [np.packbits(hit).tobytes()]})

    return tasks.select("seed", "i", "j", "x", "y").mapInPandas(throw, "seed long, i int, j int, rows int, columns int, bits binary")


def tile_triangles(tiles: DataFrame) -> DataFrame:
    """(seed, triangles): masked products of tiles over blocks i <= j <= k; a triangle of one block is in its product six times, one of two blocks twice."""
    side = lambda a, b: tiles.select("seed", F.col("i").alias(a), F.col("j").alias(b), *(F.col(c).alias(f"{c}_{a}{b}") for c in ("rows", "columns", "bits")))
    met = side("i", "j").join(side("j", "k"), ["seed", "j"]).join(side("i", "k"), ["seed", "i", "k"])
    met = met.repartition(8 * tiles.sparkSession.sparkContext.defaultParallelism, "seed", "i", "j", "k")

    def multiply(batches):
        import numpy as np
        import pandas as pd

        def tile(bits, rows, columns):
            return np.unpackbits(np.frombuffer(bits, dtype=np.uint8), count=rows * columns).reshape(rows, columns).astype(np.float32)

        for pdf in batches:
            for t in pdf.itertuples(index=False):
                walks = tile(t.bits_ij, t.rows_ij, t.columns_ij) @ tile(t.bits_jk, t.rows_jk, t.columns_jk)
                every = int((walks * tile(t.bits_ik, t.rows_ik, t.columns_ik)).sum(dtype=np.float64))
                yield pd.DataFrame({"seed": [t.seed], "triangles": [every // {3: 1, 2: 2, 1: 6}[len({t.i, t.j, t.k})]]})

    return met.mapInPandas(multiply, "seed long, triangles long").groupBy("seed").agg(F.sum("triangles").alias("triangles"))


def coin_tail(vertices: DataFrame, seeds: list[int], block: int = 512) -> DataFrame:
    """(seed, triangles, above): triangles of the fair coin graph, and whether they exceed a sixteenth of all triples."""
    spark = vertices.sparkSession
    # seeds are a short list of the caller's, one graph each
    s = spark.createDataFrame([(x,) for x in seeds], "seed long")
    counts = tile_triangles(cut(coin_tiles(vertices, seeds, max(1, -(-vertices.count() // block)))))
    n = vertices.agg(F.count("*").cast("double").alias("n"))
    return s.join(counts, "seed", "left").join(F.broadcast(n)).select("seed", F.coalesce("triangles", F.lit(0)).alias("triangles"), (F.coalesce("triangles", F.lit(0)) > F.expr("n * (n - 1) * (n - 2) / 96")).alias("above"))


def opposite_edges(edges: DataFrame) -> DataFrame:
    """(node, edges): edges opposite to each vertex in its triangles, one per triangle."""
    t = triangles(edges)
    e = t.select(F.explode(F.array(*(F.struct(F.col(x).alias("node"), F.col(y).alias("u"), F.col(z).alias("v")) for x, y, z in ("abc", "bac", "cab")))).alias("e"))
    return e.select("e.*").groupBy("node").agg(F.count_distinct("u", "v").alias("edges"))


def entropy(df: DataFrame, *columns: str) -> DataFrame:
    counts = df.groupBy(*columns).agg(F.count("*").alias("c"))
    total = counts.agg(F.sum("c").alias("t"))
    p = F.col("c") / F.col("t")
    return counts.join(F.broadcast(total)).agg(F.round(-F.sum(p * F.log2(p)), 6).alias("entropy"))


def mutual_information(df: DataFrame, x: str, y: str) -> DataFrame:
    h = [entropy(df, *c).withColumnRenamed("entropy", f"h{i}") for i, c in enumerate(((x,), (y,), (x, y)))]
    return h[0].join(F.broadcast(h[1])).join(F.broadcast(h[2])).select(F.round(F.col("h0") + F.col("h1") - F.col("h2"), 5).alias("mutual_information"))


def light_survival(vertices: DataFrame, edges: DataFrame, p: Params, seeds: list[int]) -> DataFrame:
    """(seed, light, survive): light triangles, and those whose three edges stay open under the seed's X."""
    light = classify(edges, p.threshold).filter("NOT is_heavy").select("a", "b", "c")
    out = None
    for s in seeds:
        blocked = blocked_pairs(edges, sample_x(vertices, p, s))
        alive = light
        for x, y in PAIRS:
            alive = alive.join(blocked.select(F.col("u").alias(x), F.col("v").alias(y)), [x, y], "left_anti")
        row = alive.agg(F.count("*").alias("survive")).join(F.broadcast(light.agg(F.count("*").alias("light")))).select(F.lit(s).cast("long").alias("seed"), "light", "survive")
        out = row if out is None else out.unionByName(row)
    return out


def open_support_max(vertices: DataFrame, edges: DataFrame, p: Params, seed: int) -> DataFrame:
    """Largest support of a pair that stays open, beside the bound 27 n^eps ln n."""
    alive = pair_support(edges).join(blocked_pairs(edges, sample_x(vertices, p, seed)), ["u", "v"], "left_anti")
    bound = 27 * p.threshold * math.log(max(2, p.n))
    return alive.agg(F.coalesce(F.max("support"), F.lit(0)).alias("max_support")).select("max_support", F.lit(round(bound, 6)).alias("bound"), (F.col("max_support") < bound).alias("ok"))


def hash_pair_rate(vertices: DataFrame, p: Params, buckets: int, seed: int) -> DataFrame:
    """Over all vertices' hashes: how often the two smallest keys both fall in bucket 0 while the bucket stays small."""
    h = draw_hashes(vertices, seed)
    keys = vertices.select(F.col("v").alias("x"))
    hit = h.join(keys).filter(poly_hash("x", "c0", "c1", "c2", buckets) == 0)  # test scale: all keys under all hashes
    per = hit.groupBy("node").agg(F.count("*").alias("size"), F.count_if(F.col("x") == 0).alias("k0"), F.count_if(F.col("x") == 1).alias("k1"))
    cap = 4 * (2 + (p.n - 2) / buckets)
    good = per.agg(F.count_if((F.col("k0") + F.col("k1") == 2) & (F.col("size") <= cap)).alias("events"))
    return good.select("events", F.lit(p.n).cast("long").alias("hashes"), F.lit(round(0.75 / buckets**2, 9)).alias("least_rate"))


def hash_uniformity(vertices: DataFrame, buckets: int, seed: int) -> DataFrame:
    """Joint bucket table of the keys 0, 1, 2 over all vertices' hashes."""
    h = draw_hashes(vertices, seed)
    cols = [poly_hash(f"x{k}", "c0", "c1", "c2", buckets).alias(f"b{k}") for k in range(3)]
    return h.withColumns({f"x{k}": F.lit(k).cast("long") for k in range(3)}).select(*cols).groupBy("b0", "b1", "b2").agg(F.count("*").alias("hashes"))


def all_pairs_rounds(messages: DataFrame, n: int) -> DataFrame:
    """(most_sent, most_received, rounds) of messages(src, dst, words) where any two of n vertices can talk: the busiest vertex's words over n - 1 links."""
    out = messages.groupBy("src").agg(F.sum("words").alias("w")).agg(F.coalesce(F.max("w"), F.lit(0)).cast("long").alias("most_sent"))
    into = messages.groupBy("dst").agg(F.sum("words").alias("w")).agg(F.coalesce(F.max("w"), F.lit(0)).cast("long").alias("most_received"))
    return out.crossJoin(F.broadcast(into)).withColumn("rounds", F.ceil(F.greatest("most_sent", "most_received") / F.lit(max(1, n - 1))).cast("long"))


def busiest_words(words: DataFrame, n: int) -> DataFrame:
    """all_pairs_rounds by method, out of (method, v, sent, received), partial sums of each vertex's words."""
    by = words.groupBy("method", "v").agg(F.sum("sent").alias("sent"), F.sum("received").alias("received"))
    most = by.groupBy("method").agg(F.max("sent").cast("long").alias("most_sent"), F.max("received").cast("long").alias("most_received"))
    return most.withColumn("rounds", F.ceil(F.greatest("most_sent", "most_received") / F.lit(max(1, n - 1))).cast("long"))


def rate_over(found: DataFrame, reps: int, guarantee: float) -> DataFrame:
    """(reps, hits, rate, guarantee, holds) for found(rep), the repetitions that succeeded."""
    hits = found.select("rep").distinct().agg(F.count("*").alias("hits"))
    rate = F.col("hits") / F.lit(float(reps))
    return hits.select(F.lit(reps).cast("long").alias("reps"), "hits", F.round(rate, 6).alias("rate"), F.lit(guarantee).alias("guarantee"), (rate >= guarantee).alias("holds"))
