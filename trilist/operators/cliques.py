"""The hash-filtered exchange on graphs with classes of twins that have no neighbour outside (lone cliques).

In a clique the edges that node a receives follow from one set: S, the members l with h_a(l) = 0. The edge {j, l} reaches a if one
end j is not a and speaks to a, and the other end is in S. All members speak to a if S is within the cap; if S has one member more,
only those of S speak (each leaves itself out); beyond that nobody does. So a receives a triangle if two of its vertices are in S, or
all three where only S speaks; a itself counts only as a member of S.

Nodes and their cliques meet in blocks, so neither edges nor messages are rows of a shuffle. What is in no lone clique (members of
several groups and their neighbours) stays an edge table for the operators of ``heavy``; no edge joins the two parts.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.coins import PRIME, below, coefficient, falls, poly_hash, tag
from trilist.functions.params import Params
from trilist.operators import twins
from trilist.operators.exact import PAIRS, triangles
from trilist.operators.light import slim
from trilist.operators.twins import Twins
from trilist.plans.session import cut
from trilist.sources.graphs import edges_from_groups

#: Nodes of a clique that are worked together.
CHUNK = 256
#: Members of a clique whose pairs with all others are counted together.
ROWS = 2048
#: Pairs of a clique's members that a task holds at once.
CELLS = 1 << 22


def parted(t: Twins, rows: DataFrame, groups: list[str]) -> tuple[DataFrame, DataFrame | None]:
    """For t of the groups' rows (m, *groups): members (v, k) of the lone cliques of two or more, and the edges of all others (None: there are none)."""
    lone = t.members.join(t.sizes.filter("w > 1").select("k"), "k", "left_semi")
    if t.links.isEmpty():
        return lone, None
    tied = t.links.select(F.explode(F.array("x", "y")).alias("k")).distinct()
    others = rows.join(t.members.join(tied, "k", "left_semi").select(F.col("v").alias("m")), "m", "left_semi")
    return lone.join(tied, "k", "left_anti"), edges_from_groups(others, F.col("m"), [F.col(g) for g in groups])


def meetings(lone: DataFrame, seed: int, rep: int = 0, chunk: int | None = None) -> DataFrame:
    """(k, at, ms): each clique's members with their hash coefficients, sorted by id, once for each block of its nodes; at is the block's first place."""
    drawn = lone.select("k", F.struct("v", *(coefficient(seed, rep, "v", i).alias(f"c{i}") for i in range(3))).alias("m"))
    whole = drawn.groupBy("k").agg(F.array_sort(F.collect_list("m")).alias("ms"))
    spread = whole.select("k", F.explode(F.sequence(F.lit(0), F.size("ms") - 1, F.lit(chunk or CHUNK))).alias("at"), "ms")
    return spread.repartition(8 * lone.sparkSession.sparkContext.defaultParallelism, "k", "at")


def node_sets(lone: DataFrame, seed: int, rep: int, buckets: int) -> DataFrame:
    """(k, node, s, vs): the set S of each node, and its whole clique."""
    nodes = meetings(lone, seed, rep).select("k", F.explode(F.slice("ms", F.col("at") + 1, CHUNK)).alias("n"), F.col("ms.v").alias("vs")).select("k", "n.*", "vs")
    return nodes.select("k", F.col("v").alias("node"), F.filter("vs", lambda l: poly_hash(l, "c0", "c1", "c2", buckets) == 0).alias("s"), "vs")


def received(lone: DataFrame, p: Params, seed: int, rep: int = 0, buckets: int | None = None, cap: int | None = None) -> DataFrame:
    """(node, a, b, c) of the lone cliques: pairs of each node's S and a third member, written out where they are made."""
    b, most = buckets or p.buckets, cap if cap is not None else p.bucket_cap
    sets = node_sets(lone, seed, rep, b).filter(F.size("s") <= most + 1)
    # a itself is a third vertex only as a member of S
    third = F.when(F.size("s") <= most, F.filter(F.array_except("vs", "s"), lambda o: o != F.col("node"))).otherwise(F.array().cast("array<bigint>"))
    pairs = sets.select("node", "s", third.alias("o")).select("node", "s", "o", F.explode("s").alias("x"))
    pairs = pairs.select("node", "s", "o", "x", F.explode(F.filter("s", lambda y: y > F.col("x"))).alias("y"))
    out = pairs.select("node", "x", "y", F.explode(F.concat("o", F.filter("s", lambda z: z > F.col("y")))).alias("z"))
    # x < y, so z is below, between or above them
    return out.select("node", F.least("x", "z").alias("a"), F.when(F.col("z") < F.col("x"), F.col("x")).otherwise(F.least("y", "z")).alias("b"), F.greatest("y", "z").alias("c"))


def zero_hashes(nodes: dict, keys, buckets: int):
    """Matrix of h_a(l) = 0 for all nodes a with coefficients c0, c1, c2 (rows) and keys l (columns)."""
    import numpy as np

    c0, c1, c2 = (nodes[c][:, None] for c in ("c0", "c1", "c2"))
    x = np.mod(keys, PRIME)[None, :]
    return ((c2 * x + c1) % PRIME * x + c0) % PRIME % buckets == 0


def arrays_of(batch, i: int) -> dict:
    """The members of row i of a batch of meetings, as arrays."""
    ms = batch.column("ms")[i].values
    return {c: ms.field(c).to_numpy() for c in ("v", "c0", "c1", "c2")}


def blocks_of(m: dict, at: int) -> Iterator[tuple[int, dict]]:
    """(first place, nodes) for the nodes of one meeting, so few at a time that their pairs with all members fit a task."""
    step = max(1, CELLS // len(m["v"]))
    end = min(at + CHUNK, len(m["v"]))
    for i in range(at, end, step):
        yield i, {c: x[i : min(i + step, end)] for c, x in m.items()}


def hash_words(lone: DataFrame, p: Params, seed: int) -> DataFrame:
    """(v, sent, received): words of the filtered exchange by vertex, the coefficients included, as partial sums."""
    b, most = p.buckets, p.bucket_cap

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for i in range(batch.num_rows):
                m = arrays_of(batch, i)
                d = len(m["v"])
                sent, got = np.zeros(d, np.int64), np.zeros(d, np.int64)
                for at, nodes in blocks_of(m, batch.column("at")[i].as_py()):
                    h = zero_hashes(nodes, m["v"], b)
                    size = h.sum(1, dtype=np.int64)[:, None] - h
                    size[size > most] = 0
                    n = np.arange(len(size))
                    size[n, at + n] = 0
                    sent += size.sum(0)
                    got[at + n] = size.sum(1) + 3 * (d - 1)
                    sent[at + n] += 3 * (d - 1)
                yield pa.RecordBatch.from_arrays([pa.array(m["v"]), pa.array(sent), pa.array(got)], names=["v", "sent", "received"])

    return meetings(lone, seed).mapInArrow(run, "v long, sent long, received long")


def two_hop_words(lone: DataFrame) -> DataFrame:
    """(v, sent, received) where every vertex ships its neighbour list to its neighbours."""
    w = lone.groupBy("k").agg(F.count("*").alias("w"))
    words = (F.col("w") - 1) * (F.col("w") - 1)
    return lone.join(w, "k").select("v", words.alias("sent"), words.alias("received"))


def sample_words(lone: DataFrame, p: Params, seed: int, rep: int = 0) -> DataFrame:
    """(v, sent, received): words of the neighbour samples by vertex; the coins are thrown and counted where pairs meet."""
    nodes = meetings(lone, seed, rep).select("k", F.explode(F.slice("ms.v", F.col("at") + 1, CHUNK)).alias("v"), F.col("ms.v").alias("vs"))
    kept = nodes.select("v", F.explode("vs").alias("l")).filter("v <> l").filter(falls(below(p.sample_probability), seed, rep, tag("s"), "v", "l"))
    loud = kept.groupBy("v").agg(F.count("*").alias("size")).filter(F.col("size") <= p.sample_cap)
    own = lone.join(loud, "v", "left").select("k", "v", F.coalesce("size", F.lit(0)).alias("size"))
    every = own.groupBy("k").agg(F.count("*").alias("w"), F.sum("size").alias("all"))
    return own.join(every, "k").select("v", (F.col("size") * (F.col("w") - 1)).alias("sent"), (F.col("all") - F.col("size")).alias("received"))


def weak_pairs(lone: DataFrame, p: Params, seed: int) -> DataFrame:
    """(u, v, w): pairs u < v of a clique that at most one node has in its S together: w, or null if none has.

    The product of the matrix of all S with itself, in tiles of ROWS members against all; it ends early once no pair is weak.
    """
    b, most, rows = p.buckets, p.bucket_cap, ROWS

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for i in range(batch.num_rows):
                m, at = arrays_of(batch, i), batch.column("at")[i].as_py()
                d = len(m["v"])
                tile, right = slice(at, min(at + rows, d)), slice(at, d)
                times = np.zeros((tile.stop - at, d - at), np.float32)
                places = np.zeros_like(times)
                upper = np.arange(d - at)[None, :] > np.arange(tile.stop - at)[:, None]
                for first in range(0, d, step := max(256, min(1024, CELLS // d))):
                    h = zero_hashes({c: x[first : first + step] for c, x in m.items()}, m["v"], b)
                    # beyond the cap a clique's members do not all speak to the node
                    h &= (h.sum(1) <= most)[:, None]
                    h = h.astype(np.float32)
                    left = h[:, tile]
                    times += left.T @ h[:, right]
                    places += (left * np.arange(first, first + len(h), dtype=np.float32)[:, None]).T @ h[:, right]
                    weak = (times <= 1) & upper
                    if not weak.any():
                        break
                x, y = np.nonzero(weak)
                w = m["v"][np.where(times[x, y] == 1, places[x, y], 0).astype(np.int64)]
                yield pa.RecordBatch.from_arrays([pa.array(m["v"][x + at]), pa.array(m["v"][y + at]), pa.array(w, mask=times[x, y] == 0)], names=["u", "v", "w"])

    return meetings(lone, seed, chunk=rows).mapInArrow(run, "u long, v long, w long")


def missed(lone: DataFrame, p: Params, seed: int) -> DataFrame:
    """(a, b, c): triangles of the lone cliques that no node lists.

    A node other than the third vertex with two of a triangle's vertices in its S lists it, so only weak pairs make one that is missed.
    """
    weak = cut(weak_pairs(lone, p, seed))
    found = triangles(weak.select("u", "v"))
    for i, j, third in ("abc", "acb", "bca"):
        found = found.join(weak.select(F.col("u").alias(i), F.col("v").alias(j), F.col("w").alias(f"w{third}")), [i, j]).filter(f"w{third} IS NULL OR w{third} = {third}")
    found = found.select("a", "b", "c")
    # nodes to which only their S speaks list the triangles inside it; no clique within the cap has one
    large = lone.groupBy("k").agg(F.count("*").alias("d")).filter(F.col("d") > p.bucket_cap).select("k")
    sets = node_sets(lone.join(large, "k", "left_semi"), seed, 0, p.buckets).filter(F.size("s") == p.bucket_cap + 1).select("k", "s")
    if sets.isEmpty():
        return found
    near = found.join(lone.select(F.col("v").alias("a"), "k"), "a").join(sets, "k")
    listed = near.filter(F.array_contains("s", F.col("a")) & F.array_contains("s", F.col("b")) & F.array_contains("s", F.col("c")))
    return found.join(listed.select("a", "b", "c").distinct(), ["a", "b", "c"], "left_anti")


def missed_by_edge(lone: DataFrame, p: Params, seed: int) -> DataFrame:
    """(u, v, missed): how many triangles of each edge no node lists, 0 included."""
    sides = F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in PAIRS))
    counts = cut(missed(lone, p, seed).select(F.explode(sides).alias("e")).groupBy("e.u", "e.v").agg(F.count("*").alias("n")))
    every = twins.edges(Twins(lone, lone.sparkSession.createDataFrame([], "x long, y long")), lone.select(F.col("k").alias("x"), F.col("k").alias("y")).distinct())
    return every.join(slim(counts), ["u", "v"], "left").select("u", "v", F.coalesce("n", F.lit(0)).alias("missed"))
