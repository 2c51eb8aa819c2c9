"""Triangles without heavy edges: avoid the common neighbours in a random vertex sample.

A pair is open if it has no common neighbour in the sample X. The core loop lists all triangles with three open edges:
vertices ship small offer sets, settled vertices ship the few neighbours whose offers overflow, then settled vertices
leave. With an r below the theory's value the loop may settle nobody; it then stops (the ledger says ``stalled``).
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.coins import below, coin, falls, tag
from trilist.functions.params import Params
from trilist.operators.exact import triangles, triple
from trilist.plans.session import cut, store
from trilist.sources.graphs import arcs, induced


def sample_x(vertices: DataFrame, p: Params, seed: int, rep: int = 0) -> DataFrame:
    """XSET (v): a pure function of the ids."""
    return vertices.filter(falls(below(p.x_probability), seed, rep, tag("x"), "v")).select("v")


def both_ways(edges: DataFrame) -> DataFrame:
    """The arcs of a stored table, read once for each direction: less than a list of two arcs made for each edge."""
    return edges.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(edges.select(F.col("v").alias("src"), F.col("u").alias("dst")))


def x_neighbourhoods(edges: DataFrame, xs: DataFrame) -> DataFrame:
    """NX (v, xs): the sampled neighbours of each vertex that has any."""
    few = slim(cut(xs))
    return both_ways(edges).join(few.select(F.col("v").alias("dst")), "dst", "left_semi").groupBy(F.col("src").alias("v")).agg(F.array_sort(F.collect_set("dst")).alias("xs"))


def blocked_pairs(edges: DataFrame, xs: DataFrame) -> DataFrame:
    """(u, v) with a common neighbour in X: the join through X, which needs no list at all."""
    hub = arcs(edges).join(xs.select(F.col("v").alias("src")), "src", "left_semi")
    return hub.select("src", F.col("dst").alias("u")).join(hub.select("src", F.col("dst").alias("v")), "src").filter("u < v").select("u", "v").distinct()


def open_pairs(vertices: DataFrame, edges: DataFrame, xs: DataFrame) -> DataFrame:
    """All other pairs of vertices: quadratic by definition, for small graphs."""
    every = vertices.select(F.col("v").alias("u")).join(vertices.select("v"), F.col("u") < F.col("v"))
    return every.join(blocked_pairs(edges, xs), ["u", "v"], "left_anti")


def offer_sets(edges: DataFrame, nx: DataFrame, active: DataFrame) -> DataFrame:
    """(j, k, l): for adjacent j, k the l adjacent to k with {j, l} open, all active."""
    a = arcs(induced(edges, active))
    none = F.array().cast("array<bigint>")
    with_x = a.join(nx.select(F.col("v").alias("dst"), "xs"), "dst", "left").select(F.col("src").alias("k"), "dst", F.coalesce("xs", none).alias("xs"))
    j, l = with_x.select("k", F.col("dst").alias("j"), F.col("xs").alias("xj")), with_x.select("k", F.col("dst").alias("l"), F.col("xs").alias("xl"))
    return j.join(l, "k").filter((F.col("j") != F.col("l")) & ~F.arrays_overlap("xj", "xl")).select("j", "k", "l")


def disjoint_lists(groups: DataFrame, block: int = 2048) -> DataFrame:
    """(gj, gl, w, t) for all rows gj and gl of groups (xs, g, w, t), both ways, whose lists have no common member: w is that of gj, t that of gl.

    Blocks of lists meet as 0-1 matrices over their members; the zeros of the product are the pairs.
    """
    n = max(1, -(-groups.count() // block))
    b = groups.groupBy(F.pmod(F.xxhash64("g"), F.lit(n)).alias("b")).agg(F.collect_list(F.struct("g", "w", "t", "xs")).alias("ms"))
    met = b.select(F.col("b").alias("i"), F.col("ms").alias("x")).join(b.select(F.col("b").alias("j"), F.col("ms").alias("y")), F.col("i") <= F.col("j"))
    tiles = met.repartition(8 * groups.sparkSession.sparkContext.defaultParallelism, "i", "j").select("x", "y", (F.col("i") < F.col("j")).alias("two"))

    def meet(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for x, y, two in zip(batch.column("x"), batch.column("y"), batch.column("two").to_pylist()):
                x, y = x.values, y.values
                sizes = [m.field("xs").value_lengths().to_numpy() for m in (x, y)]
                every, at = np.unique(np.concatenate([m.field("xs").flatten().to_numpy() for m in (x, y)]), return_inverse=True)
                ends = [at[: sizes[0].sum()], at[sizes[0].sum() :]]
                common = np.zeros((len(x), len(y)), np.float32)
                for c in range(0, len(every), 1024):
                    sides = []
                    for size, end in zip(sizes, ends):
                        some = (end >= c) & (end < c + 1024)
                        side = np.zeros((len(size), min(1024, len(every) - c)), np.float32)
                        side[np.repeat(np.arange(len(size)), size)[some], end[some] - c] = 1
                        sides.append(side)
                    common += sides[0] @ sides[1].T
                x, y = ({c: m.field(c).to_numpy() for c in ("g", "w", "t")} for m in (x, y))
                for first in range(0, len(common), 256):
                    i, j = np.nonzero(common[first : first + 256] == 0)
                    i += first
                    for p, q, a, b in ((x, y, i, j), (y, x, j, i))[: 1 + two]:
                        yield pa.RecordBatch.from_arrays([pa.array(p["g"][a]), pa.array(q["g"][b]), pa.array(p["w"][a]), pa.array(q["t"][b])], names=["gj", "gl", "w", "t"])

    return tiles.mapInArrow(meet, "gj long, gl long, w long, t long")


def few_open_pairs(edges: DataFrame, nx: DataFrame, active: DataFrame, most: int = 4) -> DataFrame | None:
    """(j, l): all open pairs of active vertices, both ways, or None where they would touch more than most rows an arc.

    In a dense graph nearly every pair has a sampled common neighbour, so the open ones are few and the offers follow from them.
    Lists of sampled neighbours are compared once for all vertices that have the same one.
    """
    inside = induced(edges, active)
    d = both_ways(inside).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))
    lists = cut(d.join(nx, "v", "left").select("v", "degree", F.coalesce("xs", F.array().cast("array<bigint>")).alias("xs")))
    groups = cut(lists.groupBy("xs").agg(F.min("v").alias("g"), F.count("*").alias("w"), F.sum("degree").alias("t")))
    rows = most * (lists.agg(F.sum("degree")).first()[0] or 0)
    if groups.count() ** 2 > rows:
        return None
    met = cut(disjoint_lists(groups))
    if (met.agg(F.sum(F.col("w") * F.col("t"))).first()[0] or 0) > rows:
        return None
    of = lists.join(groups.select("xs", "g"), "xs").select("v", "g")
    j, l = (of.select(F.col("v").alias(c), F.col("g").alias(f"g{c}")) for c in "jl")
    return cut(met.join(j, "gj").join(l, "gl").filter("j <> l").select("j", "l"))


def slim(df: DataFrame, most: int = 1 << 17) -> DataFrame:
    """A cut table, to be broadcast where it has few rows: its plan does not tell its size, and arcs would be shuffled to meet it."""
    return F.broadcast(df) if df.count() <= most else df


def next_to_both(pairs: DataFrame, inside: DataFrame) -> DataFrame:
    """(j, k, l) for the pairs (j, l) and the k next to both."""
    a = both_ways(inside)
    one = slim(cut(slim(cut(pairs)).join(a.select(F.col("src").alias("l"), F.col("dst").alias("k")), "l").select("j", "k", "l")))
    # arcs are distinct, so the join is a semi join that can broadcast its left side
    return one.join(a.select(F.col("src").alias("j"), F.col("dst").alias("k")), ["j", "k"])


def sizes_from_pairs(edges: DataFrame, pairs: DataFrame, active: DataFrame) -> DataFrame:
    """offer_sizes out of the open pairs (j, l): the k next to both."""
    return next_to_both(pairs, induced(edges, active)).groupBy("j", "k").agg(F.count("*").alias("size"))


def closed_from_pairs(edges: DataFrame, pairs: DataFrame, active: DataFrame) -> DataFrame:
    """open_closed out of the open pairs (j, l): those that are edges, with the k next to both."""
    inside = induced(edges, active)
    sides = slim(cut(pairs.filter("j < l"))).join(inside.select(F.col("u").alias("j"), F.col("v").alias("l")), ["j", "l"])
    met = next_to_both(sides, inside)
    return met.select("j", "k", "l").unionByName(met.select(F.col("l").alias("j"), "k", F.col("j").alias("l")))


def offers(edges: DataFrame, nx: DataFrame, active: DataFrame) -> tuple[DataFrame, DataFrame]:
    """offer_sizes and open_closed, from the open pairs where these are few."""
    pairs = few_open_pairs(edges, nx, active)
    if pairs is None:
        return offer_sizes(edges, nx, active), open_closed(edges, nx, active)
    return sizes_from_pairs(edges, pairs, active), closed_from_pairs(edges, pairs, active)


def named_lists(nx: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(v, g) and (g, xs): the sampled neighbours by name, the least vertex that has the same list; a hub's list is long, and stands once."""
    lists = nx.groupBy("xs").agg(F.min("v").alias("g"))
    return nx.join(lists, "xs").select("v", "g"), lists.select("g", "xs")


def overlapping(lists: DataFrame) -> DataFrame:
    """(g, h), each once, g itself included: names whose lists have a common member. All who hold x are next to it, so this makes no more rows than x's offers."""
    held = lists.select("g", F.explode("xs").alias("x"))
    return held.join(held.withColumnRenamed("g", "h"), "x").select("g", "h").distinct()


def offer_sizes(edges: DataFrame, nx: DataFrame, active: DataFrame) -> DataFrame:
    """(j, k, size) of the offer sets, without listing them.

    Neighbours of k with the same sampled neighbours are open to the same vertices, and most have none at all, so they are open to all: k's
    neighbours are counted by the name of that list first, and names meet names. A hub of degree d costs d rows, not d squared, and the
    hub's own list does not travel to its d neighbours.
    """
    names, lists = named_lists(nx)
    a = arcs(induced(edges, active)).select(F.col("src").alias("k"), F.col("dst").alias("j"))
    rows = a.join(names.select(F.col("v").alias("j"), "g"), "j", "left").select("k", "j", "g")
    groups = rows.groupBy("k", "g").agg(F.count("*").alias("c"))
    every = groups.groupBy("k").agg(F.sum("c").alias("every"))
    some = groups.filter("g IS NOT NULL")
    met = some.select("k", "g").join(some.select("k", F.col("g").alias("h"), "c"), "k")
    shut = met.join(overlapping(lists), ["g", "h"], "left_semi").groupBy("k", "g").agg(F.sum("c").alias("shut"))
    # j itself is shut by its own list, and where it has none is not offered to itself
    size = F.col("every") - F.coalesce("shut", F.lit(1))
    return rows.join(every, "k").join(shut, ["k", "g"], "left").select("j", "k", size.cast("long").alias("size")).filter("size > 0")


def open_closed(edges: DataFrame, nx: DataFrame, active: DataFrame) -> DataFrame:
    """(j, k, l): the offers that their receiver j can close, from the triangles of the active vertices with an open edge {j, l}."""
    inside = induced(edges, active)
    names, lists = named_lists(nx)
    both = inside.join(names.select(F.col("v").alias("u"), "g"), "u", "left").join(names.select("v", F.col("g").alias("h")), "v", "left")
    free = both.join(overlapping(lists), ["g", "h"], "left_anti").select("u", "v")
    sides = F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v"), F.col(z).alias("k")) for x, y, z in ("abc", "acb", "bca")))
    found = triangles(inside).select(F.explode(sides).alias("t")).select("t.*").join(free, ["u", "v"], "left_semi")
    return found.select(F.col("u").alias("j"), "k", F.col("v").alias("l")).unionByName(found.select(F.col("v").alias("j"), "k", F.col("u").alias("l")))


def overflow_sets(sizes: DataFrame, r: float) -> DataFrame:
    return sizes.filter(F.col("size") > r).select("j", "k")


def settled(active: DataFrame, overflow: DataFrame, r: float) -> DataFrame:
    """Active vertices with at most r overflowing neighbours."""
    n = overflow.groupBy(F.col("j").alias("v")).agg(F.count("*").alias("n"))
    return active.join(n, "v", "left").filter(F.coalesce("n", F.lit(0)) <= r).select("v")


def close_small(closed: DataFrame, overflow: DataFrame) -> DataFrame:
    """Step one: j closes the small offers of its neighbours; closed has the offers that can be."""
    return closed.join(overflow, ["j", "k"], "left_anti").select(F.col("j").alias("node"), *triple("j", "k", "l")).distinct()


def close_overflow(overflow: DataFrame, calm: DataFrame, edges: DataFrame, active: DataFrame) -> DataFrame:
    """Step two: settled j ships its overflow set to its active neighbours l, which close it."""
    a = arcs(induced(edges, active))
    loud = slim(cut(overflow.join(calm.select(F.col("v").alias("j")), "j", "left_semi")))
    if loud.isEmpty():
        return loud.select(F.col("j").alias("node"), *triple("j", "k", "k"))
    sent = loud.join(a.select(F.col("src").alias("j"), F.col("dst").alias("l")), "j").filter("k <> l")
    return sent.join(a.select(F.col("src").alias("k"), F.col("dst").alias("l")), ["k", "l"], "left_semi").select(F.col("l").alias("node"), *triple("j", "k", "l")).distinct()


@dataclass
class Trace:
    """One row per iteration, and the ledger rows (iteration, phase, rounds, words)."""

    iterations: list[tuple] = field(default_factory=list)
    ledger: list[tuple] = field(default_factory=list)
    stalled: bool = False
    over_budget: bool = False

    @property
    def rounds(self) -> int:
        return sum(r for _, _, r, _ in self.ledger)


def avoid_core(vertices: DataFrame, edges: DataFrame, xs: DataFrame, r: float, budget: float | None = None) -> tuple[DataFrame, Trace]:
    """OUT and its trace. Only counts reach the driver; tables between iterations are checkpointed."""
    edges, vertices = store(edges), cut(vertices)
    nx = cut(x_neighbourhoods(edges, xs))
    d = both_ways(edges).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))
    shipped = nx.join(d, "v").agg(F.max(F.size("xs")), F.sum(F.size("xs") * F.col("degree"))).first()
    trace, active, outs = Trace(), slim(vertices), []
    trace.ledger += [(0, "membership", 1, 2 * edges.count()), (0, "x_lists", shipped[0] or 0, shipped[1] or 0)]
    step = 0
    while (n := active.count()) and not trace.stalled:
        step += 1
        if budget is not None and trace.rounds > budget:
            trace.over_budget = True
            break
        sizes, closed = offers(edges, nx, active)
        sizes = cut(sizes)
        over = cut(overflow_sets(sizes, r))
        calm = cut(settled(active, over, r))
        outs.append(cut(close_small(closed, over).unionByName(close_overflow(over, calm, edges, active))))
        little = sizes.filter(F.col("size") <= r).agg(F.max("size"), F.sum("size")).first()
        inside = cut(both_ways(induced(edges, active)).groupBy(F.col("src").alias("j")).agg(F.count("*").alias("degree")))
        big = over.join(calm.select(F.col("v").alias("j")), "j", "left_semi").groupBy("j").agg(F.count("*").alias("n")).join(inside, "j").agg(F.max("n"), F.sum(F.col("n") * F.col("degree"))).first()
        gone = calm.count()
        trace.ledger += [(step, "small_offers", little[0] or 0, little[1] or 0), (step, "overflow", big[0] or 0, big[1] or 0), (step, "active_bits", 1, inside.agg(F.sum("degree")).first()[0] or 0)]
        trace.iterations.append((step, n, gone, over.count()))
        trace.stalled = gone == 0
        active = slim(cut(active.join(calm, "v", "left_anti")))
    out = edges.sparkSession.createDataFrame([], "node long, a long, b long, c long")
    for o in outs:
        out = out.unionByName(o)
    return out.distinct(), trace


def settles_at_once(edges: DataFrame, r: float) -> bool:
    """No vertex has more than r + 1 neighbours, so no offer overflows and the first iteration settles all."""
    return (arcs(edges).groupBy("src").count().agg(F.max("count")).first()[0] or 0) <= r + 1


def light_at_once(vertices: DataFrame, edges: DataFrame, p: Params, seed: int, reps: int, first: int = 0) -> DataFrame:
    """(rep, node, a, b, c): what the core gives in each of the draws first to reps - 1 of X, for graphs that settle at once; one plan for all."""
    every_rep = F.sequence(F.lit(first), F.lit(reps - 1))
    draws = vertices.select("v", F.explode(every_rep).alias("rep"))
    xs = draws.filter(coin(seed, "rep", tag("x"), "v") < below(p.x_probability))
    hub = arcs(edges).join(xs.select("rep", F.col("v").alias("src")), "src")
    pairs = hub.select("rep", "src", F.col("dst").alias("u")).join(hub.select("rep", "src", F.col("dst").alias("v")), ["rep", "src"]).filter("u < v")
    # only pairs that are edges matter, so the mask comes before anything is made distinct
    shut = pairs.join(edges, ["u", "v"], "left_semi").select("rep", "u", "v").distinct()
    sides = F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in (("a", "b"), ("a", "c"), ("b", "c"))))
    every = triangles(edges).select("a", "b", "c", F.explode(sides).alias("e"), every_rep.alias("reps"))
    free = every.select("a", "b", "c", F.col("e.u").alias("u"), F.col("e.v").alias("v"), F.explode("reps").alias("rep")).join(shut, ["rep", "u", "v"], "left_anti")
    return free.select("rep", F.explode(F.array("u", "v")).alias("node"), "a", "b", "c").distinct()


def light_avoid(vertices: DataFrame, edges: DataFrame, p: Params, seed: int, rep: int = 0, r: float | None = None, c: float | None = 40.0) -> tuple[DataFrame, Trace]:
    """Draw X, run the core with the theory's r (or a given one), stop once the rounds exceed the budget of constant c."""
    return avoid_core(vertices, edges, sample_x(vertices, p, seed, rep), p.r if r is None else r, None if c is None else p.budget(c))


def trace_frame(spark, trace: Trace) -> DataFrame:
    return spark.createDataFrame(trace.iterations, "iteration long, active long, settled long, overflow_pairs long")


def ledger_frame(spark, trace: Trace) -> DataFrame:
    return spark.createDataFrame([("avoid_core", *row) for row in trace.ledger], "method string, iteration long, phase string, rounds long, words long")
