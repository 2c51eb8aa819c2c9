"""Finding and listing: repetitions of the heavy and the light half."""

from __future__ import annotations

import warnings

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.params import Params, find_repetitions, list_repetitions
from trilist.operators.heavy import hash_passes, heavy_hash, heavy_sample, sample_passes
from trilist.operators.light import light_at_once, light_avoid, settles_at_once
from trilist.plans.session import cut

FOUND = "found boolean, a long, b long, c long, repetitions long"


def find_triangle(vertices: DataFrame, edges: DataFrame, delta: float = 0.01, seed: int = 1, eps: float | None = None) -> DataFrame:
    """One row: a triangle, or found = false after enough repetitions that a miss has probability delta."""
    n, edges = vertices.count(), cut(edges)
    p = Params.for_finding(n) if eps is None else Params(n, eps)
    reps = find_repetitions(delta)
    if settles_at_once(edges, p.r):
        # the first repetition mostly finds one where there is one; all others are one more plan
        for first, last in ((0, 1), (1, reps)):
            passes = sample_passes(edges, p, seed, last, first).unionByName(light_at_once(vertices, edges, p, seed, last, first))
            if last > first and (row := passes.select("rep", "a", "b", "c").orderBy("rep", "a", "b", "c").limit(1).collect()):
                return edges.sparkSession.createDataFrame([(True, row[0].a, row[0].b, row[0].c, row[0].rep + 1)], FOUND)
        return edges.sparkSession.createDataFrame([(False, None, None, None, reps)], FOUND)
    for rep in range(reps):
        for half in (lambda: heavy_sample(edges, p, seed, rep), lambda: finished(light_avoid(vertices, edges, p, seed, rep))):
            if row := half().limit(1).collect():
                return edges.sparkSession.createDataFrame([(True, row[0].a, row[0].b, row[0].c, rep + 1)], FOUND)
    return edges.sparkSession.createDataFrame([(False, None, None, None, reps)], FOUND)


def listing_passes(vertices: DataFrame, edges: DataFrame, p: Params, seed: int, reps: int, r: float | None = None) -> DataFrame:
    """(rep, half, a, b, c), distinct: what each half lists in each repetition; all repetitions are one plan where the light half settles at once."""
    strong = hash_passes(edges, p, seed, reps).select("rep", F.lit("heavy").alias("half"), "a", "b", "c").distinct()
    if settles_at_once(edges, p.r if r is None else r):
        return strong.unionByName(light_at_once(vertices, edges, p, seed, reps).select("rep", F.lit("light").alias("half"), "a", "b", "c").distinct())
    for rep in range(reps):
        strong = strong.unionByName(finished(light_avoid(vertices, edges, p, seed, rep, r=r)).select(F.lit(rep).alias("rep"), F.lit("light").alias("half"), "a", "b", "c").distinct())
    return strong


def finished(run: tuple) -> DataFrame:
    """The output of a light pass; a warning where it stalled or ran out of its budget, so that a partial result is never silent."""
    out, trace = run
    if trace.stalled or trace.over_budget:
        warnings.warn(f"a light pass {'stalled' if trace.stalled else 'ran out of its budget'} after {len(trace.iterations)} iterations; its output is partial", stacklevel=3)
    return out


def list_triangles(vertices: DataFrame, edges: DataFrame, seed: int = 1, eps: float | None = None, repetitions: int | None = None, heavy: bool = True, light: bool = True, r: float | None = None) -> DataFrame:
    """TRI: union over repetitions of both halves (or of one of them, for ablations).

    With one bucket a single heavy pass sends every edge to all neighbours and no sender is over its cap: it is exact alone.
    """
    n = vertices.count()
    p = Params.for_listing(n) if eps is None else Params(n, eps)
    out = edges.sparkSession.createDataFrame([], "a long, b long, c long")
    if heavy and p.buckets == 1:
        repetitions, light = 1, False
    passes = repetitions or list_repetitions(n)
    if heavy and light:
        return listing_passes(vertices, cut(edges), p, seed, passes, r).select("a", "b", "c").distinct()
    for rep in range(passes):
        if heavy:
            out = out.union(heavy_hash(edges, p, seed, rep).select("a", "b", "c"))
        if light:
            out = out.union(finished(light_avoid(vertices, edges, p, seed, rep, r=r)).select("a", "b", "c"))
    return out.distinct()


def find_via_listing(triangles: DataFrame) -> DataFrame:
    """Finding is no harder than listing: the smallest triangle, if any."""
    return triangles.orderBy("a", "b", "c").limit(1)
