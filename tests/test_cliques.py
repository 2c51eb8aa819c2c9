"""The hash-filtered exchange on lone cliques against the plain operators, and its cost on one large cell."""

import random

import pytest

from tests.test_twins import one_cell, shuffled_rows  # noqa: F401
from trilist import catalog
from trilist.functions.params import Params
from trilist.operators import cliques, exact, heavy, twins
from trilist.sources.graphs import edges_from_groups

CELL = 200


def rows(df):
    return sorted(map(tuple, df.collect()))


def graph(spark, sizes, seed=3):
    """Lone groups of the given sizes over mixed ids, and two groups that share a member."""
    ids = random.Random(seed).sample(range(-50, 4000), sum(sizes) + 5)
    groups, at = [], 0
    for g, n in enumerate(sizes):
        groups += [(m, g) for m in ids[at : at + n]]
        at += n
    a, b, c, d, e = ids[at:]
    df = spark.createDataFrame([*groups, *groups[:3], (a, 90), (b, 90), (c, 90), (c, 91), (d, 91), (e, 91)], "m long, g long").cache()
    t = twins.of_groups(df, ["g"])
    return *cliques.parted(t, df, ["g"]), edges_from_groups(df, df.m, [df.g]).cache()


#: A cap of the middle lets some nodes hear all, some only their S, and some nobody.
@pytest.mark.parametrize(("buckets", "cap"), [(3, 3), (3, 99)])
def test_cliques_equal_the_plain_operators(spark, monkeypatch, buckets, cap):
    monkeypatch.setattr(cliques, "CHUNK", 4)
    monkeypatch.setattr(cliques, "ROWS", 5)
    monkeypatch.setattr(cliques, "CELLS", 30)
    monkeypatch.setattr(Params, "buckets", buckets)
    monkeypatch.setattr(Params, "bucket_cap", cap)
    monkeypatch.setattr(Params, "sample_cap", 4)
    p = Params(40, 0.4)
    lone, rest, every = graph(spark, (12, 1, 2, 9))
    assert rows(rest) == rows(every.join(rest, ["u", "v"], "left_semi")) and rest.count() == 6
    listed = heavy.heavy_hash(every, p, 1)
    assert rows(cliques.received(lone, p, 1).union(heavy.heavy_hash(rest, p, 1))) == rows(listed)
    seen = listed.select("a", "b", "c").distinct()
    inside = every.join(rest, ["u", "v"], "left_anti").cache()
    lost = exact.triangles(inside).exceptAll(seen.join(lone.select(lone.v.alias("a")), "a", "left_semi")).cache()
    assert rows(cliques.missed(lone, p, 1)) == rows(lost)
    count = {(u, v): 0 for u, v in rows(inside)}
    for a, b, c in rows(lost):
        for e in ((a, b), (a, c), (b, c)):
            count[e] += 1
    assert rows(cliques.missed_by_edge(lone, p, 1)) == sorted((*e, n) for e, n in count.items())
    n = lambda df: {(r.method, r.v): (r.s, r.r) for r in df.groupBy("method", "v").agg({"sent": "sum", "received": "sum"}).toDF("method", "v", "s", "r").collect() if r.s or r.r}
    assert n(catalog.clique_words(lone, p)) == n(catalog.edge_words(inside, p))


@pytest.mark.parametrize("query", ["all_pairs_rounds", "heavy_hash", "missed_triangles", "support_diff"])
def test_one_large_cell_shuffles_its_members(spark, one_cell, query):  # noqa: F811
    def run():
        catalog.QUERIES[query](spark, one_cell).write.format("noop").mode("overwrite").save()

    assert shuffled_rows(spark, run) < 40 * CELL < CELL * (CELL - 1) // 2
