"""Twin classes against the plain operators, and their cost on one large cell."""

import random

import pytest

from trilist import catalog
from trilist.operators import exact, twins
from trilist.sources.graphs import edges_from_groups

CELL = 200
#: Queries on the cells that must not shuffle edges or triangles.
BY_CLASS = [
    "algebraic_count",
    "algebraic_find",
    "algebraic_support",
    "class_grouping_sets",
    "edge_support",
    "heavy_edges",
    "support_quantiles",
    "top_edges_by_support",
    "top_vertices",
    "topk_neighbours",
    "triangles_per_vertex",
    "degree_bound",
    "degree_ordered_listing",
    "heavy_triangles",
    "triangle_list",
]


def rows(df):
    return sorted(map(tuple, df.collect()))


def shuffled_rows(spark, run):
    """Rows that the stages of run() write to shuffles."""
    gw, store = spark.sparkContext._gateway, spark._jsc.sc().statusStore()

    def stages():
        found = store.stageList(None, False, False, gw.new_array(gw.jvm.double, 0), gw.jvm.java.util.ArrayList())
        return {(x.stageId(), x.attemptId()): x.shuffleWriteRecords() for x in map(found.apply, range(found.size()))}

    before = stages()
    run()
    return sum(n for key, n in stages().items() if key not in before)


@pytest.fixture(scope="module")
def one_cell(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("cell"))
    spark.range(CELL).selectExpr("id AS c_custkey", "1 AS c_nationkey", "'A' AS c_mktsegment").write.parquet(f"{d}/customer.parquet")
    return d


@pytest.mark.parametrize("query", BY_CLASS)
def test_one_large_cell_costs_its_members(spark, one_cell, query):
    df = catalog.QUERIES[query](spark, one_cell)
    assert shuffled_rows(spark, lambda: df.write.format("noop").mode("overwrite").save()) < 20 * CELL < CELL * (CELL - 1) // 2


def test_overlapping_groups_agree_with_the_plain_operators(spark, monkeypatch):
    monkeypatch.setattr(twins, "BLOCK", 3)
    draw = random.Random(5)
    groups = [(m, g) for m in range(40) for g in draw.sample(range(9), draw.choice((1, 1, 1, 2, 3)))] + [(90, 99), (91, 98), (92, 98)]
    df = spark.createDataFrame([*groups, *groups[:5]], "m long, g long").cache()
    t, e = twins.of_groups(df, ["g"]), edges_from_groups(df, df.m, [df.g]).cache()
    assert rows(twins.edge_support(t)) == rows(exact.edge_support(e)) == rows(exact.algebraic_support(e))
    assert rows(twins.degrees(t)) == rows(exact.degrees(e))
    want = rows(exact.triangles(e))
    assert rows(twins.triangles(t, twins.triples(t))) == rows(twins.triangles(t, twins.triples(t, exact.spread_listing))) == want
    assert twins.count(t).first().triangles == len(want)
    assert rows(twins.per_vertex(t)) == rows(exact.local_listing(e).groupBy("node").count())
    classes = twins.classify(t, 8)
    assert rows(twins.triangles(t, classes, "max_support", "is_heavy")) == rows(exact.classify(e, 8))
    best = {}
    for u, v, s in rows(exact.edge_support(e)):
        best[u] = sorted([*best.get(u, []), (-s, v)])[:2]
    assert rows(twins.top_edges(t, 2)) == sorted((u, v, -s) for u, b in best.items() for s, v in b)


def test_a_task_does_not_hold_the_triangles_of_three_blocks(spark, one_cell):
    """The second and the third member are not exploded in one piece of generated code, which would keep all rows of three blocks."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        for query in ("degree_ordered_listing", "heavy_triangles", "triangle_list"):
            plan = catalog.QUERIES[query](spark, one_cell)._jdf.queryExecution().executedPlan().toString()
            stages = [line.split("Generate")[0].strip(" :+-") for line in plan.splitlines() if "Generate explode" in line][:2]
            assert stages[0] != stages[1], query
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
