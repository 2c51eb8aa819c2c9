"""Invariants of the methods: one-sided error, exactness of special cases, loop bounds, frequencies, closed forms."""

import math
from itertools import combinations

import duckdb
import pytest

from trilist import catalog
from trilist.functions.coins import PRIME61
from trilist.functions.params import Params, find_repetitions, list_repetitions
from trilist.functions.udx import hash61, knn_edges
from trilist.operators import drivers, exact, heavy, light, measures
from trilist.plans import planner
from trilist.sources.graphs import EDGES, edges_of, load, require_schema, vertices_of

SF01 = "/root/testdata/sf0.01"


def rows(df):
    return sorted(map(tuple, df.collect()))


def brute(edges):
    e = {tuple(sorted(x)) for x in edges}
    vs = sorted({v for x in e for v in x})
    return [t for t in combinations(vs, 3) if all(p in e for p in combinations(t, 2))]


@pytest.mark.parametrize("name", ["empty", "one_edge", "triangle", "path", "cycle", "star", "complete", "book", "windmill", "coin", "halfyear", "cells"])
def test_exact_engines_agree(spark, sf, name):
    e = edges_of(spark, sf, name).cache()
    want = brute([tuple(r) for r in e.collect()])
    assert rows(exact.triangles(e)) == want
    assert rows(exact.tripartition(e, 3)) == want
    assert rows(planner.salted_triangles(e, 4)) == want
    assert sorted({t[1:] for t in rows(exact.two_hop(e))}) == want
    assert exact.algebraic_count(e).first()[0] == len(want)
    if name != "empty":
        assert rows(exact.centralised(e)) == want


@pytest.mark.parametrize("name", ["windmill", "book", "coin", "cells"])
@pytest.mark.parametrize("seed", [1, 2])
def test_outputs_are_triangles_and_ledgers_hold_caps(spark, sf, name, seed):
    v, e = vertices_of(spark, sf, name), edges_of(spark, sf, name).cache()
    p = Params(v.count(), 0.4)
    truth = set(brute([tuple(r) for r in e.collect()]))
    for out in (heavy.heavy_sample(e, p, seed), heavy.heavy_hash(e, p, seed), light.light_avoid(v, e, p, seed)[0]):
        assert {(r.a, r.b, r.c) for r in out.collect()} <= truth
    assert heavy.sample_ledger(e, p, seed).first().rounds <= p.sample_cap
    assert max(r.rounds for r in heavy.hash_ledger(e, p, seed).collect()) <= max(3, p.bucket_cap)


def test_special_cases_are_exact(spark, sf):
    e = edges_of(spark, sf, "cells").cache()
    n = vertices_of(spark, sf, "cells").count()
    want = rows(exact.triangles(e))
    assert rows(heavy.heavy_sample(e, Params(n, 0.0), 1).select("a", "b", "c").distinct()) == want
    assert rows(heavy.heavy_hash(e, Params(n, 0.4), 1, buckets=1, cap=10**9).select("a", "b", "c").distinct()) == want


def test_offers_are_asymmetric(spark, sf):
    e, v = edges_of(spark, sf, "path"), vertices_of(spark, sf, "path")
    nx = light.x_neighbourhoods(e, v.filter("v < 0"))
    sizes = {(r.j, r.k): r.size for r in light.offer_sizes(e, nx, v).collect()}
    assert sizes.get((0, 1)) == 1 and (1, 0) not in sizes


@pytest.mark.parametrize(("name", "eps", "r", "seed"), [("coin", 0.3, 20, 4), ("coin", 0.3, 30, 7), ("windmill", 0.2, 10, 4)])
def test_core_lists_all_open_triangles_within_its_bounds(spark, name, eps, r, seed):
    v, e = vertices_of(spark, SF01, name), edges_of(spark, SF01, name).cache()
    p = Params(v.count(), eps)
    xs = light.sample_x(v, p, seed)
    out, trace = light.avoid_core(v, e, xs, r)
    assert not trace.stalled
    blocked = {tuple(x) for x in light.blocked_pairs(e, xs).collect()}
    whole = [t for t in rows(exact.triangles(e)) if not any(x in blocked for x in combinations(t, 2))]
    assert whole and set(whole) <= {(x.a, x.b, x.c) for x in out.collect()}
    assert trace.rounds <= xs.count() + 1 + (math.log2(p.n) + 1) * (2 * r + 1)


def test_core_with_the_theorys_r_takes_one_iteration(spark):
    v, e = vertices_of(spark, SF01, "halfyear"), edges_of(spark, SF01, "halfyear")
    p = Params(v.count(), 0.2)
    _, trace = light.light_avoid(v, e, p, 3)
    assert len(trace.iterations) == 1 and trace.iterations[0][1] == trace.iterations[0][2]


def test_light_half_beats_two_hop_on_the_windmill(spark):
    r = catalog.QUERIES["w7_core_rounds_vs_two_hop"](spark, SF01).first()
    assert r.two_hop_rounds == 99 and r.core_rounds < 40


def test_find_and_list(spark, sf):
    v, e = vertices_of(spark, sf, "windmill"), edges_of(spark, sf, "windmill").cache()
    assert drivers.find_triangle(v, e).first().found
    free = drivers.find_triangle(vertices_of(spark, sf, "cycle"), edges_of(spark, sf, "cycle"), delta=0.5).first()
    assert not free.found and free.repetitions == find_repetitions(0.5)
    assert rows(drivers.list_triangles(v, e, repetitions=1)) == rows(exact.triangles(e))


def test_heavy_triangles_are_found_often_enough(spark):
    v, e = vertices_of(spark, SF01, "cells"), edges_of(spark, SF01, "cells").cache()
    p = Params(v.count(), 0.4)
    for seed in (1, 2):
        r = {x["class"]: x for x in measures.recall(heavy.heavy_hash(e, p, seed), e, p.threshold).collect()}
        assert r["heavy"].found / r["heavy"].total >= 1 - math.exp(-0.75) and r["all"].wrong == 0


def test_ablations(spark):
    """The light half alone misses heavy triangles; a smaller eps leaves fewer buckets and more recall to the heavy half."""
    recall = {x.eps: x.found / x.total for x in catalog.QUERIES["w4_recall_by_eps"](spark, SF01).collect()}
    assert recall[0.25] > recall[0.4]
    light_only = {x["class"]: x for x in catalog.QUERIES["w4_light_only_ablation"](spark, SF01).collect()}
    assert light_only["all"].found < light_only["all"].total


def test_bounds(spark):
    assert all(r.ok for r in catalog.QUERIES["edge_bound_check"](spark, SF01).collect())
    assert all(r.ok for r in catalog.QUERIES["open_support_max"](spark, SF01).collect())
    for r in catalog.QUERIES["light_survival"](spark, SF01).collect():
        assert r.survive >= 2 / 3 * r.light
    n = 100
    tail = catalog.QUERIES["coin_tail_share"](spark, SF01).collect()
    assert all(abs(r.triangles - math.comb(n, 3) / 8) < math.comb(n, 3) / 40 for r in tail) and all(r.above for r in tail)
    rate = catalog.QUERIES["hash_pair_rate"](spark, SF01).first()
    assert rate.events / rate.hashes >= rate.least_rate / 3  # one draw of 100 hashes, expected 0.0625


def test_parameter_rules():
    assert Params.for_listing(1000).eps == 0 and Params.for_listing(10**6).eps > 0
    assert Params(1000, 0.4).buckets == math.floor(1000**0.2)
    assert list_repetitions(1000) == math.ceil(5.4 * math.log(1000))
    assert planner.choose(10**6, 10**9, 1 << 20)[0] == "tripartition" and planner.choose(1000, 5000)[0] == "forward"


def test_hash61_agrees_with_decimal_columns(spark):
    from trilist.functions.coins import poly_hash61

    data = [(2**60 + 17 * i, 2**61 - 5 - i, 12345678901234567 + i, 2**59 + i) for i in range(20)]
    df = spark.createDataFrame(data, "x long, c0 long, c1 long, c2 long")
    got = [r[0] for r in df.select(poly_hash61("x", "c0", "c1", "c2", 11)).collect()]
    assert got == hash61(*zip(*data), 11) and PRIME61 == 2**61 - 1


def test_knn_is_exact(spark, sf):
    import numpy as np

    v = load(spark, sf, "embeddings").limit(60).cache()
    got = set(rows(knn_edges(v, 3, block=16)))
    data = v.collect()
    x = np.array([r.embedding for r in data], float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    s = x @ x.T - 9 * np.eye(len(x))
    ids = [r.vec_id for r in data]
    assert got == {tuple(sorted((ids[i], ids[j]))) for i in range(len(x)) for j in np.argsort(-s[i], kind="stable")[:3]}


def test_schema_is_checked(spark):
    with pytest.raises(ValueError):
        require_schema(spark.createDataFrame([(1, 2)], "u int, v int"), EDGES)


def test_plans_push_down_and_prune(spark, sf):
    plan = edges_of(spark, sf, "halfyear")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "l_shipdate" in plan and "l_comment" not in plan and "l_extendedprice" not in plan


QUICK = [q for q in catalog.SQL if not q.startswith(("w1_", "w2_", "w8_", "w9_"))]


@pytest.mark.parametrize("query", QUICK[::6])
def test_sql_twins(spark, sf, query):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got, want = catalog.QUERIES[query](spark, sf), con.sql(catalog.SQL[query])
    assert sorted(got.columns) == sorted(want.columns) and got.count() == len(want.fetchall())


def test_listing_queries_run_the_whole_method(spark, sf, monkeypatch):
    from trilist import catalog

    seen = []
    monkeypatch.setattr(drivers, "list_triangles", lambda v, e, **options: seen.append(options))
    for name in ("list_triangles", "w1_list", "w6_list", "w10_list"):
        catalog.QUERIES[name](spark, sf)
    assert seen == [{}] * 4


def test_listing_stops_early_only_with_one_bucket(spark, sf, monkeypatch):
    v, e = vertices_of(spark, sf, "complete"), edges_of(spark, sf, "complete")
    passes = []
    real = drivers.listing_passes
    monkeypatch.setattr(drivers, "listing_passes", lambda v, e, p, seed, reps, r=None: passes.append(reps) or real(v, e, p, seed, reps, r))
    assert rows(drivers.list_triangles(v, e)) == rows(exact.triangles(e)) and passes == []
    assert set(rows(drivers.list_triangles(v, e, eps=1.0))) <= set(rows(exact.triangles(e))) and passes == [12]
    halves = {(r.rep, r.half) for r in real(v, e, Params(8, 0.5), 1, 3).select("rep", "half").distinct().collect()}
    assert {h for _, h in halves} == {"heavy", "light"} and {r for r, _ in halves} == {0, 1, 2}


@pytest.mark.parametrize("name", ["coin", "halfyear", "windmill", "book"])
def test_offer_sizes_equal_the_listed_sets(spark, name):
    v, e = vertices_of(spark, SF01, name), edges_of(spark, SF01, name).cache()
    p = Params(v.count(), 0.2)
    nx = light.x_neighbourhoods(e, light.sample_x(v, p, 3)).cache()
    some = v.filter("v % 5 <> 0")
    sets = light.offer_sets(e, nx, some).cache()
    assert rows(light.offer_sizes(e, nx, some)) == rows(sets.groupBy("j", "k").count())
    a = e.selectExpr("u AS j", "v AS l").union(e.selectExpr("v", "u"))
    assert rows(light.open_closed(e, nx, some)) == rows(sets.join(a, ["j", "l"], "left_semi").select("j", "k", "l"))


def test_the_hubs_list_does_not_travel_to_its_neighbours(spark):
    """A hub next to all, 400 of them in X: its offers shuffle a few numbers an arc, not a copy of its list for each neighbour."""
    v = spark.range(4001).withColumnRenamed("id", "v").cache()
    e = v.filter("v > 0").selectExpr("0L AS u", "v").union(v.filter("v % 2 = 1 AND v < 4000").selectExpr("v AS u", "v + 1 AS v")).cache()
    nx = light.x_neighbourhoods(e, v.filter("v > 0 AND v % 10 = 0")).cache()
    arcs = 2 * e.count() + 0 * nx.count()
    gw, store = spark.sparkContext._gateway, spark._jsc.sc().statusStore()

    def written():
        found = store.stageList(None, False, False, gw.new_array(gw.jvm.double, 0), gw.jvm.java.util.ArrayList())
        return {(x.stageId(), x.attemptId()): x.shuffleWriteBytes() for x in map(found.apply, range(found.size()))}

    before = written()
    sizes = {(r.j, r.k): r.size for r in light.offer_sizes(e, nx, v).collect()}
    assert sum(n for key, n in written().items() if key not in before) < 100 * arcs
    # of the hub's neighbours only 9 has 10 beside it, so all others are open to it; through 10 it meets the hub, which has 10 too
    assert sizes[(9, 0)] == 3999 and sizes[(1, 0)] == 3999 and (9, 10) not in sizes


def test_passes_in_one_plan_equal_single_passes(spark):
    v, e = vertices_of(spark, SF01, "halfyear"), edges_of(spark, SF01, "halfyear").cache()
    p = Params(v.count(), 0.5)
    for rep in (0, 2):
        one = lambda df: rows(df.filter(f"rep = {rep}").drop("rep"))  # noqa: E731, B023
        assert one(heavy.sample_passes(e, p, 1, 3)) == rows(heavy.heavy_sample(e, p, 1, rep))
        assert one(heavy.hash_passes(e, p, 1, 3)) == rows(heavy.heavy_hash(e, p, 1, rep))
        assert one(light.light_at_once(v, e, p, 1, 3)) == rows(light.light_avoid(v, e, p, 1, rep)[0])
    assert rows(exact.spread_listing(e, 3)) == rows(exact.triangles(e))


def test_listing_theorem_and_guarantees_hold(spark):
    q = catalog.queries()
    last = q["w6_listing_theorem"](spark, SF01).orderBy("rep").collect()[-1]
    assert last.rep + 1 == list_repetitions(100) and last.listed == last.triangles
    for name in ("success_heavy_sample", "success_heavy_hash", "success_light_avoid"):
        assert q[name](spark, SF01).first().holds, name


def test_a_partial_light_pass_warns(spark):
    v, e = vertices_of(spark, SF01, "coin"), edges_of(spark, SF01, "coin").cache()
    with pytest.warns(UserWarning, match="partial"):
        drivers.list_triangles(v, e, seed=2, eps=0.25, repetitions=1, heavy=False, r=3)


@pytest.mark.parametrize(("name", "eps"), [("coin", 0.1), ("cells", 0.2), ("windmill", 0.2)])
def test_offers_from_few_open_pairs_equal_the_others(spark, name, eps):
    v, e = vertices_of(spark, SF01, name), edges_of(spark, SF01, name).cache()
    nx = light.x_neighbourhoods(e, light.sample_x(v, Params(v.count(), eps), 3)).cache()
    some = v.filter("v % 5 <> 0")
    pairs = light.few_open_pairs(e, nx, some, most=10**6)
    assert rows(light.sizes_from_pairs(e, pairs, some)) == rows(light.offer_sizes(e, nx, some))
    assert rows(light.closed_from_pairs(e, pairs, some)) == rows(light.open_closed(e, nx, some))
    assert light.few_open_pairs(e, nx, some, most=0) is None


def test_coin_tail_counts_by_tiles(spark):
    """Blocks of any size give the triangles of the coin graph; pairs are never rows of a shuffle."""
    from tests.test_twins import shuffled_rows
    from trilist.functions.coins import coin

    v = spark.range(70).withColumnRenamed("id", "v")
    want = []
    for seed in (1, 2):
        e = v.withColumnRenamed("v", "u").join(v).filter("u < v").filter(coin(seed, "u", "v") < 2**31)
        want.append((seed, exact.triangles(e).count()))
    for block in (20, 512):
        got = []
        moved = shuffled_rows(spark, lambda: got.extend(rows(measures.coin_tail(v, [1, 2], block).select("seed", "triangles"))))
        assert got == want and moved < 70 * 69 // 2


def test_the_coin_graph_is_made_by_many_tasks(spark):
    assert edges_of(spark, SF01, "coin").rdd.getNumPartitions() > 1


def test_few_open_pairs_shuffle_no_arcs(spark):
    """Active sets apart, the arcs of a dense graph meet its few open pairs where they lie."""
    from tests.test_twins import shuffled_rows

    v, e = vertices_of(spark, SF01, "coin"), light.cut(edges_of(spark, SF01, "coin"))
    pairs = spark.createDataFrame([(1, 5), (5, 1), (3, 7), (7, 3)], "j long, l long")
    near = {}
    for x, y in rows(e):
        near.setdefault(x, set()).add(y)
        near.setdefault(y, set()).add(x)
    got = []
    assert shuffled_rows(spark, lambda: got.extend(rows(light.next_to_both(pairs, e).select("j", "k", "l")))) < e.count() // 2
    assert sorted(got) == sorted((j, k, l) for j, l in rows(pairs) for k in near[j] & near[l])


def test_pair_coins_are_the_coins(spark):
    """Digests of many pairs at once are those of one, whatever the ids' signs and lengths."""
    import numpy as np

    from trilist.functions.coins import coin, pair_coins, pair_hits

    ids = np.array([-(2**63), -12345, -7, 0, 3, 9, 10, 99, 100, 54321, 10**9, 2**62, 2**63 - 1])
    every = spark.createDataFrame([(int(x), int(y)) for x in ids for y in ids], "x long, y long")
    for seed in (7, 123456):
        want = {(r.x, r.y): r.c for r in every.select("x", "y", coin(seed, "x", "y").alias("c")).collect()}
        got = pair_coins(seed, ids, ids)
        assert {(x, y): int(got[i, j]) for i, x in enumerate(ids) for j, y in enumerate(ids)} == want
        hits = pair_hits(seed, ids, ids)
        assert all(hits[i, j] == (x != y and want[min(x, y), max(x, y)] < 2**31) for i, x in enumerate(ids) for j, y in enumerate(ids))


def test_coin_graph_blocks_of_any_size(spark):
    """Repeated keys repeat their pairs, and the coins of blocks are those of a join."""
    from trilist.functions.coins import falls
    from trilist.sources.graphs import coin_pairs

    ids = spark.range(90).selectExpr("id * id - 50 AS v").union(spark.createDataFrame([(-50,), (14,)], "v long"))
    want = rows(ids.withColumnRenamed("v", "u").join(ids).filter("u < v").filter(falls(2**31, 7, "u", "v")))
    for block in (7, 512):
        assert rows(coin_pairs(ids, 7, block)) == want


def test_disjoint_lists_compare_no_lists_by_row(spark):
    """The pairs of lists are found in blocks, empty lists and single ones included, and no pair of lists is a row of a join."""
    import random

    draw = random.Random(3)
    data = [(sorted(draw.sample(range(100, 2000, 100), draw.choice((0, 1, 3, 9)))), 5 * g, g % 4, 2 * g) for g in range(60)]
    df = spark.createDataFrame(data, "xs array<long>, g long, w long, t long")
    want = sorted((a[1], b[1], a[2], b[3]) for a in data for b in data if not set(a[0]) & set(b[0]))
    for block in (7, 2048):
        assert rows(light.disjoint_lists(df, block)) == want
