"""Invariants of the methods on small graphs, against brute force."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from signedcluster.functions.priority import priorities
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph, normalise
from signedcluster.operators import arboricity, baselines, clip, exact, exchange, forest, measure, mis, pivot, simple
from signedcluster.operators.components import components
from signedcluster.sources import builders as B


def make(spark, n, edges):
    v = spark.range(n).select(F.col("id").alias("v"))
    return normalise(spark.createDataFrame(edges, "u long, v long"), v).stored("test")


def random_graph(spark, n, m, seed):
    draw = random.Random(seed)
    edges = draw.sample(list(itertools.combinations(range(n), 2)), m)
    return make(spark, n, edges), edges


def rows(df):
    return {r[0]: r[1] for r in df.collect()}


def greedy(edges, order):
    near = {v: set() for v in order}
    for u, v in edges:
        near[u].add(v)
        near[v].add(u)
    chosen = set()
    for v in sorted(order, key=order.get):
        if not near[v] & chosen:
            chosen.add(v)
    return chosen


def brute_cost(n, edges, cid):
    e = {tuple(sorted(x)) for x in edges}
    return sum(((u, v) in e) == (cid[u] != cid[v]) for u, v in itertools.combinations(range(n), 2))


def optimum(n, edges):
    best = 10**9

    def grow(k, label, used):
        nonlocal best
        if k == n:
            best = min(best, brute_cost(n, edges, label))
            return
        for c in range(used + 1):
            grow(k + 1, [*label, c], max(used, c + 1))

    grow(0, [], 0)
    return best


def test_all_methods_give_the_sequential_set(spark):
    for seed, n, m in ((1, 40, 90), (2, 30, 30)):
        g, edges = random_graph(spark, n, m, seed)
        order = {r[0]: (r[1], r[0]) for r in priorities(g.vertices, 42).collect()}
        want = greedy(edges, order)
        cfg = EngineConfig(chunk_den=0.3)
        ways = [
            mis.local_minima(g),
            mis.prefix_phased(g),
            mis.prefix_phased(g, cut="rank"),
            mis.prefix_phased(g, sub="chunk", cfg=cfg),
            mis.prefix_phased(g, sub="hop", radius=2),
            mis.chunked(g, cfg=cfg),
            mis.hop_compressed(g, radius=1),
            mis.hop_compressed(g, radius=4),
        ]
        for way in ways:
            assert {v for v, x in rows(way).items() if x} == want


def test_paper_constants_and_component_cap(spark):
    g, edges = random_graph(spark, 12, 14, 5)
    want = rows(mis.local_minima(g))
    assert rows(mis.chunked(g, cfg=EngineConfig.paper())) == want
    assert rows(mis.chunked(g, cfg=EngineConfig(chunk_den=0.1, local_cap=1))) == want


def test_sequential_and_serial_batches_equal_pivot(spark):
    g, _ = random_graph(spark, 30, 60, 3)
    want = rows(pivot.cluster(g))
    assert rows(baselines.sequential_pivot(g)) == want
    assert rows(baselines.serial_batches(g, 1.5)) == want


def test_baselines_cover_every_vertex(spark):
    g, edges = random_graph(spark, 25, 40, 4)
    sampled, unlocked = rows(baselines.sampled_is(g, 1.0)), rows(baselines.unlocked_batches(g, 1.5))
    assert set(sampled) == set(unlocked) == set(range(25))
    pivots = {v for v, c in sampled.items() if v == c}
    assert not any(u in pivots and v in pivots for u, v in edges)


def test_cost_matches_pairs(spark):
    g, edges = random_graph(spark, 20, 50, 6)
    found = pivot.cluster(g)
    cid = rows(found)
    row = measure.cost(g, found).first()
    assert row["cost"] == row["pos_dis"] + row["neg_dis"] == brute_cost(20, edges, cid)
    assert measure.agreements(g, found).first()["agreements"] + row["cost"] == 190


def test_exact_and_packing_and_clipping_bounds(spark):
    for seed in range(3):
        g, edges = random_graph(spark, 7, 9, 10 + seed)
        opt = optimum(7, edges)
        part = exact.optimum(g)
        assert sum(r[0] for r in part.select("opt", "component").distinct().collect()) == opt
        assert measure.packing_bound(g).first()[0] <= opt
        eps, lam = 1.0, arboricity.bounds(g)[1]
        clipped = clip.cluster(g, eps, lam, lambda rest: rest.vertices.join(exact.optimum(rest).select("v", "cid"), "v", "left").select("v", F.coalesce("cid", "v").alias("cid")))
        assert measure.cost(g, clipped).first()["cost"] <= (1 + eps) * opt


def test_pivot_mean_is_within_three(spark):
    g, edges = random_graph(spark, 7, 10, 21)
    costs = pivot.best_of(g, 24)[1].select("cost").collect()
    assert sum(r[0] for r in costs) / 24 <= 3 * optimum(7, edges)


def test_best_of_does_not_rise(spark):
    g, _ = random_graph(spark, 20, 40, 8)
    best, costs = pivot.best_of(g, 6)
    assert measure.cost(g, best).first()["cost"] == min(r["cost"] for r in costs.collect())


def test_forest_methods(spark):
    draw = random.Random(9)
    edges = [(draw.randrange(v), v) for v in range(1, 40) if v % 9]
    g = make(spark, 40, edges)
    assert forest.check(g)
    exact_cost = measure.cost(g, forest.cluster(g, "exact")).first()["cost"]
    # Leaves first: each leaf takes its only neighbour.
    near = {v: set() for v in range(40)}
    for u, v in edges:
        near[u].add(v)
        near[v].add(u)
    size, left = 0, dict(near)
    while any(left.values()):
        leaf = next(v for v, x in left.items() if len(x) == 1)
        mate = next(iter(left[leaf]))
        size += 1
        for x in (leaf, mate):
            for y in left.pop(x):
                if y in left:
                    left[y].discard(x)
    assert exact_cost == len(edges) - size
    assert measure.cost(g, forest.from_matching(g, forest.max_matching(g, "tour"))).first()["cost"] == exact_cost
    for how, bound in (("maximal", 2), ("det", 1.5), ("rand", 1.5)):
        assert measure.cost(g, forest.cluster(g, how, 0.5)).first()["cost"] <= bound * exact_cost
    colors = forest.color_reduce(forest.root(g))
    kids = colors.alias("a").join(colors.alias("b"), F.col("a.parent") == F.col("b.v"))
    assert kids.where("a.color = b.color").count() == 0 and colors.agg(F.max("color")).first()[0] < 6
    assert not forest.check(make(spark, 3, [(0, 1), (1, 2), (0, 2)]))


def test_long_path_is_contracted_in_few_rounds(spark):
    g = B.path(spark, 200).stored("path")
    ledger = RoundLedger()
    state = forest.free_vertices(forest.root(g, "tour"), ledger)
    assert len(ledger.rows) <= 12
    assert state.where("free and parent is not null").select("parent").distinct().count() == 100


def test_tight_cases(spark):
    g = B.path(spark, 4)
    assert measure.cost(g, forest.cluster(g, "exact")).first()["cost"] == 1
    assert measure.cost(g, forest.from_matching(g, g.edges.where("u = 1"))).first()["cost"] == 2
    k = 5
    b = B.barbell(spark, k)
    assert measure.cost(b, baselines.singletons(b)).first()["cost"] == k * (k - 1) + 1
    assert measure.cost(b, simple.clique_components(b)).first()["cost"] == k * (k - 1) + 1
    c = B.cliques(spark, 4, 5)
    assert measure.cost(c, simple.clique_components(c)).first()["cost"] == 0


def test_shrink_never_costs_more(spark):
    g, _ = random_graph(spark, 24, 24, 31)
    lam = arboricity.bounds(g)[1]
    start = baselines.component_clusters(g)
    end = clip.shrink(g, start, lam)
    assert measure.cost(g, end).first()["cost"] <= measure.cost(g, start).first()["cost"]
    assert measure.cluster_sizes(end).agg(F.max("size")).first()[0] <= 4 * lam - 2
    assert end.count() == 24


def test_hops_and_rounds(spark):
    g, edges = random_graph(spark, 25, 30, 12)
    near = {v: {v} for v in range(25)}
    for u, v in edges:
        near[u].add(v)
        near[v].add(u)
    for k in (1, 2, 3, 4):
        want = {}
        for root in range(25):
            seen, front = {root: 0}, {root}
            for d in range(1, k + 1):
                front = {w for v in front for w in near[v]} - seen.keys()
                seen |= dict.fromkeys(front, d)
            want |= {(root, v): d for v, d in seen.items()}
        ledger = RoundLedger()
        got = {(r[0], r[1]): r[2] for r in exchange.k_hop(g, k, ledger).collect()}
        assert got == want and len(ledger.rows) == (k - 1).bit_length()
    with pytest.raises(TypeError):
        exchange.local_round(g, g.vertices.select("v", F.array("v").alias("x")), F.col("x"), F.max, congest=True)


def test_degenerate_graphs(spark):
    none = SignedGraph(B.empty(spark).vertices, B.empty(spark).edges)
    assert pivot.cluster(none).count() == 0 and arboricity.bounds(none) == (0, 0)
    alone = B.empty(spark, 4)
    assert rows(pivot.cluster(alone)) == {v: v for v in range(4)}
    dirty = normalise(spark.createDataFrame([(1, 1), (2, 1), (1, 2), (None, 3)], "u long, v long"))
    assert [tuple(r) for r in dirty.edges.collect()] == [(1, 2)]
    pairs = B.pairs(spark, 3)
    assert rows(mis.pairs_only(pairs)) == rows(mis.local_minima(pairs))


def test_components(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, 101), (102, 101), (7, 7)]
    got = rows(components(spark.createDataFrame(edges, "u long, v long")))
    assert all(got[v] == 0 for v in range(61)) and got[102] == 100 and len(got) == 64


def test_arboricity_bounds_hold(spark):
    k6 = B.cliques(spark, 1, 6).stored("k6")
    low, high = arboricity.bounds(k6)
    assert low == 3 and high >= 3
    low, high = arboricity.bounds(B.star(spark, 30).stored("star"))
    assert low == 1 and high >= 1


def test_near_edges_of_large_groups_and_common_shingles(spark):
    from signedcluster.sources import builders as B

    sets = {k: {"a", "b", "c", "d"} for k in range(260)} | {300 + k: {"a", "b", "c", f"x{k}"} for k in range(5)} | {400: {"a", "y", "z"}, 401: {"q"}, 402: {"q", "r"}}
    rows = spark.createDataFrame([(k, s) for k, x in sets.items() for s in x], "id long, s string")
    for threshold in (0.5, 0.8):
        want = {(u, v) for u in sets for v in sets if u < v and len(sets[u] & sets[v]) >= threshold * len(sets[u] | sets[v])}
        for most in (512, 2):
            got = [tuple(r) for r in B.jaccard_edges(rows, threshold, most).select("u", "v").collect()]
            assert len(got) == len(set(got)) and set(got) == want


def test_unsolved_components_are_listed_with_a_null_optimum(spark):
    from signedcluster.model import normalise
    from signedcluster.operators import exact

    edges = [(k, k + 1) for k in range(14)] + [(20, 21), (21, 22)]
    g = normalise(spark.createDataFrame(edges, "u long, v long"), spark.range(30).select(F.col("id").alias("v")))
    got = {r["v"]: (r["cid"], r["opt"]) for r in exact.optimum(g).collect()}
    assert set(got) == {*range(15), 20, 21, 22}
    assert all(got[k] == (None, None) for k in range(15)) and all(got[k][1] == 1 for k in (20, 21, 22))
