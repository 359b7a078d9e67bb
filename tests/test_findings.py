"""Cases that larger tables brought up."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from signedcluster.functions.priority import priorities
from signedcluster.model import EngineConfig, normalise
from signedcluster.operators import baselines, exchange, measure, mis, pivot, relational


def make(spark, n, edges):
    return normalise(spark.createDataFrame(edges, "u long, v long"), spark.range(n).select(F.col("id").alias("v"))).stored("test")


def random_edges(n, m, seed):
    return random.Random(seed).sample(list(itertools.combinations(range(n), 2)), m)


def rows(df):
    return {r[0]: r[1] for r in df.collect()}


def test_pairs_only_beside_larger_components(spark):
    edges = [(0, 1), (2, 3), (4, 5), (5, 6), (6, 7), (8, 9), (9, 10), (8, 10), *[(20 + a, 20 + b) for a, b in random_edges(12, 20, 3)]]
    for seed in (1, 2, 42):
        g = make(spark, 34, edges)
        prio = priorities(g.vertices, seed)
        assert rows(mis.pairs_only(g, prio)) == rows(mis.local_minima(g, prio))


def test_packing_and_sequential_scan_list_no_wedges(spark, monkeypatch):
    edges = [(0, k) for k in range(1, 120)] + [(200 + a, 200 + b) for a, b in random_edges(20, 60, 4)]
    g = make(spark, 220, edges)
    monkeypatch.setattr(measure, "wedges", lambda g: pytest.fail("wedges listed"))
    # A star of 119 leaves alone has 59 triangles without a common pair; each takes two edges.
    assert 55 <= measure.packing_bound(make(spark, 120, edges[:119])).first()[0] <= 59
    assert 55 <= measure.packing_bound(g).first()[0] <= len(edges) // 2
    monkeypatch.setattr(type(g), "m", 10**9)
    assert rows(baselines.sequential_pivot(g)) == rows(pivot.cluster(g))


def test_table_graphs_read_their_tables(spark, tmp_path):
    from signedcluster.plans.catalogue import QUERIES
    from signedcluster.sources import builders as B

    spark.range(40).select((F.col("id") * 7 + 3).alias("p_partkey")).write.parquet(str(tmp_path / "part.parquet"))
    spark.range(40).select((F.col("id") * 5).alias("c_custkey")).write.parquet(str(tmp_path / "customer.parquet"))
    orders = [(c, 100 * c + i) for c, n in ((1, 3), (2, 5), (3, 3), (4, 3), (5, 3), (6, 3), (7, 8), (8, 2)) for i in range(n)]
    spark.createDataFrame(orders, "o_custkey long, o_orderkey long").write.parquet(str(tmp_path / "orders.parquet"))
    got = B.numbered(spark.read.parquet(str(tmp_path / "part.parquet")), "p_partkey").orderBy("id").collect()
    assert [tuple(r) for r in got] == [(k, 7 * k + 3) for k in range(40)]
    for name in ("grid", "scalefree_customers"):
        plan = QUERIES[f"graph_{name}"](spark, str(tmp_path))._jdf.queryExecution().toString()
        assert "parquet" in plan and "Range (" not in plan
    found = [tuple(r) for r in QUERIES["w_tight_barbell"](spark, str(tmp_path)).collect()]
    assert found == [(3, 2, 2, 14), (5, 0, 0, 0), (8, 0, 0, 0)]


def test_dense_graphs_in_bits(spark, monkeypatch):
    g = make(spark, 150, random_edges(148, 500, 7))
    monkeypatch.setattr(exchange, "BITS_WEDGES", 1 << 60)
    pairs = {k: {tuple(r) for r in exchange.k_hop(g, k).collect()} for k in (2, 3)}
    open_wedges = {tuple(r) for r in relational.open_wedges(g).collect()}
    dist = rows(exchange.simulate_distances(g, g.vertices.where("v < 2"), 4, 2))
    monkeypatch.setattr(exchange, "BITS_WEDGES", 0)
    for k in (2, 3):
        got = [tuple(r) for r in exchange.k_hop(g, k).collect()]
        assert len(got) == len(pairs[k]) and set(got) == pairs[k]
        assert rows(exchange.ball_sizes(g, k)) == {v: sum(r[0] == v for r in pairs[k]) for v in range(150)}
    got = [tuple(r) for r in relational.open_wedges(g).collect()]
    assert len(got) == len(open_wedges) and set(got) == open_wedges
    assert rows(exchange.simulate_distances(g, g.vertices.where("v < 2"), 4, 2, row_cap=0)) == dist


def test_copies_are_bits(spark):
    g = make(spark, 40, random_edges(36, 90, 8))
    found = pivot.runs(g, 3).collect()
    for c in range(3):
        assert {r["v"]: r["cid"] for r in found if r["copy"] == c} == rows(pivot.cluster(g, priorities(g.vertices, 42 + c)))


def test_near_sets_send_hashes_only(spark, monkeypatch):
    from signedcluster.sources import builders as B

    seen = {}
    keep = B.materialize
    monkeypatch.setattr(B, "materialize", lambda df, label="table": seen.setdefault(label, keep(df, label)))
    texts = ["a b c d e f g h", "A b, c d e f g i", "a b c d e f g h", "x", "", None, "x"]
    found = B.near_sets(spark.createDataFrame(list(enumerate(texts)), "id long, x string"), 0.5, shingles_of=B.shingle_sets).collect()
    assert sorted(tuple(r) for r in found) == [(0, 1), (0, 2), (1, 2), (3, 6)]
    assert all("string" not in dict(df.dtypes).values() for df in seen.values())


def test_near_sets_send_a_text_once_to_a_block(spark, monkeypatch):
    from signedcluster.sources import builders as B

    seen = {}
    keep = B.materialize
    monkeypatch.setattr(B, "materialize", lambda df, label="table": seen.setdefault(label, keep(df, label)))
    draw = random.Random(5)
    base = [f"w{draw.randrange(900)}" for _ in range(40)]
    texts = [" ".join([*base, f"end{k}"]) for k in range(60)] + [" ".join(f"w{draw.randrange(900)}" for _ in range(n)) for n in range(30)]
    texts += [" ".join(base[:28]), "Ä b\tc d e", "ä B c d e", "ä b c d e f"]
    sets = {k: {tuple(w[i : i + 5]) for i in range(max(len(w) - 5, 0) + 1)} for k, t in enumerate(texts) for w in [t.lower().split()]}
    want = {(u, v) for u, v in itertools.combinations(sets, 2) if len(sets[u] & sets[v]) >= 0.5 * len(sets[u] | sets[v])}
    frame = spark.createDataFrame(list(enumerate(texts)), "id long, x string")
    for most, few in ((512, 1 << 19), (7, 1 << 19), (7, 0)):
        seen.clear()
        monkeypatch.setattr(B, "FEW_IDS", few)
        found = [tuple(r) for r in B.near_sets(frame, 0.5, most, shingles_of=B.shingle_sets).select("u", "v").collect()]
        assert len(found) == len(set(found)) and set(found) == want
        # Each pair is met once, however many shingles it shares; a text goes to the cells of its block only.
        pairs = [tuple(r) for r in seen["candidates"].select("u", "v").collect()]
        assert len(pairs) == len(set(pairs))
        assert seen["needed"].groupBy("id").count().agg(F.max("count")).first()[0] <= -(-len(texts) // most)
    # Shingles that a single text has end in the task that counts them.
    assert seen["rarest_shingles"].count() < 60


def test_doc_bench_sends_hashes_of_items_only(spark, tmp_path, monkeypatch):
    from signedcluster.sources import builders as B

    seen = {}
    keep = B.materialize
    monkeypatch.setattr(B, "materialize", lambda df, label="table": seen.setdefault(label, keep(df, label)))
    draw = random.Random(6)
    texts = [" ".join(f"w{draw.randrange(2000)}" for _ in range(80)) for _ in range(30)] + ["One two", "", None, "q one TWO three four five r"]
    items = ["one two three four five", "one, TWO", "x y z"] + [" ".join(texts[7].split()[a : a + 9]) for a in (0, 40)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(list(enumerate(items)), "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    g = B.doc_bench(spark, str(tmp_path))
    got = {(u % 10**12, v % 10**12) for u, v in g.edges.collect()}
    assert got == {(33, 0), (30, 1), (7, 3), (7, 4)}
    assert {r[0] % 10**12 for r in seen["touched"].collect()} == {7, 30, 33}
    monkeypatch.setattr(B, "FEW_IDS", 0)
    assert {(u % 10**12, v % 10**12) for u, v in B.doc_bench(spark, str(tmp_path)).edges.collect()} == got


def test_rounds_count_in_the_job_that_writes(spark):
    import threading

    from signedcluster.model import RoundLedger, measured_stages
    from signedcluster.plans.catalogue import at_once
    from signedcluster.shared import measured

    back, seen = measured(spark.range(7), "seven", F.sum("id").alias("total"))
    assert (back.count(), seen["rows"], seen["total"]) == (7, 7, 21)
    g = make(spark, 40, random_edges(40, 90, 9))
    ledger = RoundLedger()
    with measured_stages(spark) as stages:
        killed = mis.kill_rounds(mis.lower_edges(g, priorities(g.vertices, 42)), ledger)
    low = rows(mis.members(g, killed))
    assert low == rows(mis.local_minima(g)) and sum(low.values()) > 0
    # Two frames are written in a round, and what is counted takes no job of its own (a broadcast may).
    assert stages[0] <= 9 * len(ledger.rows) + 4
    both = threading.Barrier(2, timeout=60)
    assert at_once([lambda k=k: (both.wait(), k)[1] for k in range(2)]) == [0, 1]
