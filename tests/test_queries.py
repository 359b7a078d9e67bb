"""Queries against their SQL in DuckDB on the smallest tables."""

import collections
import os

import duckdb
import pytest

FOLDER = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

pytestmark = pytest.mark.skipif(not os.path.isdir(FOLDER), reason="no test tables")

#: One or two of each family; all are compared by the driver.
NAMES = "greedy_mis mis_prefix_hop clip_pivot cc_three_approx forest_exact w_eps_sweep k_hop_pairs pivot_best_of join_asof stream_session udtf_pairs".split()


def canonical(v):
    return round(float(v), 6) if isinstance(v, float) or type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    from signedcluster.plans.catalogue import ORACLES, QUERIES

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{FOLDER}/{t}.parquet'")
    df = QUERIES[name](spark, FOLDER)
    cols = sorted(df.columns)
    got = collections.Counter(tuple(canonical(r[c]) for c in cols) for r in df.collect())
    cur = con.execute(ORACLES[name])
    at = [x[0] for x in cur.description]
    assert sorted(at) == cols
    want = collections.Counter(tuple(canonical(r[at.index(c)]) for c in cols) for r in cur.fetchall())
    assert got == want


def test_entry_runs(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_sinks_round_trip(spark, tmp_path):
    from signedcluster.model import RoundLedger
    from signedcluster.sources import builders as B
    from signedcluster.sources import tables as T

    g = B.cliques(spark, 3, 4)
    for fmt in ("csv", "json"):
        g.edges.write.format(fmt).save(str(tmp_path / fmt))
        assert T.edge_list(spark, str(tmp_path / fmt), fmt).m == 18
    ledger = RoundLedger()
    ledger.add("x", 0, 0, 5)
    T.write_ledger(spark, ledger, str(tmp_path / "ledger"))
    assert spark.read.json(str(tmp_path / "ledger")).count() == 1
