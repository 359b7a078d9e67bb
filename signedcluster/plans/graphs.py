"""Named graphs of the given tables."""

from __future__ import annotations

from pyspark.sql import SparkSession

from signedcluster.model import SignedGraph
from signedcluster.shared import materialize
from signedcluster.sources import builders as B
from signedcluster.sources.tables import load


def _count(spark, folder, name):
    return load(spark, folder, name).count()


def _cells(spark, folder, name, key):
    """A vertex for each row of a table, numbered in the order of its key."""
    return materialize(B.numbered(load(spark, folder, name), key).select("id"), "cells")


BUILDERS = {
    "geo": B.geo,
    "event_chain": B.event_chain,
    "conv_chain": B.conv_chain,
    "order_part": B.order_part,
    "part_supp": B.part_supp,
    "copart_1": lambda s, f: B.copart(s, f, 1),
    "copart_2": lambda s, f: B.copart(s, f, 2),
    "copart_3": lambda s, f: B.copart(s, f, 3),
    "emb_25": lambda s, f: B.emb(s, f, 0.25),
    "emb_30": lambda s, f: B.emb(s, f, 0.30),
    "emb_35": lambda s, f: B.emb(s, f, 0.35),
    "emb_40": lambda s, f: B.emb(s, f, 0.40),
    "emb_50": lambda s, f: B.emb(s, f, 0.50),
    "page_host": B.page_host,
    "doc_exact": B.doc_exact,
    "doc_near_5": lambda s, f: B.doc_near(s, f, 0.5),
    "doc_near_8": lambda s, f: B.doc_near(s, f, 0.8),
    "doc_bench": B.doc_bench,
    "scalefree_customers": lambda s, f: B.scalefree_of(_cells(s, f, "customer", "c_custkey")),
    "scalefree_orders": lambda s, f: B.scalefree(s, _count(s, f, "orders")),
    "grid": lambda s, f: B.grid(_cells(s, f, "part", "p_partkey")),
    "band": lambda s, f: B.band(s, _count(s, f, "orders")),
}


def graph(spark: SparkSession, folder: str, name: str, stored: bool = True) -> SignedGraph:
    """A named graph; ``stored`` writes its edges once, as every loop reads them many times."""
    g = BUILDERS[name](spark, folder)
    return g.stored(name) if stored else g
