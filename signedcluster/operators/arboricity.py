"""Bounds of the arboricity by rounds of peeling low-degree vertices."""

from __future__ import annotations

from math import ceil, floor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.model import RoundLedger, SignedGraph
from signedcluster.shared import discard, materialize


def bounds(g: SignedGraph, eta: float = 0.1, ledger: RoundLedger | None = None) -> tuple[int, int]:
    """(lower, upper). Each round removes the vertices whose degree is at most (1 + eta) times the mean.

    Lower: the densest remaining graph met. Upper: orienting every edge from the vertex peeled first (ties by id) leaves
    no cycle and as many edges out of a vertex as its degree when peeled, and those split into that many forests.
    """
    edges, low, high, step = materialize(g.edges, "peel"), 0, 0, 0
    while True:
        deg = materialize(edges.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg(F.count("*").alias("d")), "deg")
        n, total = deg.agg(F.count("*"), F.coalesce(F.sum("d"), F.lit(0))).first()
        if not n:
            return low, high
        low = max(low, ceil(total / 2 / max(n - 1, 1)))
        limit = floor((1 + eta) * total / n)
        peeled = deg.where(F.col("d") <= limit)
        high = max(high, peeled.agg(F.max("d")).first()[0])
        keep = deg.where(F.col("d") > limit).select("v")
        rest = edges.join(keep, "v", "left_semi").join(keep.select(F.col("v").alias("u")), "u", "left_semi").select("u", "v")
        if ledger is not None:
            ledger.add("peel", 0, step, total // 2, exchanges=3)
        old, edges, step = edges, materialize(rest, "peel"), step + 1
        discard(old)


def bounds_frame(g: SignedGraph, eta: float = 0.1) -> DataFrame:
    low, high = bounds(g, eta)
    return g.edges.sparkSession.createDataFrame([(low, high)], "lo long, hi long")
