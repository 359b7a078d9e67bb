"""Degree clipping around any inner clustering, and clusters kept below the size an optimum can have."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators import arboricity, pivot
from signedcluster.shared import materialize


def threshold(eps: float, lam: float) -> float:
    if eps <= 0:
        raise ValueError("eps must be positive")
    return 8 * (1 + eps) / eps * lam


def split(g: SignedGraph, eps: float, lam: float) -> DataFrame:
    """``(v, d, high)``: strictly above the threshold is high."""
    return g.degrees().withColumn("high", F.col("d") > F.lit(threshold(eps, lam)))


def cluster(g: SignedGraph, eps: float, lam: float, inner) -> DataFrame:
    """High-degree vertices alone, ``inner(graph) -> (v, cid)`` on the rest.

    ``lam`` must be an upper bound of the arboricity. The high set is up to a share of all vertices, so it is joined by
    shuffle unless Spark measures it small enough.
    """
    marked = materialize(split(g, eps, lam).select("v", "high"), "clip")
    rest = g.induced(marked.where("not high").select("v"))
    rest = SignedGraph(rest.vertices, materialize(rest.edges, "rest"))
    return inner(rest).select("v", "cid").unionByName(marked.where("high").select("v", F.col("v").alias("cid")))


def three_approx(g: SignedGraph, lam: int | None = None, method: str = "local", ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Expected 3-approximation: eps = 2, so the threshold is 12 lam, around pivot clustering."""
    lam = arboricity.bounds(g)[1] if lam is None else lam
    return cluster(g, 2.0, lam, lambda rest: pivot.cluster(rest, None, method, ledger, cfg))


def stats(g: SignedGraph, eps: float, lam: float) -> DataFrame:
    """Number of high vertices and of edges that touch one."""
    marked = materialize(split(g, eps, lam), "clip")
    high = marked.where("high").select("v")
    touched = g.adj.join(high, "v", "left_semi").select(F.least("v", "w").alias("a"), F.greatest("v", "w").alias("b")).distinct()
    return high.agg(F.count("*").alias("high")).join(touched.agg(F.count("*").alias("edges_touched")), F.lit(True), "inner")


def shrink(g: SignedGraph, clustering: DataFrame, lam: int, max_rounds: int = 10_000) -> DataFrame:
    """Move vertices out of clusters above 4 lam - 2 without raising the cost.

    In such a cluster some vertex has at most half of the others as neighbours; the one with fewest leaves (one a cluster
    and round). The loop ends when no cluster is above the limit or none has such a vertex (lam was too small).
    """
    now = materialize(clustering.select("v", "cid"), "shrink")
    for _ in range(max_rounds):
        sizes = now.groupBy("cid").agg(F.count("*").alias("s")).where(F.col("s") > 4 * lam - 2)
        large = materialize(now.join(sizes, "cid"), "large")
        if large.isEmpty():
            break
        inside = g.adj.join(large.select("v", "cid", "s"), "v").join(large.select(F.col("v").alias("w"), F.col("cid").alias("cw")), "w")
        deg = inside.where("cid = cw").groupBy("v").agg(F.count("*").alias("d"))
        loose = large.join(deg, "v", "left").select("v", "cid", "s", F.coalesce("d", F.lit(0)).alias("d")).where("2 * d <= s - 1")
        leave = materialize(loose.groupBy("cid").agg(F.min(F.struct("d", "v")).alias("x")).select(F.col("x.v").alias("v")), "leave")
        if leave.isEmpty():
            break
        left = now.join(leave, "v", "left_anti")
        # A cluster whose naming member left is named after its smallest member again.
        name = left.groupBy("cid").agg(F.min("v").alias("name"))
        now = materialize(left.join(name, "cid").select("v", F.col("name").alias("cid")).unionByName(leave.select("v", F.col("v").alias("cid"))), "shrink")
    return now
