"""Connected components by alternating star contractions (a logarithmic number of shuffle rounds on these graphs)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.shared import discard, measured


def _large_star(edges: DataFrame) -> DataFrame:
    """Every neighbour above a vertex is linked to the smallest vertex around that vertex."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    smallest = both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("m"))
    return both.where("v > u").join(smallest, "u").select(F.col("m").alias("u"), "v").where("u < v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Edges are ``u < v``: v and its smaller neighbours are linked to the smallest of them."""
    lowest = edges.groupBy("v").agg(F.min("u").alias("m"))
    linked = edges.join(lowest, "v")
    return (
        linked.select(F.col("m").alias("u"), F.col("u").alias("v"))
        .where("u < v")
        .unionByName(lowest.select(F.col("m").alias("u"), "v"))
        .distinct()
    )


def components(edges: DataFrame, on_round=None, max_rounds: int = 60) -> DataFrame:
    """Return ``(v, comp)`` for every endpoint of ``edges(u, v)``; ``comp`` is the smallest id reachable.

    Self loops and repeated or reversed edges are accepted; an empty input gives an empty result.  Each round writes its
    edges to the shared folder, so a lost executor never reaches further back than one round.
    """
    now = (
        edges.where("u is not null and v is not null and u <> v")
        .select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
        .distinct()
    )
    digest, seen = F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("digest"), None
    now, found = measured(now, "cc", digest)
    for step in range(max_rounds):
        state = (found["rows"], found["digest"])
        if on_round is not None:
            on_round(step, state[0])
        if state == seen or state[0] == 0:
            break
        seen = state
        old = now
        now, found = measured(_small_star(_large_star(old)), "cc", digest)
        discard(old)
    else:
        raise RuntimeError("components did not settle")
    return now.groupBy("v").agg(F.min("u").alias("comp")).unionByName(
        now.select(F.col("u").alias("v")).distinct().select("v", F.col("v").alias("comp"))
    )
