"""Operators around the methods: lookups, interval and as-of joins, windows, set operations, SQL functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from signedcluster.model import SignedGraph
from signedcluster.operators import exchange


def lookup(edges: DataFrame, state: DataFrame, side: str = "u", hint: str | None = None) -> DataFrame:
    """State of one end beside each edge; a hint (broadcast, merge, shuffle_hash) only where its size is known."""
    there = state.withColumnRenamed("v", side)
    return edges.join(there.hint(hint) if hint else there, side)


def isolated_vertices(g: SignedGraph) -> DataFrame:
    return g.vertices.join(g.adj.select("v"), "v", "left_anti")


def open_wedges(g: SignedGraph) -> DataFrame:
    """``(a, b, c)``: bad triangles with centre b. In dense graphs a task tests the wedges that end in its block of
    vertices against the bits of these, so that only open ones leave it; else wedges are joined with the edges."""
    if exchange.in_bits(g):

        def work(near, bits, names, b, blocks):
            for v, x in near:
                ends = x[x % blocks == b]
                for k in range(0, len(ends), 256):
                    c = ends[k : k + 256]
                    at = c // blocks
                    linked = bits[x][:, at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)
                    i, j = np.nonzero((linked == 0) & (x[:, None] < c[None, :]))
                    yield {"a": names[x[i]], "b": np.full(len(i), names[v]), "c": names[c[j]]}

        return exchange.column_blocks(g, work, "a long, b long, c long")
    one = g.adj.select(F.col("v").alias("b"), F.col("w").alias("a"))
    both = one.join(g.adj.select(F.col("v").alias("b"), F.col("w").alias("c")), "b").where("a < c")
    return both.join(g.edges.select(F.col("u").alias("a"), F.col("v").alias("c")), ["a", "c"], "left_anti").select("a", "b", "c")


def within_gap(rows: DataFrame, key: str, at: str, gap: int) -> DataFrame:
    """All pairs ``(u, v)`` of a key whose times differ by at most ``gap``: a range join on an equality of (key, bin)."""
    bins = F.floor(F.col(at) / gap)
    left = rows.select(F.col(key).alias("k"), F.col("id").alias("u"), F.col(at).alias("tu"), F.explode(F.array(bins, bins + 1)).alias("b"))
    right = rows.select(F.col(key).alias("k"), F.col("id").alias("v"), F.col(at).alias("tv"), bins.alias("b"))
    # The earlier row probes its own bin and the next; rows at one time are ordered by id.
    later = (F.col("tv") > F.col("tu")) | ((F.col("tv") == F.col("tu")) & (F.col("v") > F.col("u")))
    return left.join(right, ["k", "b"]).where(later & (F.col("tv") - F.col("tu") <= gap)).select("u", "v")


def as_of(probe: DataFrame, facts: DataFrame, key: str, at: str) -> DataFrame:
    """The last fact of the key before or at each probe row's time: one union, one window, no inequality join.

    ``probe(id, key, at)`` and ``facts(id, key, at)``; result ``(id, fact)`` with null where there is none.
    """
    both = probe.select("id", key, at, F.lit(None).cast("long").alias("f"), F.lit(1).alias("kind")).unionByName(
        facts.select(F.lit(None).cast("long").alias("id"), key, at, F.col("id").alias("f"), F.lit(0).alias("kind"))
    )
    w = Window.partitionBy(key).orderBy(at, "kind", "f").rowsBetween(Window.unboundedPreceding, 0)
    return both.select("id", "kind", F.last("f", ignorenulls=True).over(w).alias("fact")).where("kind = 1").select("id", "fact")


def sessions(rows: DataFrame, key: str, at: str, gap: int) -> DataFrame:
    """Running number of the session of each row: a new one after a pause above ``gap``."""
    w = Window.partitionBy(key).orderBy(at, "id")
    cut = F.coalesce(F.col(at) - F.lag(at).over(w) > gap, F.lit(True)).cast("long")
    marked = rows.withColumn("cut", cut)
    return marked.withColumn("session", F.sum("cut").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("cut")


def top_k(rows: DataFrame, k: int, by: str, tie: str) -> DataFrame:
    """The k rows with the largest ``by``, ties by ``tie``: a bounded heap a task, merged once."""
    return rows.orderBy(F.desc(by), tie).limit(k)


def host(url: Column) -> Column:
    return F.regexp_extract(url, "^https?://([^/?#]+)", 1)


@udtf(returnType="u: bigint, v: bigint")
class ClusterPairs:
    """Rows of the pairs inside one cluster, for use from SQL on clusters of bounded size."""

    def eval(self, members: list):
        members = sorted(members)
        for i, u in enumerate(members):
            for v in members[i + 1 :]:
                yield u, v


def register_sql(spark: SparkSession) -> None:
    spark.udtf.register("cluster_pairs", ClusterPairs)
