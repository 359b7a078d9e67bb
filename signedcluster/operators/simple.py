"""Constant-round rule: components that are cliques stay whole, every other vertex is alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.model import SignedGraph


def clique_components(g: SignedGraph) -> DataFrame:
    """``(v, cid)`` in a fixed number of exchanges whatever the size.

    A closed neighbourhood is named by its minimum. If every neighbour has the same name and degree, and the name has
    degree + 1 such vertices, they are all of a component and pairwise adjacent; the converse is immediate.
    """
    near = g.adj.groupBy("v").agg(F.min("w").alias("low"), F.count("*").alias("d")).select("v", F.least("v", "low").alias("name"), "d")
    there = near.select(F.col("v").alias("w"), F.col("name").alias("name_w"), F.col("d").alias("d_w"))
    same = g.adj.join(near, "v").join(there, "w").groupBy("v", "name", "d").agg(F.bool_and((F.col("name") == F.col("name_w")) & (F.col("d") == F.col("d_w"))).alias("same"))
    whole = same.groupBy("name").agg((F.bool_and("same") & (F.count("*") == F.max("d") + 1)).alias("clique")).where("clique").select("name")
    inside = same.join(whole, "name", "left_semi").select("v", F.col("name").alias("cid"))
    return g.vertices.join(inside, "v", "left").select("v", F.coalesce("cid", "v").alias("cid"))
