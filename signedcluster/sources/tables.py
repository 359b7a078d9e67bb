"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signedcluster.model import RoundLedger, SignedGraph, normalise


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def edge_list(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> SignedGraph:
    """A graph from files of ``u, v`` pairs (parquet, csv or json), with a fixed schema; see :func:`normalise`."""
    return normalise(spark.read.schema("u long, v long").options(**options).format(fmt).load(path))


def write(df: DataFrame, path: str, mode: str = "errorifexists", by: str = "v", parts: int | None = None) -> None:
    """Parquet dealt by hash of ``by``, sorted inside files so that later joins and scans can skip row groups."""
    dealt = df.repartition(parts, by) if parts else df.repartition(by)
    dealt.sortWithinPartitions(by).write.mode(mode).parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, by: str = "v", mode: str = "errorifexists") -> None:
    """A catalogue table bucketed by ``by``: joins on it with a table of as many buckets need no exchange."""
    df.write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def write_ledger(spark: SparkSession, ledger: RoundLedger, path: str, mode: str = "errorifexists") -> None:
    ledger.frame(spark).coalesce(1).write.mode(mode).json(path)


def register(g: SignedGraph, clustering: DataFrame | None = None, prefix: str = "") -> None:
    """Temporary views ``vertices``, ``edges`` and ``clustering`` for SQL."""
    g.vertices.createOrReplaceTempView(f"{prefix}vertices")
    g.edges.createOrReplaceTempView(f"{prefix}edges")
    if clustering is not None:
        clustering.createOrReplaceTempView(f"{prefix}clustering")


def packed(kind: int, key):
    """Ids of several tables in one long: kind * 10^12 + key."""
    return F.lit(kind * 10**12).cast("long") + (F.col(key) if isinstance(key, str) else key).cast("long")
