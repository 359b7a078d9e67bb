"""A complete signed graph by its positive edges, the engine's settings, and the record of rounds."""

from __future__ import annotations

import uuid
from contextlib import contextmanager
from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.shared import materialize


@dataclass(frozen=True)
class EngineConfig:
    """Defaults of the methods; results of the maximal-independent-set methods never depend on them, only costs do."""

    seed: int = 42
    prefix_c: float = 1.0
    chunk_den: float = 1.0
    iter_mult: float = 8.0
    hop_row_cap: int = 50_000_000
    local_cap: int = 5_000
    exact_cap: int = 10

    @classmethod
    def paper(cls) -> EngineConfig:
        """The constants of the published analysis."""
        return cls(chunk_den=100, iter_mult=2000)

    def with_(self, **changes) -> EngineConfig:
        return replace(self, **changes)


@dataclass
class RoundLedger:
    """A row for each round: method, phase, step, rows alive, largest group, exchanges."""

    rows: list[tuple] = field(default_factory=list)

    def add(self, method: str, phase: int, step: int, rows: int, max_group: int = 0, exchanges: int = 1) -> None:
        self.rows.append((method, phase, step, int(rows), int(max_group), int(exchanges)))

    @property
    def rounds(self) -> int:
        return sum(r[5] for r in self.rows)

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame(self.rows, "method string, phase int, step int, rows long, max_group long, exchanges int")


@contextmanager
def measured_stages(spark):
    """A list that gets the jobs and the stages (skipped ones left out) that Spark ran inside the block."""
    context, group, out = spark.sparkContext, uuid.uuid4().hex, []
    context.setJobGroup(group, "measured")
    try:
        yield out
    finally:
        tracker = context.statusTracker()
        jobs = tracker.getJobIdsForGroup(group)
        found = [x for j in jobs if (info := tracker.getJobInfo(j)) for s in info.stageIds if (x := tracker.getStageInfo(s))]
        out += [len(jobs), sum(x.numCompletedTasks > 0 for x in found)]
        context.setLocalProperty("spark.jobGroup.id", None)


class SignedGraph:
    """``vertices(v)`` and canonical positive ``edges(u, v)`` with ``u < v``; every other pair is negative."""

    def __init__(self, vertices: DataFrame, edges: DataFrame, given: DataFrame | None = None):
        """``given``: vertices known apart from the edges' ends, if ``vertices`` was made from both."""
        self.vertices, self.edges, self.given = vertices, edges, given

    def stored(self, label: str = "graph") -> SignedGraph:
        """The same graph in the shared folder; edges are computed once, also where vertices depend on them."""
        edges = materialize(self.edges, label)
        vertices = self.vertices if self.given is None else closed(self.given, edges)
        return SignedGraph(materialize(vertices, label), edges)

    @cached_property
    def n(self) -> int:
        return self.vertices.count()

    @cached_property
    def m(self) -> int:
        return self.edges.count()

    @cached_property
    def adj(self) -> DataFrame:
        back = self.edges.select(F.col("v").alias("u"), F.col("u").alias("v"))
        return self.edges.unionByName(back).select(F.col("u").alias("v"), F.col("v").alias("w"))

    def degrees(self) -> DataFrame:
        """``(v, d)`` of all vertices, zero included."""
        found = self.adj.groupBy("v").agg(F.count("*").alias("d"))
        return self.vertices.join(found, "v", "left").select("v", F.coalesce("d", F.lit(0)).cast("long").alias("d"))

    @cached_property
    def max_degree(self) -> int:
        return self.adj.groupBy("v").count().agg(F.max("count")).first()[0] or 0

    def induced(self, keep: DataFrame) -> SignedGraph:
        """The subgraph on ``keep(v)``."""
        one = self.edges.join(keep, "v", "left_semi")
        return SignedGraph(self.vertices.join(keep, "v", "left_semi"), one.join(keep.select(F.col("v").alias("u")), "u", "left_semi").select("u", "v"))


def normalise(pairs: DataFrame, vertices: DataFrame | None = None) -> SignedGraph:
    """A graph from any ``(u, v)`` pairs: nulls and self loops go, pairs are oriented and made distinct."""
    edges = (
        pairs.where("u is not null and v is not null and u <> v")
        .select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v"))
        .distinct()
    )
    given = edges.select("v").limit(0) if vertices is None else vertices.select(F.col("v").cast("long").alias("v")).where("v is not null")
    return SignedGraph(closed(given, edges), edges, given)


def closed(given: DataFrame, edges: DataFrame) -> DataFrame:
    """The given vertices and all ends of edges."""
    return given.unionByName(edges.select(F.explode(F.array("u", "v")).alias("v"))).distinct()
