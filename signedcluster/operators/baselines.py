"""The methods that the engine is compared with."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.priority import SPAN, priorities, priority
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators import mis as M
from signedcluster.operators import forest, pivot
from signedcluster.operators.components import components
from signedcluster.shared import materialize, measured


def sequential_pivot(g: SignedGraph, prio: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Ground truth: vertices in order become pivots unless an earlier neighbour is one; the others join the earliest
    pivot next to them. One task scans all lower edges in the order of their later ends, whatever their number: it sorts
    them through its disk and holds the pivots found so far alone."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    low = M.lower_edges(g, prio).select("v", F.col("pv").alias("p"), "w", "pw")
    rows = low.unionByName(prio.select("v", "p", F.lit(None).cast("long").alias("w"), F.lit(-1).cast("long").alias("pw")))

    def scan(batches):
        pivots: set[int] = set()
        now, cid = None, None
        for batch in batches:
            out_v, out_c = [], []
            # A vertex begins with its own row, its lower neighbours follow in order.
            for v, w in zip(batch.column("v").to_pylist(), batch.column("w").to_pylist(), strict=True):
                if w is None:
                    if now is not None:
                        out_v.append(now)
                        out_c.append(now if cid is None else cid)
                        if cid is None:
                            pivots.add(now)
                    now, cid = v, None
                elif cid is None and w in pivots:
                    cid = w
            yield pa.RecordBatch.from_arrays([pa.array(out_v, pa.int64()), pa.array(out_c, pa.int64())], ["v", "cid"])
        if now is not None:
            yield pa.RecordBatch.from_arrays([pa.array([now], pa.int64()), pa.array([now if cid is None else cid], pa.int64())], ["v", "cid"])

    return rows.repartition(1).sortWithinPartitions("p", "v", "pw", "w").mapInArrow(scan, "v long, cid long")


def sampled_is(g: SignedGraph, eps: float = 0.5, prio: DataFrame | None = None, ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig(), max_phases: int = 400) -> DataFrame:
    """Each phase samples alive vertices with probability eps / (largest alive degree), drops sampled vertices next to
    each other, and makes the rest pivots; neighbours join the pivot that is earliest in the initial order."""
    prio = materialize(priorities(g.vertices, cfg.seed) if prio is None else prio, "prio")
    alive, edges, out = g.vertices, g.edges, None
    for phase in range(max_phases):
        live = SignedGraph(alive, edges)
        degree = live.max_degree
        if degree == 0:
            break
        draw = priority(F.col("v"), cfg.seed + 1_000_003 * (phase + 1)) < F.lit(int(min(1.0, eps / degree) * SPAN))
        picked = alive.where(draw)
        clash = live.adj.join(picked, "v", "left_semi").join(picked.select(F.col("v").alias("w")), "w", "left_semi").select("v").distinct()
        pivots = materialize(picked.join(clash, "v", "left_anti"), "pivots")
        made = pivots.withColumn("in_mis", F.lit(True)).join(prio, "v")
        near = live.adj.join(made.select(F.col("v").alias("w"), "p"), "w").groupBy("v").agg(F.min(F.struct("p", "w")).alias("x")).select("v", F.col("x.w").alias("cid"))
        new, seen = measured(pivots.select("v", F.col("v").alias("cid")).unionByName(near), "new")
        if ledger is not None:
            ledger.add("sampled-is", phase, 0, alive.count(), exchanges=5)
        if seen["rows"]:
            out = new if out is None else out.unionByName(new)
            rest = materialize(alive.join(new, "v", "left_anti"), "alive")
            alive, edges = rest, materialize(live.induced(rest).edges, "edges")
    last = alive.select("v", F.col("v").alias("cid"))
    return last if out is None else out.unionByName(last)


def _batches(g: SignedGraph, eps: float, prio: DataFrame, process, ledger, name: str) -> DataFrame:
    """Batches of the order of about n eps / (largest alive degree) vertices; ``process(batch graph, low, prio)`` names the
    pivots of a batch, and alive neighbours of pivots join the earliest one."""
    alive, edges, out, at, phase = g.vertices, g.edges, None, 0, 0
    prio = materialize(prio, "prio")
    while at < SPAN:
        live = SignedGraph(alive, edges)
        degree = live.max_degree
        if degree == 0:
            break
        end = min(SPAN, at + int(min(1.0, eps / degree) * SPAN) + 1)
        batch, seen = measured(alive.join(prio.where((F.col("p") >= at) & (F.col("p") < end)), "v").select("v"), "batch")
        if seen["rows"]:
            pivots = materialize(process(live.induced(batch), batch, prio), "pivots")
            made = pivots.join(prio, "v").select(F.col("v").alias("w"), "p")
            near = live.adj.join(made, "w").groupBy("v").agg(F.min(F.struct("p", "w")).alias("x")).select("v", F.col("x.w").alias("cid"))
            near = near.join(pivots, "v", "left_anti")
            new = materialize(pivots.select("v", F.col("v").alias("cid")).unionByName(near), "new")
            out = new if out is None else out.unionByName(new)
            alive = materialize(alive.join(new, "v", "left_anti"), "alive")
            edges = materialize(live.induced(alive).edges, "edges")
            if ledger is not None:
                ledger.add(name, phase, 0, alive.count(), exchanges=5)
        at, phase = end, phase + 1
    last = alive.select("v", F.col("v").alias("cid"))
    return last if out is None else out.unionByName(last)


def serial_batches(g: SignedGraph, eps: float = 0.9, prio: DataFrame | None = None, ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Concurrent batches whose result equals the sequential one: in a batch, a vertex waits for its lower neighbours."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    wait = lambda inner, batch, order: M.local_minima(inner, order.join(batch, "v", "left_semi")).where("in_mis").select("v")
    return _batches(g, eps, prio, wait, ledger, "serial-batches")


def unlocked_batches(g: SignedGraph, eps: float = 0.9, prio: DataFrame | None = None, ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Concurrent batches without coordination: every alive vertex of a batch becomes a pivot, adjacent or not."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    return _batches(g, eps, prio, lambda inner, batch, order: batch, ledger, "unlocked-batches")


def singletons(g: SignedGraph) -> DataFrame:
    return g.vertices.select("v", F.col("v").alias("cid"))


def component_clusters(g: SignedGraph) -> DataFrame:
    return g.vertices.join(components(g.edges), "v", "left").select("v", F.coalesce("comp", "v").alias("cid"))


def direct_pivot(g: SignedGraph, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    return pivot.cluster(g, None, "local", None, cfg)


def maximal_matching_clusters(g: SignedGraph, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Pairs of a maximal matching: at most twice the optimum on forests."""
    return forest.from_matching(g, forest.maximal_matching(g, cfg.seed))
