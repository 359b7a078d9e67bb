"""Pivot clusterings from independent sets, and the best of several runs that share their shuffles."""

from __future__ import annotations

from functools import reduce
from math import ceil, log2

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.priority import priorities, priority
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators import mis as M
from signedcluster.operators.measure import cost_by
from signedcluster.shared import discard, materialize


def assign(g: SignedGraph, chosen: DataFrame, prio: DataFrame) -> DataFrame:
    """``(v, cid)``: members of the set keep themselves, others join their earliest neighbour in it; a vertex with
    neither (only after a method that is not maximal) stays alone."""
    pivots = chosen.where("in_mis").join(prio, "v").select(F.col("v").alias("w"), "p")
    near = g.adj.join(pivots, "w").groupBy("v").agg(F.min(F.struct("p", "w")).alias("best"))
    own = chosen.join(near, "v", "left")
    return own.select("v", F.when(F.col("in_mis"), F.col("v")).otherwise(F.coalesce("best.w", "v")).alias("cid"))


def cluster(g: SignedGraph, prio: DataFrame | None = None, method: str = "local", ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """A pivot clustering; ``method`` picks how the greedy set is found and never changes the result."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    find = {
        "local": lambda: M.local_minima(g, prio, ledger),
        "prefix": lambda: M.prefix_phased(g, prio, "local", ledger, cfg),
        "prefix-chunk": lambda: M.prefix_phased(g, prio, "chunk", ledger, cfg),
        "prefix-hop": lambda: M.prefix_phased(g, prio, "hop", ledger, cfg),
        "chunk": lambda: M.chunked(g, prio, ledger, cfg),
        "hop": lambda: M.hop_compressed(g, prio, None, ledger, cfg),
    }[method]
    return assign(g, find(), prio)


#: A vertex keeps a bit for each copy in one long.
COPIES = 64


def bit(c: int) -> int:
    return 1 << c if c < 63 else -(1 << 63)


def killed_bits(edges: DataFrame) -> DataFrame:
    """``(v, dead)``: the copies in which a vertex is killed, by rounds of local minima in all copies at once.

    ``edges(u, v, first, live)``: the copies in which u comes before v, and those in which both ends are open. A copy is a
    bit, so edges are never multiplied, and what an exchange carries is a long for each vertex and task.
    """
    none, dead = F.lit(0).cast("long"), None
    while edges.where("live <> 0").limit(1).count():
        ends = edges.select(F.explode(F.array(*[F.struct(F.col(x).alias("v"), "live", (F.col("live").bitwiseAND(late)).alias("after")) for x, late in (("u", F.bitwise_not("first")), ("v", F.col("first")))])).alias("x")).select("x.*")
        roots = ends.groupBy("v").agg(F.bit_or("live").alias("live"), F.bit_or("after").alias("after"))
        roots = materialize(roots.select("v", F.col("live").bitwiseAND(F.bitwise_not("after")).alias("root")).where("root <> 0"), "roots")
        beside = edges.join(roots.select(F.col("v").alias("u"), F.col("root").alias("ru")), "u", "left").join(roots.select("v", F.col("root").alias("rv")), "v", "left")
        hit = beside.select(F.explode(F.array(*[F.struct(F.col(x).alias("v"), F.col("live").bitwiseAND(F.coalesce(r, none)).alias("dead")) for x, r in (("v", "ru"), ("u", "rv"))])).alias("x")).select("x.*")
        now = materialize(hit.where("dead <> 0").groupBy("v").agg(F.bit_or("dead").alias("dead")), "dead")
        gone = edges.join(now.select(F.col("v").alias("u"), F.col("dead").alias("du")), "u", "left").join(now.select("v", F.col("dead").alias("dv")), "v", "left")
        left = F.col("live").bitwiseAND(F.bitwise_not(F.coalesce("du", none))).bitwiseAND(F.bitwise_not(F.coalesce("dv", none)))
        rest = materialize(gone.select("u", "v", "first", left.alias("live")).where("live <> 0"), "copies")
        discard(edges)
        edges, dead = rest, now if dead is None else dead.unionByName(now)
    dead = edges.select("v", F.col("live").alias("dead")) if dead is None else dead
    return dead.groupBy("v").agg(F.bit_or("dead").alias("dead"))


def runs(g: SignedGraph, k: int | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """``(copy, v, cid)`` of k independent runs with seeds ``cfg.seed`` and up; k is log2 n unless given."""
    k = k or max(1, ceil(log2(max(g.n, 2))))
    if k > COPIES:
        raise ValueError(f"at most {COPIES} copies")
    prio = materialize(g.vertices.select("v", F.array(*[priority(F.col("v"), cfg.seed + c) for c in range(k)]).alias("p")), "prio")
    every = F.lit(sum(bit(c) for c in range(k))).cast("long")
    both = g.edges.join(prio.select(F.col("v").alias("u"), F.col("p").alias("pu")), "u").join(prio.withColumnRenamed("p", "pv"), "v")
    # The smaller id is first among equal priorities.
    first = reduce(lambda x, y: x.bitwiseOR(y), [F.when(F.col("pu")[c] <= F.col("pv")[c], F.lit(bit(c)).cast("long")).otherwise(F.lit(0).cast("long")) for c in range(k)])
    dead = killed_bits(materialize(both.select("u", "v", first.alias("first"), every.alias("live")), "copies"))
    chosen = materialize(g.vertices.join(dead, "v", "left").select("v", every.bitwiseAND(F.bitwise_not(F.coalesce("dead", F.lit(0).cast("long")))).alias("own")), "chosen")
    pairs = g.edges.join(chosen.select(F.col("v").alias("u"), F.col("own").alias("ou")), "u").join(chosen.withColumnRenamed("own", "ov"), "v")
    ways = [F.struct(F.col(x).alias("v"), F.col(y).alias("w"), F.col(oy).bitwiseAND(F.bitwise_not(F.col(ox))).alias("near")) for x, y, ox, oy in (("u", "v", "ou", "ov"), ("v", "u", "ov", "ou"))]
    near = pairs.select(F.explode(F.array(*ways)).alias("x")).select("x.*").where("near <> 0")
    held = f"explode(filter(sequence(0L, {k - 1}L), c -> (shiftright(near, int(c)) & 1L) = 1L))"
    near = near.select("v", "w", F.expr(held).alias("copy")).join(prio.select(F.col("v").alias("w"), "p"), "w")
    best = near.groupBy("copy", "v").agg(F.min(F.struct(F.expr("p[int(copy)]").alias("p"), "w")).alias("x")).select("copy", "v", F.col("x.w").alias("w"))
    return g.vertices.select(F.explode(F.expr(f"sequence(0L, {k - 1}L)")).alias("copy"), "v").join(best, ["copy", "v"], "left").select("copy", "v", F.coalesce("w", "v").alias("cid"))


def best_of(g: SignedGraph, k: int | None = None, cfg: EngineConfig = EngineConfig()) -> tuple[DataFrame, DataFrame]:
    """(clustering of least cost, cost of each copy); ties go to the first copy."""
    every = materialize(runs(g, k, cfg), "runs")
    costs = materialize(cost_by(g, every, "copy"), "costs")
    best = costs.orderBy("cost", "copy").limit(1).select("copy")
    return every.join(F.broadcast(best), "copy", "left_semi").select("v", "cid"), costs
