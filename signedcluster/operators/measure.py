"""Cost, agreement and structure measures. Negative pairs are counted by arithmetic, never listed."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from signedcluster.functions.priority import SPAN, priorities
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators import mis as M
from signedcluster.shared import discard, materialize, measured


def pairs(n):
    """n (n - 1) / 2 in decimals: pairs of a giant cluster pass the range of a long."""
    n = n.cast("decimal(19,0)")
    return (n * (n - 1) / 2).cast("decimal(38,0)")


def cost_by(g: SignedGraph, clustering: DataFrame, *keys: str) -> DataFrame:
    """Disagreements for each value of ``keys`` (columns of ``clustering(v, cid, ...)``); no keys: one row."""
    left = clustering.select(*keys, F.col("v").alias("u"), F.col("cid").alias("cu"))
    right = clustering.select(*keys, "v", F.col("cid").alias("cv"))
    joined = g.edges.join(left, "u").join(right, ["v", *keys])
    edges = joined.groupBy(*keys).agg(
        F.coalesce(F.sum((F.col("cu") != F.col("cv")).cast("long")), F.lit(0)).alias("pos_dis"),
        F.coalesce(F.sum((F.col("cu") == F.col("cv")).cast("long")), F.lit(0)).alias("pos_agree"),
    )
    sizes = clustering.groupBy(*keys, "cid").agg(F.count("*").alias("s")).groupBy(*keys).agg(F.coalesce(F.sum(pairs(F.col("s"))), F.lit(0)).alias("inside"), F.coalesce(F.sum("s"), F.lit(0)).alias("n"))
    both = sizes.join(edges, list(keys), "left") if keys else sizes.join(edges, F.lit(True), "inner")
    pos, agree = F.coalesce("pos_dis", F.lit(0)), F.coalesce("pos_agree", F.lit(0))
    neg = (F.col("inside") - agree).cast("long")
    return both.select(
        *keys,
        pos.cast("long").alias("pos_dis"),
        neg.alias("neg_dis"),
        (pos + neg).cast("long").alias("cost"),
        agree.cast("long").alias("pos_agree"),
        (pairs(F.col("n")) - pos - agree - neg).cast("long").alias("neg_agree"),
    )


def cost(g: SignedGraph, clustering: DataFrame) -> DataFrame:
    return cost_by(g, clustering).select("pos_dis", "neg_dis", "cost")


def agreements(g: SignedGraph, clustering: DataFrame) -> DataFrame:
    return cost_by(g, clustering).select("pos_agree", "neg_agree", (F.col("pos_agree") + F.col("neg_agree")).alias("agreements"))


def cluster_sizes(clustering: DataFrame) -> DataFrame:
    return clustering.groupBy("cid").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("clusters"))


def wedges(g: SignedGraph) -> DataFrame:
    """``(b, a, c)``: centre b with neighbours a < c."""
    one = g.adj.select(F.col("v").alias("b"), F.col("w").alias("a"))
    return one.join(g.adj.select(F.col("v").alias("b"), F.col("w").alias("c")), "b").where("a < c")


def bad_triangle_count(g: SignedGraph) -> DataFrame:
    """Wedges without their closing edge, by counts: wedges from degrees, minus three for each triangle.

    Triangles are met along edges from lower to higher (degree, id), so no hub lists its wedges.
    """
    deg = g.degrees()
    total = deg.agg(F.coalesce(F.sum(pairs(F.col("d"))), F.lit(0)).alias("wedges"))
    e = g.edges.join(deg.select(F.col("v").alias("u"), F.col("d").alias("du")), "u").join(deg.withColumnRenamed("d", "dv"), "v")
    up = F.struct(F.col("du").alias("d"), F.col("u").alias("v")) < F.struct(F.col("dv").alias("d"), F.col("v").alias("v"))
    out = e.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"))
    two = out.join(out.select("x", F.col("y").alias("z")), "x").where("y < z")
    closed = two.join(g.edges.select(F.col("u").alias("y"), F.col("v").alias("z")), ["y", "z"]).agg(F.count("*").alias("t"))
    return total.join(closed, F.lit(True), "inner").select((F.col("wedges") - 3 * F.col("t")).cast("long").alias("bad_triangles"), F.col("t").alias("triangles"))


def packing_bound(g: SignedGraph, seed: int = 42, rounds: int = 6) -> DataFrame:
    """A set of bad triangles that share no pair: a lower bound on any clustering's cost.

    In each round a hash deals every edge not yet used to one of its ends, and a centre puts the edges dealt to it in pairs
    by another hash, so no two triangles of a round share an edge. Pairs whose outer ends are linked, or were used in a
    round before, are left out, and of those with the same outer ends the first by hash is taken. A round lists half as
    many triangles as there are edges at most, never the wedges. After ``rounds`` it ends with the first that adds less
    than a thousandth of what is taken; any set of them is a bound.
    """
    left, linked, used, total, n, k = materialize(g.edges, "left"), g.edges.select(F.col("u").alias("a"), F.col("v").alias("c")), None, 0, 0, 0
    while k < rounds or 1000 * n > total:
        here = F.pmod(F.xxhash64("u", "v", F.lit(seed), F.lit(k)), F.lit(2)) == 0
        dealt = left.select(F.when(here, F.col("u")).otherwise(F.col("v")).alias("b"), F.when(here, F.col("v")).otherwise(F.col("u")).alias("w"))
        place = F.row_number().over(Window.partitionBy("b").orderBy(F.xxhash64("w", "b", F.lit(seed), F.lit(k)), "w"))
        two = dealt.withColumn("at", F.floor((place + 1) / 2)).groupBy("b", "at").agg(F.min("w").alias("a"), F.max("w").alias("c"))
        bad = two.where("a < c").select("a", "b", "c").join(linked, ["a", "c"], "left_anti")
        if used is not None:
            bad = bad.join(used, ["a", "c"], "left_anti")
        taken = bad.groupBy("a", "c").agg(F.min(F.struct(F.xxhash64("a", "b", "c", F.lit(seed)).alias("h"), "b")).alias("t"))
        taken, seen = measured(taken.select("a", F.col("t.b").alias("b"), "c"), "taken")
        n = seen["rows"]
        k, total = k + 1, total + n
        if not n:
            continue
        outer = taken.select("a", "c")
        used = outer if used is None else used.unionByName(outer)
        sides = taken.select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("c").alias("x"), F.col("b").alias("y")))).alias("e"))
        sides = sides.select(F.least("e.x", "e.y").alias("u"), F.greatest("e.x", "e.y").alias("v"))
        rest = materialize(left.join(sides, ["u", "v"], "left_anti"), "left")
        discard(left)
        left = rest
    return g.vertices.sparkSession.createDataFrame([(total,)], "packing long")


def dependency_depth(g: SignedGraph, prio: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Rounds of local minima until every vertex with an edge is decided."""
    ledger = RoundLedger()
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    M.kill_rounds(M.lower_edges(g, prio), ledger)
    return g.vertices.sparkSession.createDataFrame([(len(ledger.rows),)], "depth long")


def residual_degree(g: SignedGraph, permille=(50, 100, 250, 500), prio: DataFrame | None = None, chosen: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Largest degree among vertices not yet decided after each prefix of the order (by hashed share).

    One greedy set serves every prefix: after prefix t, a vertex is gone if it is in the prefix or next to a member of
    the set inside it.
    """
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    chosen = materialize(M.local_minima(g, prio) if chosen is None else chosen, "mis")
    pivots = chosen.where("in_mis").join(prio, "v").select(F.col("v").alias("w"), "p")
    gone = g.adj.join(pivots, "w").groupBy("v").agg(F.min("p").alias("q"))
    when = materialize(prio.join(gone, "v", "left").select("v", F.least("p", F.coalesce("q", F.lit(SPAN))).alias("t")), "when")
    both = g.edges.join(when.withColumnRenamed("t", "tv"), "v").join(when.select(F.col("v").alias("u"), F.col("t").alias("tu")), "u")
    last = both.select(F.explode(F.array("u", "v")).alias("v"), F.least("tu", "tv").alias("t"))
    cuts = F.explode(F.array(*[F.lit(x) for x in permille]))
    alive = last.withColumn("permille", cuts).where(F.col("t") >= F.expr(f"permille * {SPAN // 1000}L"))
    found = alive.groupBy("permille", "v").agg(F.count("*").alias("d")).groupBy("permille").agg(F.max("d").alias("max_degree"))
    every = g.vertices.sparkSession.createDataFrame([(int(x),) for x in permille], "permille int")
    return every.join(found, "permille", "left").select("permille", F.coalesce("max_degree", F.lit(0)).cast("long").alias("max_degree"))


def prefix_degree(g: SignedGraph, prio: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Vertices and largest degree of the first prefix graph."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    bound = int(min(1.0, M.prefix_cuts(g.n, g.max_degree, cfg.prefix_c)[0]) * SPAN)
    low = M.lower_edges(g, prio).where(F.col("pv") < bound)
    n = prio.where(F.col("p") < bound).agg(F.count("*").alias("vertices"))
    d = low.select(F.explode(F.array("v", "w")).alias("v")).groupBy("v").count().agg(F.coalesce(F.max("count"), F.lit(0)).alias("max_degree"))
    return n.join(d, F.lit(True), "inner")


def chunk_component_sizes(g: SignedGraph, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """Largest component and number of components of the chunk graphs (components of one vertex left out)."""
    from signedcluster.operators.components import components

    low = M.lower_edges(g, priorities(g.vertices, cfg.seed))
    inner = low.where(M.chunk_number(F.col("pv"), g.max_degree, cfg) == M.chunk_number(F.col("pw"), g.max_degree, cfg))
    comp = components(inner.select(F.col("v").alias("u"), F.col("w").alias("v")))
    sizes = comp.groupBy("comp").agg(F.count("*").alias("s"))
    return sizes.agg(F.count("*").alias("components"), F.coalesce(F.max("s"), F.lit(1)).alias("largest"))


def sketch_profile(g: SignedGraph, clustering: DataFrame) -> DataFrame:
    """Approximate number of clusters and quartiles of the degree, in one pass each."""
    return clustering.agg(F.approx_count_distinct("cid").alias("clusters")).join(
        g.degrees().agg(F.percentile_approx("d", [0.25, 0.5, 0.75]).alias("degree_quartiles")), F.lit(True), "inner"
    )
