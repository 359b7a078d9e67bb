"""Clusterings of forests through matchings: clusters of matched pairs, everything else alone."""

from __future__ import annotations

from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.priority import priority
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators import clip
from signedcluster.operators.components import components
from signedcluster.shared import discard, materialize


def check(g: SignedGraph) -> bool:
    """A graph is a forest exactly if it has as many edges as vertices minus components."""
    ends = components(g.edges).agg(F.count("*"), F.count_distinct("comp")).first()
    return g.m == ends[0] - ends[1]


def root_by_levels(g: SignedGraph, roots: DataFrame, max_depth: int) -> DataFrame | None:
    """``(v, parent)`` by breadth-first levels; None if a tree is deeper than ``max_depth``."""
    done = materialize(roots.select("v", F.lit(None).cast("long").alias("parent")), "levels")
    front = done
    for _ in range(max_depth):
        step = g.adj.join(front.select("v", F.col("parent").alias("above")), "v").where("above is null or w <> above")
        front = materialize(step.select(F.col("w").alias("v"), F.col("v").alias("parent")), "front")
        if front.isEmpty():
            return done
        done = done.unionByName(front)
    return None


def root_by_tour(g: SignedGraph) -> DataFrame:
    """``(v, parent)`` of every vertex with an edge, in a logarithmic number of joins however deep the trees.

    Each edge is walked both ways. The walk that follows u -> v leaves v towards its next neighbour after u (cyclic), so
    a tree is one cycle. Pointer doubling finds the smallest directed edge of each cycle, the cycle is cut before it,
    and doubling again ranks edges by how far they are from the cut; of the two walks of an edge the earlier goes down.
    """
    from pyspark.sql import Window

    order = Window.partitionBy("v").orderBy("w")
    ring = g.adj.select("v", "w", F.lead("w").over(order).alias("after"), F.min("w").over(Window.partitionBy("v")).alias("first"))
    # From (w -> v) the tour goes on with (v -> after).
    hop = ring.select(F.col("w").alias("a"), F.col("v").alias("b"), F.coalesce("after", "first").alias("c"))
    edge = lambda x, y: F.struct(F.col(x).alias("a"), F.col(y).alias("b"))
    tour = materialize(hop.select(edge("a", "b").alias("e"), edge("b", "c").alias("to")), "tour")
    low = materialize(tour.select("e", "to", F.least("e", "to").alias("low")), "tour")
    while True:
        far = low.select(F.col("e").alias("to"), F.col("to").alias("to2"), F.col("low").alias("low2"))
        new = materialize(low.join(far, "to").select("e", F.col("to2").alias("to"), F.least("low", "low2").alias("low"), (F.col("low2") < F.col("low")).alias("changed")), "tour")
        changed = not new.where("changed").isEmpty()
        discard(low)
        low = new.drop("changed")
        if not changed:
            break
    start = low.select("e", "low")
    rank = tour.join(start, "e").select("e", F.when(F.col("to") != F.col("low"), F.col("to")).alias("to"), F.lit(1).cast("long").alias("left"))
    rank = materialize(rank, "rank")
    while not rank.where("to is not null").isEmpty():
        far = rank.select(F.col("e").alias("to"), F.col("to").alias("to2"), F.col("left").alias("left2"))
        new = rank.join(far, "to", "left").select("e", F.col("to2").alias("to"), (F.col("left") + F.coalesce("left2", F.lit(0))).alias("left"))
        old, rank = rank, materialize(new, "rank")
        discard(old)
    back = rank.select(F.struct(F.col("e.b").alias("a"), F.col("e.a").alias("b")).alias("e"), F.col("left").alias("other"))
    down = rank.join(back, "e").where("left > other").select(F.col("e.b").alias("v"), F.col("e.a").alias("parent"))
    roots = start.select(F.col("low.a").alias("v")).distinct().select("v", F.lit(None).cast("long").alias("parent"))
    return down.unionByName(roots)


def root(g: SignedGraph, method: str = "auto", max_depth: int = 32) -> DataFrame:
    """``(v, parent)`` with a null parent at roots and isolated vertices."""
    if method != "tour":
        top = g.vertices.join(components(g.edges), "v", "left").where("comp is null or comp = v").select("v")
        found = root_by_levels(g, top, max_depth if method == "auto" else 1 << 30)
        if found is not None:
            return found
    made = root_by_tour(g)
    return made.unionByName(g.vertices.join(made, "v", "left_anti").select("v", F.lit(None).cast("long").alias("parent")))


def free_vertices(parents: DataFrame, ledger: RoundLedger | None = None) -> DataFrame:
    """``(v, parent, free)``: a vertex is free if none of its children is (so leaves are).

    Contraction in logarithmic rounds: vertices whose children are all known, or one of which is free, are decided (rake);
    a vertex with one undecided child is the negation of that child, and chains of such vertices are shortened by pointer
    doubling with a parity (compress).
    """
    state = materialize(parents.select("v", "parent", F.lit(None).cast("boolean").alias("free"), F.lit(None).cast("long").alias("ptr"), F.lit(0).alias("odd")), "free")
    step = 0
    while True:
        kids = state.where("parent is not null").groupBy(F.col("parent").alias("v")).agg(
            F.coalesce(F.bool_or("free"), F.lit(False)).alias("any_free"),
            F.sum(F.col("free").isNull().cast("int")).alias("open"),
            F.min(F.when(F.col("free").isNull(), F.col("v"))).alias("only"),
        )
        raked = state.join(kids, "v", "left").select(
            "v",
            "parent",
            F.when(F.col("free").isNotNull(), F.col("free"))
            .when(F.coalesce("any_free", F.lit(False)), F.lit(False))
            .when(F.coalesce("open", F.lit(0)) == 0, F.lit(True))
            .alias("free"),
            F.when(F.col("ptr").isNotNull(), F.col("ptr")).when(F.col("open") == 1, F.col("only")).alias("ptr"),
            F.when(F.col("ptr").isNotNull(), F.col("odd")).otherwise(1).alias("odd"),
        )
        raked = materialize(raked, "free")
        there = raked.select(F.col("v").alias("ptr"), F.col("free").alias("free2"), F.col("ptr").alias("ptr2"), F.col("odd").alias("odd2"))
        jumped = raked.join(there, "ptr", "left").select(
            "v",
            "parent",
            F.coalesce("free", F.when(F.col("odd") % 2 == 1, ~F.col("free2")).otherwise(F.col("free2"))).alias("free"),
            F.coalesce("ptr2", "ptr").alias("ptr"),
            F.when(F.col("ptr2").isNotNull(), (F.col("odd") + F.col("odd2")) % 2).otherwise(F.col("odd")).cast("int").alias("odd"),
        )
        new = materialize(jumped, "free")
        left = new.where("free is null").count()
        if ledger is not None:
            ledger.add("contract", 0, step, left, exchanges=2)
        discard(state)
        discard(raked)
        state, step = new, step + 1
        if not left:
            return state.select("v", "parent", "free")


def max_matching(g: SignedGraph, method: str = "auto") -> DataFrame:
    """``(u, v)`` of a maximum matching of a forest: every vertex that is not free takes its smallest free child."""
    state = free_vertices(root(g, method))
    pairs = state.where("free and parent is not null").groupBy("parent").agg(F.min("v").alias("kid"))
    return pairs.select(F.least("parent", "kid").alias("u"), F.greatest("parent", "kid").alias("v"))


def from_matching(g: SignedGraph, matching: DataFrame) -> DataFrame:
    """``(v, cid)``: matched pairs together, the rest alone."""
    ends = matching.select(F.explode(F.array("u", "v")).alias("v"), F.col("u").alias("cid"))
    return g.vertices.join(ends, "v", "left").select("v", F.coalesce("cid", "v").alias("cid"))


def matched(matching: DataFrame) -> DataFrame:
    return matching.select(F.explode(F.array("u", "v")).alias("v"))


def maximal_matching(g: SignedGraph, seed: int = 42, max_rounds: int | None = None) -> DataFrame:
    """Rounds of edges that are first (by hash) at both ends. A cap on rounds may leave it short of maximal."""
    order = priority(F.concat_ws("-", F.col("u"), F.col("v")), seed)
    edges = materialize(g.edges.select("u", "v", order.alias("p")), "edges")
    out, n = g.edges.limit(0), 0
    while not edges.isEmpty() and (max_rounds is None or n < max_rounds):
        key = F.struct("p", "u", "v").alias("k")
        first = edges.select(F.explode(F.array("u", "v")).alias("x"), key).groupBy("x").agg(F.min("k").alias("k"))
        won = materialize(first.groupBy("k").count().where("count = 2").select("k.u", "k.v"), "won")
        out = out.unionByName(won)
        gone = matched(won)
        rest = edges.join(gone, "v", "left_anti").join(gone.select(F.col("v").alias("u")), "u", "left_anti").select("u", "v", "p")
        old, edges, n = edges, materialize(rest, "edges"), n + 1
        discard(old)
    return out


def color_reduce(parents: DataFrame, max_steps: int = 10) -> DataFrame:
    """``(v, parent, color)`` with fewer than 6 colours, a vertex and its parent always different.

    The colour starts as the id; each step keeps only the position and value of the lowest bit that differs from the
    parent's, so the number of colours falls to its logarithm (five steps for any 64-bit ids).
    """
    state = materialize(parents.select("v", "parent", F.col("v").alias("color")), "colors")
    for _ in range(max_steps):
        if not state.where("color > 5").limit(1).count():
            break
        above = state.select(F.col("v").alias("parent"), F.col("color").alias("other"))
        other = F.coalesce("other", F.when(F.col("color").bitwiseAND(F.lit(1)) == 0, F.lit(1)).otherwise(F.lit(0)).cast("long"))
        diff = F.col("color").bitwiseXOR(other)
        lowest = F.bit_count(diff.bitwiseAND(-diff) - 1)
        bit = F.expr("0").cast("long") + F.expr("shiftright(color, pos)").bitwiseAND(F.lit(1))
        joined = state.join(above, "parent", "left").withColumn("pos", lowest)
        old, state = state, materialize(joined.select("v", "parent", (F.col("pos") * 2 + bit).cast("long").alias("color")), "colors")
        discard(old)
    return state


def colored_matching(g: SignedGraph, parents: DataFrame | None = None) -> DataFrame:
    """A maximal matching of a forest without randomness: colour by colour, unmatched vertices ask their unmatched parent,
    which takes the smallest. After its colour's turn, an edge has a matched end."""
    parents = root(g) if parents is None else parents
    colors = color_reduce(parents)
    out, used = g.edges.limit(0), g.vertices.limit(0)
    for c in range(6):
        asking = colors.where((F.col("color") == c) & F.col("parent").isNotNull()).join(used, "v", "left_anti")
        asking = asking.join(used.select(F.col("v").alias("parent")), "parent", "left_anti")
        won = materialize(asking.groupBy("parent").agg(F.min("v").alias("kid")).select(F.least("parent", "kid").alias("u"), F.greatest("parent", "kid").alias("v")), "won")
        out = out.unionByName(won)
        used = used.unionByName(matched(won))
    return out


def augment(g: SignedGraph, matching: DataFrame, max_len: int, seed: int = 42, max_rounds: int | None = None) -> DataFrame:
    """Flip disjoint augmenting paths of at most ``max_len`` edges until none is left (or for ``max_rounds``).

    Paths are grown by joins from free vertices, an edge outside and an edge of the matching at a time; on a clipped
    forest there are few. Of paths that share a vertex, those first at all their vertices are flipped.
    """
    now = materialize(matching, "matching")
    n = 0
    while max_rounds is None or n < max_rounds:
        mate = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        free = materialize(g.vertices.join(matched(now), "v", "left_anti"), "unmatched")
        ends = free.select(F.col("v").alias("w"), F.lit(True).alias("free"))
        paths = free.select(F.array("v").alias("path"), F.col("v").alias("tip"))
        found = None
        for edges in range(1, max_len + 1, 2):
            step = paths.join(g.adj.select(F.col("v").alias("tip"), "w"), "tip").where(~F.array_contains("path", F.col("w")))
            step = step.join(ends, "w", "left").select(F.concat("path", F.array("w")).alias("path"), "w", "free")
            done = step.where("free and path[0] < w").select("path")
            found = done if found is None else found.unionByName(done)
            if edges + 2 <= max_len:
                on = step.where("free is null").join(mate.select(F.col("u").alias("w"), F.col("v").alias("x")), "w")
                paths = materialize(on.where(~F.array_contains("path", F.col("x"))).select(F.concat("path", F.array("x")).alias("path"), F.col("x").alias("tip")), "paths")
        found = materialize(found.withColumn("p", F.xxhash64("path", F.lit(seed + n))), "found")
        if found.isEmpty():
            break
        key = F.struct("p", "path").alias("k")
        first = found.select(F.explode("path").alias("x"), key).groupBy("x").agg(F.min("k").alias("k"))
        flip = first.groupBy("k").agg(F.count("*").alias("c")).where("c = size(k.path)").select("k.path")
        flip = materialize(flip, "flip")
        i = F.explode(F.expr("sequence(0, size(path) - 2)")).alias("i")
        pair = flip.select("path", i).select(F.expr("least(path[i], path[i+1])").alias("u"), F.expr("greatest(path[i], path[i+1])").alias("v"), (F.col("i") % 2 == 0).alias("new"))
        pair = materialize(pair, "pair")
        keep = now.join(pair.where("not new").select("u", "v"), ["u", "v"], "left_anti")
        old, now, n = now, materialize(keep.unionByName(pair.where("new").select("u", "v")), "matching"), n + 1
        discard(old)
    return now


def cluster(g: SignedGraph, how: str = "exact", eps: float = 0.5, cfg: EngineConfig = EngineConfig(), rounds: int | None = None) -> DataFrame:
    """A clustering of a forest.

    ``exact``: maximum matching. ``maximal``: any maximal matching (at most twice the optimum). ``det`` and ``rand``:
    clip at arboricity one, then a matching without augmenting paths below 2 ceil(1/eps) edges, deterministic from a
    colouring, or from random orders. Flips go on until no such path is left, so both reach 1 + eps; with a cap of
    ``rounds`` on the flips ``rand`` may stop short of it.
    Methods but ``exact`` work on each tree by itself, because the ratio holds for each tree, not for a sum of trees.
    """
    if how == "exact":
        return from_matching(g, max_matching(g))
    if how == "maximal":
        return from_matching(g, maximal_matching(g, cfg.seed))
    if not 0 < eps <= 1:
        raise ValueError("0 < eps <= 1")
    longest = 2 * ceil(1 / eps) - 1

    def inner(rest: SignedGraph) -> DataFrame:
        if how == "det":
            start, cap = colored_matching(rest), None
        else:
            start, cap = maximal_matching(rest, cfg.seed), rounds
        return from_matching(rest, augment(rest, start, longest, cfg.seed, cap))

    return clip.cluster(g, eps, 1, inner)
