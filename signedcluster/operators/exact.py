"""Optimum clusterings of small components, by dynamic programming over subsets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.groups import map_groups
from signedcluster.model import SignedGraph
from signedcluster.operators.components import components
from signedcluster.shared import materialize


def best_partition(vertices: list[int], edges: list[tuple[int, int]]) -> tuple[int, dict[int, int]]:
    """(least number of disagreements, vertex -> smallest member of its cluster) of a graph of few vertices."""
    order = sorted(vertices)
    at = {v: k for k, v in enumerate(order)}
    n = len(order)
    near = [0] * n
    for u, v in edges:
        near[at[u]] |= 1 << at[v]
        near[at[v]] |= 1 << at[u]
    # Gain of a cluster against singletons: positives inside minus negatives inside.
    gain = [0] * (1 << n)
    for s in range(1, 1 << n):
        low = (s & -s).bit_length() - 1
        rest = s & (s - 1)
        inside = (near[low] & rest).bit_count()
        gain[s] = gain[rest] + 2 * inside - rest.bit_count()
    best = [0] * (1 << n)
    pick = [0] * (1 << n)
    for s in range(1, 1 << n):
        low = s & -s
        rest = s ^ low
        part, top, arg = rest, None, low
        while True:
            c = part | low
            value = gain[c] + best[s ^ c]
            if top is None or value > top:
                top, arg = value, c
            if not part:
                break
            part = (part - 1) & rest
        best[s], pick[s] = top, arg
    out, s = {}, (1 << n) - 1
    while s:
        c = pick[s]
        name = order[(c & -c).bit_length() - 1]
        for k in range(n):
            if c >> k & 1:
                out[order[k]] = name
        s ^= c
    return len(edges) - best[(1 << n) - 1] if n else 0, out


def optimum(g: SignedGraph, max_comp: int = 10) -> DataFrame:
    """``(component, v, cid, opt)`` of every vertex with an edge. Components of more than ``max_comp`` vertices are not
    solved (the problem is hard): their rows have null ``cid`` and ``opt``. Isolated vertices cost nothing and are not listed."""
    comp = materialize(components(g.edges), "comp")
    sizes = comp.groupBy("comp").agg(F.count("*").alias("n"))
    small = sizes.where(F.col("n") <= max_comp).select("comp")
    null = F.lit(None).cast("long")
    unsolved = comp.join(sizes.where(F.col("n") > max_comp).select("comp"), "comp", "left_semi")
    unsolved = unsolved.select(F.col("comp").alias("component"), "v", null.alias("cid"), null.alias("opt"))
    rows = g.edges.join(comp, "v").join(small, "comp", "left_semi").select("comp", "u", "v")

    def solve(c, cols):
        edges = list(zip(cols["u"], cols["v"], strict=True))
        opt, found = best_partition(list({x for e in edges for x in e}), edges)
        return [(int(c), v, cid, opt) for v, cid in found.items()]

    return map_groups(rows, "comp", solve, "component long, v long, cid long, opt long").unionByName(unsolved)
