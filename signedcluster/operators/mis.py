"""Greedy maximal independent sets of a random order.

All methods give the same set: the one a sequential scan by (priority, id) takes. They work on *lower edges*
``(v, w, pv, pw)``: w comes before v. A vertex is in the set exactly if it is never killed by a lower neighbour in the
set, so only killed vertices are kept.
"""

from __future__ import annotations

from math import ceil, floor, log, log2

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.groups import map_groups
from signedcluster.functions.priority import SPAN, priorities
from signedcluster.model import EngineConfig, RoundLedger, SignedGraph
from signedcluster.operators.components import components
from signedcluster.shared import discard, materialize, measured


def lower_edges(g: SignedGraph, prio: DataFrame) -> DataFrame:
    """Edges from the later to the earlier end, priorities stored once so that later steps filter without a join."""
    both = g.edges.join(prio.select(F.col("v").alias("u"), F.col("p").alias("pu")), "u").join(prio.withColumnRenamed("p", "pv"), "v")
    first = F.struct(F.col("pu").alias("p"), F.col("u").alias("v"))
    second = F.struct(F.col("pv").alias("p"), F.col("v").alias("v"))
    low, high = F.least(first, second), F.greatest(first, second)
    return both.select(high["v"].alias("v"), low["v"].alias("w"), high["p"].alias("pv"), low["p"].alias("pw"))


def without(edges: DataFrame, gone: DataFrame) -> DataFrame:
    """Lower edges with neither end in ``gone(v)``."""
    return edges.join(gone, "v", "left_anti").join(gone.select(F.col("v").alias("w")), "w", "left_anti").select("v", "w", "pv", "pw")


def kill_rounds(low: DataFrame, ledger: RoundLedger | None = None, phase: int = 0, method: str = "local") -> DataFrame:
    """Killed vertices of the graph of ``low``, by rounds of local minima; each round's edges shrink geometrically."""
    killed, step = None, 0
    low, seen = measured(low, "low")
    while n := seen["rows"]:
        ends = low.select(F.explode(F.array(F.struct("w", F.lit(False).alias("late")), F.struct(F.col("v").alias("w"), F.lit(True).alias("late")))).alias("x"))
        roots = ends.groupBy("x.w").agg(F.bool_or("x.late").alias("late")).where("not late").select("w")
        now = materialize(low.join(roots, "w", "left_semi").select("v").distinct(), "killed")
        rest, seen = measured(without(low, now), "low")
        discard(low)
        low = rest
        killed = now if killed is None else killed.unionByName(now)
        if ledger is not None:
            ledger.add(method, phase, step, n, exchanges=4)
        step += 1
    return low.select("v") if killed is None else killed


def members(g: SignedGraph, killed: DataFrame) -> DataFrame:
    """``(v, in_mis)`` of all vertices."""
    return g.vertices.join(killed.withColumn("dead", F.lit(True)).distinct(), "v", "left").select("v", F.col("dead").isNull().alias("in_mis"))


def local_minima(g: SignedGraph, prio: DataFrame | None = None, ledger: RoundLedger | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    return members(g, kill_rounds(lower_edges(g, prio), ledger))


def pairs_only(g: SignedGraph, prio: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """The set in one round where every edge is alone: its later end is out. Edges that meet another one, in a graph of
    larger degree, go to rounds of local minima; no such edge touches a lone one."""
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    low = lower_edges(g, prio)
    if g.max_degree <= 1:
        return members(g, low.select("v"))
    low = materialize(low, "low")
    crowded = low.select(F.explode(F.array("v", "w")).alias("v")).groupBy("v").count().where("count > 1").select("v")
    crowded = materialize(crowded, "crowded")
    alone = without(low, crowded)
    rest = low.join(alone.select("v", "w"), ["v", "w"], "left_anti").select("v", "w", "pv", "pw")
    return members(g, alone.select("v").unionByName(kill_rounds(rest)))


def prefix_cuts(n: int, max_degree: int, c: float) -> list[float]:
    """Shares of the order at the ends of the phases; phase i takes about c n ln n / (degree / 2^i) vertices."""
    cuts, total, i = [], 0.0, 0
    while total < 1 and i <= ceil(log2(max(max_degree, 2))) + 1:
        total = min(1.0, total + c * log(max(n, 3)) * 2**i / max(max_degree, 1))
        cuts.append(total)
        i += 1
    return cuts if cuts and cuts[-1] >= 1 else [*cuts, 1.0]


def nth_priorities(prio: DataFrame, places: list[int], bits: int = 16) -> list[int]:
    """The priorities at 0-based ``places`` of the order: a histogram of the leading ``bits``, then the vertices of the few
    bins that hold a place. A hashed order fills bins evenly, so a bin has about n / 2^bits priorities."""
    if not places:
        return []
    width = SPAN >> bits
    own = F.floor(F.col("p") / width).cast("long")
    counts = dict(prio.groupBy(own.alias("bin")).count().collect())
    ends, total = [], 0
    for k in sorted(counts):
        total += counts[k]
        ends.append((total, k))
    found = [next((k, place - (end - counts[k])) for end, k in ends if place < end) for place in places]
    held: dict[int, list[int]] = {}
    for k, p in prio.where(own.isin([k for k, _ in found])).select(own, "p").collect():
        held.setdefault(k, []).append(p)
    return [sorted(held[k])[at] for k, at in found]


def prefix_phased(
    g: SignedGraph,
    prio: DataFrame | None = None,
    sub: str = "local",
    ledger: RoundLedger | None = None,
    cfg: EngineConfig = EngineConfig(),
    cut: str = "hash",
    radius: int | None = None,
) -> DataFrame:
    """Phases over growing prefixes of the order, each solved by ``sub`` (local, chunk or hop); then the remainder.

    ``cut='hash'`` takes the prefix by a bound on the hashed priority; ``'rank'`` by exact position, found by counting
    (see :func:`nth_priorities`). Neither sorts the vertices.
    """
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    n, degree = g.n, g.max_degree
    low = materialize(lower_edges(g, prio), "low")
    cuts = prefix_cuts(n, degree, cfg.prefix_c)
    if cut == "rank":
        places = [min(n - 1, int(x * n)) for x in cuts if x < 1]
        bounds = [*nth_priorities(prio, places), SPAN]
    else:
        bounds = [int(x * SPAN) if x < 1 else SPAN for x in cuts]
    killed = low.select("v").limit(0)
    for phase, bound in enumerate(bounds):
        inside = low.where(F.col("pv") < bound)
        dead = materialize(solve(inside, sub, n, ledger, cfg, phase, radius), "dead")
        alive = low.where((F.col("pw") < bound) & (F.col("pv") >= bound)).join(dead.select(F.col("v").alias("w")), "w", "left_anti")
        more = materialize(alive.select("v").distinct(), "dead")
        rest, seen = measured(without(low.where((F.col("pw") >= bound) & (F.col("pv") >= bound)), more), "low")
        killed = killed.unionByName(dead).unionByName(more)
        discard(low)
        low, left = rest, seen["rows"]
        if ledger is not None:
            ledger.add(f"prefix-{sub}", phase, 0, left, exchanges=3)
        if not left:
            break
    return members(g, killed)


def solve(low: DataFrame, sub: str, n: int, ledger, cfg: EngineConfig, phase: int, radius: int | None) -> DataFrame:
    if sub == "chunk":
        return chunk_kills(low, n, ledger, cfg, phase)
    if sub == "hop":
        return hop_kills(low, n, radius, ledger, cfg, phase)
    return kill_rounds(low, ledger, phase)


def degree_of(low: DataFrame) -> int:
    ends = low.select(F.explode(F.array("v", "w")).alias("v"))
    return ends.groupBy("v").count().agg(F.max("count")).first()[0] or 0


def chunks_a_phase(degree: int, cfg: EngineConfig) -> int:
    return max(1, ceil(cfg.iter_mult * log2(max(degree, 2))))


def chunk_number(p, degree: int, cfg: EngineConfig):
    """Number of the chunk of a priority, for any number of chunks: phase i has iter_mult log2(degree) chunks that each
    hold about 2^i / (den degree) of the order, so it begins where 2^i - 1 phases of the first width end."""
    many = chunks_a_phase(degree, cfg)
    width = SPAN / (cfg.chunk_den * max(degree, 1))
    phase = F.floor(F.log2(p / F.lit(many * width) + 1))
    inside = F.floor((p - (F.pow(F.lit(2.0), phase) - 1) * (many * width)) / (F.pow(F.lit(2.0), phase) * width))
    return (phase * many + F.greatest(F.lit(0), F.least(F.lit(many - 1), inside))).cast("long")


def chunk_schedule(degree: int, cfg: EngineConfig) -> list[tuple[int, int, float]]:
    """(phase, chunks in it, share of the order in one) until the whole order is covered."""
    many, out, at, phase = chunks_a_phase(degree, cfg), [], 0.0, 0
    while at < 1:
        share = 2**phase / (cfg.chunk_den * max(degree, 1))
        n = min(many, ceil(round((1 - at) / share, 9)))
        out.append((phase, n, share))
        at, phase = at + many * share, phase + 1
    return out


def greedy_component(_, rows) -> list[tuple]:
    """Killed vertices of one component of lower edges, by a scan in order."""
    lower: dict[int, list[int]] = {}
    at: dict[int, tuple] = {}
    for v, w, pv, pw in zip(rows["v"], rows["w"], rows["pv"], rows["pw"], strict=True):
        lower.setdefault(v, []).append(w)
        at[v], at[w] = (pv, v), (pw, w)
    dead: set[int] = set()
    for v in sorted(at, key=at.get):
        if any(w not in dead for w in lower.get(v, ())):
            dead.add(v)
    return [(v,) for v in dead]


def chunk_kills(low: DataFrame, n: int, ledger=None, cfg: EngineConfig = EngineConfig(), phase: int = 0) -> DataFrame:
    """Chunks of the order in turn; each shatters into small components that one task solves whole.

    The components of all chunks are learnt in one call (an edge counts if its ends share a chunk), so a chunk costs one
    exchange by component and one join for what it kills later. A component above ``cfg.local_cap`` edges goes to rounds
    of local minima instead.
    """
    low = materialize(low, "low")
    degree = degree_of(low)
    if not degree:
        return low.select("v")
    low = low.withColumn("cv", chunk_number(F.col("pv"), degree, cfg)).withColumn("cw", chunk_number(F.col("pw"), degree, cfg))
    inner = low.where("cv = cw")
    comp = materialize(components(inner.select(F.col("v").alias("u"), F.col("w").alias("v"))), "comp")
    low = materialize(low.join(comp, "v", "left"), "low")
    sizes = low.where("cv = cw").groupBy("cv", "comp").count()
    large = {(r[0], r[1]) for r in sizes.where(F.col("count") > cfg.local_cap).select("cv", "comp").collect()}
    present = [r[0] for r in low.select(F.explode(F.array("cv", "cw")).alias("c")).distinct().orderBy("c").collect()]
    killed = low.select("v").limit(0)
    for step, c in enumerate(present):
        mine = low.where((F.col("cv") == c) & (F.col("cw") == c))
        if any(k == c for k, _ in large):
            dead = kill_rounds(mine.select("v", "w", "pv", "pw"), ledger, phase)
        else:
            dead = map_groups(mine.select("comp", "v", "w", "pv", "pw"), "comp", greedy_component, "v long")
        dead = materialize(dead, "dead")
        gone = dead.select(F.col("v").alias("w"))
        more = materialize(low.where((F.col("cw") == c) & (F.col("cv") > c)).join(gone, "w", "left_anti").select("v").distinct(), "dead")
        killed = killed.unionByName(dead).unionByName(more)
        both = dead.unionByName(more)
        rest = low.where((F.col("cw") > c) & (F.col("cv") > c)).join(both, "v", "left_anti")
        kept = materialize(rest.join(both.select(F.col("v").alias("w")), "w", "left_anti").select("v", "w", "pv", "pw", "cv", "cw", "comp"), "low")
        discard(low)
        low = kept
        left = low.count()
        if ledger is not None:
            ledger.add("chunk", phase, step, left, exchanges=4)
        if not left:
            break
    return killed


def chunked(g: SignedGraph, prio: DataFrame | None = None, ledger=None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    return members(g, chunk_kills(lower_edges(g, prio), g.n, ledger, cfg))


def hop_radius(n: int, degree: int, delta: float = 0.5) -> int:
    """The largest radius (one at least) with degree^radius <= n^delta."""
    return 1 if degree < 2 else max(1, floor(delta * log(max(n, 2)) / log(degree)))


def decide_root(root, rows) -> list[tuple]:
    """Status of one root from its ball of lower edges: 1 in, 2 out, or none if it hangs on what is beyond the ball."""
    lower: dict[int, list[int]] = {}
    known: dict[int, int] = {}
    for v, w, s in zip(rows["v"], rows["w"], rows["s"], strict=True):
        lower.setdefault(v, [])
        if w is not None:
            lower[v].append(w)
            if s:
                known[w] = s
    order, seen, stack = [], set(), [(root, False)]
    while stack:
        v, done = stack.pop()
        if done:
            order.append(v)
        elif v not in seen and v not in known and v in lower:
            seen.add(v)
            stack.append((v, True))
            stack += [(w, False) for w in lower[v]]
    for v in order:
        got = [known.get(w, 0) for w in lower[v]]
        known[v] = 2 if 1 in got else 0 if 0 in got else 1
    return [(int(root), known[root])] if known.get(root) else []


def hop_kills(low: DataFrame, n: int, radius: int | None = None, ledger=None, cfg: EngineConfig = EngineConfig(), phase: int = 0) -> DataFrame:
    """Each vertex gathers its lower neighbourhood of ``radius`` hops by doubling, then every phase decides as many steps
    inside one task as the radius allows; statuses are refreshed between phases.

    Only falling paths are gathered (later vertices cannot matter). While the estimated rows pass ``cfg.hop_row_cap`` the
    radius is lowered, which the ledger tells (method ``hop-radius``); at radius one a ball is a vertex's own edges.
    """
    low = materialize(low, "low")
    degree = degree_of(low)
    if not degree:
        return low.select("v")
    radius = radius or hop_radius(n, degree)
    edges = low.count()
    while radius > 1 and edges * min(degree, 1000) ** (radius - 1) > cfg.hop_row_cap:
        radius -= 1
    if ledger is not None:
        ledger.add("hop-radius", phase, radius, edges, exchanges=0)
    reach = low.select(F.col("v").alias("root"), F.col("w").alias("at"), F.lit(1).alias("hops"))
    reach = reach.unionByName(low.select(F.explode(F.array("v", "w")).alias("root")).distinct().select("root", F.col("root").alias("at"), F.lit(0).alias("hops")))
    have = 1
    while have < radius - 1:
        far = reach.select(F.col("root").alias("at"), F.col("at").alias("to"), F.col("hops").alias("more"))
        reach = reach.join(far, "at").select("root", F.col("to").alias("at"), (F.col("hops") + F.col("more")).alias("hops"))
        reach = materialize(reach.where(F.col("hops") <= radius - 1).groupBy("root", "at").agg(F.min("hops").alias("hops")), "reach")
        have *= 2
    reach = reach.where(F.col("hops") <= radius - 1)
    ball = materialize(reach.join(low.select(F.col("v").alias("at"), "w"), "at", "left").select("root", F.col("at").alias("v"), "w"), "ball")
    state, step = low.select(F.col("v").alias("root"), F.lit(0).alias("s")).limit(0), 0
    while True:
        open_roots = ball.join(state.select("root"), "root", "left_anti")
        rows = open_roots.join(state.select(F.col("root").alias("w"), "s"), "w", "left").select("root", "v", "w", F.coalesce("s", F.lit(0)).alias("s"))
        new = materialize(map_groups(rows, "root", decide_root, "root long, s int"), "state")
        made = new.count()
        if ledger is not None:
            ledger.add("hop", phase, step, made, exchanges=2)
        if not made:
            break
        state, step = state.unionByName(new), step + 1
    return state.where("s = 2").select(F.col("root").alias("v"))


def hop_compressed(g: SignedGraph, prio: DataFrame | None = None, radius: int | None = None, ledger=None, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    prio = priorities(g.vertices, cfg.seed) if prio is None else prio
    return members(g, hop_kills(lower_edges(g, prio), g.n, radius, ledger, cfg))
