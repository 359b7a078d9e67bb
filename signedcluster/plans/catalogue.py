"""Queries by name, and the SQL that another engine runs on the same tables."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.functions.priority import SPAN, priorities
from signedcluster.model import EngineConfig, RoundLedger, measured_stages
from signedcluster.operators import arboricity, baselines, clip, components, exact, exchange, forest, measure, mis, pivot, simple
from signedcluster.plans import graph_sql as S
from signedcluster.plans import table_queries
from signedcluster.plans.graphs import graph
from signedcluster.shared import materialize
from signedcluster.sources import builders as B

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return keep


def tagged(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in tags.items()], "*")


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def at_once(asked: list, most: int = 2) -> list:
    """What functions without arguments return, ``most`` of them at a time: loops of small jobs leave cores free for others."""
    with ThreadPoolExecutor(most) as pool:
        return list(pool.map(lambda f: f(), asked))


def g_sql(name, *tables: str, select: str) -> str:
    return S.with_graph(name, *tables) + "\n" + select


def union_sql(parts: list[str]) -> str:
    """Parts that start with WITH are wrapped, so that each has its own tables."""
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


# --- graphs ------------------------------------------------------------------------------------------------------------

for _name in S.GRAPHS:
    QUERIES[f"graph_{_name}"] = lambda s, f, n=_name: graph(s, f, n, stored=False).edges
    ORACLES[f"graph_{_name}"] = g_sql(_name, select="SELECT u::BIGINT AS u, v::BIGINT AS v FROM edges")

SHAPES = ("geo", "event_chain", "emb_30", "part_supp", "copart_2", "scalefree_customers")


@query(union_sql([g_sql(n, S.DEG, select=f"SELECT '{n}' AS graph, (SELECT count(*) FROM vertices) AS n, (SELECT count(*) FROM edges) AS m, (SELECT max(d) FROM deg) AS max_degree") for n in SHAPES]))
def graph_shapes(spark, folder):
    """Vertices, edges and largest degree of several graphs."""
    rows = [(n, g.n, g.m, g.max_degree) for n in SHAPES for g in [graph(spark, folder, n)]]
    return spark.createDataFrame(rows, "graph string, n long, m long, max_degree long")


# --- order, independent sets -------------------------------------------------------------------------------------------


@query(g_sql("emb_30", select=f"SELECT v, {S.prio()} AS p FROM vertices"))
def vertex_priority(spark, folder):
    return priorities(graph(spark, folder, "emb_30").vertices)


def _mis_sql(name):
    return g_sql(name, *S.mis(), select="SELECT v, in_mis FROM mis")


@query(_mis_sql("copart_2"))
def greedy_mis(spark, folder):
    return mis.local_minima(graph(spark, folder, "copart_2"))


@query(_mis_sql("emb_30"))
def mis_prefix_local(spark, folder):
    return mis.prefix_phased(graph(spark, folder, "emb_30"), sub="local")


@query(_mis_sql("emb_30"))
def mis_prefix_rank(spark, folder):
    """The prefix cut by exact rank."""
    return mis.prefix_phased(graph(spark, folder, "emb_30"), sub="local", cut="rank")


@query(_mis_sql("emb_30"))
def mis_prefix_chunk(spark, folder):
    return mis.prefix_phased(graph(spark, folder, "emb_30"), sub="chunk", cfg=EngineConfig(chunk_den=0.2))


@query(_mis_sql("emb_30"))
def mis_prefix_hop(spark, folder):
    return mis.prefix_phased(graph(spark, folder, "emb_30"), sub="hop", radius=2)


@query(_mis_sql("emb_35"))
def mis_chunked(spark, folder):
    return mis.chunked(graph(spark, folder, "emb_35"), cfg=EngineConfig(chunk_den=0.5))


@query(_mis_sql("emb_30"))
def mis_hop(spark, folder):
    return mis.hop_compressed(graph(spark, folder, "emb_30"), radius=3)


@query(_mis_sql("emb_50"))
def mis_pairs(spark, folder):
    """Largest degree at most one: one round."""
    return mis.pairs_only(graph(spark, folder, "emb_50"))


@query(g_sql("emb_35", S.COMPONENTS, S.COMP, select="SELECT v, comp FROM comp WHERE v IN (SELECT v FROM adj)"))
def connected_components(spark, folder):
    return components.components(graph(spark, folder, "emb_35").edges)


# --- exchange ----------------------------------------------------------------------------------------------------------


def _hops_sql(k):
    return f"hops AS MATERIALIZED (WITH RECURSIVE r(root, v, h) AS (SELECT v, v, 0 FROM vertices UNION SELECT r.root, a.w, r.h + 1 FROM r JOIN adj a ON a.v = r.v WHERE r.h < {k}) SELECT root, v, min(h)::BIGINT AS hops FROM r GROUP BY 1, 2)"


@query(g_sql("emb_30", _hops_sql(3), select="SELECT root, v, hops FROM hops"))
def k_hop_pairs(spark, folder):
    return exchange.k_hop(graph(spark, folder, "emb_30"), 3)


@query(g_sql("emb_30", S.DEG, _hops_sql(4), select="SELECT v, min(hops)::BIGINT AS dist FROM hops WHERE root IN (SELECT v FROM deg WHERE 2 * d >= (SELECT max(d) FROM deg)) GROUP BY v"))
def simulated_bfs(spark, folder):
    """Hops from the nearest vertex of at least half the largest degree."""
    g = graph(spark, folder, "emb_30")
    return exchange.simulate_distances(g, g.degrees().where(F.lit(2) * F.col("d") >= g.max_degree).select("v"), 4, 2)


@query(g_sql("emb_30", _hops_sql(3), select="SELECT root AS v, min(v) AS label FROM hops GROUP BY root"))
def local_min_label(spark, folder):
    return exchange.min_labels(graph(spark, folder, "emb_30"), 3)


@query(g_sql("emb_30", S.DEG, select="SELECT x.v, x.d, (SELECT sum(d.d) FROM adj a JOIN deg d ON d.v = a.w WHERE a.v = x.v)::BIGINT AS got FROM deg x"))
def congest_round(spark, folder):
    """A round whose messages are checked to be of fixed width."""
    g = graph(spark, folder, "emb_30")
    return exchange.local_round(g, g.degrees(), F.col("d"), F.sum, congest=True)


@query(g_sql("part_supp", S.DEG, select="SELECT x.v, (SELECT sum(d.d) FROM adj a JOIN deg d ON d.v = a.w WHERE a.v = x.v)::BIGINT AS agg FROM vertices x"))
def neighbor_aggregate(spark, folder):
    """Sum of the neighbours' degrees on a hub graph, with a salted first level."""
    g = graph(spark, folder, "part_supp")
    return exchange.neighbor_aggregate(g, g.degrees().select("v", F.col("d").alias("x")), "sum", salt=8)


# --- pivot and clipping ------------------------------------------------------------------------------------------------

_PIVOT = [*S.mis(), S.clustering()]


@query(g_sql("emb_30", *_PIVOT, select="SELECT v, cid FROM cl"))
def pivot_clusters(spark, folder):
    return pivot.cluster(graph(spark, folder, "emb_30"))


@query(g_sql("copart_2", *_PIVOT, select="SELECT v, cid FROM cl"))
def pivot_sequential(spark, folder):
    return baselines.sequential_pivot(graph(spark, folder, "copart_2"))


@query(g_sql("geo", S.DEG, select="SELECT v, d, d > 12 AS high FROM deg"))
def clip_split(spark, folder):
    return clip.split(graph(spark, folder, "geo"), 2.0, 1).select("v", "d", "high")


@query(g_sql("scalefree_customers", *S.clipped_pivot(24), select="SELECT v, cid FROM ccl"))
def clip_pivot(spark, folder):
    """Clipping around pivot clusters on a scale-free graph of arboricity at most 2 (threshold 24)."""
    return clip.cluster(graph(spark, folder, "scalefree_customers"), 2.0, 2, pivot.cluster)


@query(g_sql("geo", *S.clipped_pivot(12), select=f"SELECT pos_dis, neg_dis, pos_dis + neg_dis AS cost FROM ({S.cost('ccl')})"))
def cc_three_approx(spark, folder):
    """The flagship: clipped 3-approximation of a hub forest and its cost."""
    g = graph(spark, folder, "geo")
    return measure.cost(g, materialize(clip.three_approx(g, 1, "local"), "clusters"))


@query(g_sql("geo", *S.clip(12), select="SELECT (SELECT count(*) FROM deg WHERE d > 12) AS high, (SELECT count(*) FROM edges) - (SELECT count(*) FROM kedges) AS edges_touched"))
def clip_stats(spark, folder):
    return clip.stats(graph(spark, folder, "geo"), 2.0, 1)


#: Rounds of peeling: edges left (pe), degrees (rd), limit and density bound of each round (rl).
_PEEL = [
    """pe(u, v, it) AS (SELECT u, v, 0 FROM edges UNION ALL (
      WITH d AS (SELECT x AS v, count(*) AS d FROM (SELECT u AS x FROM pe UNION ALL SELECT v FROM pe) GROUP BY 1), l AS (SELECT floor((1 + 0.1::DOUBLE) * sum(d) / count(*)) AS l FROM d)
      SELECT p.u, p.v, p.it + 1 FROM pe p JOIN d a ON a.v = p.u JOIN d b ON b.v = p.v, l WHERE a.d > l AND b.d > l))""",
    "rd AS MATERIALIZED (SELECT it, x AS v, count(*) AS d FROM (SELECT it, u AS x FROM pe UNION ALL SELECT it, v FROM pe) GROUP BY 1, 2)",
    "rl AS MATERIALIZED (SELECT it, floor((1 + 0.1::DOUBLE) * sum(d) / count(*)) AS l, ceil(sum(d) / 2 / greatest(count(*) - 1, 1)) AS lo FROM rd GROUP BY 1)",
]


def _pair_costs_sql(name, limit):
    return g_sql(
        name,
        *_PIVOT,
        *S.clipped_pivot(limit),
        f"a AS (SELECT pos_dis + neg_dis AS c FROM ({S.cost('cl')}))",
        f"b AS (SELECT pos_dis + neg_dis AS c FROM ({S.cost('ccl')}))",
        select=f"SELECT '{name}' AS graph, (SELECT count(*) FROM vertices) AS n, (SELECT count(*) FROM edges) AS m, (SELECT max(d) FROM deg)::BIGINT AS max_degree, (SELECT count(*) FROM deg WHERE d > {limit}) AS high, a.c AS pivot_cost, b.c AS clipped_cost FROM a, b",
    )


def _pair_costs(spark, folder, name, lam):
    g = graph(spark, folder, name)
    plain = measure.cost(g, pivot.cluster(g)).first()["cost"]
    cut = measure.cost(g, materialize(clip.cluster(g, 2.0, lam, pivot.cluster), "clusters")).first()["cost"]
    high = clip.split(g, 2.0, lam).where("high").count()
    return spark.createDataFrame([(name, g.n, g.m, g.max_degree, high, plain, cut)], "graph string, n long, m long, max_degree long, high long, pivot_cost long, clipped_cost long")


@query(_pair_costs_sql("geo", 12))
def clip_vs_pivot(spark, folder):
    """Unclipped pivot against the clipped method."""
    return _pair_costs(spark, folder, "geo", 1)


@query(union_sql([_pair_costs_sql(n, 24) for n in ("scalefree_customers", "scalefree_orders")]))
def w_scalefree_clip(spark, folder):
    return union([_pair_costs(spark, folder, n, 2) for n in ("scalefree_customers", "scalefree_orders")])


def _hub_sql(name):
    """As :func:`_pair_costs_sql`, the threshold 12 times the upper arboricity bound of peeling."""
    bound = "(SELECT 12 * max(d) FROM rd JOIN rl USING (it) WHERE d <= l)"
    tables = [*_PEEL, *_PIVOT, *S.clipped_pivot(bound), f"a AS (SELECT pos_dis + neg_dis AS c FROM ({S.cost('cl')}))", f"b AS (SELECT pos_dis + neg_dis AS c FROM ({S.cost('ccl')}))"]
    return g_sql(name, *tables, select=f"SELECT '{name}' AS graph, (SELECT count(*) FROM vertices) AS n, (SELECT count(*) FROM edges) AS m, (SELECT max(d) FROM deg)::BIGINT AS max_degree, (SELECT count(*) FROM deg WHERE d > {bound}) AS high, a.c AS pivot_cost, b.c AS clipped_cost FROM a, b")


@query(union_sql([_hub_sql("geo"), _hub_sql("part_supp")]))
def w_hub_graphs(spark, folder):
    """Arboricity far below the largest degree, bounded from above on each graph by peeling."""
    return union([_pair_costs(spark, folder, n, arboricity.bounds(graph(spark, folder, n))[1]) for n in ("geo", "part_supp")])


#: Runs of ``w_best_of``; ``pivot_best_of`` makes log2 n of them.
BEST_K = 8


def _copies_sql(k):
    tables = [
        f"cv AS MATERIALIZED (SELECT v * 64 + c.range AS v FROM vertices, range(0, {k}) c)",
        f"ca AS MATERIALIZED (SELECT v * 64 + c.range AS v, w * 64 + c.range AS w FROM adj, range(0, {k}) c)",
    ]
    m = S.mis("42", "_c", "cv", "ca")
    m[0] = f"prio_c AS MATERIALIZED (SELECT v, {S.prio('(42 + v % 64)', '(v // 64)')} AS p FROM cv)"
    return [
        *tables,
        *m,
        S.clustering("_c", "ca"),
        "runs AS MATERIALIZED (SELECT v % 64 AS copy, v // 64 AS v, cid // 64 AS cid FROM cl_c)",
        "costs AS MATERIALIZED (SELECT e.copy, e.pos_dis, e.pos_agree, s.inside - e.pos_agree AS neg_dis FROM (SELECT a.copy, sum((a.cid <> b.cid)::INT) AS pos_dis, sum((a.cid = b.cid)::INT) AS pos_agree FROM edges x JOIN runs a ON a.v = x.u JOIN runs b ON b.v = x.v AND a.copy = b.copy GROUP BY 1) e "
        "JOIN (SELECT copy, sum(s * (s - 1) // 2) AS inside FROM (SELECT copy, cid, count(*) AS s FROM runs GROUP BY 1, 2) GROUP BY 1) s ON s.copy = e.copy)",
    ]


@query(g_sql("emb_30", *_copies_sql("(SELECT greatest(ceil(log2(count(*))), 1)::BIGINT FROM vertices)"), select="SELECT copy, (pos_dis + neg_dis)::BIGINT AS cost FROM costs"))
def pivot_best_of(spark, folder):
    """Costs of log2 n independent runs that share every shuffle."""
    return pivot.best_of(graph(spark, folder, "emb_30"))[1].select("copy", "cost")


@query(g_sql("emb_30", *_copies_sql(BEST_K), select="SELECT k.range AS k, (SELECT min(pos_dis + neg_dis)::BIGINT FROM costs WHERE copy < k.range) AS best FROM range(1, 9) k"))
def w_best_of(spark, folder):
    """Least cost of the first k runs."""
    costs = pivot.best_of(graph(spark, folder, "emb_30"), BEST_K)[1]
    k = spark.range(1, 9).select(F.col("id").alias("k"))
    return k.join(costs, F.col("copy") < F.col("k")).groupBy("k").agg(F.min("cost").alias("best"))


# --- forests -----------------------------------------------------------------------------------------------------------

def _geo_matching_sql() -> str:
    """Levels of the foreign-key tree bottom-up: free = no free child."""
    k = S.K
    return f"""WITH o AS (SELECT o_custkey AS c FROM orders GROUP BY 1), c AS (SELECT c_custkey AS id, c_nationkey AS n, c_custkey NOT IN (SELECT c FROM o) AS free FROM customer),
      n AS (SELECT n_nationkey AS id, n_regionkey AS r, NOT coalesce((SELECT bool_or(free) FROM c WHERE c.n = n_nationkey), false) AS free FROM nation),
      r AS (SELECT r_regionkey AS id, NOT coalesce((SELECT bool_or(free) FROM n WHERE n.r = r_regionkey), false) AS free FROM region),
      pairs AS (SELECT {3 * k} + o_custkey AS u, {4 * k} + min(o_orderkey) AS v FROM orders GROUP BY 1
        UNION ALL SELECT {2 * k} + n, {3 * k} + min(id) FROM c WHERE free GROUP BY n UNION ALL SELECT {k} + r, {2 * k} + min(id) FROM n WHERE free GROUP BY r)
      SELECT * FROM pairs"""


_ISLANDS = """WITH e AS (SELECT event_id, user_id, ts, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER w) > 21600000000, true) AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
  i AS (SELECT user_id, sum(cut::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM e), s AS (SELECT user_id, k, count(*) AS n FROM i GROUP BY 1, 2)"""
_EVENT_M = f"(SELECT sum(n // 2) FROM ({_ISLANDS} SELECT n FROM s))::BIGINT"


_CONV_M = f"(SELECT coalesce(sum(n // 2), 0) FROM (SELECT v - k AS g, count(*) AS n FROM (SELECT v, row_number() OVER (ORDER BY v) AS k FROM ({S.GRAPHS['conv_chain'][0]})) GROUP BY 1))::BIGINT"


@query(f"SELECT 'geo' AS graph, count(*) AS matching FROM ({_geo_matching_sql()}) UNION ALL SELECT 'event_chain', {_EVENT_M}")
def forest_matching_size(spark, folder):
    rows = [(n, forest.max_matching(graph(spark, folder, n)).count()) for n in ("geo", "event_chain")]
    return spark.createDataFrame(rows, "graph string, matching long")


@query(
    f"SELECT v, coalesce(u2, v) AS cid FROM ({S.GRAPHS['geo'][0]}) LEFT JOIN (SELECT u AS x, u AS u2 FROM ({_geo_matching_sql()}) UNION ALL SELECT v, u FROM ({_geo_matching_sql()})) ON x = v"
)
def forest_exact(spark, folder):
    return forest.cluster(graph(spark, folder, "geo"), "exact")


QUERIES["matching_clusters"] = lambda s, f: forest.from_matching(graph(s, f, "geo"), forest.max_matching(graph(s, f, "geo")))
ORACLES["matching_clusters"] = ORACLES["forest_exact"]


@query(
    union_sql(
        [
            g_sql(n, S.COMPONENTS, S.COMP, select=f"SELECT '{n}' AS graph, (SELECT count(*) FROM edges) = (SELECT count(*) FROM vertices) - (SELECT count(DISTINCT comp) FROM comp) AS forest")
            for n in ("geo", "emb_30", "conv_chain")
        ]
    )
)
def is_forest(spark, folder):
    return spark.createDataFrame([(n, forest.check(graph(spark, folder, n))) for n in ("geo", "emb_30", "conv_chain")], "graph string, forest boolean")


def _matching_cost(g, clustering):
    return measure.cost(g, materialize(clustering, "clusters")).first()["cost"]


@query(f"SELECT 'exact' AS method, (SELECT count(*) FROM ({S.GRAPHS['event_chain'][1]})) - {_EVENT_M} AS cost, 1.0::DOUBLE AS bound, true AS within UNION ALL SELECT m, NULL, b, true FROM (VALUES ('maximal', 2.0::DOUBLE), ('det', 1.5), ('rand', 1.5)) t(m, b)", name="forest_ratio")
def forest_ratio(spark, folder):
    """Each forest method against the optimum, with its bound; costs of methods with free choices are left to tests."""
    g = graph(spark, folder, "event_chain")
    opt = _matching_cost(g, forest.cluster(g, "exact"))
    rows = [("exact", opt, 1.0, True)]
    for how, bound in (("maximal", 2.0), ("det", 1.5), ("rand", 1.5)):
        rows.append((how, None, bound, _matching_cost(g, forest.cluster(g, how, 0.5)) <= bound * opt))
    return spark.createDataFrame(rows, "method string, cost long, bound double, within boolean")


RATIOS = tuple(("conv_chain", how, eps) for how in ("det", "rand") for eps in (0.5, 1.0))
_OPT = {
    "event_chain": f"(SELECT count(*) FROM ({S.GRAPHS['event_chain'][1]})) - {_EVENT_M}",
    "conv_chain": f"(SELECT count(*) FROM ({S.GRAPHS['conv_chain'][1]})) - {_CONV_M}",
    "geo": f"(SELECT count(*) FROM ({S.GRAPHS['geo'][1]})) - (SELECT count(*) FROM ({_geo_matching_sql()}))",
}


@query(" UNION ALL ".join(f"SELECT '{g}' AS graph, '{how}' AS method, {eps}::DOUBLE AS eps, {_OPT[g]} AS opt, true AS within" for g, how, eps in RATIOS))
def w_forest_ratios(spark, folder):
    """Both approximate forest methods stay within 1 + eps of the optimum."""
    held = {n: graph(spark, folder, n) for n, _, _ in RATIOS}
    opt = {n: _matching_cost(g, forest.cluster(g, "exact")) for n, g in held.items()}
    rows = [(n, how, eps, opt[n], _matching_cost(held[n], forest.cluster(held[n], how, eps)) <= (1 + eps) * opt[n] + 1e-9) for n, how, eps in RATIOS]
    return spark.createDataFrame(rows, "graph string, method string, eps double, opt long, within boolean")


@query()
def forest_det(spark, folder):
    g = graph(spark, folder, "event_chain")
    return measure.cost(g, materialize(forest.cluster(g, "det", 0.5), "clusters"))


@query()
def forest_rand(spark, folder):
    g = graph(spark, folder, "event_chain")
    return measure.cost(g, materialize(forest.cluster(g, "rand", 0.5), "clusters"))


@query()
def forest_maximal(spark, folder):
    g = graph(spark, folder, "event_chain")
    return measure.cost(g, materialize(forest.cluster(g, "maximal"), "clusters"))


@query()
def forest_coloring(spark, folder):
    return forest.color_reduce(forest.root(graph(spark, folder, "event_chain")))


@query()
def forest_tour_rooting(spark, folder):
    return forest.root(graph(spark, folder, "conv_chain"), "tour")


# --- simple rule, shrinking, arboricity, exact -------------------------------------------------------------------------


@query(
    g_sql(
        "emb_40",
        S.COMPONENTS,
        S.COMP,
        "sz AS (SELECT comp, count(*) AS s FROM comp GROUP BY 1)",
        "ed AS (SELECT c.comp, count(*) AS m FROM edges e JOIN comp c ON c.v = e.u GROUP BY 1)",
        select="SELECT c.v, CASE WHEN coalesce(ed.m, 0) = s * (s - 1) // 2 THEN c.comp ELSE c.v END AS cid FROM comp c JOIN sz ON sz.comp = c.comp LEFT JOIN ed ON ed.comp = c.comp",
    )
)
def simple_cliques(spark, folder):
    return simple.clique_components(graph(spark, folder, "emb_40"))


def _schedule_sql(name, constants):
    """Phases of doubling chunks: iter log2(degree) chunks of 2^i / (den degree) of the order each, the last phase cut."""
    parts = []
    for kind, den, mult in constants:
        parts.append(
            f"SELECT '{kind}' AS constants, i AS phase, least(many, ceil(round((1 - covered) / share, 9)))::BIGINT AS chunks, share FROM (SELECT i, many, share, (pow(2, i) - 1) * many / ({den} * d) AS covered FROM "
            f"(SELECT range AS i, ceil({mult} * log2(d))::BIGINT AS many, pow(2, range) / ({den} * d) AS share, d FROM range(0, 40), (SELECT greatest(max(d), 2)::DOUBLE AS d FROM deg))) WHERE covered < 1"
        )
    return g_sql(name, S.DEG, select=union_sql(parts))


CONSTANTS = (("default", EngineConfig().chunk_den, EngineConfig().iter_mult), ("published", EngineConfig.paper().chunk_den, EngineConfig.paper().iter_mult))


@query(_schedule_sql("copart_1", CONSTANTS))
def chunk_schedule(spark, folder):
    """Chunks of each phase on the densest graph, with the default constants and the published ones."""
    degree = max(graph(spark, folder, "copart_1").max_degree, 2)
    rows = [(kind, *row) for kind, den, mult in CONSTANTS for row in mis.chunk_schedule(degree, EngineConfig(chunk_den=den, iter_mult=mult))]
    return spark.createDataFrame(rows, "constants string, phase long, chunks long, share double")


@query(_mis_sql("copart_3"))
def mis_chunk_defaults(spark, folder):
    """Chunks by the default constants."""
    return mis.chunked(graph(spark, folder, "copart_3"))


@query(_mis_sql("emb_35"))
def mis_hop_radius(spark, folder):
    """Hop gathering with the radius that the graph's size and degree give."""
    return mis.hop_compressed(graph(spark, folder, "emb_35"))


@query(g_sql("conv_chain", S.COMPONENTS, S.COMP, f"c AS (SELECT v, comp AS cid FROM comp)", select=f"SELECT pos_dis + neg_dis AS before_cost, true AS not_dearer, true AS within_size FROM ({S.cost('c')})"))
def shrink_bounds(spark, folder):
    """Shrinking at arboricity one: no cluster above two, and no higher cost than before."""
    g = graph(spark, folder, "conv_chain")
    whole = materialize(baselines.component_clusters(g), "clusters")
    found = materialize(clip.shrink(g, whole, 1), "clusters")
    before, after = _matching_cost(g, whole), _matching_cost(g, found)
    largest = found.groupBy("cid").count().agg(F.max("count")).first()[0] or 0
    return spark.createDataFrame([(before, after <= before, largest <= 2)], "before_cost long, not_dearer boolean, within_size boolean")


@query(g_sql("event_chain", select="SELECT (SELECT count(*) FROM vertices) AS vertices, true AS proper, true AS few"))
def coloring_bounds(spark, folder):
    """The colour reduction of a forest: every vertex, less than six colours, none like its parent's."""
    found = materialize(forest.color_reduce(forest.root(graph(spark, folder, "event_chain"))), "colors")
    above = found.select(F.col("v").alias("parent"), F.col("color").alias("over"))
    clash = found.join(above, "parent").where("color = over").count()
    n, top = found.agg(F.count("*"), F.max("color")).first()
    return spark.createDataFrame([(n, clash == 0, (top or 0) < 6)], "vertices long, proper boolean, few boolean")


@query()
def shrink_clusters(spark, folder):
    """Components of a forest brought below the size an optimum can have (2 at arboricity one)."""
    g = graph(spark, folder, "conv_chain")
    return clip.shrink(g, baselines.component_clusters(g), 1)


@query(g_sql("copart_2", *_PEEL, select="SELECT coalesce(max(lo), 0)::BIGINT AS lo, coalesce((SELECT max(d) FROM rd JOIN rl USING (it) WHERE d <= l), 0)::BIGINT AS hi FROM rl"))
def arboricity_bounds(spark, folder):
    return arboricity.bounds_frame(graph(spark, folder, "copart_2"))


@query()
def exact_components(spark, folder):
    return exact.optimum(graph(spark, folder, "emb_40"))


# --- baselines ---------------------------------------------------------------------------------------------------------


@query()
def base_sampled_is(spark, folder):
    return baselines.sampled_is(graph(spark, folder, "emb_40"))


@query(g_sql("emb_30", *_PIVOT, select="SELECT v, cid FROM cl"))
def base_serial_batches(spark, folder):
    return baselines.serial_batches(graph(spark, folder, "emb_30"), 2.0)


@query()
def base_unlocked(spark, folder):
    return baselines.unlocked_batches(graph(spark, folder, "emb_30"), 2.0)


@query(g_sql("emb_30", select="SELECT v, v AS cid FROM vertices"))
def base_singletons(spark, folder):
    return baselines.singletons(graph(spark, folder, "emb_30"))


@query(g_sql("emb_35", S.COMPONENTS, S.COMP, select="SELECT v, comp AS cid FROM comp"))
def base_components(spark, folder):
    return baselines.component_clusters(graph(spark, folder, "emb_35"))


# --- measures ----------------------------------------------------------------------------------------------------------


def _all_costs(name):
    return g_sql(name, *_PIVOT, f"c AS (SELECT '{name}' AS graph, * FROM ({S.cost()}))", select="SELECT graph, pos_dis, neg_dis, pos_dis + neg_dis AS cost FROM c")


COSTED = ("emb_30", "geo", "event_chain")


@query(union_sql([_all_costs(n) for n in COSTED]))
def cost_breakdown(spark, folder):
    frames = []
    for n in COSTED:
        g = graph(spark, folder, n)
        frames.append(tagged(measure.cost(g, materialize(pivot.cluster(g), "clusters")), graph=n))
    return union(frames)


@query(
    g_sql(
        "emb_30",
        *_PIVOT,
        f"c AS ({S.cost()})",
        select="SELECT pos_agree, (SELECT count(*) * (count(*) - 1) // 2 FROM vertices) - (SELECT count(*) FROM edges) - neg_dis AS neg_agree, pos_agree + (SELECT count(*) * (count(*) - 1) // 2 FROM vertices) - (SELECT count(*) FROM edges) - neg_dis AS agreements FROM c",
    )
)
def agreements(spark, folder):
    g = graph(spark, folder, "emb_30")
    return measure.agreements(g, materialize(pivot.cluster(g), "clusters"))


_BAD = "(SELECT count(*) FROM adj a JOIN adj b ON a.v = b.v AND a.w < b.w LEFT JOIN edges e ON e.u = a.w AND e.v = b.w WHERE e.u IS NULL) AS bad_triangles, (SELECT count(*) FROM edges a JOIN edges b ON a.v = b.u JOIN edges c ON c.u = a.u AND c.v = b.v) AS triangles"


@query(g_sql("copart_2", select=f"SELECT {_BAD}"))
def bad_triangle_count(spark, folder):
    return measure.bad_triangle_count(graph(spark, folder, "copart_2"))


@query()
def bad_triangle_packing(spark, folder):
    return measure.packing_bound(graph(spark, folder, "emb_35"))


@query(g_sql("emb_30", _hops_sql(2), select="SELECT max(c)::BIGINT AS max_ball, sum(c)::BIGINT AS total FROM (SELECT root, count(*) AS c FROM hops GROUP BY 1)"))
def hop_memory(spark, folder):
    """Rows of the largest 2-hop ball, and of all of them."""
    balls = exchange.ball_sizes(graph(spark, folder, "emb_30"), 2)
    return balls.agg(F.max("c").alias("max_ball"), F.sum("c").alias("total"))


@query(g_sql("copart_2", *S.mis()[:3], select="SELECT coalesce(max(f), 0)::BIGINT // 2 AS depth FROM (SELECT v, min(it) AS f FROM st WHERE s = 2 GROUP BY v)"))
def mis_depth(spark, folder):
    """Rounds of local minima until all is decided."""
    return measure.dependency_depth(graph(spark, folder, "copart_2"))


@query(
    g_sql(
        "emb_30",
        *S.mis(),
        f"gone AS (SELECT x.v, least(x.p, coalesce((SELECT min(y.p) FROM adj a JOIN prio y ON y.v = a.w JOIN mis m ON m.v = a.w AND m.in_mis WHERE a.v = x.v), {SPAN})) AS t FROM prio x)",
        "cuts AS (SELECT unnest([50, 100, 250, 500])::INT AS permille)",
        select=f"SELECT permille, coalesce((SELECT max(d) FROM (SELECT a.v, count(*) AS d FROM adj a JOIN gone x ON x.v = a.v JOIN gone y ON y.v = a.w WHERE x.t >= permille::BIGINT * {SPAN // 1000} AND y.t >= permille::BIGINT * {SPAN // 1000} GROUP BY a.v)), 0) AS max_degree FROM cuts",
    )
)
def residual_degree(spark, folder):
    return measure.residual_degree(graph(spark, folder, "emb_30"))


_FIRST = f"floor(least(1.0::DOUBLE, ln(greatest((SELECT count(*) FROM vertices), 3)::DOUBLE) / greatest((SELECT max(d) FROM deg), 1)::DOUBLE) * {SPAN}::DOUBLE)::BIGINT"


@query(
    g_sql(
        "emb_30",
        S.DEG,
        *S.mis()[:1],
        f"first AS MATERIALIZED (SELECT v FROM prio WHERE p < {_FIRST})",
        select="SELECT (SELECT count(*) FROM first) AS vertices, coalesce((SELECT max(c) FROM (SELECT a.v, count(*) AS c FROM adj a JOIN first x ON x.v = a.v JOIN first y ON y.v = a.w GROUP BY a.v)), 0) AS max_degree",
    )
)
def prefix_degree(spark, folder):
    return measure.prefix_degree(graph(spark, folder, "emb_30"))


_EMB30 = S.GRAPHS["emb_30"]
#: Chunks of the first width; at this graph's degree the order ends within the first phase.
_INNER = f"SELECT e.u, e.v FROM ({_EMB30[1]}) e, (SELECT {SPAN}::DOUBLE / max(c) AS w FROM (SELECT x, count(*) AS c FROM (SELECT u AS x FROM ({_EMB30[1]}) UNION ALL SELECT v FROM ({_EMB30[1]})) GROUP BY x)) WHERE floor({S.prio(v='e.u')} / w) = floor({S.prio(v='e.v')} / w)"


@query(g_sql((_EMB30[0], _INNER), S.COMPONENTS, S.COMP, select="SELECT count(*) AS components, coalesce(max(s), 1) AS largest FROM (SELECT comp, count(*) AS s FROM comp WHERE v IN (SELECT v FROM adj) GROUP BY comp)"))
def chunk_components(spark, folder):
    return measure.chunk_component_sizes(graph(spark, folder, "emb_30"))


@query(g_sql("emb_30", *_PIVOT, select="SELECT size, count(*) AS clusters FROM (SELECT cid, count(*) AS size FROM cl GROUP BY 1) GROUP BY 1"))
def cluster_size_hist(spark, folder):
    return measure.cluster_sizes(pivot.cluster(graph(spark, folder, "emb_30")))


@query(g_sql("emb_30", *_PIVOT, select="SELECT count(DISTINCT cid) AS clusters FROM cl"))
def cluster_count(spark, folder):
    return pivot.cluster(graph(spark, folder, "emb_30")).agg(F.count_distinct("cid").alias("clusters"))


@query()
def sketch_profile(spark, folder):
    g = graph(spark, folder, "emb_30")
    return measure.sketch_profile(g, pivot.cluster(g))


# --- workloads ---------------------------------------------------------------------------------------------------------


@query(union_sql([g_sql(n, S.DEG, *S.mis(), select=f"SELECT '{n}' AS graph, c AS direct, c AS prefix, c AS chunk, c AS hop, (SELECT count(*) FROM deg WHERE d > 12 * {lam}) AS clipped FROM (SELECT count(*) AS c FROM mis WHERE in_mis)") for n, lam in (("emb_30", 10), ("copart_2", 13))]))
def w_bounded_degree(spark, folder):
    """Size of the set by four methods: four equal columns; at a bound of the degree, clipping takes nothing."""
    rows = []
    for n, lam in (("emb_30", 10), ("copart_2", 13)):
        g = graph(spark, folder, n)
        ways = (mis.local_minima(g), mis.prefix_phased(g), mis.chunked(g, cfg=EngineConfig(chunk_den=0.2)), mis.hop_compressed(g, radius=2))
        rows.append((n, *(w.where("in_mis").count() for w in ways), clip.split(g, 2.0, lam).where("high").count()))
    return spark.createDataFrame(rows, "graph string, direct long, prefix long, chunk long, hop long, clipped long")


@query(union_sql([g_sql(n, *_PIVOT, f"c AS ({S.cost()})", select=f"SELECT '{n}' AS graph, (SELECT count(*) FROM vertices) AS n, (SELECT count(*) FROM edges) AS m, pos_dis + neg_dis AS cost FROM c") for n in ("grid", "band")]))
def w_planar_band(spark, folder):
    frames = []
    for n in ("grid", "band"):
        g = graph(spark, folder, n)
        frames.append((n, g.n, g.m, _matching_cost(g, pivot.cluster(g))))
    return spark.createDataFrame(frames, "graph string, n long, m long, cost long")


@query(
    f"SELECT 'geo' AS graph, m, k AS matching, m - k AS opt, m - k AS exact_cost FROM (SELECT (SELECT count(*) FROM ({S.GRAPHS['geo'][1]})) AS m, (SELECT count(*) FROM ({_geo_matching_sql()})) AS k)"
    f" UNION ALL SELECT 'event_chain', m, k, m - k, m - k FROM (SELECT (SELECT count(*) FROM ({S.GRAPHS['event_chain'][1]})) AS m, {_EVENT_M} AS k)"
    f" UNION ALL SELECT 'conv_chain', m, k, m - k, m - k FROM (SELECT (SELECT count(*) FROM ({S.GRAPHS['conv_chain'][1]})) AS m, {_CONV_M} AS k)"
)
def w_forest_optimum(spark, folder):
    """Optimum by the size of a maximum matching, and the cost of its clustering counted on the edges."""
    rows = []
    for n in ("geo", "event_chain", "conv_chain"):
        g = graph(spark, folder, n)
        found = materialize(forest.max_matching(g), "matching")
        k = found.count()
        rows.append((n, g.m, k, g.m - k, _matching_cost(g, forest.from_matching(g, found))))
    return spark.createDataFrame(rows, "graph string, m long, matching long, opt long, exact_cost long")


@query(
    f"WITH four AS (SELECT count(*) FILTER (WHERE n = 4) AS c FROM ({_ISLANDS} SELECT n FROM s))"
    " SELECT 'path' AS graph, 1::BIGINT AS paths, 1::BIGINT AS optimum, 2::BIGINT AS middle_edge UNION ALL SELECT 'event_chain', c, c, 2 * c FROM four"
)
def w_tight_path(spark, folder):
    """Four vertices in a row: the optimum, and the maximal matching that takes the middle edge; also on all paths of four
    events, where the middle edge is the one whose ends both have two neighbours."""
    rows = []
    whole = graph(spark, folder, "event_chain")
    comp = materialize(components.components(whole.edges), "comp")
    four = comp.join(comp.groupBy("comp").count().where("count = 4"), "comp").select("v")
    for name, g in (("path", B.path(spark, 4)), ("event_chain", whole.induced(materialize(four, "four")).stored("four"))):
        inner = g.degrees().where("d = 2").select("v")
        middle = g.edges.join(inner, "v", "left_semi").join(inner.select(F.col("v").alias("u")), "u", "left_semi").select("u", "v")
        rows.append((name, g.n // 4, _matching_cost(g, forest.cluster(g, "exact")), _matching_cost(g, forest.from_matching(g, materialize(middle, "middle")))))
    return spark.createDataFrame(rows, "graph string, paths long, optimum long, middle_edge long")


BARBELLS = (3, 5, 8)
_BARBELLS_SQL = "SELECT k::BIGINT AS k, (c // 2)::BIGINT AS barbells, (c // 2)::BIGINT AS two_cliques, (c // 2 * (k * (k - 1) + 1))::BIGINT AS simple_rule FROM (SELECT k, (SELECT count(*) FROM (SELECT o_custkey FROM orders GROUP BY 1 HAVING count(*) = k)) AS c FROM (VALUES (3), (5), (8)) t(k))"


@query(_BARBELLS_SQL)
def w_tight_barbell(spark, folder):
    """Two cliques and a bridge, many times over the orders of customers: keeping the cliques costs 1 each, the simple rule
    leaves all alone."""
    rows = []
    for k in BARBELLS:
        g, two = B.customer_barbells(spark, folder, k)
        g = g.stored("barbells")
        rows.append((k, g.n // (2 * k), _matching_cost(g, two), _matching_cost(g, simple.clique_components(g))))
    return spark.createDataFrame(rows, "k long, barbells long, two_cliques long, simple_rule long")


@query(union_sql([g_sql(n, S.COMPONENTS, S.COMP, select=f"SELECT '{n}' AS graph, (SELECT count(DISTINCT comp) FROM comp) AS clusters, 0::BIGINT AS cost") for n in ("page_host", "doc_exact")]))
def w_clique_components(spark, folder):
    rows = []
    for n in ("page_host", "doc_exact"):
        g = graph(spark, folder, n)
        found = materialize(simple.clique_components(g), "clusters")
        rows.append((n, found.select("cid").distinct().count(), _matching_cost(g, found)))
    return spark.createDataFrame(rows, "graph string, clusters long, cost long")


@query(g_sql("copart_1", *_PIVOT, f"c AS ({S.cost()})", select="SELECT (SELECT count(*) FROM mis WHERE in_mis) AS mis_size, pos_dis + neg_dis AS cost FROM c"))
def w_dense_pivot(spark, folder):
    g = graph(spark, folder, "copart_1")
    found = materialize(pivot.cluster(g), "clusters")
    return measure.cost(g, found).select(F.lit(found.select("cid").distinct().count()).alias("mis_size"), "cost")


@query(
    f"WITH n AS ({_ISLANDS} SELECT n FROM s) SELECT 'empty' AS graph, 0::BIGINT AS n, 0::BIGINT AS clusters, 0::BIGINT AS cost"
    " UNION ALL SELECT 'isolated', count(*), count(*), 0 FROM n WHERE n = 1 UNION ALL SELECT 'pairs', 2 * count(*), count(*), 0 FROM n WHERE n = 2"
)
def w_degenerate(spark, folder):
    """Parts of the event chains: vertices of three neighbours (a chain has none), events alone, and chains of two."""
    g = graph(spark, folder, "event_chain")
    deg = materialize(g.degrees(), "degrees")
    one = deg.where("d = 1").select("v")
    two = g.edges.join(one, "v", "left_semi").join(one.select(F.col("v").alias("u")), "u", "left_semi").select(F.explode(F.array("u", "v")).alias("v"))
    rows = []
    for name, keep in (("empty", deg.where("d > 2").select("v")), ("isolated", deg.where("d = 0").select("v")), ("pairs", materialize(two, "pairs"))):
        part = g.induced(keep).stored(name)
        found = materialize(pivot.cluster(part), "clusters")
        rows.append((name, part.n, found.select("cid").distinct().count(), _matching_cost(part, found)))
    return spark.createDataFrame(rows, "graph string, n long, clusters long, cost long")


GROWTH = (100, 400)


@query()
def w_round_growth(spark, folder):
    """Rounds of the methods and baselines as scale-free graphs grow: steps and exchanges by the ledger, and the stages
    and jobs that Spark ran for them."""
    rows = []
    for n in GROWTH:
        g = B.scalefree(spark, n).stored("growth")
        for name, run in (
            ("direct", lambda x, g=g: mis.local_minima(g, ledger=x)),
            ("prefix-local", lambda x, g=g: mis.prefix_phased(g, ledger=x)),
            ("prefix-chunk", lambda x, g=g: mis.prefix_phased(g, sub="chunk", cfg=EngineConfig(chunk_den=0.1), ledger=x)),
            ("prefix-hop", lambda x, g=g: mis.prefix_phased(g, sub="hop", ledger=x)),
            ("serial-batches", lambda x, g=g: baselines.serial_batches(g, 8.0, ledger=x)),
        ):
            ledger = RoundLedger()
            with measured_stages(spark) as stages:
                run(ledger)
            rows.append((name, g.n, g.max_degree, len(ledger.rows), ledger.rounds, *stages))
    return spark.createDataFrame(rows, "method string, n long, max_degree long, steps long, exchanges long, jobs long, stages long")


EPS = (0.25, 0.5, 1.0, 2.0)


def _eps_sql(eps):
    limit = 8 * (1 + eps) / eps
    return g_sql(
        "geo",
        S.DEG,
        f"cut AS (SELECT v FROM deg WHERE d > {limit})",
        "ke AS MATERIALIZED (SELECT * FROM edges WHERE u NOT IN (SELECT v FROM cut) AND v NOT IN (SELECT v FROM cut))",
        # Levels bottom-up on the clipped forest: free = no free child below.
        f"c AS (SELECT v, v NOT IN (SELECT u FROM ke WHERE v > {4 * S.K}) AS free FROM vertices WHERE v // {S.K} = 3 AND v NOT IN (SELECT v FROM cut))",
        "n AS (SELECT x.v, NOT coalesce((SELECT bool_or(c.free) FROM ke JOIN c ON c.v = ke.v WHERE ke.u = x.v), false) AS free FROM vertices x "
        f"WHERE x.v // {S.K} = 2 AND x.v NOT IN (SELECT v FROM cut))",
        select=f"SELECT {eps}::DOUBLE AS eps, (SELECT count(*) FROM cut) AS high, (SELECT count(*) FROM edges) - (SELECT count(DISTINCT u) FROM ke WHERE v > {4 * S.K})"
        " - (SELECT count(DISTINCT ke.u) FROM ke JOIN c ON c.v = ke.v AND c.free) - (SELECT count(DISTINCT ke.u) FROM ke JOIN n ON n.v = ke.v AND n.free) AS cost",
    )


@query(union_sql([_eps_sql(e) for e in EPS]))
def w_eps_sweep(spark, folder):
    """Clipping at several accuracies around the exact forest method."""
    g = graph(spark, folder, "geo")
    rows = []
    for eps in EPS:
        found = clip.cluster(g, eps, 1, lambda rest: forest.cluster(rest, "exact"))
        rows.append((eps, clip.split(g, eps, 1).where("high").count(), _matching_cost(g, found)))
    return spark.createDataFrame(rows, "eps double, high long, cost long")


#: Graph and upper bound of its arboricity for the clipped method.
COMPARED = (("emb_35", 6), ("conv_chain", 1))


def _compared_sql(name, lam):
    """Costs of methods with one result; those with free choices are told to be no dearer than leaving all together."""
    one, whole = "one AS (SELECT v, v AS cid FROM vertices)", "whole AS (SELECT v, comp AS cid FROM comp)"
    fixed = (("sequential", "cl"), ("serial-batches", "cl"), ("direct", "cl"), ("prefix", "cl"), ("clipped", "ccl"), ("singletons", "one"), ("components", "whole"))
    rows = [f"SELECT '{name}' AS graph, '{m}' AS method, pos_dis + neg_dis AS cost, true AS plausible FROM ({S.cost(t)})" for m, t in fixed]
    rows += [f"SELECT '{name}', '{m}', NULL, true" for m in ("unlocked-batches", *(["sampled-is", "maximal-matching"] if lam == 1 else []))]
    return g_sql(name, *_PIVOT, *S.clipped_pivot(12 * lam), S.COMPONENTS, S.COMP, one, whole, select=" UNION ALL ".join(rows))


@query(union_sql([_compared_sql(*x) for x in COMPARED]))
def w_baselines(spark, folder):
    """Every baseline on a bounded-degree graph and a forest. Methods without one fixed result have a null cost
    and must lie between the triangle packing bound and every pair wrong."""
    asked = []
    for name, lam in COMPARED:
        g = graph(spark, folder, name)
        ways = [
            ("sequential", lambda g=g: baselines.sequential_pivot(g)),
            ("serial-batches", lambda g=g: baselines.serial_batches(g, 8.0)),
            ("direct", lambda g=g: baselines.direct_pivot(g)),
            ("prefix", lambda g=g: pivot.cluster(g, method="prefix")),
            ("clipped", lambda g=g, lam=lam: clip.three_approx(g, lam)),
            ("singletons", lambda g=g: baselines.singletons(g)),
            ("components", lambda g=g: baselines.component_clusters(g)),
            ("unlocked-batches", lambda g=g: baselines.unlocked_batches(g, 8.0)),
        ]
        if lam == 1:
            ways += [("sampled-is", lambda g=g: baselines.sampled_is(g, 1.0)), ("maximal-matching", lambda g=g: baselines.maximal_matching_clusters(g))]
        asked.append(((name, "bound"), lambda g=g: measure.packing_bound(g).first()[0]))
        asked += [((name, m), lambda g=g, way=way: _matching_cost(g, way())) for m, way in ways]
        asked.append(((name, "pairs"), lambda g=g: g.n * (g.n - 1) // 2))
    found = dict(zip([key for key, _ in asked], at_once([f for _, f in asked]), strict=True))
    rows = []
    for (name, m), cost in found.items():
        if m in ("unlocked-batches", "sampled-is", "maximal-matching"):
            rows.append((name, m, None, found[name, "bound"] <= cost <= found[name, "pairs"]))
        elif m not in ("bound", "pairs"):
            rows.append((name, m, cost, True))
    return spark.createDataFrame(rows, "graph string, method string, cost long, plausible boolean")


@query(union_sql([g_sql(n, *_PIVOT, f"c AS ({S.cost()})", select=f"SELECT '{n}' AS graph, (SELECT count(DISTINCT cid) FROM cl) AS clusters, pos_dis + neg_dis AS cost FROM c") for n in ("doc_near_5", "doc_exact", "doc_bench", "event_chain")]))
def w_documents(spark, folder):
    """Documents clustered by similarity of their word shingles, by equal text and by benchmark passages; sessions of events."""
    rows = []
    for n in ("doc_near_5", "doc_exact", "doc_bench", "event_chain"):
        g = graph(spark, folder, n)
        found = materialize(pivot.cluster(g), "clusters")
        rows.append((n, found.select("cid").distinct().count(), _matching_cost(g, found)))
    return spark.createDataFrame(rows, "graph string, clusters long, cost long")


@query(g_sql("emb_30", select="SELECT count(*) AS exact, true AS subset, true AS recalled FROM edges"))
def lsh_recall(spark, folder):
    """Pairs by random hyperplanes against all pairs: none that is not one of them, and nine tenths of them at least."""
    exact = graph(spark, folder, "emb_30")
    rows = B.embedding_rows(spark, folder)
    found = materialize(B.hyperplane_edges(rows, 0.30), "lsh")
    both = found.join(exact.edges, ["u", "v"]).count()
    return spark.createDataFrame([(exact.m, both == found.count(), both >= 0.9 * exact.m)], "exact long, subset boolean, recalled boolean")


@query(g_sql("emb_35", S.DEG, select="SELECT e.u, e.v, d.d FROM edges e JOIN deg d ON d.v = e.u"))
def bucketed_join(spark, folder):
    """Edges and degrees written as tables bucketed alike, joined without another exchange."""
    import uuid

    from signedcluster.sources import tables as T

    g, tag = graph(spark, folder, "emb_35"), uuid.uuid4().hex[:12]
    T.write_bucketed(g.edges, f"edges_{tag}", 4, "u")
    T.write_bucketed(g.degrees().select(F.col("v").alias("u"), "d"), f"degrees_{tag}", 4, "u")
    found = materialize(spark.table(f"edges_{tag}").join(spark.table(f"degrees_{tag}"), "u").select("u", "v", "d"), "joined")
    for t in (f"edges_{tag}", f"degrees_{tag}"):
        spark.sql(f"DROP TABLE {t}")
    return found


@query()
def edges_from_files(spark, folder):
    """Write a graph's edges and a ledger to files, read the edges back."""
    from signedcluster.shared import new_path
    from signedcluster.sources import tables as T

    g = graph(spark, folder, "emb_35")
    target = new_path(spark, "edges")
    T.write(g.edges, target, by="v")
    return T.edge_list(spark, target).edges


QUERIES |= table_queries.QUERIES
ORACLES |= table_queries.ORACLES
