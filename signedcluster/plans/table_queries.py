"""Queries of the operators around the methods, and of the streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from signedcluster.functions.priority import priorities
from signedcluster.model import normalise
from signedcluster.operators import mis, pivot, relational
from signedcluster.plans import graph_sql as S
from signedcluster.plans.graphs import graph
from signedcluster.shared import materialize
from signedcluster.sources.tables import load, packed, register
from signedcluster.streaming import events as E

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


for _t, _key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey"), ("documents", "doc_id"), ("embeddings", "vec_id")):
    QUERIES[f"scan_{_t}"] = lambda s, f, t=_t, k=_key: load(s, f, t).agg(F.count("*").alias("n"), F.max(k).cast("long").alias("last"))
    ORACLES[f"scan_{_t}"] = f"SELECT count(*) AS n, max({_key})::BIGINT AS last FROM {_t}"


@query("SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT l_partkey AS a, l_suppkey AS b FROM lineitem UNION ALL SELECT l_suppkey, l_partkey FROM lineitem) WHERE a <> b")
def edges_normalised(spark, folder):
    """Pairs in both directions, with repeats and self loops, made canonical."""
    line = load(spark, folder, "lineitem")
    return normalise(line.select(F.col("l_partkey").alias("u"), F.col("l_suppkey").alias("v")).unionByName(line.select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v")))).edges


@query(S.with_graph("copart_2", S.DEG, "low AS MATERIALIZED (SELECT v FROM deg WHERE 2 * d <= (SELECT max(d) FROM deg))") + " SELECT u, v FROM edges WHERE u IN (FROM low) AND v IN (FROM low)")
def induced_subgraph(spark, folder):
    """The edges between vertices of at most half the largest degree."""
    g = graph(spark, folder, "copart_2")
    return g.induced(g.degrees().where(F.lit(2) * F.col("d") <= g.max_degree).select("v")).edges


@query("SELECT o_orderkey AS u, c_mktsegment AS segment FROM orders JOIN customer ON o_custkey = c_custkey")
def join_equi(spark, folder):
    orders = load(spark, folder, "orders").select(F.col("o_custkey").alias("c"), F.col("o_orderkey").alias("u"))
    return relational.lookup(orders, load(spark, folder, "customer").select(F.col("c_custkey").alias("v"), F.col("c_mktsegment").alias("segment")), "c").select("u", "segment")


@query(S.with_graph("emb_35") + " SELECT v FROM vertices WHERE v NOT IN (SELECT v FROM adj)")
def isolated_vertices(spark, folder):
    return relational.isolated_vertices(graph(spark, folder, "emb_35"))


@query(S.with_graph("emb_35") + " SELECT a.w AS a, a.v AS b, b.w AS c FROM adj a JOIN adj b ON a.v = b.v AND a.w < b.w LEFT JOIN edges e ON e.u = a.w AND e.v = b.w WHERE e.u IS NULL")
def open_wedges(spark, folder):
    return relational.open_wedges(graph(spark, folder, "emb_35"))


@query(S.with_graph("emb_30", *S.mis()[:2]) + " SELECT v, w FROM low")
def lower_neighbours(spark, folder):
    g = graph(spark, folder, "emb_30")
    return mis.lower_edges(g, priorities(g.vertices)).select("v", "w")


_EVENTS = "SELECT event_id AS id, user_id, epoch_us(ts) AS t, event_type FROM events"


def _events(spark, folder):
    return load(spark, folder, "events").select(F.col("event_id").alias("id"), "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_type", "value")


@query(f"SELECT a.id AS u, b.id AS v FROM ({_EVENTS}) a JOIN ({_EVENTS}) b ON a.user_id = b.user_id AND (b.t, b.id) > (a.t, a.id) AND b.t - a.t <= 3600000000")
def join_interval(spark, folder):
    return relational.within_gap(_events(spark, folder), "user_id", "t", 3_600_000_000)


@query(
    f"SELECT p.id, (SELECT arg_max(c.id, (c.t, c.id)) FROM ({_EVENTS}) c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND c.t <= p.t) AS fact FROM ({_EVENTS}) p WHERE p.event_type = 'purchase'"
)
def join_asof(spark, folder):
    """The last click of the user at or before each purchase."""
    e = _events(spark, folder)
    return relational.as_of(e.where("event_type = 'purchase'"), e.where("event_type = 'click'"), "user_id", "t")


@query(S.with_graph("part_supp", S.DEG) + " SELECT d, count(*) AS vertices FROM deg GROUP BY d")
def degree_histogram(spark, folder):
    return graph(spark, folder, "part_supp", stored=False).degrees().groupBy("d").agg(F.count("*").alias("vertices"))


_DOC_PAIRS = S.with_graph("doc_exact") + f", x AS (SELECT a.lang, a.source FROM edges e JOIN documents a ON a.doc_id + {7 * S.K} = e.u)"


def _doc_pairs(spark, folder):
    docs = load(spark, folder, "documents").select(packed(7, "doc_id").alias("u"), "lang", "source")
    return graph(spark, folder, "doc_exact").edges.join(docs, "u")


@query(_DOC_PAIRS + " SELECT lang, source, count(*) AS edges FROM x GROUP BY CUBE (lang, source)")
def cost_cube(spark, folder):
    return _doc_pairs(spark, folder).cube("lang", "source").agg(F.count("*").alias("edges"))


@query(_DOC_PAIRS + " SELECT lang, source, count(*) AS edges FROM x GROUP BY ROLLUP (lang, source)")
def cost_rollup(spark, folder):
    return _doc_pairs(spark, folder).rollup("lang", "source").agg(F.count("*").alias("edges"))


@query(_DOC_PAIRS + " SELECT lang, source, count(*) AS edges FROM x GROUP BY GROUPING SETS ((lang), (source), ())")
def cost_grouping_sets(spark, folder):
    _doc_pairs(spark, folder).createOrReplaceTempView("doc_pairs")
    return spark.sql("SELECT lang, source, count(*) AS edges FROM doc_pairs GROUP BY GROUPING SETS ((lang), (source), ())")


@query(S.with_graph("emb_30", *S.mis(), S.clustering(), S.DEG) + " SELECT cl.v, cid, row_number() OVER (PARTITION BY cid ORDER BY d DESC, cl.v) AS place FROM cl JOIN deg ON deg.v = cl.v")
def cluster_rank(spark, folder):
    """Place of each member in its cluster by degree."""
    g = graph(spark, folder, "emb_30")
    both = pivot.cluster(g).join(g.degrees(), "v")
    return both.select("v", "cid", F.row_number().over(Window.partitionBy("cid").orderBy(F.desc("d"), "v")).cast("long").alias("place"))


@query(f"SELECT id, sum(cut) OVER (PARTITION BY user_id ORDER BY t, id ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM (SELECT *, coalesce((t - lag(t) OVER (PARTITION BY user_id ORDER BY t, id) > 21600000000)::INT, 1) AS cut FROM ({_EVENTS}))")
def session_ids(spark, folder):
    return relational.sessions(_events(spark, folder), "user_id", "t", 21_600_000_000).select("id", "session")


@query("SELECT event_id AS id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events")
def moving_events(spark, folder):
    w = Window.partitionBy("user_id").orderBy("t", "id").rowsBetween(-2, 0)
    return _events(spark, folder).select("id", F.round(F.avg("value").over(w), 6).alias("mean3"))


@query(S.with_graph("part_supp", S.DEG) + " SELECT v, d FROM deg ORDER BY d DESC, v LIMIT 10")
def topk_hubs(spark, folder):
    return relational.top_k(graph(spark, folder, "part_supp", stored=False).degrees(), 10, "d", "v")


def _edges(t):
    return f"(SELECT u, v FROM ({S.emb(t)[1]}))"


@query(
    f"SELECT 'union' AS op, count(*) AS n FROM ({_edges(0.30)} UNION {_edges(0.35)}) UNION ALL SELECT 'intersect', count(*) FROM ({_edges(0.30)} INTERSECT {_edges(0.35)}) UNION ALL SELECT 'except', count(*) FROM ({_edges(0.30)} EXCEPT {_edges(0.35)})"
)
def edges_setops(spark, folder):
    a, b = graph(spark, folder, "emb_30").edges, graph(spark, folder, "emb_35").edges
    count = lambda df, op: df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
    return count(a.unionByName(b).distinct(), "union").unionByName(count(a.intersect(b), "intersect")).unionByName(count(a.exceptAll(b), "except"))


@query("SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host FROM pages")
def page_hosts(spark, folder):
    return load(spark, folder, "pages").select("page_id", relational.host(F.col("url")).alias("host"))


@query("SELECT doc_id, md5(trim(regexp_replace(lower(text), '[ \\t\\n\\r\\f]+', ' ', 'g'), ' ')) AS h FROM documents")
def doc_norm_hash(spark, folder):
    return load(spark, folder, "documents").select("doc_id", F.md5(F.trim(F.regexp_replace(F.lower("text"), r"[ \t\n\r\f]+", " "))).alias("h"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS events FROM events GROUP BY 1")
def events_daily(spark, folder):
    return load(spark, folder, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("events"))


@query(S.with_graph("emb_35") + " SELECT v, array_to_string(list_sort(list(w)), ',') AS near FROM adj GROUP BY v")
def neighbour_arrays(spark, folder):
    g = graph(spark, folder, "emb_35")
    return g.adj.groupBy("v").agg(F.array_join(F.array_sort(F.collect_list("w")), ",").alias("near"))


@query("SELECT (json_extract_string(props, '$.k'))::BIGINT AS k, count(*) AS events FROM events GROUP BY 1")
def json_props(spark, folder):
    return load(spark, folder, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("events"))


@query(S.with_graph("emb_35") + " SELECT w AS v, count(*) AS d FROM adj GROUP BY 1")
def edge_endpoints(spark, folder):
    e = graph(spark, folder, "emb_35").edges
    return e.select(F.explode(F.array("u", "v")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))


@query(S.with_graph("emb_35", *S.mis(), S.clustering()) + " SELECT a.v AS u, b.v FROM cl a JOIN cl b ON a.cid = b.cid AND a.v < b.v")
def udtf_pairs(spark, folder):
    """Pairs inside clusters by a table function called from SQL."""
    relational.register_sql(spark)
    g = graph(spark, folder, "emb_35")
    pivot.cluster(g).groupBy("cid").agg(F.collect_list("v").alias("members")).createOrReplaceTempView("members")
    return spark.sql("SELECT p.u, p.v FROM members, LATERAL cluster_pairs(members) p")


@query(S.with_graph("emb_35", *S.mis(), S.clustering()) + f" SELECT pos_dis, neg_dis FROM ({S.cost()})")
def sql_cost(spark, folder):
    """Cost of a clustering in SQL over registered views."""
    g = graph(spark, folder, "emb_35")
    register(g, materialize(pivot.cluster(g), "clusters"))
    return spark.sql("""
        WITH e AS (SELECT count_if(a.cid <> b.cid) AS pos_dis, count_if(a.cid = b.cid) AS same FROM edges JOIN clustering a ON a.v = edges.u JOIN clustering b ON b.v = edges.v),
             s AS (SELECT coalesce(sum(n * (n - 1) div 2), 0) AS inside FROM (SELECT count(*) AS n FROM clustering GROUP BY cid))
        SELECT pos_dis, inside - same AS neg_dis FROM e, s""")


@query(S.with_graph("conv_chain") + ", r(v, d) AS (SELECT v, 0 FROM vertices WHERE v NOT IN (SELECT v FROM edges) UNION ALL SELECT e.v, r.d + 1 FROM r JOIN edges e ON e.u = r.v) SELECT max(d)::BIGINT AS depth, count(*) AS n FROM r")
def recursive_depth(spark, folder):
    """Longest chain by recursive SQL (small chains only)."""
    register(graph(spark, folder, "conv_chain"))
    return spark.sql("""
        WITH RECURSIVE r(v, d) AS (SELECT v, 0 FROM vertices WHERE v NOT IN (SELECT v FROM edges) UNION ALL SELECT e.v, r.d + 1 FROM r JOIN edges e ON e.u = r.v)
        SELECT max(d)::BIGINT AS depth, count(*) AS n FROM r""")


@query("SELECT (epoch_us(ts) // 21600000000) * 21600000000 AS start_us, event_type, count(*) AS events, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, folder):
    return E.finished(E.windows(E.event_stream(spark, folder)), "tumbling").withColumn("total", F.round("total", 4))


@query("SELECT (epoch_us(ts) // 10800000000 - k.range) * 10800000000 AS start_us, event_type, count(*) AS events, round(sum(value), 4) AS total FROM events, range(0, 2) k GROUP BY 1, 2")
def stream_sliding(spark, folder):
    return E.finished(E.windows(E.event_stream(spark, folder), "6 hours", "3 hours"), "sliding").withColumn("total", F.round("total", 4))


@query(
    "WITH e AS (SELECT user_id, epoch_us(ts) AS t, event_id, coalesce((epoch_us(ts) - epoch_us(lag(ts) OVER w) >= 21600000000)::INT, 1) AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),"
    " s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS k FROM e)"
    " SELECT user_id, min(t) AS start_us, max(t) + 21600000000 AS end_us, count(*) AS events FROM s GROUP BY user_id, k"
)
def stream_session(spark, folder):
    return E.finished(E.session_windows(E.event_stream(spark, folder)), "session")


@query("SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id FROM events GROUP BY 1")
def stream_last_event(spark, folder):
    return E.finished(E.last_events(E.event_stream(spark, folder)), "last")


@query(
    "SELECT least(a.event_id, b.event_id) AS u, greatest(a.event_id, b.event_id) AS v FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE"
)
def stream_edges(spark, folder):
    """Stream-stream interval join that turns near events into positive edges."""
    a, b = E.event_stream(spark, folder), E.event_stream(spark, folder)
    return E.finished(E.near_pairs(a, b), "stream-edges", "append")


@query(S.with_graph("conv_chain", *S.mis(), S.clustering()) + " SELECT v, cid FROM cl WHERE v IN (SELECT v FROM adj)")
def stream_recluster(spark, folder):
    """A graph in two batches: the second re-clusters only the components that it touches."""
    edges = graph(spark, folder, "conv_chain").edges
    first, second = edges.where("u % 3 <> 0"), edges.where("u % 3 = 0")
    g = normalise(first).stored("first")
    return E.recluster(g.edges, materialize(pivot.cluster(g), "clusters"), second)[1]
