"""The same graphs and methods in SQL, for checks against another engine."""

from __future__ import annotations

K = 10**12


def _ends(*selects: str) -> str:
    return " UNION ".join(selects)


def _canonical(pairs: str) -> str:
    return f"SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM ({pairs}) WHERE a <> b"


_ends_of_edges = "SELECT u AS v FROM edges UNION SELECT v FROM edges"

_shingle = (
    "SELECT id, unnest(list_distinct(CASE WHEN len(w) <= 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3),"
    " lambda i: array_to_string(w[i:i + 4], ' ')) END)) AS s FROM (SELECT {kind} + {key} AS id, regexp_extract_all(lower(text), '[\\w\\p{{L}}\\p{{M}}\\p{{N}}]+') AS w FROM {table} WHERE text IS NOT NULL)"
)


def _near(t: float) -> str:
    sh = _shingle.format(kind=7 * K, key="doc_id", table="documents")
    return f"""WITH sh AS MATERIALIZED ({sh}), size AS MATERIALIZED (SELECT id, count(*) AS n FROM sh GROUP BY 1)
      SELECT p.u, p.v FROM (SELECT a.id AS u, b.id AS v, count(*) AS k FROM sh a JOIN sh b ON a.s = b.s AND a.id < b.id GROUP BY 1, 2) p
      JOIN size i ON i.id = p.u JOIN size j ON j.id = p.v WHERE p.k >= {t} * (i.n + j.n - p.k)"""


def copart(k: int) -> tuple[str, str]:
    edges = f"""SELECT {5 * K} + a.l_partkey AS u, {5 * K} + b.l_partkey AS v FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a
      JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
      GROUP BY 1, 2 HAVING count(*) >= {k}"""
    return f"SELECT {5 * K} + p_partkey AS v FROM part", edges


def emb(t: float) -> tuple[str, str]:
    return "SELECT vec_id::BIGINT AS v FROM embeddings", f"""SELECT a.vec_id::BIGINT AS u, b.vec_id::BIGINT AS v FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id
      WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= {t}"""


def scalefree(size: str, k: int, p: int) -> tuple[str, str]:
    h = "(('0x' || substr(md5('7:' || j || ':' || i), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"
    power = "*".join(["h"] * p)
    return f"SELECT range AS v FROM range(0, ({size}))", _canonical(
        f"SELECT floor(j * ({power}))::BIGINT AS a, j AS b FROM (SELECT j, i, {h} AS h FROM (SELECT range AS j FROM range({k}, ({size}))) CROSS JOIN (SELECT range AS i FROM range(0, {k})))"
    )


#: name -> (vertices, edges); vertices may refer to ``edges``.
GRAPHS: dict[str, tuple[str, str]] = {
    "geo": (
        _ends(f"SELECT {K} + r_regionkey AS v FROM region", f"SELECT {2 * K} + n_nationkey FROM nation", f"SELECT {3 * K} + c_custkey FROM customer", f"SELECT {4 * K} + o_orderkey FROM orders"),
        f"""SELECT {K} + n_regionkey AS u, {2 * K} + n_nationkey AS v FROM nation
            UNION SELECT {2 * K} + c_nationkey, {3 * K} + c_custkey FROM customer UNION SELECT {3 * K} + o_custkey, {4 * K} + o_orderkey FROM orders""",
    ),
    "event_chain": (
        "SELECT event_id AS v FROM events",
        """SELECT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT event_id AS a, lead(event_id) OVER w AS b, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS gap
           FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE b IS NOT NULL AND gap <= 21600000000""",
    ),
    "conv_chain": (
        "SELECT DISTINCT conv_id * 100 + turn AS v FROM conversations",
        "SELECT DISTINCT a.conv_id * 100 + a.turn AS u, a.conv_id * 100 + a.turn + 1 AS v FROM conversations a JOIN conversations b ON a.conv_id * 100 + a.turn + 1 = b.conv_id * 100 + b.turn",
    ),
    "order_part": (_ends_of_edges, f"SELECT DISTINCT {4 * K} + l_orderkey AS u, {5 * K} + l_partkey AS v FROM lineitem"),
    "part_supp": (_ends_of_edges, f"SELECT DISTINCT {5 * K} + l_partkey AS u, {6 * K} + l_suppkey AS v FROM lineitem"),
    "copart_1": copart(1),
    "copart_2": copart(2),
    "copart_3": copart(3),
    "emb_25": emb(0.25),
    "emb_30": emb(0.30),
    "emb_35": emb(0.35),
    "emb_40": emb(0.40),
    "emb_50": emb(0.50),
    "page_host": (
        "SELECT page_id::BIGINT AS v FROM pages",
        """SELECT a.page_id::BIGINT AS u, b.page_id::BIGINT AS v FROM pages a JOIN pages b ON a.page_id < b.page_id
           AND regexp_extract(a.url, '^https?://([^/?#]+)', 1) = regexp_extract(b.url, '^https?://([^/?#]+)', 1)""",
    ),
    "doc_exact": (
        f"SELECT {7 * K} + doc_id AS v FROM documents",
        f"""WITH d AS (SELECT {7 * K} + doc_id AS id, trim(regexp_replace(lower(text), '[ \\t\\n\\r\\f]+', ' ', 'g'), ' ') AS k FROM documents)
            SELECT a.id AS u, b.id AS v FROM d a JOIN d b ON a.k = b.k AND a.id < b.id""",
    ),
    "doc_near_5": (f"SELECT {7 * K} + doc_id AS v FROM documents", _near(0.5)),
    "doc_near_8": (f"SELECT {7 * K} + doc_id AS v FROM documents", _near(0.8)),
    "doc_bench": (
        _ends_of_edges,
        f"""SELECT DISTINCT a.id AS u, b.id AS v FROM ({_shingle.format(kind=7 * K, key="doc_id", table="documents")}) a
            JOIN ({_shingle.format(kind=8 * K, key="item_id", table="benchmark")}) b ON a.s = b.s""",
    ),
    "scalefree_customers": scalefree("SELECT count(*) FROM customer", 2, 2),
    "scalefree_orders": scalefree("SELECT count(*) FROM orders", 2, 2),
    "grid": (
        "SELECT range AS v FROM range(0, (SELECT count(*) FROM part))",
        """WITH s AS (SELECT count(*) AS n, ceil(sqrt(count(*)))::BIGINT AS side FROM part)
           SELECT id AS u, id + 1 AS v FROM (SELECT range AS id FROM range(0, (SELECT n FROM s))), s WHERE id % side <> side - 1 AND id + 1 < n
           UNION SELECT id, id + side FROM (SELECT range AS id FROM range(0, (SELECT n FROM s))), s WHERE id + side < n""",
    ),
    "band": (
        "SELECT range AS v FROM range(0, (SELECT count(*) FROM orders))",
        "SELECT a.range AS u, a.range + d.range AS v FROM range(0, (SELECT count(*) FROM orders)) a, range(1, 3) d WHERE a.range + d.range < (SELECT count(*) FROM orders)",
    ),
}


def path(n: int) -> tuple[str, str]:
    return f"SELECT range AS v FROM range(0, {n})", f"SELECT range AS u, range + 1 AS v FROM range(0, {max(n - 1, 0)})"


def with_graph(name_or_pair, *more: str) -> str:
    """``WITH RECURSIVE edges, vertices, adj`` of a graph and more tables."""
    v, e = GRAPHS[name_or_pair] if isinstance(name_or_pair, str) else name_or_pair
    parts = [
        f"edges AS MATERIALIZED ({e})",
        f"vertices AS MATERIALIZED ({v})",
        "adj AS MATERIALIZED (SELECT u AS v, v AS w FROM edges UNION ALL SELECT v, u FROM edges)",
        *more,
    ]
    return "WITH RECURSIVE " + ",\n".join(parts)


def prio(seed: str = "42", v: str = "v") -> str:
    return f"('0x' || substr(md5({seed} || ':' || {v}), 1, 15))::BIGINT"


def mis(seed: str = "42", suffix: str = "", vertices: str = "vertices", adj: str = "adj") -> list[str]:
    """Tables prio, low, st, mis: states 0 open, 1 in, 2 out, the whole state each iteration."""
    s = suffix
    return [
        f"prio{s} AS MATERIALIZED (SELECT v, {prio(seed)} AS p FROM {vertices})",
        f"low{s} AS MATERIALIZED (SELECT a.v, a.w FROM {adj} a JOIN prio{s} x ON x.v = a.v JOIN prio{s} y ON y.v = a.w WHERE (y.p, y.v) < (x.p, x.v))",
        f"""st{s}(v, s, it) AS (SELECT v, 0, 0 FROM {vertices} UNION ALL
          SELECT c.v, CASE WHEN c.s <> 0 THEN c.s WHEN coalesce(max(CASE WHEN o.s = 1 THEN 1 END), 0) = 1 THEN 2 WHEN coalesce(max(CASE WHEN o.s = 0 THEN 1 END), 0) = 0 THEN 1 ELSE 0 END, c.it + 1
          FROM st{s} c LEFT JOIN low{s} l ON l.v = c.v LEFT JOIN st{s} o ON o.v = l.w WHERE EXISTS (SELECT 1 FROM st{s} WHERE s = 0) GROUP BY c.v, c.s, c.it)""",
        f"mis{s} AS MATERIALIZED (SELECT v, s = 1 AS in_mis FROM st{s} WHERE it = (SELECT max(it) FROM st{s}))",
    ]


def clustering(suffix: str = "", adj: str = "adj") -> str:
    """Table cl(v, cid) of the pivot rule."""
    s = suffix
    return f"""cl{s} AS MATERIALIZED (SELECT m.v, CASE WHEN m.in_mis THEN m.v ELSE (array_agg(a.w ORDER BY p.p, p.v))[1] END AS cid
      FROM mis{s} m LEFT JOIN (SELECT a.* FROM {adj} a JOIN mis{s} i ON i.v = a.w AND i.in_mis) a ON a.v = m.v LEFT JOIN prio{s} p ON p.v = a.w GROUP BY m.v, m.in_mis)"""


def cost(cl: str = "cl", edges: str = "edges") -> str:
    """Scalar subselects pos, inside, pairs of a clustering."""
    return f"""SELECT coalesce(sum(CASE WHEN a.cid <> b.cid THEN 1 ELSE 0 END), 0)::BIGINT AS pos_dis,
      ((SELECT coalesce(sum(s * (s - 1) // 2), 0) FROM (SELECT count(*) AS s FROM {cl} GROUP BY cid)) - coalesce(sum(CASE WHEN a.cid = b.cid THEN 1 ELSE 0 END), 0))::BIGINT AS neg_dis,
      coalesce(sum(CASE WHEN a.cid = b.cid THEN 1 ELSE 0 END), 0)::BIGINT AS pos_agree
      FROM {edges} e JOIN {cl} a ON a.v = e.u JOIN {cl} b ON b.v = e.v"""


COMPONENTS = """lab(v, c, it, moved) AS (SELECT v, v, 0, true FROM vertices UNION ALL
  SELECT x.v, least(x.c, coalesce(min(y.c), x.c)), x.it + 1, least(x.c, coalesce(min(y.c), x.c)) < x.c
  FROM lab x LEFT JOIN adj a ON a.v = x.v LEFT JOIN lab y ON y.v = a.w WHERE EXISTS (SELECT 1 FROM lab WHERE moved) GROUP BY x.v, x.c, x.it)"""
COMP = "comp AS MATERIALIZED (SELECT v, c AS comp FROM lab WHERE it = (SELECT max(it) FROM lab))"
DEG = "deg AS MATERIALIZED (SELECT x.v, count(a.w) AS d FROM vertices x LEFT JOIN adj a ON a.v = x.v GROUP BY x.v)"


def clip(limit: float) -> list[str]:
    """Tables deg, keep(v), kedges, kadj of the clipped graph."""
    return [
        DEG,
        f"keep AS MATERIALIZED (SELECT v FROM deg WHERE d <= {limit})",
        "kedges AS MATERIALIZED (SELECT e.* FROM edges e JOIN keep a ON a.v = e.u JOIN keep b ON b.v = e.v)",
        "kadj AS MATERIALIZED (SELECT u AS v, v AS w FROM kedges UNION ALL SELECT v, u FROM kedges)",
    ]


def clipped_pivot(limit: float, seed: str = "42") -> list[str]:
    """Tables up to ccl(v, cid): high vertices alone, pivot clusters on the rest."""
    return [*clip(limit), *mis(seed, "_k", "keep", "kadj"), clustering("_k", "kadj"), "ccl AS MATERIALIZED (SELECT * FROM cl_k UNION ALL SELECT v, v FROM deg WHERE v NOT IN (SELECT v FROM keep))"]
