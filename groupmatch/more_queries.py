"""Queries on other graphs and around the methods."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupmatch import oracle_sql as O
from groupmatch import streaming
from groupmatch.durable import settle, settle_counted, shared_folder
from groupmatch.functions import membership, udfs
from groupmatch.model import GroupPattern, MembershipRule
from groupmatch.model import pattern as P
from groupmatch.operators import candidates, explore, paths, prune
from groupmatch.queries import _LINK, _graph, graph_stats, register
from groupmatch.sources import graphs, io

_M = O.mixed
t = graphs.table

# Builders of the other graphs.
_REAL = O.handover() + """, rv AS (SELECT c_custkey AS id, [c_mktsegment, r_name] AS labels, (c_acctbal + 1000.0::DOUBLE) / 11000.0::DOUBLE AS influence FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
re AS (SELECT src, dst, sum(CASE WHEN l_returnflag = 'R' THEN 0.0 ELSE 1.0 END)::DOUBLE / count(*) AS trust, least(1.0::DOUBLE, count(*) / 4.0::DOUBLE) AS intimacy FROM raw WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst)"""
register("scan_handover_real", f"WITH {_REAL} SELECT src, dst, trust, intimacy FROM re")(lambda s, d: graphs.handover_real(s, d).edges)
register("scan_handover_real_vertices", f"WITH {_REAL} SELECT id, labels, influence FROM rv")(lambda s, d: graphs.handover_real(s, d).vertices)
_K = [k * 10**13 for k in range(6)]
_TYPED = f"""SELECT {_K[1]} + o_custkey AS src, {_K[3]} + l_partkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey 
UNION SELECT {_K[3]} + l_partkey, {_K[2]} + l_suppkey FROM lineitem UNION SELECT {_K[1]} + c_custkey, {_K[4]} + c_nationkey FROM customer
UNION SELECT {_K[2]} + s_suppkey, {_K[4]} + s_nationkey FROM supplier UNION SELECT {_K[4]} + n_nationkey, {_K[5]} + n_regionkey FROM nation"""
register("scan_typed", _TYPED)(lambda s, d: graphs.typed(s, d).edges.select("src", "dst"))
_CLICK = "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst"
register("scan_click", _CLICK)(lambda s, d: graphs.click(s, d).edges.select("src", "dst"))
_DOT = "list_sum(list_transform(range(1, 65), lambda i: a.x[i] * b.x[i]))"
_SIM = f"""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings),
n AS (SELECT vec_id, x, sqrt(list_sum(list_transform(x, lambda y: y * y))) AS l FROM e),
p AS (SELECT a.vec_id AS src, b.vec_id AS dst, list_inner_product(a.x, b.x) / (a.l * b.l) AS c FROM n a JOIN n b ON a.vec_id <> b.vec_id)
SELECT src, dst, rank FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY round(c, 9) DESC, dst) AS rank FROM p WHERE c >= 0.15) WHERE rank <= 8"""
register("scan_similar", _SIM)(lambda s, d: graphs.similar(s, d).edges.select("src", "dst", F.round(F.lit(1.0) / F.col("intimacy")).cast("long").alias("rank")))
_TURN = "SELECT src, dst FROM (SELECT conv_id * 100000 + turn AS src, lead(conv_id * 100000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL"
register("scan_turns", _TURN)(lambda s, d: graphs.turns(s, d).edges.select("src", "dst"))
_LINKS = """WITH h AS (SELECT page_id, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS href FROM pages),
n AS (SELECT page_id, count(*) AS n FROM h GROUP BY 1)
SELECT a.page_id AS src, b.page_id AS dst, count(*)::DOUBLE / any_value(n) AS trust FROM h a JOIN h b ON a.href = b.href AND a.page_id < b.page_id JOIN n ON n.page_id = a.page_id GROUP BY 1, 2"""
register("scan_links", _LINKS)(lambda s, d: graphs.links(s, d).edges.select("src", "dst", "trust"))
_WORDS = lambda c: f"regexp_extract_all(lower({c}), '[^ \\t\\n\\r]+')"
_EVID = f"""WITH k AS (SELECT {10**13} + item_id AS dst, ' ' || array_to_string({_WORDS('text')}, ' ') || ' ' AS passage FROM benchmark),
w AS (SELECT doc_id AS src, ' ' || array_to_string({_WORDS('text')}, ' ') || ' ' AS words FROM documents)
SELECT src, dst FROM w JOIN k ON contains(words, passage) UNION SELECT src, dst FROM (SELECT doc_id AS src, lead(doc_id) OVER (PARTITION BY source ORDER BY doc_id) AS dst FROM documents) WHERE dst IS NOT NULL"""
register("scan_evidence", _EVID)(lambda s, d: graphs.evidence(s, d).edges.select("src", "dst"))

# Patterns on them.
_SHAPES: dict[str, tuple[str, GroupPattern]] = {
    "typed_groups": ("typed", P.pattern("typed", {"cust": "customer", "part": "part", "nation": "nation", "supp": "supplier"}, [("cust", "part", 1), ("part", "supp", 1), ("cust", "nation", 1), ("supp", "nation", 1)], 0.2)),
    "similar_groups": ("similar", P.pattern("similar", {"a": "1", "b": "2", "c": "3"}, [("a", "b", 2), ("a", "c", 2), ("b", "c", 2)], None)),
    "click_groups": ("click", P.pattern("click", {"a": "purchase", "b": "click", "c": "view"}, [("a", "b", 1), ("b", "c", 1), ("a", "c", 2)], 0.5)),
    "link_groups": ("links", P.pattern("links", {"a": "en", "b": "fr", "c": "de"}, [("a", "b", 2), ("b", "c", 2)], None)),
    "evidence_groups": ("evidence", P.pattern("evidence", {"a": "en", "b": "item"}, [("a", "b", 2)], None)),
}
_KINDS = [("customer", "c_custkey"), ("supplier", "s_suppkey"), ("part", "p_partkey"), ("nation", "n_nationkey"), ("region", "r_regionkey")]
_TYPED_V = " UNION ALL ".join(f"SELECT {_K[k]} + {key} AS id, '{name}' AS label, {O.influence(f'({_K[k]} + {key})')} FROM {name}" for k, (name, key) in enumerate(_KINDS, 1))
_CLICK_V = f"SELECT user_id AS id, arg_max(event_type, {{'n': n, 't': event_type}}) AS label, {O.influence('user_id')} FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id"
_PAGE_V = f"SELECT page_id AS id, regexp_extract(url, '://[^/]*/([a-z][a-z])/', 1) AS label, {O.influence('page_id')} FROM pages"
_DOC_V = f"SELECT doc_id AS id, lang AS label, quality::DOUBLE AS influence FROM documents LEFT JOIN (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY 1) USING (doc_id) UNION ALL SELECT {10**13} + item_id, 'item', 1.0 FROM benchmark"
_VEC_V = f"SELECT vec_id AS id, label::VARCHAR AS label, {O.influence('vec_id')} FROM embeddings WHERE embedding IS NOT NULL"
_TURN_V = f"SELECT conv_id * 100000 + turn AS id, role AS label, {O.influence('(conv_id * 100000 + turn)')} FROM conversations"
_DATA = {
    "typed": (_TYPED_V, O.scored(_TYPED)),
    "click": (_CLICK_V, O.scored(_CLICK)),
    "similar": (_VEC_V, f"SELECT src, dst, 1.0::DOUBLE AS trust, 1.0::DOUBLE AS intimacy FROM ({_SIM})"),
    "links": (_PAGE_V, f"SELECT src, dst, trust, 1.0::DOUBLE AS intimacy FROM ({_LINKS})"),
    "evidence": (_DOC_V, O.scored(_EVID)),
    "turns": (_TURN_V, f"SELECT src, dst, 1.0::DOUBLE AS trust, 1.0::DOUBLE AS intimacy FROM ({_TURN})"),
}
_PROFILE = "SELECT '{name}' AS graph, (SELECT count(*) FROM ({v})) AS vertices, CAST(coalesce(sum(d), 0) AS BIGINT) AS edges, coalesce(sum(d), 0) / (SELECT count(*) FROM ({v})) AS mean_degree, coalesce(max(d), 0) AS max_degree FROM (SELECT src, count(*) AS d FROM ({e}) GROUP BY src)"
_HAND = f"WITH {O.handover(3)} SELECT * FROM "
_EVERY = _DATA | {"handover": (_HAND + "vtx", _HAND + "edg"), "handover_real": (f"WITH {_REAL} SELECT * FROM rv", f"WITH {_REAL} SELECT * FROM re")}
register("graph_stats", " UNION ALL ".join(_PROFILE.format(name=n, v=v, e=e) for n, (v, e) in _EVERY.items()))(graph_stats)
for _name, (_source, _shape) in _SHAPES.items():
    _text = O.groups(_shape, "SELECT leader, node, v FROM members", 6, data=O.graph(*_DATA[_source]))
    register(_name, _text)(lambda s, d, g=_source, p=_shape: explore.match(graphs.GRAPHS[g](s, d), p, ends_only=True).members())
_CHAIN = f"""WITH x AS ({_TURN}), r AS (SELECT conv_id * 100000 + turn AS id, role FROM conversations),
a AS (SELECT s.id AS leader, u.id AS u, v.id AS v FROM x p JOIN r s ON s.id = p.src AND s.role = 'system' JOIN r u ON u.id = p.dst AND u.role = 'user' JOIN x q ON q.src = u.id JOIN r v ON v.id = q.dst AND v.role = 'assistant')
SELECT leader, 'system' AS node, leader AS v FROM a UNION SELECT leader, 'user', u FROM a UNION SELECT leader, 'assistant', v FROM a"""
register("turn_chain", _CHAIN)(lambda s, d: explore.match(graphs.turns(s, d), P.chain()).members())

# Filters and joins.
register("flt_labels", f"WITH {_REAL} SELECT id FROM rv WHERE list_has_all(labels, ['BUILDING', 'ASIA'])")(lambda s, d: graphs.handover_real(s, d).vertices.where(F.size(F.array_except(F.array(F.lit("BUILDING"), F.lit("ASIA")), "labels")) == 0).select("id"))
register("flt_scores", f"WITH {O.handover()} SELECT src, dst FROM edg WHERE trust >= 0.45 AND intimacy >= 0.45")(lambda s, d: _graph(s, d).edges.where("trust >= 0.45 AND intimacy >= 0.45").select("src", "dst"))
_STEP = f"WITH {O.handover()} SELECT a.src, count(*) AS n FROM edg a JOIN edg b ON a.dst = b.src GROUP BY a.src"
#: Most rows that are sent to every task at once, about; more go piece by piece. With 0 none are sent.
_SMALL = 1 << 20
for _hint in ("broadcast", "merge", "shuffle_hash"):

    def _frontier(s, d, hint=_hint):
        e = _graph(s, d).edges
        a, b = e.select("src", F.col("dst").alias("mid")), e.select(F.col("src").alias("mid"))
        if hint != "broadcast":
            return a.join(b.hint(hint), "mid").groupBy("src").agg(F.count("*").alias("n"))
        # One row a vertex is sent, not one an edge, in as many pieces as there are `_SMALL` rows.
        b, count = settle_counted(b.groupBy("mid").agg(F.count("*").alias("m")), "degrees")
        if not _SMALL:
            return a.join(b, "mid").groupBy("src").agg(F.sum("m").alias("n"))
        pieces = max(1, -(-count // _SMALL))
        if pieces == 1:
            return a.join(b.hint(hint), "mid").groupBy("src").agg(F.sum("m").alias("n"))
        a, piece = settle(a, "steps"), F.pmod(F.xxhash64("mid"), F.lit(pieces))
        each = [a.where(piece == i).join(b.where(piece == i).hint(hint), "mid").groupBy("src").agg(F.sum("m").alias("n")) for i in range(pieces)]
        return reduce(DataFrame.unionByName, each).groupBy("src").agg(F.sum("n").alias("n"))

    register({"broadcast": "join_broadcast", "merge": "join_sort_merge", "shuffle_hash": "join_shuffle_hash"}[_hint], _STEP)(_frontier)
register("join_semi", f"WITH {O.handover()} SELECT id FROM vtx WHERE id IN (SELECT src FROM edg)")(lambda s, d: _graph(s, d).vertices.join(_graph(s, d).edges, F.col("id") == F.col("src"), "left_semi").select("id"))
register("join_anti", f"WITH {O.handover()} SELECT id FROM vtx WHERE id NOT IN (SELECT dst FROM edg)")(lambda s, d: _graph(s, d).vertices.join(_graph(s, d).edges, F.col("id") == F.col("dst"), "left_anti").select("id"))
register("join_outer", "SELECT d.doc_id, source, quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")(lambda s, d: t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "full_outer").select("doc_id", "source", "quality"))
register("join_cross", "SELECT r_name, s_suppkey FROM region, supplier")(lambda s, d: t(s, d, "region").crossJoin(t(s, d, "supplier")).select("r_name", "s_suppkey"))


@register("join_range", "SELECT a.o_orderkey AS a, b.o_orderkey AS b FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey AND abs(date_diff('day', CAST(a.o_orderdate AS DATE), CAST(b.o_orderdate AS DATE))) <= 7")
def join_range(spark, sf_dir):
    """Band join on days: each order meets its own and the neighbouring seven-day bins."""
    o = t(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", F.datediff("o_orderdate", F.lit("1970-01-01")).alias("day"))
    a = o.select("o_custkey", F.col("o_orderkey").alias("a"), F.col("day").alias("x"), F.explode(F.array(*(F.floor(F.col("day") / 7) + k for k in (-1, 0, 1)))).alias("bin"))
    b = o.select("o_custkey", F.col("o_orderkey").alias("b"), F.col("day").alias("y"), F.floor(F.col("day") / 7).alias("bin"))
    return a.join(b, ["o_custkey", "bin"]).where("a < b AND abs(x - y) <= 7").select("a", "b")


_ASOF = """SELECT event_id, o_orderkey FROM (SELECT event_id, user_id, ts FROM events) e ASOF LEFT JOIN
(SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY 1, 2) o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts"""


@register("join_asof", _ASOF)
def join_asof(spark, sf_dir):
    """The last order before each event: one sorted pass over both tables per customer."""
    e = t(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("k"), "ts", F.lit(None).cast("long").alias("o"))
    o = t(spark, sf_dir, "orders").groupBy("o_custkey", "o_orderdate").agg(F.max("o_orderkey").alias("o")).select(F.lit(None).cast("long").alias("event_id"), F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), "o")
    w = Window.partitionBy("k").orderBy("ts", F.col("event_id").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("o_orderkey", F.last("o", True).over(w)).where("event_id IS NOT NULL").select("event_id", "o_orderkey")


register("join_interval", "SELECT p.event_id AS purchase, e.event_id AS event FROM events p JOIN events e ON e.user_id = p.user_id AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 5 MINUTE WHERE p.event_type = 'purchase'")(
    lambda s, d: t(s, d, "events").where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("at"))
    .join(t(s, d, "events").select("user_id", F.col("event_id").alias("event"), "ts"), "user_id").where("ts > at AND ts <= at + INTERVAL 5 MINUTES").select("purchase", "event")
)
register("join_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal > 2 * b.s_acctbal AND b.s_acctbal > 0")(
    lambda s, d: t(s, d, "supplier").alias("a").join(t(s, d, "supplier").alias("b"), F.expr("a.s_nationkey = b.s_nationkey AND a.s_acctbal > 2 * b.s_acctbal AND b.s_acctbal > 0")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))
)

# Aggregates.
_deg = lambda s, d: _graph(s, d).edges.groupBy("src").agg(F.count("*").alias("n"))
_DEG = f"WITH {O.handover()}, dg AS (SELECT src, count(*) AS n FROM edg GROUP BY src)"
register("agg_degree", f"{_DEG} SELECT src, n FROM dg")(_deg)
register("agg_degree_hist", f"{_DEG} SELECT n, count(*) AS vertices FROM dg GROUP BY n")(lambda s, d: _deg(s, d).groupBy("n").agg(F.count("*").alias("vertices")))
register("agg_distinct", f"WITH {O.handover()} SELECT count(DISTINCT src) AS a, count(DISTINCT dst) AS b FROM edg")(lambda s, d: _graph(s, d).edges.agg(F.count_distinct("src").alias("a"), F.count_distinct("dst").alias("b")))
register("agg_approx_distinct")(lambda s, d: _graph(s, d).edges.agg(F.approx_count_distinct("src", 0.02).alias("a")))
register("agg_percentile", f"{_DEG} SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90, quantile_cont(n, 0.99) AS p99 FROM dg")(lambda s, d: _deg(s, d).agg(*(F.percentile("n", q).alias(f"p{int(q * 100)}") for q in (0.5, 0.9, 0.99))))
_PLACED = "SELECT c_mktsegment AS segment, r_name AS region FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_placed = lambda s, d: graphs.handover_real(s, d).vertices.select(F.col("labels")[0].alias("segment"), F.col("labels")[1].alias("region"))
register("agg_cube", f"SELECT segment, region, count(*) AS n FROM ({_PLACED}) GROUP BY CUBE (segment, region)")(lambda s, d: _placed(s, d).cube("segment", "region").agg(F.count("*").alias("n")))
register("agg_rollup", f"SELECT segment, region, count(*) AS n FROM ({_PLACED}) GROUP BY ROLLUP (segment, region)")(lambda s, d: _placed(s, d).rollup("segment", "region").agg(F.count("*").alias("n")))


@register("agg_grouping_sets", f"SELECT segment, region, count(*) AS n FROM ({_PLACED}) GROUP BY GROUPING SETS ((segment), (region), ())")
def agg_grouping_sets(spark, sf_dir):
    return _placed(spark, sf_dir).groupingSets([["segment"], ["region"], []], "segment", "region").agg(F.count("*").alias("n"))


_P1 = P.one_source()
_MASK = f"WITH {O.handover()},\n{O.candidates(_P1)},\n{O.relations(_P1)}, inc AS (" + " UNION ALL ".join(f"SELECT {_P1.index(e.src)} AS u, v AS x, {e.bit} AS b FROM e{e.no} UNION ALL SELECT {_P1.index(e.dst)}, w, {e.bit} FROM e{e.no}" for e in _P1.edges) + ") SELECT u, x, CAST(bit_or(b) AS BIGINT) AS mask FROM inc GROUP BY u, x"


@register("agg_mask", _MASK)
def agg_mask(spark, sf_dir):
    g = _graph(spark, sf_dir)
    edges = g.scored_edges()
    at = lambda u: candidates.select(g, _P1.node(u)).select(F.col("v").alias("at"))
    from groupmatch.model import MatchOptions

    rels = [paths.match_edge(at(e.src), edges, e, at(e.dst), MatchOptions()).select(F.lit(e.no).alias("edge_no"), "v", "w") for e in _P1.edges]
    out = rels[0]
    for r in rels[1:]:
        out = out.unionByName(r)
    return prune.incident(out, _P1, [])


_members = lambda s, d: explore.match(_graph(s, d), _P1).members()
register("agg_collect", O.groups(_P1, "SELECT leader, list_sort(list(v)) AS vs FROM members GROUP BY leader"))(lambda s, d: _members(s, d).groupBy("leader").agg(F.array_sort(F.collect_list("v")).alias("vs")))
register("agg_pivot", O.groups(_P1, "SELECT leader, " + ", ".join(f"count(*) FILTER (WHERE node = '{n.name}') AS {n.name}" for n in _P1.nodes) + " FROM members GROUP BY leader"))(
    lambda s, d: _members(s, d).groupBy("leader").pivot("node", [n.name for n in _P1.nodes]).count().na.fill(0)
)

# Windows, order and sets.
_O = "o_custkey, o_orderkey"
_orders = lambda s, d: t(s, d, "orders")
_by = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
register("win_rank", "SELECT o_orderkey, rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS r FROM orders")(lambda s, d: _orders(s, d).select("o_orderkey", F.rank().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"))).alias("r")))
register("win_ntile", "SELECT o_orderkey, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS q FROM orders")(lambda s, d: _orders(s, d).select("o_orderkey", F.ntile(4).over(_by()).alias("q")))
register("win_lag", "SELECT o_orderkey, date_diff('day', CAST(lag(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS DATE), CAST(o_orderdate AS DATE)) AS gap FROM orders")(
    lambda s, d: _orders(s, d).select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(_by())).alias("gap"))
)
register("win_running", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS n FROM orders")(lambda s, d: _orders(s, d).select("o_orderkey", F.count("*").over(_by().rowsBetween(Window.unboundedPreceding, 0)).alias("n")))
_DAY = lambda: Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-7, 0)
register("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 7 PRECEDING AND CURRENT ROW) AS n FROM orders")(
    lambda s, d: _orders(s, d).withColumn("day", F.datediff("o_orderdate", F.lit("1970-01-01"))).select("o_orderkey", F.count("*").over(_DAY()).alias("n"))
)
register("top_k", f"{_DEG} SELECT src, n FROM dg ORDER BY n DESC, src LIMIT 10")(lambda s, d: _deg(s, d).orderBy(F.desc("n"), "src").limit(10))
register("sort_multi", "SELECT n_name, n_regionkey FROM nation ORDER BY n_regionkey DESC, n_name")(lambda s, d: t(s, d, "nation").select("n_name", "n_regionkey").orderBy(F.desc("n_regionkey"), "n_name"))
register("limit_offset", f"{_DEG} SELECT src, n FROM dg ORDER BY n DESC, src LIMIT 10 OFFSET 5")(lambda s, d: _deg(s, d).orderBy(F.desc("n"), "src").offset(5).limit(10))
_ends = lambda s, d: (_graph(s, d).edges.select("src"), _graph(s, d).edges.select(F.col("dst").alias("src")))
for _op, _word, _call in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b))):
    register(_op, f"WITH {O.handover()} SELECT src FROM edg {_word} SELECT dst FROM edg")(lambda s, d, c=_call: c(*_ends(s, d)))

# Scalar functions.
register("fn_string", "SELECT page_id, lower(regexp_extract(url, '://([^/?#]*)', 1)) AS host, length(url) AS n, split_part(url, '/', 3) AS part FROM pages")(
    lambda s, d: t(s, d, "pages").select("page_id", F.lower(F.regexp_extract("url", "://([^/?#]*)", 1)).alias("host"), F.length("url").alias("n"), F.split_part("url", F.lit("/"), F.lit(3)).alias("part"))
)
register("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS first FROM orders")(
    lambda s, d: _orders(s, d).select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", "o_orderdate").alias("first"))
)
register("fn_math", f"WITH {O.handover()} SELECT src, dst, round(trust * intimacy, 9) AS a, round(pow(trust, 0.5), 9) AS b, round(exp(-trust), 9) AS c FROM edg")(
    lambda s, d: _graph(s, d).edges.select("src", "dst", F.round(F.col("trust") * F.col("intimacy"), 9).alias("a"), F.round(F.pow("trust", F.lit(0.5)), 9).alias("b"), F.round(F.exp(-F.col("trust")), 9).alias("c"))
)
register("fn_array", "SELECT vec_id, embedding[1] AS first, len(embedding) AS n, embedding[2:4] AS some FROM embeddings")(lambda s, d: t(s, d, "embeddings").select("vec_id", F.element_at("embedding", 1).alias("first"), F.size("embedding").alias("n"), F.slice("embedding", 2, 3).alias("some")))
register("fn_map", f"WITH {O.handover()} SELECT id, influence AS work, influence / 2 AS home FROM vtx")(
    lambda s, d: _graph(s, d).vertices.withColumn("m", F.create_map(F.lit("work"), "influence", F.lit("home"), F.col("influence") / 2)).select("id", F.col("m")["work"].alias("work"), F.element_at("m", "home").alias("home"))
)
register("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
register("fn_struct", "SELECT c_custkey, c_name, c_nationkey FROM customer")(lambda s, d: t(s, d, "customer").select(F.struct("c_custkey", "c_name", "c_nationkey").alias("x")).select("x.*"))

# SQL surface.


def _viewed(s, d):
    io.register_views(explore.match(_graph(s, d), _P1))
    return s


register("subquery_exists", O.groups(_P1, "SELECT DISTINCT v FROM members m WHERE EXISTS (SELECT 1 FROM edg WHERE src = m.v AND trust > 0.9)"))(lambda s, d: _viewed(s, d).sql("SELECT DISTINCT v FROM members m WHERE EXISTS (SELECT 1 FROM edges WHERE src = m.v AND trust > 0.9)"))
register("subquery_in", O.groups(_P1, "SELECT id FROM vtx WHERE id IN (SELECT leader FROM members)"))(lambda s, d: _viewed(s, d).sql("SELECT id FROM vertices WHERE id IN (SELECT leader FROM members)"))
register("cte_query", O.groups(_P1, ", x AS (SELECT node, count(*) AS n FROM members GROUP BY node) SELECT node, n FROM x WHERE n > 1"))(lambda s, d: _viewed(s, d).sql("WITH x AS (SELECT node, count(*) AS n FROM members GROUP BY node) SELECT node, n FROM x WHERE n > 1"))
register("sql_membership", f"WITH {O.handover()} SELECT id, CASE WHEN influence >= 0.5 THEN 1.0 ELSE influence / 0.5 END AS degree FROM vtx")(lambda s, d: _viewed(s, d).sql("SELECT id, membership_ratio(influence, 0.5D) AS degree FROM vertices"))
_REACH = "WITH RECURSIVE " + O.handover() + ", r(v, h) AS (SELECT 1::BIGINT, 0 UNION SELECT dst, h + 1 FROM r JOIN edg ON src = v WHERE h < 3) SELECT v, min(h) AS h FROM r GROUP BY v"


@register("recursive_reach", _REACH)
def recursive_reach(spark, sf_dir):
    from groupmatch.operators.locality import ball

    return ball(_graph(spark, sf_dir), spark.createDataFrame([(1,)], "leader long"), 3, directed=True).select("v", F.col("dist").alias("h"))


# Functions in Python.
register("udf_membership", f"WITH {O.handover()} SELECT id, least(influence / 0.5, 1.0) AS degree FROM vtx")(
    lambda s, d: _graph(s, d).vertices.select("id", membership.degree(F.col("influence"), 0.5, MembershipRule("custom", 0.9, (lambda x: (x / 0.5).clip(upper=1.0),))).alias("degree"))
)
register("udaf_fold", f"WITH {O.handover()} SELECT src, min(trust) AS worst FROM edg GROUP BY src")(lambda s, d: _graph(s, d).edges.groupBy("src").agg(udfs.worst_fold("trust").alias("worst")))


@register("udtf_explain")
def udtf_explain(spark, sf_dir):
    """Why candidates left: pattern edges they lack in the unpruned relations."""
    masked = agg_mask(spark, sf_dir)
    masked.createOrReplaceTempView("masked")
    spark.udtf.register("explain_group", udfs.ExplainGroup)
    need = {_P1.index(n.name): (n.name, _P1.mask(n.name)) for n in _P1.nodes}
    names = ", ".join(f"'{e.src}->{e.dst}'" for e in _P1.edges)
    node = "CASE u " + " ".join(f"WHEN {u} THEN '{n}'" for u, (n, _) in need.items()) + " END"
    mask = "CASE u " + " ".join(f"WHEN {u} THEN {m}" for u, (_, m) in need.items()) + " END"
    return spark.sql(f"SELECT x, g.node, g.missing FROM masked, LATERAL explain_group({node}, mask, CAST({mask} AS BIGINT), array({names})) g")


for _shape in ("step", "linear", "sigmoid"):
    _rule = {"step": MembershipRule("step", 0.9), "linear": MembershipRule("linear", 0.9, (0.2, 0.8)), "sigmoid": MembershipRule("sigmoid", 0.9, (0.5, 8.0))}[_shape]
    _expr = {"step": "CASE WHEN influence >= 0.5 THEN 1.0 ELSE 0.0 END", "linear": "least(greatest((influence - 0.2::DOUBLE) / (0.8::DOUBLE - 0.2::DOUBLE), 0.0), 1.0)", "sigmoid": "1.0 / (1.0 + exp(-8.0::DOUBLE * (influence - 0.5::DOUBLE)))"}[_shape]
    register(f"membership_{_shape}", f"WITH {O.handover()} SELECT id, round({_expr}, 9) AS degree FROM vtx")(lambda s, d, r=_rule: _graph(s, d).vertices.select("id", F.round(membership.degree(F.col("influence"), 0.5, r), 9).alias("degree")))

# Streams, run to the end of the given events; append mode holds back what the watermark hasn't passed.
_LATE = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
register("stream_tumbling")(lambda s, d: streaming.run_to_table(streaming.tumbling(streaming.replay(s, d))))
register("stream_tumbling_all", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: streaming.run_to_table(streaming.tumbling(streaming.replay(s, d)).select("start", "event_type", "n"), "complete"))
register("stream_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL (15 * k) MINUTE for k in [0, 1, 2, 3]]) AS start FROM events) GROUP BY start")(lambda s, d: streaming.run_to_table(streaming.sliding(streaming.replay(s, d)), "complete"))
register("stream_session")(lambda s, d: streaming.run_to_table(streaming.sessions(streaming.replay(s, d))))
register("stream_dedup", "SELECT event_id, user_id FROM events")(lambda s, d: streaming.run_to_table(streaming.deduplicated(streaming.replay(s, d)).select("event_id", "user_id")))
register("stream_join", "SELECT event_id, user_id, n AS orders FROM events JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) ON user_id = o_custkey")(lambda s, d: streaming.run_to_table(streaming.joined(streaming.replay(s, d), t(s, d, "orders"))))
register("stream_stateful", "SELECT user_id, src_type, dst_type FROM (SELECT user_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src_type, event_type AS dst_type FROM events) WHERE src_type IS NOT NULL")(
    lambda s, d: streaming.run_to_table(streaming.transitions(streaming.replay(s, d)))
)


@register("stream_refresh", O.members(_P1))
def stream_refresh(spark, sf_dir):
    """Groups after the last edges arrive, by matching touched leaders only."""
    g = _graph(spark, sf_dir)
    late = g.edges.where("src % 50 = 1")
    from groupmatch.model import SocialGraph

    before = explore.match(SocialGraph(g.vertices, g.edges.where("src % 50 <> 1")), _P1).members()
    return streaming.refreshed(g, _P1, before, late)


# Sinks.
_LNK = O.groups(_P1, f", lnk AS ({O.links(_P1)}) SELECT leader, edge_no, v, w, hops FROM lnk")
for _fmt in ("parquet", "csv", "json"):

    def _trip(s, d, fmt=_fmt):
        place = f"{shared_folder(s)}/trip-{uuid.uuid4().hex}"
        rows = explore.match(_graph(s, d), _P1).links().select("leader", "edge_no", "v", "w", "hops")
        rows.write.format(fmt).save(place)
        return s.read.format(fmt).schema(rows.schema).load(place)

    register(f"sink_roundtrip_{_fmt}", _LNK)(_trip)
