"""Queries of the engine and their DuckDB forms."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupmatch import oracle_sql as O
from groupmatch.functions.membership import least_value
from groupmatch.model import MatchOptions
from groupmatch.model import pattern as P
from groupmatch.operators import baselines, candidates, explore, locality, measures, paths, simulate, sweep
from groupmatch.session import ship
from groupmatch.sources import graphs

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = lambda spark, sf_dir: f(ship(spark), sf_dir)
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups of two_source, combined strategy, minimum 0.3."""
    return explore.match(graphs.handover(ship(spark), sf_dir), P.two_source(0.3)).members()


def _graph(spark, sf_dir):
    return graphs.handover(spark, sf_dir, 3)


# Graphs, scores and candidates.
register("scan_vertices", f"WITH {O.handover()} SELECT id, label FROM vtx")(lambda s, d: _graph(s, d).vertices.select("id", F.col("labels")[0].alias("label")))
register("scan_edges", f"WITH {O.handover()} SELECT src, dst FROM edg")(lambda s, d: _graph(s, d).edges.select("src", "dst"))
register("scored_vertices", f"WITH {O.handover()} SELECT id, influence FROM vtx")(lambda s, d: _graph(s, d).vertices.select("id", "influence"))
register("scored_edges", f"WITH {O.handover()} SELECT * FROM edg")(lambda s, d: _graph(s, d).edges)
_PATTERNS = {"p1": P.one_source, "p2": P.two_source, "p3": P.far_source, "p4": P.full_team}
_CANDS = " UNION ALL ".join(f"SELECT '{k}' AS pattern, * FROM (WITH {O.candidates(f()).replace('cnd AS MATERIALIZED', 'c AS')} SELECT * FROM c)" for k, f in _PATTERNS.items())


@register("role_candidates", f"WITH {O.handover()}, a AS ({_CANDS}) SELECT pattern, node, count(*) AS n FROM a GROUP BY ALL")
def role_candidates(spark, sf_dir):
    g = _graph(spark, sf_dir)
    parts = [candidates.select_all(g, f()).select(F.lit(k).alias("pattern"), "node", "v") for k, f in _PATTERNS.items()]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out.groupBy("pattern", "node").agg(F.count("*").alias("n"))


def graph_stats(spark, sf_dir):
    out = None
    for name, build in graphs.GRAPHS.items():
        row = build(spark, sf_dir).profile().select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@register("complexity_drivers", f"WITH {O.handover()} SELECT (SELECT count(*) FROM vtx) AS n, CAST(4 AS BIGINT) AS pattern_nodes, 1.0::DOUBLE AS pattern_degree, (SELECT count(*) FROM edg) / (SELECT count(*) FROM vtx) AS data_degree, CAST(3 AS BIGINT) AS hops")
def complexity_drivers(spark, sf_dir):
    from groupmatch.plans.cost import drivers

    return drivers(_graph(spark, sf_dir), P.two_source())


# Bounded paths and edge relations.
def _edge_inputs(spark, sf_dir, p, no):
    g = _graph(spark, sf_dir)
    e = next(x for x in p.edges if x.no == no)
    at = lambda u: candidates.select(g, p.node(u)).select(F.col("v").alias("at"))
    return g.scored_edges(), e, at(e.src), at(e.dst)


_P1, _P2, _P3 = P.one_source(), P.two_source(), P.far_source()
_REL = f"WITH {O.handover()},\n{O.candidates(_P1)},\n{O.relation(_P1.edges[1], 'rel')}"


@register("bounded_paths", _REL + " SELECT hops, count(*) AS paths FROM (SELECT p.*, c.v AS t FROM (SELECT v, w, hops FROM rel_1 UNION ALL SELECT v, w, hops FROM rel_2 UNION ALL SELECT v, w, hops FROM rel_3) p JOIN cnd c ON c.v = p.w AND c.node = 'SD') GROUP BY hops")
def bounded_paths(spark, sf_dir):
    edges, e, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.level_counts(starts, edges, e, ends, MatchOptions(edge_mode="path"))


_LINK = "v, w, path, hops, trust, intimacy, influence, worst"


@register("edge_relation", f"{_REL} SELECT {_LINK} FROM rel")
def edge_relation(spark, sf_dir):
    edges, e, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.match_edge(starts, edges, e, ends, MatchOptions())


@register("edge_relation_reverse", f"{_REL} SELECT {_LINK} FROM rel")
def edge_relation_reverse(spark, sf_dir):
    edges, e, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.match_edge(ends, edges, e, starts, MatchOptions(), "in")


@register("edge_relation_search_first", f"{_REL} SELECT {_LINK} FROM rel")
def edge_relation_search_first(spark, sf_dir):
    edges, e, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.match_edge(starts, edges, e, ends, MatchOptions(eager_bounds=False, last_hop_filter=False))


# Minima that differ, so that the path chosen first may fail where another one of its pair passes.
_UNEVEN = replace(_P1.edges[1], min_trust=0.2, min_intimacy=0.6, min_influence=0.4)
_FIRST = O.relation(replace(_UNEVEN, min_trust=0.0, min_intimacy=0.0, min_influence=0.0), "rel")
_TESTS = " AND ".join(f"{k} >= {least_value(m, _UNEVEN.rule)!r}" for k, m in _UNEVEN.minima().items())


@register("edge_relation_choose_first", f"WITH {O.handover()},\n{O.candidates(_P1)},\n{_FIRST} SELECT {_LINK} FROM rel WHERE {_TESTS}")
def edge_relation_choose_first(spark, sf_dir):
    edges, _, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.match_edge(starts, edges, _UNEVEN, ends, MatchOptions(choose_first=True))


@register("edge_relation_test_first", f"WITH {O.handover()},\n{O.candidates(_P1)},\n{O.relation(_UNEVEN, 'rel')} SELECT {_LINK} FROM rel")
def edge_relation_test_first(spark, sf_dir):
    edges, _, starts, ends = _edge_inputs(spark, sf_dir, _P1, 1)
    return paths.match_edge(starts, edges, _UNEVEN, ends, MatchOptions())


# Groups: every pattern, every strategy.
for _key, _make in _PATTERNS.items():
    register(f"groups_{_key}", O.members(_make()))(lambda s, d, f=_make: explore.match(_graph(s, d), f()).members())
for _key, _make in (("p1", P.one_source), ("p2", P.two_source)):
    for _strategy in ("plain", "reverse", "cached", "combined", "local"):
        register(f"groups_{_key}_{_strategy}", O.members(_make()))(lambda s, d, f=_make, x=_strategy: explore.match(_graph(s, d), f(), x).members())
    _tail = f", lnk AS ({O.links(_make())}) SELECT leader, edge_no, {_LINK} FROM lnk"
    register(f"links_{_key}", O.groups(_make(), _tail))(lambda s, d, f=_make: explore.match(_graph(s, d), f()).links())
    _tail = f", lnk AS ({O.links(_make())}), a AS (SELECT leader, count(*) AS n FROM members GROUP BY 1), b AS (SELECT leader, count(*) AS m FROM lnk GROUP BY 1) SELECT count(*) AS groups, avg(n) AS mean_members, avg(m) AS mean_links FROM a JOIN b USING (leader)"

    def _sizes(s, d, f=_make):
        c = explore.match(_graph(s, d), f()).counts()
        return c.agg(F.count("*").alias("groups"), F.avg("n_members").alias("mean_members"), F.avg("n_links").alias("mean_links"))

    register(f"group_sizes_{_key}", O.groups(_make(), _tail))(_sizes)
    register(f"exact_{_key}", O.assignments(_make(), "SELECT leader, count(*) AS assignments, max(worst) AS best FROM asg GROUP BY leader"))(
        lambda s, d, f=_make: baselines.edge_join(_graph(s, d), f()).groupBy("leader").agg(F.count("*").alias("assignments"), F.max("worst").alias("best"))
    )
register("groups_p3_scan", O.members(_P3))(lambda s, d: explore.match(_graph(s, d), _P3, "combined", MatchOptions(reverse_chain=False)).members())
register("groups_p2_ablated", O.members(_P2))(lambda s, d: explore.match(_graph(s, d), _P2, "combined", MatchOptions(global_reduce=False, eager_bounds=False, last_hop_filter=False)).members())
register("twin_cover", O.members(P.twin_cover(0.3), 14))(lambda s, d: explore.match(_graph(s, d), P.twin_cover(0.3)).members())
register("twin_mixed", O.members(P.twin_mixed(0.3), 14))(lambda s, d: explore.match(_graph(s, d), P.twin_mixed(0.3)).members())
_TOP = "SELECT leader, PM, BA, SD, ST, worst FROM (SELECT *, row_number() OVER (PARTITION BY leader ORDER BY worst DESC, PM, BA, SD, ST) AS r FROM asg) WHERE r <= 3"
register("exact_top_k", O.assignments(_P2, _TOP))(lambda s, d: baselines.edge_join(_graph(s, d), _P2, k=3).drop("rank"))
register("exact_injective", O.assignments(_P2, "SELECT count(*) AS n FROM asg", True))(lambda s, d: baselines.edge_join(_graph(s, d), _P2, True).agg(F.count("*").alias("n")))
for _key, _make in (("p1", P.one_source), ("p2", P.two_source)):
    register(f"exact_{_key}_per_leader", O.assignments(_make(), "SELECT leader, count(*) AS assignments, max(worst) AS best FROM asg GROUP BY leader"))(
        lambda s, d, f=_make: baselines.edge_join(_graph(s, d), f(), per_leader=True).groupBy("leader").agg(F.count("*").alias("assignments"), F.max("worst").alias("best"))
    )
    _names = [n.name for n in _make().nodes]
    _pairs = [(e.src, e.dst) for e in _make().edges]
    _each = ", ".join(f"count(DISTINCT {n}) AS n_{n}" for n in _names) + ", " + ", ".join(f"count(DISTINCT {{'a': {a}, 'b': {b}}}) AS e_{i}" for i, (a, b) in enumerate(_pairs))
    _mean = f"SELECT count(*) AS groups, avg({' + '.join(f'n_{n}' for n in _names)}) AS mean_members, avg({' + '.join(f'e_{i}' for i in range(len(_pairs)))}) AS mean_links FROM (SELECT leader, {_each} FROM asg GROUP BY leader)"

    def _exact_sizes(s, d, f=_make, names=_names, pairs=_pairs):
        rows = baselines.edge_join(_graph(s, d), f(), per_leader=True)
        # Distinct nodes and matched paths of each leader, as the assignments hold them together.
        node = rows.select("leader", F.inline(F.array(*(F.struct(F.lit(n).alias("node"), F.col(n).alias("v")) for n in names)))).distinct().groupBy("leader").agg(F.count("*").alias("n"))
        path = rows.select("leader", F.inline(F.array(*(F.struct(F.lit(i).alias("no"), F.col(a).alias("v"), F.col(b).alias("w")) for i, (a, b) in enumerate(pairs))))).distinct().groupBy("leader").agg(F.count("*").alias("m"))
        return node.join(path, "leader").agg(F.count("*").alias("groups"), F.avg("n").alias("mean_members"), F.avg("m").alias("mean_links"))

    register(f"exact_sizes_{_key}", O.assignments(_make(), _mean))(_exact_sizes)
_GROUPED = " UNION ".join(f"SELECT leader, '{n.name}' AS node, {n.name} AS v FROM asg" for n in _P2.nodes)
register("exact_grouped", O.assignments(_P2, _GROUPED))(lambda s, d: baselines.edge_join_grouped(_graph(s, d), _P2))


def _embedding_sql(p):
    q = p.with_minimum(None)
    rel = ", ".join(f"e{e.no} AS (SELECT src AS v, dst AS w, 1.0 AS worst FROM edg JOIN cnd a ON a.v = src AND a.node = '{e.src}' JOIN cnd b ON b.v = dst AND b.node = '{e.dst}')" for e in q.edges)
    text = O.assignments(q, "SELECT leader, count(*) AS n FROM asg GROUP BY leader", True)
    return text.replace(O.relations(q), rel)


register("embeddings", _embedding_sql(_P1))(lambda s, d: baselines.embeddings(_graph(s, d), _P1).groupBy("leader").agg(F.count("*").alias("n")))


_TWIN = P.twin_mixed(0.3)
_AGREE = O.groups(_TWIN, ", x AS (SELECT DISTINCT e0.v AS leader FROM e0, e1, e2, e3, e4, e5 WHERE e0.v = e1.v AND e0.w = e2.v AND e1.w = e3.v AND e2.w = e3.w AND e4.v = e0.w AND e5.v = e1.w AND e4.w = e5.w), m AS (SELECT DISTINCT leader FROM members) SELECT count(*) FILTER (WHERE m.leader IS NOT NULL AND x.leader IS NOT NULL) AS in_both, count(*) FILTER (WHERE x.leader IS NULL) AS only_first, count(*) FILTER (WHERE m.leader IS NULL) AS only_second FROM m FULL JOIN x ON m.leader = x.leader", 14)


@register("agreement", _AGREE)
def agreement(spark, sf_dir):
    g = _graph(spark, sf_dir)
    return measures.agreement(explore.match(g, _TWIN).members(), baselines.edge_join(g, _TWIN))


# Older models.
for _mode in ("edge", "path", "constrained"):
    register(f"sim_child_{_mode}", O.simulation(_P1, _mode, True))(lambda s, d, m=_mode: simulate.child(_graph(s, d), _P1, m))
    register(f"sim_dual_{_mode}", O.simulation(_P1, _mode, False))(lambda s, d, m=_mode: simulate.dual(_graph(s, d), _P1, m))
_CRISP = _P1.with_minimum(0.5, crisp=True)
register("sim_child_crisp", O.simulation(_CRISP, "constrained", True))(lambda s, d: simulate.child(_graph(s, d), _P1, "constrained", False))
register("sim_fuzzy_strong_crisp", O.members(_CRISP))(lambda s, d: simulate.fuzzy_strong(_graph(s, d), _P1, False))
register("sim_strong", O.members(_P1))(lambda s, d: simulate.strong(_graph(s, d), _P1, "constrained"))
register("false_members", f"WITH {O.handover()},\n{O.candidates(_P1)},\n{O.relations(_P1)},\n{O.fixpoint(_P1, 8, True, False).replace('s_', 'q_').replace('members AS', 'wide AS')},\n{O.fixpoint(_P1, 5)}\nSELECT node, v FROM wide EXCEPT SELECT node, v FROM members")(lambda s, d: baselines.false_members(_graph(s, d), _P1))
for _attr in ("node", "trust", "intimacy", "influence"):
    _only = P.two_source(0.7).only(_attr)
    register(f"groups_only_{_attr}", O.groups(_only, "SELECT count(DISTINCT leader) AS groups, count(*) AS n FROM members", 6))(
        lambda s, d, p=_only: explore.match(_graph(s, d), p, ends_only=True).members().agg(F.count_distinct("leader").alias("groups"), F.count("*").alias("n"))
    )


# Parameters.
def _sweep(rows):
    return lambda s, d: _swept(s, d, rows)


def _swept(spark, sf_dir, rows):
    g, out = _graph(spark, sf_dir), None
    for label, p in rows:
        row = explore.match(g, p).members().agg(F.count_distinct("leader").alias("groups"), F.count("*").alias("members")).select(F.lit(label).alias("setting"), "groups", "members")
        out = row if out is None else out.unionByName(row)
    return out


def _swept_sql(rows):
    return " UNION ALL ".join(f"SELECT * FROM ({O.groups(p, chr(10) + f'SELECT {chr(39)}{label}{chr(39)} AS setting, count(DISTINCT leader) AS groups, count(*) AS members FROM members', 6)})" for label, p in rows)


_THRESHOLDS = [(f"{k} min {m} cut {c}", f(None).with_minimum(m, c)) for k, f in (("p1", P.one_source), ("p2", P.two_source)) for m in (0.3, 0.5, 0.8) for c in (0.8, 0.9, 1.0)]


@register("groups_by_threshold", _swept_sql(_THRESHOLDS))
def groups_by_threshold(spark, sf_dir):
    """Settings of one shape differ in their minimum and cut only, so their edges are matched once."""
    g, out = _graph(spark, sf_dir), None
    for k in ("p1", "p2"):
        shapes = {label: p for label, p in _THRESHOLDS if label.startswith(k)}
        found = sweep.members(g, shapes).groupBy("setting").agg(F.count_distinct("leader").alias("groups"), F.count("*").alias("members"))
        # A setting without any group counts too.
        every = spark.createDataFrame([(x,) for x in shapes], "setting string")
        row = every.join(found, "setting", "left").na.fill(0).select("setting", "groups", "members")
        out = row if out is None else out.unionByName(row)
    return out


_BOUNDS = [(f"bound {h}", _P2.with_hops(1, h)) for h in (1, 2, 3)]
register("groups_by_bound", _swept_sql(_BOUNDS))(_sweep(_BOUNDS))


@register("cache_hits")
def cache_hits(spark, sf_dir):
    """(edge_no, kind, plain, cached, reverse, combined): starts expanded for each pattern edge."""
    out = None
    for name, asked in explore.requests(_graph(spark, sf_dir), _P2).items():
        row = measures.request_table(spark, asked).select("edge_no", F.col("requests").alias(name))
        out = row if out is None else out.join(row, "edge_no", "full_outer")
    return out


_TOPG = f", lnk AS ({O.links(_P2)}) SELECT leader, count(*) AS n_links, min(worst) AS least, avg(worst) AS mean FROM lnk GROUP BY leader ORDER BY least DESC, n_links DESC, leader LIMIT 10"
register("top_groups", O.groups(_P2, _TOPG))(lambda s, d: measures.top_groups(explore.match(_graph(s, d), _P2)))
register("group_count", O.groups(_P2, "SELECT count(DISTINCT leader) AS groups FROM members"))(lambda s, d: measures.group_count(explore.match(_graph(s, d), _P2)))
_IND = f", lnk AS ({O.links(_P1)}), z AS (SELECT leader, path, unnest(range(1, len(path))) AS i FROM lnk) SELECT DISTINCT leader, path[i] AS src, path[i + 1] AS dst FROM z"
register("path_explode", O.groups(_P1, _IND))(lambda s, d: explore.match(_graph(s, d), _P1).induced_edges())
_BALL = "WITH RECURSIVE " + O.handover() + f",\n{O.candidates(_P1)},\n{O.relations(_P1)},\n{O.fixpoint(_P1, 5)},\nld AS (SELECT DISTINCT leader FROM members), nb AS (SELECT src, dst FROM edg UNION SELECT dst, src FROM edg), b(leader, v, dist) AS (SELECT leader, leader, 0 FROM ld UNION SELECT leader, dst, dist + 1 FROM b JOIN nb ON src = v WHERE dist < 2) SELECT leader, v, min(dist) AS dist FROM b GROUP BY 1, 2"


@register("ball", _BALL)
def ball(spark, sf_dir):
    g = _graph(spark, sf_dir)
    leaders = explore.match(g, _P1).members().select("leader").distinct()
    return locality.ball(g, leaders, 2)


from groupmatch import more_queries, workload_queries  # noqa: E402, F401
