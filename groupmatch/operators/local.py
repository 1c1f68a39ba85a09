"""The local strategy: each leader's surroundings are explored by one Python function, for cross-checks."""

from __future__ import annotations

from functools import reduce
from operator import add

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.model import GroupPattern, MatchOptions, SocialGraph

from . import candidates, paths


def explore_ball(edges: list[tuple], roles: dict[str, set[int]], p: GroupPattern, leader: int, floor: float, simple: bool = True):
    """Members of one leader's group over the edges (src, dst, trust, intimacy, influence of both) of its ball."""
    out: dict[int, list[tuple]] = {}
    score: dict[int, float] = {}
    for s, d, t, r, a, b in edges:
        out.setdefault(s, []).append((d, t, r))
        score[s], score[d] = a, b
    limits = {e.no: {k: floor * m for k, m in e.minima().items()} for e in p.edges}

    def pairs(e, v):
        found, todo = set(), [((v,), 1.0, 1.0)]
        while todo:
            path, t, r = todo.pop()
            if len(path) > 1 and path[-1] in roles[e.dst]:
                mean = reduce(add, (score[x] for x in path), 0.0) / len(path)  # left to right, as Spark folds
                values = {"trust": t, "intimacy": r, "influence": mean}
                if all(values[k] is not None and values[k] >= m for k, m in limits[e.no].items()):
                    found.add(path[-1])
            if len(path) <= e.max_hops:
                todo += [(path + (d,), t * x, r * y) for d, x, y in out.get(path[-1], ()) if (d not in path if simple else True) and d != path[-1]]
        return found

    roles = {u: (vs & {leader} if u == p.leader else vs) for u, vs in roles.items()}
    links = {(e.no, v): pairs(e, v) for e in p.edges for v in roles[e.src]}
    alive = {u: set(vs) for u, vs in roles.items()}
    while True:
        before = sum(map(len, alive.values()))
        for e in p.edges:
            alive[e.src] = {v for v in alive[e.src] if links[e.no, v] & alive[e.dst]}
            reached = set().union(*(links[e.no, v] for v in alive[e.src])) if alive[e.src] else set()
            alive[e.dst] &= reached
        if sum(map(len, alive.values())) == before:
            return alive if all(alive.values()) else {}


def _supported(p: GroupPattern, opt: MatchOptions) -> float:
    """The one cut of all rules; raises where this strategy would answer another question."""
    rules = {x.rule for x in (*p.nodes, *p.edges)}
    cuts = {1.0 if r is None else r.cut for r in {e.rule for e in p.edges}}
    if any(r is not None and r.kind != "ratio" for r in rules) or len(cuts) > 1:
        raise ValueError("strategy local takes ratio rules with one cut for all edges")
    if opt.fold != "product" or opt.influence_span != "all" or opt.choose_first or opt.edge_mode != "constrained":
        raise ValueError("strategy local takes product folds, whole paths and constraints that are tested first")
    return cuts.pop()


def _around(g: SocialGraph, p: GroupPattern, opt: MatchOptions, heads: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(edges, inside, roles): the graph's scored edges, and what of it each leader's exploration can use: the edges
    (leader, ...) on admissible paths along the pattern from the leader, and the candidates (leader, node, v) at their ends.

    Every member has links for all its pattern edges, so spanning edges lead from the leader to it."""
    edges = settle(paths.useful_edges(g, p, opt), "edges")
    every = settle(candidates.select_all(g, p), "candidates")
    at = {p.leader: heads.select("leader", F.col("leader").alias("at"))}
    spanning = p.spanning_steps()
    ways = None
    for e, forward in spanning + [(e, True) for e in p.edges if all(e.no != x.no for x, _ in spanning)]:
        near, far, way, c, d = (e.src, e.dst, "out", "v", "w") if forward else (e.dst, e.src, "in", "w", "v")
        ends = every.where(F.col("node") == far).select(F.col("v").alias("at"))
        found = paths.expand(at[near].select("at").distinct(), edges, e, ends, opt, way).select("v", "w", "path")
        own = found.join(at[near].withColumnRenamed("at", c), c)
        if far in at:
            own = own.join(at[far].withColumnRenamed("at", d), ["leader", d], "left_semi")
        own = settle(own.select("leader", "v", "w", "path"), "ways")
        if far not in at:
            at[far] = settle(own.select("leader", F.col(d).alias("at")).distinct(), "reached")
        ways = own if ways is None else ways.unionByName(own)
    hop = F.explode(F.arrays_zip(F.expr("slice(path, 1, size(path) - 1)").alias("src"), F.expr("slice(path, 2, size(path) - 1)").alias("dst")))
    pairs = ways.select("leader", hop.alias("e")).select("leader", "e.src", "e.dst").distinct()
    roles = None
    for u, x in at.items():
        part = x.select("leader", F.lit(u).alias("node"), F.col("at").alias("v"))
        roles = part if roles is None else roles.unionByName(part)
    return edges, pairs.join(edges, ["src", "dst"]), roles


def match_local(g: SocialGraph, p: GroupPattern, opt: MatchOptions, leaders: DataFrame | None = None):
    """Members come from each leader's surroundings; links are the best paths between members of one leader.

    Ratio rules with one cut and product folds only; other options raise."""
    from .explore import GroupResult

    cut = _supported(p, opt)
    heads = candidates.select(g, p.node(p.leader)).select(F.col("v").alias("leader"))
    heads = heads if leaders is None else heads.join(leaders.select("leader"), "leader", "left_semi")
    edges, inside, roles = _around(g, p, opt, settle(heads, "heads"))

    def run(key, edges: pa.Table, own: pa.Table) -> pa.Table:
        leader = key[0].as_py()
        sets: dict[str, set[int]] = {n.name: set() for n in p.nodes}
        for u, v in zip(own["node"].to_pylist(), own["v"].to_pylist()):
            sets[u].add(v)
        rows = zip(*(edges[c].to_pylist() for c in ("src", "dst", "trust", "intimacy", "src_influence", "dst_influence")))
        got = explore_ball(list(rows), sets, p, leader, cut, opt.path_mode == "simple")
        out = [(u, v) for u, vs in got.items() for v in sorted(vs)]
        return pa.table({"leader": pa.array([leader] * len(out), pa.int64()), "node": pa.array([u for u, _ in out], pa.string()), "v": pa.array([v for _, v in out], pa.int64())})

    members = settle(inside.groupBy("leader").cogroup(roles.groupBy("leader")).applyInArrow(run, "leader long, node string, v long"), "members")
    links = None
    for e in p.edges:
        at = lambda u: members.where(F.col("node") == u)
        ends = at(e.dst).select(F.col("v").alias("at")).distinct()
        rel = paths.match_edge(at(e.src).select(F.col("v").alias("at")).distinct(), edges, e, ends, opt)
        a = at(e.src).select("leader", "v")
        b = at(e.dst).select("leader", F.col("v").alias("w"))
        own = rel.join(a, "v").join(b, ["leader", "w"], "left_semi").withColumn("edge_no", F.lit(e.no))
        links = own if links is None else links.unionByName(own)
    return GroupResult(p, g, links.select("leader", "edge_no", "v", "w", "path", "hops", "trust", "intimacy", "influence", "worst"), members)
