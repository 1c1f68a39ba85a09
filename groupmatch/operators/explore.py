"""Fuzzy strong simulation by exploration from leaders, for all leaders at once.

Two switches make the four strategies: `reverse` finds further sources backward over inverse
edges, `cache` expands each start once without the leader. Without the cache the leader is a
column of the frontier, which is the repeated work that the cache avoids.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle, settle_counted
from groupmatch.model import GroupPattern, MatchOptions, SocialGraph
from groupmatch.plans.order import explain, steps

from . import candidates, paths, prune
from .store import PathStore

STRATEGIES = {"plain": (False, False), "reverse": (True, False), "cached": (False, True), "combined": (True, True)}
_LINK = ["edge_no", "v", "w", "path", "hops", "trust", "intimacy", "influence", "worst"]


@dataclass
class GroupResult:
    """The groups, as flat relations; nested forms are made on demand."""

    pattern: GroupPattern
    graph: SocialGraph
    _links: DataFrame
    _members: DataFrame
    work: dict = field(default_factory=dict)
    text: str = ""

    def members(self) -> DataFrame:
        """(leader, node, v)."""
        return self._members

    def links(self) -> DataFrame:
        """(leader, edge_no, v, w, path, hops, trust, intimacy, influence, worst)."""
        return self._links

    def vertices(self) -> DataFrame:
        """(leader, v): every vertex on a matched path, and lone leaders."""
        on_paths = self._links.select("leader", F.explode("path").alias("v"))
        return on_paths.unionByName(self._members.select("leader", "v")).distinct()

    def induced_edges(self) -> DataFrame:
        """(leader, src, dst): the data edges of matched paths."""
        hop = F.explode(F.arrays_zip(F.expr("slice(path, 1, size(path) - 1)").alias("src"), F.expr("slice(path, 2, size(path) - 1)").alias("dst")))
        return self._links.select("leader", hop.alias("e")).select("leader", "e.src", "e.dst").distinct()

    def subgraphs(self) -> DataFrame:
        """(leader, members, links), nested and sorted."""
        m = self._members.groupBy("leader").agg(F.array_sort(F.collect_list(F.struct("node", "v"))).alias("members"))
        e = self._links.groupBy("leader").agg(F.array_sort(F.collect_list(F.struct(*_LINK))).alias("links"))
        return m.join(e, "leader", "left")

    def counts(self) -> DataFrame:
        """(leader, n_members, n_links)."""
        m = self._members.groupBy("leader").agg(F.count("*").alias("n_members"))
        e = self._links.groupBy("leader").agg(F.count("*").alias("n_links"))
        return m.join(e, "leader", "left").select("leader", "n_members", F.coalesce("n_links", F.lit(0)).alias("n_links"))

    def plan(self) -> str:
        return self.text


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _starts(p, u, found, keys, leaders=None) -> DataFrame | None:
    """Matches of node u known so far (keys..., at): targets of all its matched incoming edges and sources
    of edges matched backward - the incoming check before any outgoing work."""
    if leaders is not None and u == p.leader:
        return leaders
    parts = [rel.select(*keys, F.col("w").alias("at")).distinct() for no, rel in found.items() if _edge(p, no).dst == u]
    parts += [rel.select(*keys, F.col("v").alias("at")).distinct() for no, rel in found.items() if _edge(p, no).src == u]
    return reduce(lambda a, b: a.join(b, [*keys, "at"], "left_semi"), parts) if parts else None


def _edge(p, no):
    return next(e for e in p.edges if e.no == no)


def match_edges(g: SocialGraph, p: GroupPattern, reverse: bool, cache: bool, opt: MatchOptions, leaders: DataFrame | None = None, count: bool = False, held: list[DataFrame] | None = None, store: PathStore | None = None, given: tuple[DataFrame, DataFrame] | None = None, ask_only: bool = False, ends_only: bool = False, worst_only: bool = False) -> tuple[dict[int, DataFrame], dict]:
    """The edge relations by number; with `cache` without, else with the column leader. Frames that are kept
    for several reads go to `held`, for `release`; lost blocks are computed again from the tables. `given`: the scored edges and
    candidates, where they are at hand. `ask_only`: requests are counted, so the last edge, which no step reads, is not expanded.
    `ends_only`: the relations hold v and w, without paths and scores; `worst_only`: and the best path's worst aggregate."""
    if store is not None and not cache:
        raise ValueError("kept answers have no leaders: use strategy cached or combined")
    held = [] if held is None else held
    # Written at each step: a plan that nested all steps before it would be analysed again and again.
    edges, every = given or prepared(g, p, opt, store)
    cand = {n.name: every.where(F.col("node") == n.name).select(F.col("v").alias("at")) for n in p.nodes}
    keys = [] if cache else ["leader"]
    first = cand[p.leader] if leaders is None else cand[p.leader].join(leaders.select(F.col("leader").alias("at")), "at", "left_semi")
    first = first if cache else first.select(F.col("at").alias("leader"), "at")
    found: dict[int, DataFrame] = {}
    # What is reached from a scanned node only is the same for every leader: it is expanded without the leader,
    # which `bind` adds as soon as a match of one of the edge's ends is known for it.
    free: dict[int, DataFrame] = {}
    scanned: dict[str, DataFrame] = {}
    work: dict = {"requests": {}}

    columns = ["v", "w"] if ends_only else ["v", "w", "worst"] if worst_only else _LINK[1:]

    def bind(no: int) -> None:
        e = _edge(p, no)
        ends = {c: _starts(p, u, found, keys, first) for c, u in (("v", e.src), ("w", e.dst))}
        ends = {c: known.withColumnRenamed("at", c) for c, known in ends.items() if known is not None}
        if not ends:
            return
        (c, known), *others = ends.items()
        rel = free.pop(no).join(known, c)
        for c, known in others:
            rel = rel.join(known, [*keys, c], "left_semi")
        found[no] = settle(rel.select(*keys, *columns), "relation")

    order = steps(p, reverse, opt.reverse_chain)
    for s in order:
        if s.kind == "scan":
            own = scanned[s.node] = cand[s.node]
            if not cache and opt.max_rows is not None and (n := first.select("leader").distinct().count() * own.count()) > opt.max_rows:
                raise ValueError(f"{n} pairs of leaders and {s.node} candidates exceed max_rows={opt.max_rows}; use strategy reverse, cached or combined")
            continue
        e = s.edge
        near, far, way = (s.node, e.dst, "out") if s.kind == "forward" else (e.dst, e.src, "in")
        for no in [no for no in free if near in (_edge(p, no).src, _edge(p, no).dst)]:
            bind(no)
        known = _starts(p, near, found, keys, first)
        lone = known is None
        starts = known if not lone else scanned[near] if near in scanned else _starts(p, near, free, [])
        if s.kind == "backward":
            starts = starts.join(cand[e.dst], "at", "left_semi")
        if count:
            starts, n = settle_counted(starts, "starts")
            # Each leader asks for the starts that have no leader yet.
            work["requests"][e.no] = (s.kind, n * (first.select("leader").distinct().count() if lone and not cache else 1))
            if ask_only and s is order[-1]:
                return found, work
        if store is not None:
            rel = store.answer(p.name, starts, edges, e, p.node(far), cand[far], opt, way)
        elif ends_only:
            rel = paths.reach(starts, edges, e, cand[far], opt, way)
        elif worst_only and not opt.choose_first:
            rel = paths.expand(starts, edges, e, cand[far], opt, way).groupBy(*(c for c in starts.columns if c != "at"), "v", "w").agg(F.max("worst").alias("worst"))
        else:
            rel = paths.match_edge(starts, edges, e, cand[far], opt, way)
        (free if lone and not cache else found)[e.no] = settle(rel, "relation")
    while free:
        for no in list(free):
            bind(no)
    return found, work


def prepared(g: SocialGraph, p: GroupPattern, opt: MatchOptions, store: PathStore | None = None) -> tuple[DataFrame, DataFrame]:
    """(scored edges, candidates), written. A store's edges serve other patterns too, so all are kept for it."""
    edges = settle(g.scored_edges() if store is not None else paths.useful_edges(g, p, opt), "edges")
    return edges, settle(candidates.select_all(g, p), "candidates")


def requests(g: SocialGraph, p: GroupPattern, names: tuple[str, ...] = tuple(STRATEGIES), options: MatchOptions | None = None) -> dict[str, dict[int, tuple[str, int]]]:
    """By strategy and edge, how the edge is matched and the starts that it is asked for. No groups are made of the relations."""
    opt = options or MatchOptions()
    given = prepared(g, p, opt)
    return {name: match_edges(g, p, *STRATEGIES[name], opt, count=True, given=given, ask_only=True)[1]["requests"] for name in names}


def _kept(df: DataFrame, held: list[DataFrame]) -> DataFrame:
    held.append(df.persist())
    return df


def release(held: list[DataFrame]) -> None:
    while held:
        held.pop().unpersist()


_PAIR = ["edge_no", "v", "w"]


def _with_leaders(p: GroupPattern, links: DataFrame, leaders: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Links (keys..., edge_no, v, w) that a leader (keys..., leader) reaches along the pattern's spanning edges, keyed by leader."""
    keys = keys or []
    at = {p.leader: leaders.select(*keys, "leader", F.col("leader").alias("x"))}
    for e, forward in p.spanning_steps():
        rel = links.where(F.col("edge_no") == e.no)
        near, far, old, new = ("v", "w", e.src, e.dst) if forward else ("w", "v", e.dst, e.src)
        rel = rel.select(*keys, F.col(near).alias("x"), F.col(far).alias("y"))
        at[new] = settle(at[old].join(rel, [*keys, "x"]).select(*keys, "leader", F.col("y").alias("x")).distinct(), "reached")
    out = []
    for e in p.edges:
        a = at[e.src].select(*keys, "leader", F.col("x").alias("v"))
        b = at[e.dst].select(*keys, "leader", F.col("x").alias("w"))
        rows = links.where(F.col("edge_no") == e.no).join(a, [*keys, "v"])
        out.append(rows.join(b, [*keys, "leader", "w"], "left_semi").select(*keys, "leader", *_PAIR))
    return _union(out)


#: About as many links meet in one task of `_outward`.
_BLOCK = 1 << 22


def _outward(at: DataFrame, rel: DataFrame, keys: list[str]) -> DataFrame:
    """(keys..., leader, at): the far ends of links (keys..., near, far) from the vertices (keys..., leader, at), each once a leader.

    A block of leaders meets a block of far ends, whose links come as one list a near end: a row for each leader, near and
    far end is never made, and no pair of two blocks is the same."""
    parts = int(at.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    slices = 1 + rel.count() // _BLOCK
    cell = [*keys, "i", "j"]
    lists = rel.groupBy(*keys, F.col("near").alias("at"), F.pmod(F.xxhash64("far"), F.lit(slices).cast("long")).alias("j")).agg(F.collect_list("far").alias("far"))
    mine = at.select(*keys, F.pmod(F.xxhash64("leader"), F.lit(parts)).alias("i"), "leader", "at")
    theirs = mine.select(*keys, "i", "at").distinct().join(lists, [*keys, "at"]).select(*(F.col(c).alias(c) for c in (*cell, "at", "far")))
    mine = mine.select(*keys, "i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(slices - 1).cast("long"))).alias("j"), "leader", "at")

    def run(key, mine: pa.Table, theirs: pa.Table) -> pa.Table:
        leaders, ends = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if mine.num_rows and theirs.num_rows:
            far = theirs["far"].combine_chunks()
            far = far.combine_chunks() if isinstance(far, pa.ChunkedArray) else far
            every, code = np.unique(far.values.to_numpy(zero_copy_only=False), return_inverse=True)
            starts = far.offsets.to_numpy()
            near = theirs["at"].to_numpy()
            row = dict(zip(near.tolist(), range(len(near))))
            leader, x = mine["leader"].to_numpy(), mine["at"].to_numpy()
            order = np.argsort(leader, kind="stable")
            heads, first = np.unique(leader[order], return_index=True)
            for head, own in zip(heads, np.split(x[order], first[1:])):
                held = np.zeros(len(every), bool)
                for r in map(row.get, own.tolist()):
                    if r is not None:
                        held[code[starts[r] : starts[r + 1]]] = True
                ends.append(every[held])
                leaders.append(np.full(len(ends[-1]), head))
        out = np.concatenate(leaders)
        named = {k: pa.array([v.as_py()] * len(out), v.type) for k, v in zip(keys, key)}
        return pa.table(named | {"leader": pa.array(out, pa.int64()), "at": pa.array(np.concatenate(ends), pa.int64())})

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in at.select(*keys, "leader", "at").schema)
    return mine.groupBy(*cell).cogroup(theirs.groupBy(*cell)).applyInArrow(run, schema)


def by_leader(p: GroupPattern, links: DataFrame, keys: list[str] | None = None, max_rounds: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """(links, members, rounds): the greatest consistent part of links (keys..., edge_no, v, w) for each leader, with the column
    leader, its members, and the rounds by leader.

    Only edges on or between the pattern's circles need rounds by leader. An edge of a tree that hangs on them is
    followed once inward without leaders, so that what lacks it leaves, and once outward from the members found."""
    keys = keys or []
    rel = {e.no: links.where(F.col("edge_no") == e.no).select(*keys, "v", "w") for e in p.edges}
    hanging, left = p.hanging(), list(p.edges)
    for e, outward in hanging:
        left.remove(e)
        near, inner = ("v", e.src) if outward else ("w", e.dst)
        ends = [(f.no, c) for f in left for c, u in (("v", f.src), ("w", f.dst)) if u == inner]
        if ends:
            have = settle(rel[e.no].select(*keys, F.col(near).alias("x")).distinct(), "have")
        for no, c in ends:
            rel[no] = rel[no].join(have.withColumnRenamed("x", c), [*keys, c], "left_semi")
    own = [e.no for e in p.out_edges(p.leader)]
    hung = [(e.no, "w") for e, outward in hanging if not outward and e.dst == p.leader]
    heads = [rel[no].select(*keys, F.col(c).alias("leader")).distinct() for no, c in [(no, "v") for no in own] + hung if own]
    heads = reduce(lambda a, b: a.join(b, [*keys, "leader"], "left_semi"), heads) if heads else links.select(*keys, F.col("v").alias("leader")).limit(0)
    heads = settle(heads, "heads")
    rounds, parts = 0, []
    if left:
        names = {u for e in left for u in (e.src, e.dst)}
        core = replace(p, nodes=tuple(n for n in p.nodes if n.name in names), edges=tuple(left))
        inner = _with_leaders(core, _union([rel[e.no].select(*keys, F.lit(e.no).alias("edge_no"), "v", "w") for e in left]), heads, keys)
        # The leader's own role is played by the leader alone.
        inner, rounds = prune.cascade(inner.where(~F.col("edge_no").isin(own) | (F.col("v") == F.col("leader"))), core, [*keys, "leader"], max_rounds=max_rounds)
        inside = prune.members(inner, core, [*keys, "leader"])
        inside = settle(inside, "inside") if hanging else inside
        parts.append(inner.select(*keys, "leader", *_PAIR))
    else:
        inside = heads.select(*keys, "leader", F.lit(p.leader).alias("node"), F.col("leader").alias("v"))
    found = {n.name: inside.where(F.col("node") == n.name).select(*keys, "leader", F.col("v").alias("at")) for n in p.nodes}
    every = [inside.select(*keys, "leader", "node", "v")]
    for e, outward in reversed(hanging):
        near, far, inner, outer = ("v", "w", e.src, e.dst) if outward else ("w", "v", e.dst, e.src)
        rows = found[inner].withColumnRenamed("at", near).join(rel[e.no], [*keys, near])
        parts.append(rows.select(*keys, "leader", F.lit(e.no).alias("edge_no"), "v", "w"))
        found[outer] = settle(_outward(found[inner], rel[e.no].select(*keys, F.col(near).alias("near"), F.col(far).alias("far")), keys), "reached")
        every.append(found[outer].select(*keys, "leader", F.lit(outer).alias("node"), F.col("at").alias("v")))
    return _union(parts), _union(every), rounds


def match(g: SocialGraph, p: GroupPattern, strategy: str = "combined", options: MatchOptions | None = None, leaders: DataFrame | None = None, count: bool = False, store: PathStore | None = None, ends_only: bool = False) -> GroupResult:
    """All groups of `p` in `g`: for each leader vertex the largest consistent set of matches.

    strategy: plain, reverse, cached, combined (same result, different work) or local (one Python
    exploration per leader over its ball). `leaders` restricts the leader vertices. `store` keeps matched edges of
    this graph between matches (cached and combined). `ends_only`: for members alone; links then have (leader, edge_no, v, w)
    and no paths are kept."""
    opt = options or MatchOptions()
    if strategy == "local":
        from .local import match_local

        if store is not None:
            raise ValueError("strategy local keeps no answers")
        return match_local(g, p, opt, leaders)
    reverse, cache = STRATEGIES[strategy]
    if not p.edges:
        only = candidates.select(g, p.node(p.leader)).select(F.col("v").alias("leader"))
        only = only if leaders is None else only.join(leaders.select("leader"), "leader", "left_semi")
        empty = g.edges.sparkSession.createDataFrame([], "leader long, edge_no int, v long, w long, path array<long>, hops int, trust double, intimacy double, influence double, worst double")
        return GroupResult(p, g, empty, only.select("leader", F.lit(p.leader).alias("node"), F.col("leader").alias("v")))
    held: list[DataFrame] = []
    try:
        return _grouped(g, p, reverse, cache, opt, leaders, count, held, store, ends_only and store is None)
    finally:
        release(held)


def _grouped(g, p, reverse, cache, opt, leaders, count, held, store, ends_only) -> GroupResult:
    found, work = match_edges(g, p, reverse, cache, opt, leaders, count, held, store, ends_only=ends_only)
    keys = [] if cache else ["leader"]
    full = _union([rel.select(*keys, F.lit(no).alias("edge_no"), *(["v", "w"] if ends_only else _LINK[1:])) for no, rel in found.items()])
    # The rounds only need the ends of links; paths and scores join those that stay.
    links = full.select(*keys, *_PAIR)
    if cache:
        if opt.global_reduce:
            # Only a reduction before the leaders are attached: rounds that remove little don't pay.
            links, work["global_rounds"] = prune.cascade(links, p, [], max_rounds=opt.max_rounds, least_share=opt.global_share)
        else:
            links = settle(links, "links")
        links, inside, work["rounds"] = by_leader(p, links, max_rounds=opt.max_rounds)
    else:
        own = [e.no for e in p.out_edges(p.leader)]
        # The leader's own role is played by the leader alone.
        links = links.where(~F.col("edge_no").isin(own) | (F.col("v") == F.col("leader")))
        links, work["rounds"] = prune.cascade(links, p, ["leader"], max_rounds=opt.max_rounds)
        inside = prune.members(links, p, ["leader"])
    if ends_only:
        return GroupResult(p, g, links.select("leader", *_PAIR), inside, work, explain(p, reverse, opt.reverse_chain))
    return GroupResult(p, g, links.join(full, [*keys, *_PAIR]).select("leader", *_LINK), inside, work, explain(p, reverse, opt.reverse_chain))


def match_progressive(g: SocialGraph, p: GroupPattern, batches: int, strategy: str = "combined", options: MatchOptions | None = None):
    """Yields results for hashed parts of the leaders; each part is bounded and can be retried alone."""
    every = candidates.select(g, p.node(p.leader)).select(F.col("v").alias("leader"))
    for b in range(batches):
        yield match(g, p, strategy, options, every.where(F.pmod(F.xxhash64("leader"), F.lit(batches)) == b))
