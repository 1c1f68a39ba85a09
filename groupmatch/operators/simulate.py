"""Older matching models: child, dual and strong simulation, edge to edge, bounded or constrained."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.model import GroupPattern, MatchOptions, SocialGraph

from . import candidates, explore, paths, prune


def _crisp(p: GroupPattern) -> GroupPattern:
    nodes = tuple(replace(n, rule=None) for n in p.nodes)
    return replace(p, nodes=nodes, edges=tuple(replace(e, rule=None) for e in p.edges))


def _relations(g: SocialGraph, p: GroupPattern, mode: str) -> tuple[DataFrame, DataFrame]:
    """(candidates, links); the links are written, so that nothing stays in memory."""
    if mode != "constrained":
        p = p.with_minimum(None)
    opt = MatchOptions(edge_mode=mode)
    held: list[DataFrame] = []
    edges = explore._kept(g.scored_edges(), held)
    every = candidates.select_all(g, p)
    cand = {n.name: every.where(F.col("node") == n.name).select(F.col("v").alias("at")) for n in p.nodes}
    rels = [paths.expand(cand[e.src], edges, e, cand[e.dst], opt).select(F.lit(e.no).alias("edge_no"), "v", "w").distinct() for e in p.edges]
    links = settle(reduce(DataFrame.unionByName, rels), "relations")
    explore.release(held)
    return every, links


def _matches(every: DataFrame, links: DataFrame, p: GroupPattern, child_only: bool) -> DataFrame:
    """Matches after the fixpoint: those with all bits, and candidates of nodes that need none."""
    links, _ = prune.cascade(links, p, [], child_only)
    names = F.array(*(F.lit(n.name) for n in p.nodes))
    held = prune.alive(links, p, [], child_only).select(F.element_at(names, F.col("u") + 1).alias("node"), F.col("x").alias("v"))
    free = [n.name for n in p.nodes if not (p.out_mask(n.name) if child_only else p.mask(n.name))]
    out = held.unionByName(every.where(F.col("node").isin(free))).distinct()
    full = out.select("node").distinct().count() == len(p.nodes)
    return out if full else out.limit(0)


def child(g: SocialGraph, p: GroupPattern, mode: str = "edge", fuzzy: bool = True) -> DataFrame:
    """(node, v): every match has, for each outgoing pattern edge, a match beyond it.

    mode: 'edge' (edge to edge), 'path' (hop bounds), 'constrained' (and aggregates). Empty
    unless every pattern node has a match."""
    p = p if fuzzy else _crisp(p)
    return _matches(*_relations(g, p, mode), p, True)


def dual(g: SocialGraph, p: GroupPattern, mode: str = "edge", fuzzy: bool = True) -> DataFrame:
    """(node, v): child and parent conditions together."""
    p = p if fuzzy else _crisp(p)
    return _matches(*_relations(g, p, mode), p, False)


def strong(g: SocialGraph, p: GroupPattern, mode: str = "edge", fuzzy: bool = True) -> DataFrame:
    """(leader, node, v): dual simulation within the ball of the pattern's diameter around a leader match.

    A match that survives has all its edges, so links along the pattern's spanning edges lead from it to the
    leader and it lies within the diameter: dual matches are reached that way, and no ball of data edges is made."""
    p = p if fuzzy else _crisp(p)
    _, links = _relations(g, p, mode)
    links, _ = prune.cascade(links, p, [])
    own = [e.no for e in p.out_edges(p.leader)]
    heads = links.where(F.col("edge_no").isin(own)).select(F.col("v").alias("leader")).distinct()
    inside = explore._with_leaders(p, links, heads)
    inside, _ = prune.cascade(inside.where(~F.col("edge_no").isin(own) | (F.col("v") == F.col("leader"))), p, ["leader"])
    return prune.members(inside, p, ["leader"])


def fuzzy_strong(g: SocialGraph, p: GroupPattern, fuzzy: bool = True) -> DataFrame:
    """(leader, node, v) of the proposed model; without rules its crisp form."""
    return explore.match(g, p if fuzzy else _crisp(p)).members()
