"""Patterns of one shape that differ in their minimum only, matched together."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.functions.membership import least_value
from groupmatch.model import GroupPattern, MatchOptions, SocialGraph

from . import explore, prune


def floor(p: GroupPattern) -> float:
    """The one least value that all constraints of `p` ask for; raises where there are several."""
    parts = [(n.min_influence, n.rule) for n in p.nodes] + [(m, e.rule) for e in p.edges for m in (e.min_trust, e.min_intimacy, e.min_influence)]
    found = {None if m is None else least_value(m, rule) for m, rule in parts}
    if len(found) > 1 or None in found:
        raise ValueError("a sweep takes patterns whose constraints all have one least value")
    return found.pop()


def members(g: SocialGraph, patterns: dict[str, GroupPattern]) -> DataFrame:
    """(setting, leader, node, v) of patterns by setting.

    The edges are matched once, with the smallest least value. A pair's best path has the largest worst aggregate,
    so the pair stays in a setting whose least value neither that nor the influence of its ends is below."""
    floors = {k: floor(p) for k, p in patterns.items()}
    p = patterns[min(floors, key=floors.get)]
    if len({tuple((e.no, e.src, e.dst, e.max_hops) for e in q.edges) + tuple((n.name, n.labels) for n in q.nodes) + (q.leader,) for q in patterns.values()}) > 1:
        raise ValueError("a sweep takes patterns of one shape")
    opt = MatchOptions()
    found, _ = explore.match_edges(g, p, True, True, opt, worst_only=True)
    v = settle(g.vertices.select("id", "influence"), "influence")
    rows = explore._union([rel.select(F.lit(no).alias("edge_no"), "v", "w", "worst") for no, rel in found.items()])
    for c in ("v", "w"):
        rows = rows.join(v.select(F.col("id").alias(c), F.col("influence").alias(f"of_{c}")), c)
    level = F.least("worst", "of_v", "of_w")
    fits = F.array_compact(F.array(*(F.when(level >= F.lit(low), F.lit(k)) for k, low in floors.items())))
    links = rows.select(F.explode(fits).alias("setting"), "edge_no", "v", "w")
    links, _ = prune.cascade(links, p, ["setting"], least_share=opt.global_share)
    return explore.by_leader(p, links, ["setting"])[1]
