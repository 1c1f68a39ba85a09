"""Baselines: exact-style matching by joining edge relations, and plain embeddings."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.model import GroupPattern, MatchOptions, SocialGraph

from . import candidates, explore


def edge_join(g: SocialGraph, p: GroupPattern, injective: bool = False, k: int | None = None, options: MatchOptions | None = None, per_leader: bool = False) -> DataFrame:
    """One row for each assignment of vertices to pattern nodes: leader, a column per node, worst.

    Every pattern edge is matched with its constraints, then the relations are joined along
    the pattern. `injective`: no vertex plays two nodes. `k`: the best k assignments per leader.
    `per_leader`: as the compared method does, each leader explores by itself, forward only and without
    shared relations; the rows are the same."""
    held: list[DataFrame] = []
    rows = settle(_assignments(g, p, injective, k, options or MatchOptions(), per_leader, held), "assignments")
    explore.release(held)
    return rows


def _assignments(g, p, injective, k, options, per_leader, held) -> DataFrame:
    found, _ = explore.match_edges(g, p, not per_leader, not per_leader, options, held=held)
    own = ["leader"] if per_leader else []
    rows, bound, left = None, set(), list(p.edges)
    if not left:
        return candidates.select(g, p.node(p.leader)).select(F.col("v").alias("leader"), F.col("v").alias(p.leader), F.lit(None).cast("double").alias("worst"))
    while left:
        e = next(x for x in left if rows is None and x.src == p.leader or x.src in bound or x.dst in bound)
        left.remove(e)
        rel = found[e.no].select(*own, F.col("v").alias(e.src), F.col("w").alias(e.dst), F.col("worst").alias("__worst"))
        if own and p.leader in (e.src, e.dst):
            rel = rel.where(F.col("leader") == F.col(p.leader))
        if rows is None:
            rows = rel.withColumnRenamed("__worst", "worst")
        else:
            rows = rows.join(rel, [*own, *sorted({e.src, e.dst} & bound)]).withColumn("worst", F.least("worst", "__worst")).drop("__worst")
        bound |= {e.src, e.dst}
    names = [n.name for n in p.nodes]
    if injective:
        rows = rows.where(F.size(F.array_distinct(F.array(*names))) == len(names))
    rows = rows.select(F.col(p.leader).alias("leader"), *names, "worst")
    if k is not None:
        rank = F.row_number().over(Window.partitionBy("leader").orderBy(F.desc("worst"), *names))
        rows = rows.withColumn("rank", rank).where(F.col("rank") <= k)
    return rows


def edge_join_grouped(g: SocialGraph, p: GroupPattern, injective: bool = False) -> DataFrame:
    """(leader, node, v): the assignments of one leader taken together."""
    rows = edge_join(g, p, injective)
    role = F.array(*(F.struct(F.lit(n.name).alias("node"), F.col(n.name).alias("v")) for n in p.nodes))
    return rows.select("leader", F.inline(role)).distinct()


def embeddings(g: SocialGraph, p: GroupPattern, injective: bool = True) -> DataFrame:
    """Subgraph isomorphisms (or homomorphisms) edge to edge, labels only."""
    rows, bound, left = None, set(), list(p.edges)
    every = candidates.select_all(g, p.with_minimum(None))
    data = g.edges.select("src", "dst").where("src <> dst").distinct()
    cand = {n.name: every.where(F.col("node") == n.name).select("v") for n in p.nodes}
    while left:
        e = next(x for x in left if rows is None or x.src in bound or x.dst in bound)
        left.remove(e)
        rel = data.select(F.col("src").alias(e.src), F.col("dst").alias(e.dst))
        for u in (e.src, e.dst):
            if u not in bound:
                rel = rel.join(cand[u].select(F.col("v").alias(u)), u, "left_semi")
        rows = rel if rows is None else rows.join(rel, sorted({e.src, e.dst} & bound))
        bound |= {e.src, e.dst}
    names = [n.name for n in p.nodes]
    if injective:
        rows = rows.where(F.size(F.array_distinct(F.array(*names))) == len(names))
    return rows.select(F.col(p.leader).alias("leader"), *names)


def false_members(g: SocialGraph, p: GroupPattern) -> DataFrame:
    """(node, v) that the bounded model returns though no group of the proposed model holds them."""
    from .simulate import child

    return child(g, p, "constrained").join(explore.match(g, p).members().select("node", "v").distinct(), ["node", "v"], "left_anti")
