"""Removal of matches that lack a required edge, until nothing changes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle_counted
from groupmatch.model import GroupPattern
from groupmatch.plans.order import masks


def incident(links: DataFrame, p: GroupPattern, keys: list[str], child_only: bool = False) -> DataFrame:
    """(keys..., u, v, mask): the edge bits each match has."""
    bits = {e.no: (e.bit, p.index(e.src), p.index(e.dst)) for e in p.edges}
    pick = lambda k: F.create_map(*(F.lit(x) for no, t in bits.items() for x in (no, t[k])))[F.col("edge_no")]
    near = F.struct(pick(1).alias("u"), F.col("v").alias("x"), pick(0).cast("long").alias("bit"))
    far = F.struct(pick(2).alias("u"), F.col("w").alias("x"), (F.lit(0) if child_only else pick(0)).cast("long").alias("bit"))
    ends = links.select(*keys, F.inline(F.array(near, far)))
    return ends.groupBy(*keys, "u", "x").agg(F.bit_or("bit").alias("mask"))


def members(links: DataFrame, p: GroupPattern, keys: list[str]) -> DataFrame:
    """(keys..., node, v): the ends of links, by node."""
    names = F.array(*(F.lit(n.name) for n in p.nodes))
    return incident(links, p, keys).select(*keys, F.element_at(names, F.col("u") + 1).alias("node"), F.col("x").alias("v"))


def alive(links: DataFrame, p: GroupPattern, keys: list[str], child_only: bool = False) -> DataFrame:
    """(keys..., u, x) of matches that have every required bit."""
    need = masks(p, child_only)
    required = F.create_map(*(F.lit(x) for u, m in need.items() for x in (u, m)))[F.col("u")].cast("long")
    return incident(links, p, keys, child_only).where(F.col("mask").bitwiseAND(required) == required).select(*keys, "u", "x")


def _kept(links: DataFrame, living: DataFrame, p: GroupPattern, keys: list[str]) -> DataFrame:
    ends = {e.no: (p.index(e.src), p.index(e.dst)) for e in p.edges}
    pick = lambda k: F.create_map(*(F.lit(x) for no, t in ends.items() for x in (no, t[k])))[F.col("edge_no")]
    rows = links.withColumn("__a", pick(0)).withColumn("__b", pick(1))
    a = living.select(*(F.col(k).alias(f"__k_{k}") for k in keys), F.col("u").alias("__u"), F.col("x").alias("__x"))

    def semi(df, node, vertex):
        test = (F.col(node) == F.col("__u")) & (F.col(vertex) == F.col("__x"))
        for k in keys:
            test = test & (F.col(k) == F.col(f"__k_{k}"))
        return df.join(a, test, "left_semi")

    return semi(semi(rows, "__a", "v"), "__b", "w").drop("__a", "__b")


def cascade(links: DataFrame, p: GroupPattern, keys: list[str], child_only: bool = False, max_rounds: int | None = None, least_share: float = 0.0) -> tuple[DataFrame, int]:
    """The greatest part of `links` in which every end has all its edges, and the rounds it took.

    Each round is one mask aggregate and two semi-joins, written to the shared folder. Every round but
    the last removes links, so the rounds end by themselves; `max_rounds` raises before that. With
    `least_share` the rounds also stop after one that removes at most that share of the links: the result
    is then a superset of the greatest part."""
    links, count = settle_counted(links, "links")
    done = 0
    while max_rounds is None or done < max_rounds:
        done += 1
        links, left = settle_counted(_kept(links, alive(links, p, keys, child_only), p, keys), "links")
        if count - left <= least_share * count:
            return links, done
        count = left
    raise RuntimeError(f"links did not settle within {max_rounds} rounds")
