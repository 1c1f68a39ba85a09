"""Estimates that choose a direction for an edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.model import GroupPattern, SocialGraph


def drivers(g: SocialGraph, p: GroupPattern) -> DataFrame:
    """n, pattern nodes, mean out-degrees of pattern and data, and the longest hop bound."""
    f = g.profile()
    return f.select(
        F.col("vertices").alias("n"), F.lit(len(p.nodes)).cast("long").alias("pattern_nodes"),
        F.lit(len(p.edges) / len(p.nodes)).alias("pattern_degree"), F.col("mean_degree").alias("data_degree"),
        F.lit(max((e.max_hops for e in p.edges), default=0)).cast("long").alias("hops"),
    )


def direction(starts: int, ends: int, out_degree: float, in_degree: float, hops: int) -> str:
    """The cheaper side to expand from."""
    return "out" if starts * out_degree**hops <= ends * in_degree**hops else "in"


def estimated_paths(starts: int, degree: float, hops: int) -> float:
    return float(sum(starts * degree**h for h in range(1, hops + 1)))
