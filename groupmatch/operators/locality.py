"""Balls of bounded radius around vertices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.model import SocialGraph


def _neighbours(g: SocialGraph, directed: bool = False) -> DataFrame:
    out = g.edges.select("src", "dst")
    both = out if directed else out.unionByName(out.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return settle(both.where("src <> dst").distinct(), "neighbours")


def near(g: SocialGraph, starts: DataFrame, radius: int) -> DataFrame:
    """(v): vertices within `radius` hops of any of `starts` (v), over edges taken either way."""
    both = _neighbours(g)
    seen = front = settle(starts.select("v").distinct(), "near")
    for _ in range(radius):
        step = front.join(both, front["v"] == both["src"]).select(F.col("dst").alias("v")).distinct()
        front = settle(step.join(seen, "v", "left_anti"), "near")
        seen = seen.unionByName(front)
    return seen


def ball(g: SocialGraph, leaders: DataFrame, radius: int, directed: bool = False) -> DataFrame:
    """(leader, v, dist): vertices within `radius` hops of each leader, over edges taken either way."""
    both = _neighbours(g, directed)
    seen = leaders.select("leader", F.col("leader").alias("v"), F.lit(0).alias("dist"))
    front = seen
    for d in range(1, radius + 1):
        step = front.join(both, front["v"] == both["src"]).select("leader", F.col("dst").alias("v")).distinct()
        front = settle(step.join(seen.select("leader", "v"), ["leader", "v"], "left_anti").withColumn("dist", F.lit(d)), "ball")
        seen = seen.unionByName(front)
    return seen
