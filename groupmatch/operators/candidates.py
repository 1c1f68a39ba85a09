"""Vertices that may play a pattern node."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from groupmatch.functions.membership import passes
from groupmatch.model import GroupPattern, PatternNode, SocialGraph


def fits(n: PatternNode) -> Column:
    """All labels are held and influence passes."""
    test = passes(F.col("influence"), n.min_influence, n.rule)
    for label in n.labels:
        test = test & F.array_contains("labels", label)
    return F.coalesce(test, F.lit(False))


def select(g: SocialGraph, n: PatternNode) -> DataFrame:
    return g.vertices.where(fits(n)).select(F.col("id").alias("v"))


def select_all(g: SocialGraph, p: GroupPattern) -> DataFrame:
    """(node, v) for every pattern node, in one scan of the vertices."""
    roles = F.array_compact(F.array(*(F.when(fits(n), F.lit(n.name)) for n in p.nodes)))
    return g.vertices.select(F.explode(roles).alias("node"), F.col("id").alias("v"))
