"""Labels of connected components from star-like links, on tables in the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle


def merge_labels(labels: DataFrame, links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """labels (key, label), links (x, y: keys) -> labels where linked keys have the same.

    Works on labels, not keys: the links become edges between labels, their components are
    found by alternating large-star and small-star steps, and labels are mapped once. A hub's
    edges are rows of a join, which adaptive execution can split; none are collected."""
    a = labels.select(F.col("key").alias("x"), F.col("label").alias("p"))
    b = labels.select(F.col("key").alias("y"), F.col("label").alias("q"))
    edges = links.join(a, "x").join(b, "y").where("p <> q")
    edges = settle(edges.select(F.greatest("p", "q").alias("u"), F.least("p", "q").alias("v")).distinct(), "label-edges")
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        small = small.select("u", F.col("m").alias("v")).unionByName(small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")))
        following = settle(small.distinct(), "label-edges")
        n = following.count()
        stars = following.agg(F.count_distinct("u").alias("u"), F.count("*").alias("n")).first()
        chained = following.join(following.select(F.col("u").alias("v")).distinct(), "v", "left_semi").isEmpty()
        edges = following
        if n == 0 or (chained and stars["u"] == stars["n"]):
            break
    else:
        raise RuntimeError("components did not settle within max_rounds")
    head = edges.select(F.col("u").alias("label"), F.col("v").alias("head"))
    return settle(labels.join(head, "label", "left").select("key", F.coalesce("head", "label").alias("label")), "labels")
