"""Measures of results and of runs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .explore import GroupResult


def group_count(r: GroupResult) -> DataFrame:
    return r.members().agg(F.count_distinct("leader").alias("groups"))


def mean_members(r: GroupResult) -> DataFrame:
    """(groups, mean_members, mean_vertices): matched (node, vertex) pairs and distinct vertices per group."""
    per = r.members().groupBy("leader").agg(F.count("*").alias("n"), F.count_distinct("v").alias("d"))
    return per.agg(F.count("*").alias("groups"), F.avg("n").alias("mean_members"), F.avg("d").alias("mean_vertices"))


def mean_links(r: GroupResult) -> DataFrame:
    per = r.links().groupBy("leader").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("groups"), F.avg("n").alias("mean_links"))


def timed(run) -> tuple[float, GroupResult]:
    """Wall seconds until members and links are computed, and the result."""
    t = time.perf_counter()
    r = run()
    for df in (r.members(), r.links()):
        df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t, r


def speedup(times: dict[str, float], base: str = "combined") -> dict[str, float]:
    return {k: v / times[base] for k, v in times.items() if k != base}


def result_curve(parts) -> list[tuple[float, int]]:
    """(elapsed seconds, groups so far) from an iterator of results."""
    start, total, out = time.perf_counter(), 0, []
    for r in parts:
        total += r.members().select("leader").distinct().count()
        out.append((time.perf_counter() - start, total))
    return out


def stored_bytes(rows: DataFrame, row_bytes: int) -> DataFrame:
    """(rows, bytes) of a kept relation at a given width."""
    return rows.agg(F.count("*").alias("rows")).select("rows", (F.col("rows") * row_bytes).alias("bytes"))


def graph_bytes(g, reverse: bool) -> DataFrame:
    """Adjacency at 32 bytes an edge; strategies that match backward keep the inverse lists too."""
    return stored_bytes(g.edges, 32).select("rows", (F.col("bytes") * (2 if reverse else 1)).alias("bytes"))


def agreement(ours: DataFrame, other: DataFrame) -> DataFrame:
    """(in_both, only_first, only_second): leaders of two results."""
    a = ours.select("leader", F.lit(1).alias("a")).distinct()
    b = other.select("leader", F.lit(1).alias("b")).distinct()
    j = a.join(b, "leader", "full_outer")
    one = lambda c: F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0)).cast("long")
    return j.agg(one(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("in_both"), one(F.col("b").isNull()).alias("only_first"), one(F.col("a").isNull()).alias("only_second"))


def credibility(r: GroupResult) -> DataFrame:
    """(leader, n_links, least, mean): worst aggregates of a group's paths."""
    return r.links().groupBy("leader").agg(F.count("*").alias("n_links"), F.min("worst").alias("least"), F.avg("worst").alias("mean"))


def top_groups(r: GroupResult, k: int = 10) -> DataFrame:
    return credibility(r).orderBy(F.desc("least"), F.desc("n_links"), "leader").limit(k)


def work(r: GroupResult, session) -> DataFrame:
    """(edge_no, kind, requests): starts that each pattern edge expanded, from match(..., count=True)."""
    return request_table(session, r.work["requests"])


def request_table(session, requests: dict[int, tuple[str, int]]) -> DataFrame:
    """(edge_no, kind, requests) of one strategy."""
    rows = [(int(no), kind, int(n)) for no, (kind, n) in requests.items()]
    return session.createDataFrame(rows, "edge_no int, kind string, requests long")


def curve_table(spark, points: list[tuple[str, str, float, int]]) -> DataFrame:
    """(strategy, pattern, elapsed, groups, total): cumulative counts over time."""
    df = spark.createDataFrame(points, "strategy string, pattern string, elapsed double, groups long")
    w = Window.partitionBy("strategy", "pattern").orderBy("elapsed")
    return df.withColumn("total", F.sum("groups").over(w))


def written_bytes(df: DataFrame) -> int:
    """Bytes of the files of a table written by `settle`."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def strategy_bytes(g, p, strategies) -> list[tuple[str, str, int]]:
    """(strategy, part, bytes) that a run keeps: the adjacency, its inverse where edges are matched
    backward, and the edge relations, all as written."""
    from groupmatch.durable import settle

    from .explore import STRATEGIES, match_edges
    from groupmatch.model import MatchOptions

    edges = written_bytes(settle(g.scored_edges(), "edges"))
    out = []
    for name in strategies:
        reverse, cache = STRATEGIES[name]
        found, _ = match_edges(g, p, reverse, cache, MatchOptions())
        out += [(name, "adjacency", edges), (name, "inverse", edges if reverse else 0), (name, "relations", sum(map(written_bytes, found.values())))]
    return out


def sampled(g, share: float, seed: int = 0) -> DataFrame:
    """A reproducible share of the vertices, by a digest of seed and id: for estimates."""
    bucket = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
    return g.vertices.where(bucket < F.lit(int(share * (1 << 32))))
