"""The data graph: vertices (id, labels, influence[, influence_by]) and edges (src, dst, trust, intimacy[, attrs])."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SocialGraph:
    vertices: DataFrame
    edges: DataFrame

    def inverse(self) -> SocialGraph:
        """Every edge turned round."""
        e = self.edges
        return SocialGraph(self.vertices, e.select(*(F.col({"src": "dst", "dst": "src"}.get(c, c)).alias(c) for c in e.columns)).select(*e.columns))

    def in_domain(self, name: str) -> SocialGraph:
        """Influence of one field, out of the map of fields."""
        return SocialGraph(self.vertices.withColumn("influence", F.col("influence_by")[name]), self.edges)

    def scored_edges(self, least: dict[str, float] | None = None, ends: Column | None = None) -> DataFrame:
        """Edges with the influence of both ends; the paths' only input. Self loops are left out. `least`: only edges
        whose scores reach these values; `ends`: only edges between vertices that pass this test."""
        v = (self.vertices if ends is None else self.vertices.where(ends)).select("id", "influence")
        a = v.select(F.col("id").alias("src"), F.col("influence").alias("src_influence"))
        b = v.select(F.col("id").alias("dst"), F.col("influence").alias("dst_influence"))
        e = self.edges.select("src", "dst", "trust", "intimacy").where("src <> dst")
        for k, low in (least or {}).items():
            e = e.where(F.col(k) >= F.lit(low))
        return e.join(a, "src").join(b, "dst").select("src", "dst", "trust", "intimacy", "src_influence", "dst_influence")

    def profile(self) -> DataFrame:
        """(vertices, edges, mean_degree, max_degree)."""
        n = self.vertices.agg(F.count("*").alias("vertices"))
        d = self.edges.groupBy("src").agg(F.count("*").alias("d"))
        m = d.agg(F.coalesce(F.sum("d"), F.lit(0)).alias("edges"), F.coalesce(F.max("d"), F.lit(0)).alias("max_degree"))
        return n.crossJoin(m).select("vertices", "edges", (F.col("edges") / F.col("vertices")).alias("mean_degree"), "max_degree")

    def bucketed(self, name: str, buckets: int) -> SocialGraph:
        """Saved as tables bucketed by source (and, turned round, by target), so that frontier joins
        shuffle the frontier only."""
        spark = self.edges.sparkSession
        self.vertices.write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(f"{name}_vertices")
        self.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(f"{name}_edges_out")
        self.edges.write.bucketBy(buckets, "dst").sortBy("dst").mode("overwrite").saveAsTable(f"{name}_edges_in")
        return SocialGraph(spark.table(f"{name}_vertices"), spark.table(f"{name}_edges_out"))
