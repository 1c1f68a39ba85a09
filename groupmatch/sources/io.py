"""Readers and writers of edge lists, patterns and groups."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupmatch.model import GroupPattern
from groupmatch.operators.explore import GroupResult


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#") -> DataFrame:
    """(src, dst) of a text edge list with comment lines; malformed lines are left out."""
    rows = spark.read.schema("src long, dst long").option("sep", sep).option("comment", comment).option("mode", "PERMISSIVE").csv(path)
    return rows.where("src IS NOT NULL AND dst IS NOT NULL")


def write_edge_list(edges: DataFrame, path: str, sep: str = "\t") -> None:
    edges.select("src", "dst").write.mode("overwrite").option("sep", sep).csv(path)


def read_vertices(spark: SparkSession, path: str) -> DataFrame:
    """CSV with header id, labels (separated by |), influence."""
    rows = spark.read.schema("id long, labels string, influence double").option("header", True).csv(path)
    return rows.withColumn("labels", F.split("labels", r"\|"))


def read_pattern(spark: SparkSession, path: str) -> GroupPattern:
    return GroupPattern.from_json(spark.read.option("wholetext", True).text(path).first()[0])


def write_pattern(spark: SparkSession, p: GroupPattern, path: str) -> None:
    spark.createDataFrame([(p.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def write_groups(r: GroupResult, path: str) -> None:
    """Members and links as Parquet, and nested groups as JSON."""
    r.members().write.mode("overwrite").parquet(f"{path}/members")
    r.links().write.mode("overwrite").parquet(f"{path}/links")
    r.subgraphs().write.mode("overwrite").json(f"{path}/groups")


def save_groups(r: GroupResult, name: str, buckets: int = 16) -> None:
    """Members and links as tables bucketed by leader, so that groups join without a shuffle."""
    r.members().write.bucketBy(buckets, "leader").sortBy("leader").mode("overwrite").saveAsTable(f"{name}_members")
    r.links().write.bucketBy(buckets, "leader").sortBy("leader").mode("overwrite").saveAsTable(f"{name}_links")


def register_views(r: GroupResult) -> None:
    """Temporary views vertices, edges, members and links, and the SQL function membership_ratio."""
    spark = r.graph.edges.sparkSession
    for name, df in (("vertices", r.graph.vertices), ("edges", r.graph.edges), ("members", r.members()), ("links", r.links())):
        df.createOrReplaceTempView(name)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION membership_ratio(v DOUBLE, m DOUBLE) RETURNS DOUBLE RETURN CASE WHEN v >= m THEN 1.0D ELSE v / m END")
