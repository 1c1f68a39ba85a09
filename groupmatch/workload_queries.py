"""Queries on runs: kept answers, growth, results over time, bytes by strategy, samples."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from groupmatch import oracle_sql as O
from groupmatch import streaming
from groupmatch.durable import shared_folder
from groupmatch.functions import udfs
from groupmatch.model import pattern as P
from groupmatch.operators import baselines, explore, measures
from groupmatch.operators.store import PathStore
from groupmatch.queries import _graph, register
from groupmatch.sources import graphs

_P1, _P2 = P.one_source(), P.two_source()


@register("store_reuse", O.members(_P2))
def store_reuse(spark, sf_dir):
    """Groups of a second pattern from a store that a first one filled: they share an edge."""
    g, store = _graph(spark, sf_dir), PathStore(spark)
    explore.match(g, _P1, store=store)
    return explore.match(g, _P2, store=store).members()


@register("store_repeated", f"SELECT unnest([{', '.join(str(e.no) for e in _P1.edges)}])::INTEGER AS edge_no, 0::BIGINT AS expanded")
def store_repeated(spark, sf_dir):
    """Starts that a repeated match expands, by edge: none, starts without paths included."""
    g, store = _graph(spark, sf_dir), PathStore(spark)
    for _ in range(2):
        explore.match(g, _P1, "cached", store=store)
    again = store.log[len(_P1.edges) :]
    return spark.createDataFrame([(no, expanded) for _, no, _, expanded, _ in again], "edge_no int, expanded long")


_GROWTH = "SELECT {k}::INTEGER AS k, (SELECT count(*) FROM edg) AS edges, count(DISTINCT leader) AS groups, count(*) AS members FROM members"


@register("growth_by_handovers", " UNION ALL ".join(f"SELECT * FROM ({O.groups(_P1, _GROWTH.format(k=k), 6, data=O.handover(k))})" for k in (1, 2, 3)))
def growth_by_handovers(spark, sf_dir):
    """Groups as the graph grows by further handovers of an order: k = 1, 2, 3."""
    out = None
    for k in (1, 2, 3):
        g = graphs.handover(spark, sf_dir, k)
        found = explore.match(g, _P1).members().agg(F.count_distinct("leader").alias("groups"), F.count("*").alias("members"))
        row = g.edges.agg(F.count("*").alias("edges")).crossJoin(found).select(F.lit(k).alias("k"), "edges", "groups", "members")
        out = row if out is None else out.unionByName(row)
    return out


@register("result_curves", O.groups(_P1, "SELECT unnest(['plain', 'combined']) AS strategy, (SELECT count(DISTINCT leader) FROM members) AS total"))
def result_curves(spark, sf_dir):
    """(strategy, total): the last point of each curve of groups over time, from results in parts."""
    g, points = _graph(spark, sf_dir), []
    for name in ("plain", "combined"):
        before = 0
        for elapsed, total in measures.result_curve(explore.match_progressive(g, _P1, 2, name)):
            points.append((name, _P1.name, elapsed, total - before))
            before = total
    return measures.curve_table(spark, points).groupBy("strategy").agg(F.max("total").alias("total"))


@register("memory_by_strategy")
def memory_by_strategy(spark, sf_dir):
    rows = measures.strategy_bytes(_graph(spark, sf_dir), _P2, ("reverse", "cached", "combined"))
    return spark.createDataFrame(rows, "strategy string, part string, bytes long")


register("sample_vertices", f"WITH {O.handover()} SELECT id FROM vtx WHERE ('0x' || substr(md5('7:' || CAST(id AS VARCHAR)), 1, 8))::BIGINT < {int(0.25 * (1 << 32))}")(lambda s, d: measures.sampled(_graph(s, d), 0.25, 7).select("id"))
register("agg_best", f"WITH {O.handover()} SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY trust DESC, dst) AS r FROM edg) WHERE r = 1")(
    lambda s, d: _graph(s, d).edges.groupBy("src").agg(F.min_by("dst", F.struct((-F.col("trust")).alias("a"), F.col("dst").alias("b"))).alias("dst"))
)
register("map_in_pandas_local", f"WITH {O.handover()} SELECT src, dst, least(trust, intimacy) AS worst FROM edg")(lambda s, d: _graph(s, d).edges.mapInPandas(udfs.worst_of_edge, "src long, dst long, worst double"))
_CRISP = _P1.with_minimum(0.5, crisp=True)
register("exact_crisp", O.assignments(_CRISP, "SELECT leader, count(*) AS assignments FROM asg GROUP BY leader"))(lambda s, d: baselines.edge_join(_graph(s, d), _CRISP).groupBy("leader").agg(F.count("*").alias("assignments")))


@register("stream_late", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events WHERE date_trunc('hour', ts) + INTERVAL 2 HOUR <= (SELECT max(ts) FROM events) GROUP BY 1, 2")
def stream_late(spark, sf_dir):
    """Tumbling counts when every event comes again thirty days late: the watermark keeps the late ones out."""
    place = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    events = graphs.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    # Two runs of one stream, so that the late part can't come first.
    for part, rows in enumerate((events, events.withColumn("ts", F.expr("ts - INTERVAL 30 DAYS")))):
        rows.write.parquet(f"{place}/in/{part}")
        counts = streaming.tumbling(spark.readStream.schema(events.schema).parquet(f"{place}/in/*")).select("start", "event_type", "n")
        counts.writeStream.format("parquet").option("path", f"{place}/out").option("checkpointLocation", f"{place}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(counts.schema).parquet(f"{place}/out")
