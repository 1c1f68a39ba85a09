"""Headline queries, timed: one JSON line.

The graph is prepared once, outside the times. Every run starts without cached frames and computes its own
relations. Each strategy runs once, then all again in shuffled order while under REPEAT seconds have passed, then
p2_plain if under LIMIT have; a time is the median of a strategy's runs, and what did not run is in `not_run`. `exact` is the compared method: on P1 each leader explores by itself and
assignments are enumerated; on P2 that takes many minutes here, so `exact_shared` enumerates over shared relations.
"""

from __future__ import annotations

import json
import os
import random
import sys
import tempfile
import time
from statistics import median

from pyspark.sql import SparkSession

from groupmatch.durable import settle
from groupmatch.model import SocialGraph
from groupmatch.model import pattern as P
from groupmatch.operators import baselines, explore, measures
from groupmatch.session import ship
from groupmatch.sources import graphs

REPEAT, LIMIT = 60.0, float(os.environ.get("BENCH_LIMIT", "240"))
MINIMUM = 0.5


def main() -> None:
    cpus, sf = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    conf = {"spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "12g", "spark.ui.enabled": "false", "spark.driver.host": "127.0.0.1", "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}
    conf["spark.sql.adaptive.coalescePartitions.parallelismFirst"] = "false"  # fewer, fuller tasks
    conf["spark.checkpoint.dir"] = "file://" + tempfile.mkdtemp(prefix="bench-")
    spark = ship(SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    g = graphs.handover(spark, sf, 3)
    g = SocialGraph(settle(g.vertices, "vertices"), settle(g.edges, "edges"))
    runs = {}
    for key, make in (("p1", P.one_source), ("p2", P.two_source)):
        for strategy in explore.STRATEGIES:
            runs[f"{key}_{strategy}"] = lambda f=make, s=strategy: explore.match(g, f(MINIMUM), s).members()
    runs["p1_exact"] = lambda: baselines.edge_join(g, P.one_source(MINIMUM), per_leader=True)
    runs["p2_exact_shared"] = lambda: baselines.edge_join(g, P.two_source(MINIMUM))
    runs["p1_combined"]().count()  # compiled once
    order = [f"{key}_{s}" for s in ("combined", "exact", "exact_shared", "plain", "reverse", "cached") for key in ("p1", "p2")]
    runs = {name: runs[name] for name in order if name in runs}
    last = "p2_plain"  # a product of leaders and candidates, the slowest by far
    again = [n for n in runs if n != last] * 2
    random.Random(1).shuffle(again)
    times: dict[str, list[float]] = {name: [] for name in runs}
    start = time.perf_counter()
    for name in [*(n for n in runs if n != last), *again, last]:
        if time.perf_counter() - start > (REPEAT if times[name] else LIMIT):
            continue
        spark.catalog.clearCache()
        began = time.perf_counter()
        runs[name]().write.format("noop").mode("overwrite").save()
        times[name].append(time.perf_counter() - began)
        print(f"{name} {times[name][-1]:.2f}", file=sys.stderr, flush=True)
    found = {name: round(median(t), 3) for name, t in times.items() if t}
    ratios = {key: {k: round(v, 2) for k, v in measures.speedup({n[3:]: t for n, t in found.items() if n.startswith(key)}).items()} for key in ("p1", "p2") if f"{key}_combined" in found}
    print(json.dumps({"metric": f"group matching, handover(3), minimum {MINIMUM}", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "times_combined": ratios, "not_run": sorted(set(runs) - set(found)), "sf": sf}))


if __name__ == "__main__":
    main()
