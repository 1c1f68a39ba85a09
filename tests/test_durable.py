import gc
import os
import time

from groupmatch import durable


def test_written_tables_go_with_their_last_reader(spark):
    kept = durable.settle(spark.range(5), "kept")
    derived = durable.settle(spark.range(7), "derived").selectExpr("id + 1 AS x").distinct()
    durable.settle(spark.range(9), "lost").count()
    places = {x[0].rsplit("/", 1)[1].split("-")[0]: x[0].removeprefix("file://") for x in durable._written(spark)[-3:]}
    for _ in range(20):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        durable.sweep(spark)
        if not os.path.exists(places["lost"]):
            break
        time.sleep(0.2)
    assert not os.path.exists(places["lost"]) and os.path.exists(places["kept"])
    assert kept.count() == 5 and derived.count() == 7


def test_files_of_ended_steps_go_while_a_query_runs(spark, monkeypatch):
    monkeypatch.setattr(durable, "COLLECT_S", 0)
    durable.settle(spark.range(9), "ended").count()
    place = next(x[0] for x in durable._written(spark) if "/ended-" in x[0]).removeprefix("file://")
    for _ in range(5):
        durable.settle(spark.range(3), "next")
    assert not os.path.exists(place)
