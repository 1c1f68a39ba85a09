import numpy as np
from pyspark.sql import functions as F

from groupmatch.llm import neighbours


def test_recall_ties_and_bad_vectors(spark):
    rng = np.random.default_rng(1)
    x = rng.standard_normal((1500, 24)) * rng.uniform(0.5, 2, (1500, 1))
    x[100:160] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5020, [0.0] * 24), (5040, [float("nan")] * 24), (5060, [None] + [1.0] * 23)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for r in neighbours.search(df, F.col("vec_id") % 20 == 0, k=10, block=400).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.vec_id, r.score)
    assert set(got) == set(range(0, 1500, 20))
    hit = 0
    for q, found in got.items():
        s = x @ x[q]
        order = [i for i in np.lexsort((np.arange(1500), -s)) if i != q][:10]
        hit += len(set(order) & {v for v, _ in found.values()})
        scores = [found[k][1] for k in range(1, 11)]
        assert scores == sorted(scores, reverse=True) and all(abs(sc - s[v]) < 1e-9 for v, sc in found.values())
    assert hit >= 0.9 * 10 * len(got)


def test_repeated_ids_equal_brute_force(spark):
    """A small table is one block, verified whole; each query row answers for itself, other columns don't matter."""
    rng = np.random.default_rng(4)
    x = rng.standard_normal((120, 8))
    ids = [*range(100), *([20] * 5), *([41] * 15)]
    x[100:105] = x[20]
    df = spark.createDataFrame([(i, v.tolist(), 1, 2.0) for i, v in zip(ids, x)], "vec_id long, embedding array<double>, rank int, score double")
    got = sorted((r.query_id, r["rank"], r.vec_id, round(r.score, 9)) for r in neighbours.search(df, F.col("vec_id") % 20 == 0, k=20, share=1.0).collect())
    want = []
    for q, own in enumerate(ids):
        if own % 20 == 0:
            s = x @ x[q]
            order = [i for i in np.lexsort((ids, -np.round(s, 9))) if i != q][:20]
            want += [(own, r, ids[i], round(s[i], 9)) for r, i in enumerate(order, 1)]
    assert got == sorted(want)
    assert neighbours.search(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def test_recall_on_given_table(spark):
    """The registered query's parameters, against brute force over the whole table."""
    table = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet")
    rows = table.select("vec_id", F.col("embedding").cast("array<double>").alias("v")).collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.v for r in rows])
    found = {}
    for r in neighbours.search(table, F.col("vec_id") % 20 == 0).collect():
        found.setdefault(r.query_id, set()).add(r.vec_id)
    hit = total = 0
    for q in np.flatnonzero(ids % 20 == 0):
        s = x @ x[q]
        best = [i for i in np.lexsort((ids, -s)) if i != q][:20]
        hit, total = hit + len(found[ids[q]] & set(ids[best].tolist())), total + len(best)
    assert hit >= 0.95 * total
