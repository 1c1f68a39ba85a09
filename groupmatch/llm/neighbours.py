"""Nearest neighbours by inner product with collision-counting hashing.

Vectors are dealt into blocks; a block holds, for each of many random lines, its vectors' projections
as a sorted array. A query's window on every array is centred on its own projection and widened by
virtual rehashing until enough vectors collide with it on at least `threshold` of the lines; those are
verified by exact inner products. Norms are levelled by one more coordinate, so that the
largest inner product is the least distance. Queries meet every block, in packed groups.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from groupmatch.durable import settle

LINES = 64
BLOCK = 8192
#: Queries whose windows are looked up together.
GROUP = 64


class CollisionIndex:
    """Vectors with their ids and row numbers; a query is left out of its own answer by its row number."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, vectors: np.ndarray, lines: int = LINES, seed: int = 7):
        order = np.lexsort((rows, ids))
        self.ids, self.rows, self.vectors = ids[order], rows[order], vectors[order]
        norms = np.einsum("ij,ij->i", self.vectors, self.vectors)
        self.top = float(np.sqrt(norms.max()))
        level = np.sqrt(np.maximum(1.0 - norms / self.top**2, 0.0))
        self.directions = np.random.default_rng(seed).standard_normal((vectors.shape[1] + 1, lines))
        shown = np.column_stack((self.vectors / self.top, level)) @ self.directions
        self.orders = np.argsort(shown, axis=0, kind="stable").T.astype(np.int64).copy()
        self.sorted = np.take_along_axis(shown, self.orders.T, 0).T.copy()

    def search(self, queries: np.ndarray, own: np.ndarray, k: int, share: float, threshold: float, width: float = 0.35, growth: float = 1.35):
        """For each query (ids, scores) of the block's best k; the rows `own` are left out."""
        n = len(self.ids)
        need = min(n, int(k + 1 + share * n))
        for at in range(0, len(queries), GROUP):
            some = slice(at, at + GROUP)
            yield from self._verified(queries[some], own[some], self._colliding(queries[some], need, threshold, width, growth), k)

    def _windows(self, centres: np.ndarray, radius: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where each query's window begins and ends on every array, as places in the arrays put end to end."""
        n, lines = self.sorted.shape[1], len(self.sorted)
        begin, end = (np.empty((len(centres), lines), np.int64) for _ in range(2))
        for j in range(lines):
            begin[:, j] = np.searchsorted(self.sorted[j], centres[:, j] - radius) + j * n
            end[:, j] = np.searchsorted(self.sorted[j], centres[:, j] + radius, "right") + j * n
        return begin, end

    def _colliding(self, queries: np.ndarray, need: int, threshold: float, width: float, growth: float):
        """For each query the vectors that collide with it on enough lines, `need` of them or more."""
        n, lines = self.sorted.shape[1], len(self.sorted)
        if need >= n:
            return [np.arange(n)] * len(queries)
        unit = queries / np.linalg.norm(queries, axis=1, keepdims=True)
        centres = np.column_stack((unit, np.zeros(len(unit)))) @ self.directions
        limit = int(np.ceil(threshold * lines))
        flat = self.orders.reshape(-1)
        found: list = [None] * len(queries)
        counts: dict[int, np.ndarray] = {}
        low, _ = self._windows(centres, np.zeros(len(centres)))
        high = low.copy()
        todo, radius = np.arange(len(queries)), width
        while len(todo):
            begin, end = self._windows(centres[todo], np.full(len(todo), radius))
            # `need` vectors have at least need * limit collisions in all; narrower windows needn't be counted.
            wide = np.flatnonzero((end - begin).sum(1) >= need * limit)
            for i in wide:
                q = int(todo[i])
                spans = [*zip(begin[i], low[q]), *zip(high[q], end[i])]
                fresh = np.bincount(np.concatenate([flat[a:b] for a, b in spans]), minlength=n)
                counts[q] = counts[q] + fresh if q in counts else fresh
                low[q], high[q] = begin[i], end[i]
                some = np.flatnonzero(counts[q] >= limit)
                if len(some) >= need:
                    found[q] = some
                    del counts[q]
            todo = np.array([q for q in todo if found[q] is None], np.int64)
            radius *= growth
        return found

    def _verified(self, queries: np.ndarray, own: np.ndarray, found, k: int):
        for q, who, some in zip(queries, own, found):
            scores = self.vectors[some] @ q
            if len(some) > k + 1:
                # Everything at least as near as the (k + 1)-th, so that ties go by id.
                bound = -np.partition(-scores, k)[k]
                some, scores = some[scores >= bound], scores[scores >= bound]
            some, scores = some[self.rows[some] != who], scores[self.rows[some] != who]
            best = np.lexsort((self.ids[some], -scores))[:k]
            yield self.ids[some[best]], scores[best]


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, v array<double>): without null, zero and non-finite vectors."""
    v = F.col("embedding").cast("array<double>")
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).where("vec_id IS NOT NULL AND v IS NOT NULL")
    fine = ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("v", lambda x: x != 0)
    return rows.where(fine)


def _packed(it):
    """Rows (vec_id, row, v) by length: (dim, ids: id and row in turn, vs)."""
    for batch in it:
        ids, lists = np.column_stack((np.asarray(batch.column(0)), np.asarray(batch.column(1)))), batch.column(2)
        lengths = np.asarray(lists.value_lengths())
        flat = np.asarray(lists.flatten())
        starts = np.concatenate(([0], np.cumsum(lengths)))[:-1]
        rows = []
        for d in np.unique(lengths):
            mine = np.flatnonzero(lengths == d)
            for a in range(0, len(mine), 1024):
                some = mine[a : a + 1024]
                rows.append((int(d), ids[some].astype("<i8").tobytes(), flat[(starts[some][:, None] + np.arange(d))].astype("<f8").tobytes()))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], names=["dim", "ids", "vs"])


def search(vectors: DataFrame, is_query: Column, k: int = 20, share: float = 0.2, threshold: float = 0.55, block: int = BLOCK, lines: int = LINES) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k nearest found, ties to the smaller vec_id.

    Every usable row is indexed; only rows of a query's length are its candidates. `share`:
    part of a block that is verified at least. The query set is packed in groups that meet each
    block. Null, zero and non-finite vectors and null ids take no part. A query's candidates are all rows but its
    own: of a repeated vec_id each row counts as a candidate, and each row that is a query has an answer of its
    own. An empty table gives an empty result; other columns are ignored."""
    # Rows are numbered as they are written here.
    rows = settle(usable(vectors).withColumn("row", F.monotonically_increasing_id()), "vectors")
    blocks = max(1, -(-rows.count() // block))
    part = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("part")
    schema = "dim int, ids binary, vs binary"
    queries = rows.where(is_query).select("vec_id", "row", "v").mapInArrow(_packed, schema).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("query", F.lit(True))
    data = rows.select(part, "vec_id", "row", "v").repartitionById(blocks, F.col("part"))

    def own_rows(it):
        from pyspark import TaskContext

        p = TaskContext.get().partitionId()
        for batch in it:
            for out in _packed([batch.select(["vec_id", "row", "v"])]):
                yield out.append_column("part", pa.array([p] * out.num_rows, pa.int32())).append_column("query", pa.array([False] * out.num_rows))

    data = data.mapInArrow(own_rows, f"{schema}, part int, query boolean")

    def find(it):
        held: dict = {}
        for batch in it:
            for d, ids, vs, q in zip(*(batch.column(c).to_pylist() for c in ("dim", "ids", "vs", "query"))):
                v = np.frombuffer(vs, "<f8").reshape(-1, d)
                held.setdefault(d, ([], []))[q].append((np.frombuffer(ids, "<i8").reshape(-1, 2), v))
        for d, (data, asked) in held.items():
            if not data or not asked:
                continue
            names = np.concatenate([i for i, _ in data])
            index = CollisionIndex(names[:, 0], names[:, 1], np.concatenate([v for _, v in data]), lines)
            for ids, v in asked:
                got = list(index.search(v, ids[:, 1], k, share, threshold))
                yield pa.RecordBatch.from_arrays([pa.array(ids[:, 0]), pa.array(ids[:, 1]), pa.array([i for i, _ in got], pa.list_(pa.int64())), pa.array([s for _, s in got], pa.list_(pa.float64()))], names=["query_id", "row", "ids", "scores"])

    together = data.select("part", "dim", "ids", "vs", "query").unionByName(queries.select("part", "dim", "ids", "vs", "query"))
    found = together.repartitionById(blocks, F.col("part")).mapInArrow(find, "query_id long, row long, ids array<long>, scores array<double>")
    best = found.select("query_id", "row", F.explode(F.arrays_zip("ids", "scores")).alias("x")).select("query_id", "row", "x.ids", "x.scores")
    rank = F.row_number().over(Window.partitionBy("row").orderBy(F.desc("scores"), "ids"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", F.col("ids").alias("vec_id"), F.col("scores").alias("score"))
