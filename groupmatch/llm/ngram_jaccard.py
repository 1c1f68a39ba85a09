"""Exact Jaccard self-join of documents on word n-grams by vertical partitioning.

The n-grams' hashes are the global order. It is cut into fragments, one per reduce task;
each document's set is cut along. A fragment holds every document's segment of that range,
so it knows for each n-gram who shares it and counts partial overlaps on its own; sums over
the fragments give each document's (and each examined pair's) overlap.

No step lists the pairs within a group of copies:

1.  Equal sets are one class (one key), so exact copies cost one member each.
2.  Pass one counts, per fragment and then in sum, how many n-grams of a class occur in any
    other class. A class whose sum is under the threshold's share of its own size can't link
    with anything and leaves; segments keep shared n-grams only.
3.  In each fragment the n-grams of a class vote for their best-placed holder; the class is
    compared with the holder that gets most votes (partial overlaps, summed), and links join
    labels. This linear step unites most copies with the text they come from.
4.  Classes that could still link under another label are found by counting as in pass two,
    under labels. Those that share a prefix n-gram meet in squares of bounded size, where
    overlaps come from matrix products and only links that join labels leave the task.

Links that are skipped join classes already under one label, so components are exact.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, IntegerType, LongType, StructField, StructType

from .components import merge_labels
from groupmatch.durable import settle, settle_counted
from .textops import LOWER, distinct, mix, sliced, take_spans, trimmed, utf8, windows, words_by_text

FLUSH = 1 << 20
_MASK = np.uint64((1 << 48) - 1)

_SEGMENTS = StructType(
    [StructField("part", IntegerType()), StructField("doc_id", LongType()), StructField("n", LongType())]
    + [StructField("key", LongType())]
    + [StructField(c, BinaryType()) for c in ("keys", "counts", "hashes")]
)


def ngram_set(hashes: np.ndarray, n: int) -> np.ndarray:
    """Sorted distinct n-gram hashes of one document; a shorter one is a single n-gram."""
    if not len(hashes):
        return hashes
    grams = windows(hashes, n)
    if not len(grams):
        grams = mix(windows(hashes, len(hashes)) + np.uint64(len(hashes)))
    return distinct(grams)


def class_key(grams: np.ndarray) -> int:
    """64-bit key of a set; equal sets have equal keys."""
    parts = (np.bitwise_xor.reduce(mix(grams * np.uint64(0xA0761D6478BD642F))), np.add.reduce(mix(grams ^ np.uint64(0xE7037ED1A0B428DB))))
    return int(windows(np.array([*parts, len(grams)], np.uint64), 3).view(np.int64)[0])


def _six(h: np.ndarray) -> bytes:
    return h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _eight(raw: bytes) -> np.ndarray:
    out = np.zeros((len(raw) // 6, 8), np.uint8)
    out[:, :6] = np.frombuffer(raw, np.uint8).reshape(-1, 6)
    return out.reshape(-1).view("<u8")


def _fragment_of(grams: np.ndarray, parts: int) -> np.ndarray:
    return ((grams >> np.uint64(48)) * np.uint64(parts) >> np.uint64(16)).astype(np.int32)


def _blob(counts: np.ndarray, sizes=()) -> bytes:
    """Counts in a byte each (255: in four more at the end), then sizes, if any, in four bytes each."""
    return np.minimum(counts, 255).astype(np.uint8).tobytes() + counts[counts >= 255].astype("<i4").tobytes() + np.asarray(sizes, "<i4").tobytes()


def _unblob(raw: bytes, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The n counts and their sizes (0 where the blob has none)."""
    counts = np.frombuffer(raw[:n], np.uint8).astype(np.int64)
    large = np.flatnonzero(counts == 255)
    rest = np.frombuffer(raw[n:], "<i4")
    counts[large] = rest[: len(large)]
    return counts, rest[len(large) :] if len(rest) > len(large) else np.zeros(n, np.int32)


def _packed(keys, lengths, grams, parts):
    """Rows (part, keys, counts, hashes) of many documents' sets, dealt out by fragment. Whole sizes would
    be repeated in every fragment, so they go once to the task that gathers the class, without hashes."""
    owner = np.repeat(np.arange(len(keys), dtype=np.int32), lengths)
    part = _fragment_of(grams, parts)
    order = np.argsort(part, kind="stable")
    part, owner, low = part[order], owner[order], (grams & _MASK)[order]
    edges = np.searchsorted(part, np.arange(parts + 1))
    bucket, whole = _bucket(keys, parts), np.asarray(lengths)
    for q in np.unique(bucket).tolist():
        mine = np.flatnonzero(bucket == q)
        yield q, keys[mine].astype("<i8").tobytes(), whole[mine].astype("<i4").tobytes(), None
    for p in range(parts):
        a, b = edges[p], edges[p + 1]
        if a == b:
            continue
        own = owner[a:b]
        first = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1])))
        counts = _blob(np.diff(np.append(first, len(own))))
        yield int(p), keys[own[first]].astype("<i8").tobytes(), counts, _six(low[a:b])


def _segment_rows(n: int, parts: int):
    def run(it):
        sent: set[int] = set()
        for batch in (part for whole in it for part in sliced(whole, 1, 16 << 20)):
            ids, texts = batch.column(0).to_pylist(), utf8(batch.column(1))
            rows, held, size = [], [], 0

            def flush(held, rows):
                for p, k, c, h in _packed(np.array([x for x, _ in held], np.int64), [len(g) for _, g in held], np.concatenate([g for _, g in held]), parts):
                    rows.append((p, None, None, None, k, c, h))

            for i, hashes in words_by_text([t.translate(LOWER) for t in texts]):
                grams = ngram_set(hashes, n)
                key = class_key(grams) if len(grams) else None
                rows.append((int(mix(np.array([i + len(sent)], np.uint64))[0] % np.uint64(parts)), ids[i], len(grams), key, None, None, None))
                if key is not None and key not in sent:
                    sent.add(key)
                    held.append((key, grams))
                    size += len(grams)
                    if size >= FLUSH:
                        flush(held, rows)
                        yield from _arrow(rows, _SEGMENTS)
                        rows, held, size = [], [], 0
            if held:
                flush(held, rows)
            yield from _arrow(rows, _SEGMENTS)

    return run


_ARROW = {IntegerType: pa.int32(), LongType: pa.int64(), BinaryType: pa.binary()}


def _arrow(rows, schema: StructType):
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(list(c), _ARROW[type(f.dataType)]) for c, f in zip(zip(*rows), schema)], names=schema.names)


class _Gathered:
    """All segments of one fragment, each class once. `width`: numbers carried along with each key."""

    def __init__(self, width: int = 0):
        self.keys, self.counts, self.sizes, self.hashes, self.more, self.width = [], [], [], [], [], width

    def add(self, keys: bytes, counts: bytes, hashes: bytes, more: bytes = b""):
        self.keys.append(np.frombuffer(keys, "<i8"))
        for held, values in zip((self.counts, self.sizes), _unblob(counts, len(keys) // 8)):
            held.append(values)
        self.hashes.append(_eight(hashes))
        self.more.append(np.frombuffer(more, "<i8").reshape(-1, max(self.width, 1)))

    def sorted(self):
        """(keys, whole sizes, numbers of each key, owner of each entry, entry hash), entries by hash."""
        keys, counts, sizes, hashes = (np.concatenate(x) for x in (self.keys, self.counts, self.sizes, self.hashes))
        more = np.concatenate(self.more)
        self.__init__(self.width)
        owner = np.repeat(np.arange(len(keys), dtype=np.int32), counts)
        uniq, first = np.unique(keys, return_index=True)
        if len(uniq) < len(keys):
            keep = np.zeros(len(keys), bool)
            keep[first] = True
            mask = keep[owner]
            owner, hashes = owner[mask], hashes[mask]
        order = np.argsort(hashes)
        return keys, sizes, more, owner[order], hashes[order]


def _runs(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    first = np.flatnonzero(np.concatenate(([True], hashes[1:] != hashes[:-1])))
    return first, np.diff(np.append(first, len(hashes)))


_BLOBS = [StructField(c, BinaryType()) for c in ("keys", "counts", "hashes", "levels")]
_SHARED = StructType([StructField("bucket", IntegerType()), StructField("doc_id", LongType()), StructField("n", LongType()), StructField("key", LongType()), StructField("part", IntegerType()), *_BLOBS])


def _bucket(keys: np.ndarray, parts: int) -> np.ndarray:
    return (mix(keys.view(np.uint64)) % np.uint64(parts)).astype(np.int32)


def _by_bucket(parts, part, keys, sizes, owner, hashes, levels):
    """Packed rows of a fragment's remaining entries for the tasks that gather whole classes; `sizes` of
    None where these come by themselves."""
    order = np.lexsort((owner, _bucket(keys, parts)[owner]))
    owner, hashes, levels = owner[order], hashes[order], levels[order]
    bucket = _bucket(keys, parts)[owner]
    edges = np.searchsorted(bucket, np.arange(parts + 1))
    for q in range(parts):
        a, b = edges[q], edges[q + 1]
        if a < b:
            start, count = _runs(owner[a:b])
            who = owner[a:b][start]
            yield q, None, None, None, part, keys[who].astype("<i8").tobytes(), _blob(count, () if sizes is None else sizes[who]), _six(hashes[a:b]), levels[a:b].tobytes()


def _shared_rows(parts: int):
    """Pass one in one fragment: the segments' n-grams that two classes or more hold."""

    def run(it):
        held, part = _Gathered(), None
        for batch in it:
            rows = []
            for p, d, n, k, keys, counts, hashes in zip(*batch.to_pydict().values()):
                if keys is None:
                    rows.append((None, d, n, k, None, None, None, None, None))
                elif hashes is None:
                    rows.append((p, None, None, None, None, keys, counts, None, None))
                else:
                    part = p
                    held.add(keys, counts, hashes)
            yield from _arrow(rows, _SHARED)
        if part is None:
            return
        keys, _, _, owner, hashes = held.sorted()
        _, length = _runs(hashes)
        both = np.repeat(length > 1, length)
        yield from _arrow(list(_by_bucket(parts, part, keys, None, owner[both], hashes[both], np.zeros(int(both.sum()), np.uint8))), _SHARED)

    return run


def _outside_rows(parts: int):
    """The same under labels: n-grams that some other label holds too, with the log of their holders."""

    def run(it):
        held, part = _Gathered(1), None
        for batch in it:
            for p, k, c, h, m in zip(*(batch.column(x).to_pylist() for x in ("part", "keys", "counts", "hashes", "more"))):
                part = p
                held.add(k, c, h, m)
        if part is None:
            return
        keys, sizes, more, owner, hashes = held.sorted()
        label = more[:, 0]
        first, length = _runs(hashes)
        several = np.minimum.reduceat(label[owner], first) != np.maximum.reduceat(label[owner], first)
        level = np.minimum(np.log2(length), 60).astype(np.uint8)
        keep = np.repeat(several, length)
        yield from _arrow(list(_by_bucket(parts, part, keys, sizes, owner[keep], hashes[keep], np.repeat(level, length)[keep])), _SHARED)

    return run


def _collect(it):
    """(key, size, grams, levels) of each class, gathered over the fragments; grams carry the fragment."""
    keys, counts, sizes, hashes, levels, known = [], [], [], [], [], ([], [])
    for batch in it:
        for p, k, c, h, v in zip(*(batch.column(x).to_pylist() for x in ("part", "keys", "counts", "hashes", "levels"))):
            if h is None:
                known[0].append(np.frombuffer(k, "<i8"))
                known[1].append(np.frombuffer(c, "<i4"))
                continue
            keys.append(np.frombuffer(k, "<i8"))
            for held, values in zip((counts, sizes), _unblob(c, len(k) // 8)):
                held.append(values)
            hashes.append(_eight(h) | (np.uint64(p) << np.uint64(48)))
            levels.append(np.frombuffer(v, np.uint8))
    if not keys:
        return None
    keys, counts, sizes, hashes, levels = (np.concatenate(x) for x in (keys, counts, sizes, hashes, levels))
    if known[0]:
        names, first = np.unique(np.concatenate(known[0]), return_index=True)
        sizes = np.concatenate(known[1])[first][np.searchsorted(names, keys)]
    owner, size = np.repeat(keys, counts), np.repeat(sizes, counts)
    order = np.argsort(owner, kind="stable")
    owner, size, hashes, levels = owner[order], size[order], hashes[order], levels[order]
    start, count = _runs(owner)
    return owner[start], size[start].astype(np.int64), start, count, hashes, levels


def _lists(values: np.ndarray, start: np.ndarray, count: np.ndarray) -> pa.Array:
    if not len(start):
        return pa.array([], pa.list_(pa.int64()))
    edges = np.concatenate(([0], np.cumsum(count)))
    return pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(take_spans(values, start, count)))


def _set_rows(percent: int):
    """Classes whose shared n-grams reach the threshold, with those n-grams."""

    def run(it):
        got = _collect(it)
        if got is None:
            return
        key, size, start, count, hashes, _ = got
        fine = np.flatnonzero(count * 100 >= size * percent)
        for a in range(0, len(fine), 1000):
            f = fine[a : a + 1000]
            yield pa.RecordBatch.from_arrays([pa.array(key[f]), pa.array(size[f]), pa.array(count[f], pa.int64()), _lists(hashes.view(np.int64), start[f], count[f])], names=["key", "n", "n_shared", "grams"])

    return run


def _prefix_rows(percent: int):
    """(key, gram): of each class that still reaches the threshold under other labels, the prefix, in
    the order of rarity and hash, of which any similar class under another label holds a part."""

    def run(it):
        got = _collect(it)
        if got is None:
            return
        key, size, start, count, hashes, levels = got
        keys, grams = [], []
        for k, n, s, c in zip(key, size, start, count):
            length = int(c) + int(-n * percent // 100) + 1  # outside - ceil(share of the size) + 1
            if length > 0:
                h, v = hashes[s : s + c], levels[s : s + c]
                grams.append(h[np.lexsort((h, v))[:length]])
                keys.append(np.full(len(grams[-1]), k))
        if keys:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.concatenate(grams).view(np.int64))], names=["key", "gram"])

    return run


def _count_batches(parts, keys, others, counts):
    """Packed (bucket, keys, others, counts): a fragment's sums, one row for each gathering task."""
    bucket = _bucket(keys, parts)
    order = np.argsort(bucket, kind="stable")
    keys, others, counts = keys[order], others[order], counts[order]
    edges = np.searchsorted(bucket[order], np.arange(parts + 1))
    rows = [(q, *(x[edges[q] : edges[q + 1]].astype("<i8").tobytes() for x in (keys, others, counts))) for q in range(parts) if edges[q] < edges[q + 1]]
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary(), pa.binary()))], names=["bucket", "keys", "others", "counts"])


_COUNTS = "bucket int, keys binary, others binary, counts binary"


def _summed_rows(it):
    """(key, other, n): for each key the other with the largest sum over the fragments."""
    got = [[], [], []]
    for batch in it:
        for row in zip(*(batch.column(c).to_pylist() for c in ("keys", "others", "counts"))):
            for held, raw in zip(got, row):
                held.append(np.frombuffer(raw, "<i8"))
    if not got[0]:
        return
    keys, others, counts = (np.concatenate(x) for x in got)
    order = np.lexsort((others, keys))
    keys, others, counts = keys[order], others[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], (keys[1:] != keys[:-1]) | (others[1:] != others[:-1]))))
    keys, others, counts = keys[first], others[first], np.add.reduceat(counts, first)
    order = np.lexsort((others, counts, keys))
    last = order[np.concatenate((keys[order][1:] != keys[order][:-1], [True]))]
    yield pa.RecordBatch.from_arrays([pa.array(keys[last]), pa.array(others[last]), pa.array(counts[last])], names=["key", "other", "n"])


def _summed(counted: DataFrame, parts: int) -> DataFrame:
    return counted.repartitionById(parts, F.col("bucket")).mapInArrow(trimmed(_summed_rows), "key long, other long, n long")


def _vote_rows(parts: int):
    """In one fragment: for each class, how many n-grams others hold, and whose they are first.

    `more` carries the rank; of an n-gram's holders the best placed gets the votes of the others."""

    def run(it):
        held, any_row = _Gathered(1), False
        for batch in it:
            for k, c, h, m in zip(*(batch.column(x).to_pylist() for x in ("keys", "counts", "hashes", "more"))):
                held.add(k, c, h, m)
                any_row = True
        if not any_row:
            return
        keys, _, more, owner, hashes = held.sorted()
        order = np.lexsort((keys[owner], more[owner, 0], hashes))
        owner, hashes = owner[order], hashes[order]
        first, length = _runs(hashes)
        best = np.repeat(owner[first], length)
        other = owner != best
        codes, votes = np.unique(owner[other].astype(np.int64) * len(keys) + best[other], return_counts=True)
        yield from _count_batches(parts, keys[codes // len(keys)], keys[codes % len(keys)], votes)

    return run


def _overlap_rows(parts: int):
    """In one fragment: n-grams that each class has in common with the class it names in `more`."""

    def run(it):
        held, any_row = _Gathered(1), False
        for batch in it:
            for k, c, h, m in zip(*(batch.column(x).to_pylist() for x in ("keys", "counts", "hashes", "more"))):
                held.add(k, c, h, m)
                any_row = True
        if not any_row:
            return
        keys, _, more, owner, hashes = held.sorted()
        place = {k: i for i, k in enumerate(keys.tolist())}
        partner = np.array([place.get(x, -1) for x in more[:, 0].tolist()])
        _, length = _runs(hashes)
        run_no = np.repeat(np.arange(len(length)), length)
        present = np.sort(run_no * len(keys) + owner)
        wants = partner[owner] >= 0
        asked = run_no[wants] * len(keys) + partner[owner[wants]]
        at = np.minimum(np.searchsorted(present, asked), len(present) - 1)
        n = np.bincount(owner[wants][present[at] == asked], minlength=len(keys))
        some = np.flatnonzero(n)
        yield from _count_batches(parts, keys[some], more[some, 0], n[some])

    return run


def _dealt(sets: DataFrame, number: Column, parts: int, sized: bool = False) -> DataFrame:
    """Sets (key, n, grams) with a number each, cut into the fragments again; `sized`: with their sizes."""

    def run(it):
        for batch in it:
            for a in range(0, batch.num_rows, 2000):
                some = batch.slice(a, 2000)
                keys, n, more = (np.asarray(some.column(i)) for i in range(3))
                lists = some.column(3)
                grams, lengths = np.asarray(lists.flatten()).view(np.uint64), np.asarray(lists.value_lengths())
                owner = np.repeat(np.arange(len(keys)), lengths)
                fragment = (grams >> np.uint64(48)).astype(np.int32)
                order = np.argsort(fragment, kind="stable")
                fragment, owner, low = fragment[order], owner[order], (grams & _MASK)[order]
                edges = np.searchsorted(fragment, np.arange(parts + 1))
                rows = []
                for p in range(parts):
                    x, y = edges[p], edges[p + 1]
                    if x < y:
                        start, count = _runs(owner[x:y])
                        who = owner[x:y][start]
                        rows.append((p, keys[who].astype("<i8").tobytes(), _blob(count, n[who] if sized else ()), _six(low[x:y]), more[who].astype("<i8").tobytes()))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary()))], names=["part", "keys", "counts", "hashes", "more"])

    given = sets.select("key", "n", number.cast("long").alias("more"), "grams")
    return given.mapInArrow(trimmed(run), "part int, keys binary, counts binary, hashes binary, more binary").repartitionById(parts, F.col("part"))


def sets_and_classes(docs: DataFrame, n: int, percent: int, parts: int):
    """(documents: doc_id, n, key), (classes that may link: key, n, n_shared, grams)."""
    segments = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(trimmed(_segment_rows(n, parts)), _SEGMENTS)
    one = settle(segments.repartitionById(parts, F.col("part")).mapInArrow(trimmed(_shared_rows(parts)), _SHARED), "jaccard-shared")
    members = one.where("keys IS NULL").select("doc_id", "n", "key")
    shared = one.where("keys IS NOT NULL").select("bucket", "part", *(f.name for f in _BLOBS))
    sets = shared.repartitionById(parts, F.col("bucket")).mapInArrow(trimmed(_set_rows(percent)), "key long, n long, n_shared long, grams array<long>")
    return members, settle(sets, "jaccard-sets")


#: Rows of two numbers that are sent to every task, so that the sets they join with stay in place.
NARROW_ROWS = 1 << 20


def _narrow(rows: DataFrame, count: int) -> DataFrame:
    return F.broadcast(rows) if count <= NARROW_ROWS else rows


def link_labels(sets: DataFrame, percent: int, parts: int) -> DataFrame:
    """(key, label): classes joined by a chain of links have one label."""
    # Best placed: a large share of common n-grams, as the text that others were copied from has.
    rank = F.lit(10**6) - (F.col("n_shared") * 10**6 / F.col("n")).cast("long")
    votes = _summed(_dealt(sets, rank, parts).mapInArrow(trimmed(_vote_rows(parts)), _COUNTS), parts)
    tally = _narrow(*settle_counted(votes.select("key", F.col("other").alias("holder")), "jaccard-votes"))
    named = settle(sets.join(tally, "key", "left").select("key", "n", "grams", F.coalesce("holder", F.lit(0)).alias("holder")), "jaccard-named")
    common = _summed(_dealt(named, F.col("holder"), parts).mapInArrow(trimmed(_overlap_rows(parts)), _COUNTS), parts).select("key", F.col("n").alias("common"))
    size = named.select(F.col("key").alias("y"), F.col("n").alias("m"))
    pairs = common.join(named.select("key", "n", "holder"), "key").join(size, F.col("holder") == F.col("y"))
    links = pairs.where(F.col("common") * 100 >= (F.col("n") + F.col("m") - F.col("common")) * percent).select(F.col("key").alias("x"), "y")
    labels = merge_labels(sets.select("key", F.col("key").alias("label")), settle(links, "jaccard-links"))
    labelled = settle(sets.join(_narrow(labels, labels.count()), "key").select("key", "n", "grams", "label"), "jaccard-labelled")
    rest = _rest(labelled, percent, parts)
    return merge_labels(labels, settle(rest, "jaccard-links"))


SIDE = 1024


def _rest(sets: DataFrame, percent: int, parts: int) -> DataFrame:
    """All further links across labels, as a spanning part of them (x, y).

    Similar classes under different labels share a prefix n-gram, so they are in one component of the
    classes by prefix n-grams. Components are cut into squares of SIDE by SIDE classes; a task compares
    its square by products of incidence matrices and returns links that join more labels only."""
    outside = _dealt(sets, F.col("label"), parts, sized=True).mapInArrow(trimmed(_outside_rows(parts)), _SHARED).select("bucket", "part", *(f.name for f in _BLOBS))
    prefixes = settle(outside.repartitionById(parts, F.col("bucket")).mapInArrow(trimmed(_prefix_rows(percent)), "key long, gram long"), "jaccard-prefixes")
    heads = prefixes.groupBy("gram").agg(F.min("key").alias("y"))
    edges = prefixes.join(heads, "gram").where("key <> y").select(F.col("key").alias("x"), "y").distinct()
    edges = settle(edges, "jaccard-edges")
    if edges.isEmpty():
        return edges
    own = prefixes.select("key", F.col("key").alias("label")).distinct()
    groups = merge_labels(own, edges).select("key", F.col("label").alias("area"))
    areas = groups.groupBy("area").agg(F.count("*").alias("members")).where("members > 1")
    areas = areas.select("area", F.ceil(F.col("members") / SIDE).cast("int").alias("sides"))
    rows = sets.join(groups.join(areas, "area"), "key").withColumn("side", F.pmod(F.xxhash64("key"), F.col("sides")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("sides") - 1)))
    square = F.struct(F.least("side", "other").alias("a"), F.greatest("side", "other").alias("b"))
    small = F.col("sides") == 1
    rows = rows.select("key", "label", "n", "grams", "area", "side", F.when(small, F.pmod(F.xxhash64("area"), F.lit(parts))).otherwise(F.col("area")).alias("bin"), square.alias("square"), small.alias("small"))
    return rows.groupBy("bin", "small", "square").applyInArrow(_squares(percent), "x long, y long")


def _squares(percent: int):
    def run(table: pa.Table) -> pa.Table:
        keys, label, n, area, side = (table[c].to_numpy() for c in ("key", "label", "n", "area", "side"))
        lists = table["grams"].combine_chunks()
        grams, lengths = np.asarray(lists.flatten()), np.asarray(lists.value_lengths())
        starts = np.concatenate(([0], np.cumsum(lengths)))[:-1]
        xs, ys = [], []
        order = np.argsort(area, kind="stable")
        first, count = _runs(area[order])
        for f, c in zip(first, count):
            mine = order[f : f + c]
            low = side[mine].min()
            left, right = mine[side[mine] == low], mine[side[mine] != low]
            for i, j in _linked(left, right if len(right) else left, keys, label, n, grams, starts, lengths, percent):
                xs.append(keys[i])
                ys.append(keys[j])
        return pa.table({"x": pa.array(xs, pa.int64()), "y": pa.array(ys, pa.int64())})

    return run


def _linked(left, right, keys, label, n, grams, starts, lengths, percent, chunk: int = 2048):
    """Pairs (row of left, row of right) that link labels not yet joined in this square."""
    if len(np.unique(label[np.concatenate((left, right))])) < 2:
        return
    sides = []
    for rows in (left, right):
        sides.append((take_spans(grams, starts[rows], lengths[rows]), np.repeat(np.arange(len(rows)), lengths[rows])))
    vocabulary = np.intersect1d(sides[0][0], sides[1][0])
    common = np.zeros((len(left), len(right)), np.float32)
    coded = []
    for values, owner in sides:
        at = np.minimum(np.searchsorted(vocabulary, values), max(len(vocabulary) - 1, 0))
        ok = vocabulary[at] == values if len(vocabulary) else np.zeros(len(values), bool)
        order = np.argsort(at[ok], kind="stable")
        coded.append((at[ok][order], owner[ok][order]))
    for a in range(0, len(vocabulary), chunk):
        parts = []
        for (at, owner), rows in zip(coded, (left, right)):
            x, y = np.searchsorted(at, (a, a + chunk))
            m = np.zeros((len(rows), min(chunk, len(vocabulary) - a)), np.float32)
            m[owner[x:y], at[x:y] - a] = 1
            parts.append(m)
        common += parts[0] @ parts[1].T
    both = np.rint(common).astype(np.int64)
    fits = both * 100 >= (n[left][:, None] + n[right][None, :] - both) * percent
    fits &= label[left][:, None] != label[right][None, :]
    root = {x: x for x in np.unique(label[np.concatenate((left, right))]).tolist()}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i, j in zip(*np.nonzero(fits)):
        p, q = find(int(label[left[i]])), find(int(label[right[j]]))
        if p != q:
            root[max(p, q)] = min(p, q)
            yield left[i], right[j]


def jaccard_components(docs: DataFrame, n: int = 4, percent: int = 85, parts: int | None = None) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row.

    Two rows link when 100 * |intersection| >= percent * |union| of their sets of word
    n-grams (A-Z lower-cased; a text of fewer words is one n-gram). Null, empty and blank
    texts have an empty set and link with nothing. component_id is the smallest doc_id reachable
    by links; rows with null doc_id keep null unless a linked row has one. Repeated rows are
    returned as often as they come. An empty table gives an empty result. Sets are compared by hashes of n-grams,
    48 bits and the fragment's (50 bits with 4 fragments, 63 with 32,768), classes by a 64-bit key. `parts`: fragments, by default
    spark.sql.shuffle.partitions; a fragment should hold a few million n-grams.
    """
    spark = docs.sparkSession
    parts = min(parts or int(spark.conf.get("spark.sql.shuffle.partitions")), 1 << 15)
    members, sets = sets_and_classes(docs, n, percent, parts)
    labels = link_labels(sets, percent, parts)
    first = members.where("key IS NOT NULL").groupBy("key").agg(F.min("doc_id").alias("first"))
    named = first.join(labels, "key").select("key", "first", "label")
    least = named.groupBy("label").agg(F.min("first").alias("least"))
    linked = settle(named.join(least, "label").select("key", "least"), "jaccard-components")
    component = first.join(linked, "key", "left").select("key", F.coalesce("least", "first").alias("component_id"))
    return members.join(component, "key", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, n: int = 4, percent: int = 85) -> DataFrame:
    """The documents with one row of each component kept: a row with its smallest doc_id.

    Rows are told apart by all their columns, not by doc_id: two unlike texts under one doc_id both stay,
    equal rows with words are copies of each other. Rows with an empty set (null, empty and
    blank texts) link with nothing and stay, each of them. Null doc_ids come last, ties go by a hash of the row, so
    reruns agree. An empty table stays empty."""
    names = docs.columns
    given = docs.withColumn("__row", F.xxhash64(*names))
    found = jaccard_components(given.select(F.col("__row").alias("doc_id"), "text"), n, percent)
    per = found.groupBy(F.col("doc_id").alias("__row")).agg(F.min("component_id").alias("component"), F.max("n_shingles").alias("size"), F.count("*").alias("rows"))
    numbers = given.groupBy("__row").agg(F.min(F.col("doc_id").cast("long")).alias("id"))
    rows = settle(per.join(numbers, "__row"), "jaccard-rows")
    order = F.struct(F.col("id").isNull().alias("a"), F.col("id").alias("b"), F.col("__row").alias("c"))
    heads = rows.where("size > 0").groupBy("component").agg(F.min_by(F.struct("__row", "rows"), order).alias("head")).select("head.*")
    heads = settle(heads.unionByName(rows.where("size = 0").select("__row", F.lit(1).cast("long").alias("rows"))), "jaccard-heads")
    kept = given.join(heads, "__row")
    # Equal rows are rare but may be many: each task keeps one of them before they meet.
    once = kept.where("rows > 1").withColumn("__text", F.sha2("text", 256)).dropDuplicates(["__row", "__text"])
    return kept.where("rows = 1").select(*names).unionByName(once.select(*names))
