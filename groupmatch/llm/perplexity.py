"""Quality rules with a perplexity model: modified Kneser-Ney over 5-grams of the characters themselves.

Characters are not folded, so every script counts and the model grows with the corpus. Each task
lists the distinct 5-grams of its texts with counts, Spark adds them up, lower orders are continuation
counts, and probabilities come from joins by n-gram: tables of any size. Texts are scored against
sorted arrays of n-gram hashes. While the model's rows are within a stated bound these arrays are
broadcast and no text is shuffled; beyond it, documents are dealt into chunks and each chunk gets back
the 5-grams that it asked for. Both ways give the same scores.

Each language has a lower and an upper bound of log-perplexity around its own median;
documents outside, such as gibberish above or repeated boilerplate below, are rejected.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from groupmatch.durable import settle, settle_counted

from .textops import _IS_BREAK, batches, distinct, give_back, mix, sliced, trimmed, utf8, windows, words_by_text

REACH = 5
PAD = 3
#: Distinct 5-grams that a counting task holds before it hands them on.
HELD = 1 << 22
#: Most model rows (12 bytes each) that are broadcast.
BROADCAST_ROWS = 1 << 23
#: Bytes of text in a chunk beyond that, and the least number of chunks.
CHUNK, CHUNKS = 32 << 20, 12
GRID = 1000
#: Robust deviations on either side of a language's median that are kept.
WIDTH = 3.5
_STEP = np.uint64(0xD6E8FEB86659FD93)


def grams_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Padded code points of all texts, where the 5-gram of every character and text end begins, its hash,
    and where each text's 5-grams start."""
    points = [np.frombuffer(t.decode("utf-8").encode("utf-32-le"), np.uint32) for t in texts]
    sizes = np.array([len(p) for p in points])
    flat = np.full(int(sizes.sum()) + (REACH - 1) * (len(texts) + 1), PAD, np.uint32)
    keep = np.zeros(len(flat), bool)
    at = REACH - 1
    for p in points:
        flat[at : at + len(p)] = p
        keep[at : at + len(p) + 1] = True
        at += len(p) + REACH - 1
    begins = np.flatnonzero(keep) - (REACH - 1)
    hashes = np.zeros(len(flat) - REACH + 1, np.uint64)
    for k in range(REACH):
        hashes = hashes * _STEP + flat[k : k + len(hashes)]
    return flat, begins, _finished(hashes[begins]), np.concatenate(([0], np.cumsum(sizes + 1)[:-1]))


def string_hashes(grams: pa.Array) -> np.ndarray:
    """The same hash of 5-grams that come as strings."""
    points = np.frombuffer("".join(grams.to_pylist()).encode("utf-32-le"), np.uint32).reshape(-1, REACH)
    hashes = np.zeros(len(points), np.uint64)
    for k in range(REACH):
        hashes = hashes * _STEP + points[:, k]
    return _finished(hashes)


def _finished(hashes: np.ndarray) -> np.ndarray:
    """63 bits, so that signed and unsigned order agree."""
    return (mix(hashes) >> np.uint64(1)).view(np.int64)


def _merged(parts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    if len(parts) == 1:
        return parts[0]
    hashes, grams, n = map(np.concatenate, zip(*parts))
    order = np.argsort(hashes)
    hashes = hashes[order]
    first = np.flatnonzero(np.concatenate(([True], hashes[1:] != hashes[:-1])))
    return hashes[first], grams[order[first]], np.add.reduceat(n[order], first)


def _strings(grams: np.ndarray) -> pa.Array:
    body = grams.astype("<u4").tobytes().decode("utf-32-le").encode("utf-8")
    sizes = (1 + (grams >= 0x80) + (grams >= 0x800) + (grams >= 0x10000)).sum(axis=1)
    offsets = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
    return pa.StringArray.from_buffers(len(grams), pa.py_buffer(offsets.tobytes()), pa.py_buffer(body))


def _listed(held: dict):
    for (chunk, lang), parts in held.items():
        _, grams, n = _merged(parts)
        for k in range(0, len(n), 100_000):
            part = slice(k, k + 100_000)
            m = len(n[part])
            yield pa.RecordBatch.from_arrays([pa.array([chunk] * m, pa.int32()), pa.array([lang] * m, pa.string()), _strings(grams[part]), pa.array(n[part], pa.int64())], names=["chunk", "lang", "gram", "n"])


def _gram_rows(it):
    # For each (chunk, lang): a merged part, then parts that together are no larger.
    held: dict[tuple, list] = {}
    for whole in it:
        for batch in sliced(whole, 2):
            keys, texts = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())), utf8(batch.column(2))
            for key in dict.fromkeys(keys):
                mine = [t for t, own in zip(texts, keys) if own == key and t]
                parts = held.setdefault(key, [])
                for group in batches(mine):
                    flat, begins, hashes, _ = grams_of([mine[i] for i in group])
                    at = np.argsort(hashes)
                    first = np.flatnonzero(np.concatenate(([True], np.diff(hashes[at]) != 0)))
                    parts.append((hashes[at[first]], flat[begins[at[first]][:, None] + np.arange(REACH)], np.diff(np.append(first, len(at)))))
                    if sum(len(p[2]) for p in parts[1:]) > len(parts[0][2]):
                        parts[:] = [_merged(parts)]
            if sum(len(p[2]) for parts in held.values() for p in parts) > HELD:
                yield from _listed(held)
                held = {}
    yield from _listed({k: parts for k, parts in held.items() if parts})


def count_grams(docs: DataFrame) -> DataFrame:
    """(chunk, lang, gram, n): distinct 5-grams of each task's (and chunk's) texts; needs chunk, lang and text."""
    return docs.select("chunk", "lang", "text").mapInArrow(trimmed(_gram_rows), "chunk int, lang string, gram string, n long")


def _discount(k: int, ones: str, some: str, more: str) -> Column:
    """The discount of counts of k (3: or more) from counts of counts, kept within 0.05 of 0 and k; a half
    where too little is known."""
    y = F.col("n1") / (F.col("n1") + 2 * F.col("n2"))
    plain = F.when(F.col(some) > 0, k - (k + 1) * y * F.col(more) / F.col(some)).otherwise(0.5)
    known = (F.col("n1") > 0) & (F.col("n2") > 0)
    return F.when(known, F.least(F.greatest(plain, F.lit(0.05)), F.lit(k - 0.05))).otherwise(0.5).alias(ones)


def train(grams: DataFrame) -> DataFrame:
    """(lang, gram, log_p): log-probability of the last character of every 5-gram that occurs, a table of any size."""
    tables = {REACH: settle(grams.groupBy("lang", "gram").agg(F.sum("n").alias("n")), "grams")}
    for k in range(REACH - 1, 0, -1):
        # continuation counts: distinct left neighbours
        rest = F.substring("gram", 2, k).alias("gram")
        tables[k] = settle(tables[k + 1].groupBy("lang", rest).agg(F.count("*").alias("n")), "grams")
    count = lambda c: F.count_if(c).cast("double")
    small = None
    for k, t in tables.items():
        own = t.groupBy("lang").agg(*(count(F.col("n") == j).alias(f"n{j}") for j in (1, 2, 3, 4)), F.count("*").alias("symbols")).withColumn("order", F.lit(k))
        small = own if small is None else small.unionByName(own)
    # A row for each language and order.
    small = settle(small.select("lang", "order", "symbols", _discount(1, "d1", "n1", "n2"), _discount(2, "d2", "n2", "n3"), _discount(3, "d3", "n3", "n4")), "discounts")
    out = None
    for k in range(1, REACH + 1):
        rows = tables[k].withColumn("head", F.substring("gram", 1, k - 1))
        heads = rows.groupBy("lang", "head").agg(F.sum("n").alias("total"), count(F.col("n") == 1).alias("c1"), count(F.col("n") == 2).alias("c2"), count(F.col("n") > 2).alias("c3"))
        heads = heads.join(small.where(F.col("order") == k), "lang")
        rows = rows.join(heads, ["lang", "head"])
        if out is not None:
            rows = rows.withColumn("rest", F.substring("gram", 2, k - 1)).join(out, ["lang", "rest"])
        base = F.lit(1.0) / F.col("symbols") if out is None else F.col("lower")
        d = F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3"))
        gamma = (F.col("d1") * F.col("c1") + F.col("d2") * F.col("c2") + F.col("d3") * F.col("c3")) / F.col("total")
        p = F.greatest(F.col("n") - d, F.lit(0.0)) / F.col("total") + gamma * base
        out = rows.select("lang", F.col("gram").alias("rest"), p.alias("lower"))
    return out.select("lang", F.col("rest").alias("gram"), F.log("lower").cast("float").alias("log_p"))


_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True


def repeated_words(hashes: np.ndarray) -> int:
    """Words within 5-word windows that occur twice or more in the text."""
    w = windows(hashes, 5)
    if len(w) < 2:
        return 0
    s = np.sort(w)
    twice = s[1:][s[1:] == s[:-1]]
    if not len(twice):
        return 0
    twice = distinct(twice)
    at = np.searchsorted(twice, w)
    hit = twice[np.minimum(at, len(twice) - 1)] == w
    cover = np.zeros(len(hashes) + 1, np.int64)
    where = np.flatnonzero(hit)
    np.add.at(cover, where, 1)
    np.add.at(cover, where + 5, -1)
    return int(np.count_nonzero(np.cumsum(cover)[:-1]))


def repeated_lines(text: bytes) -> int:
    lines = text.split(b"\n")
    seen = set(lines)
    if len(seen) == len(lines):
        return 0
    worded = [x for x in lines if x.strip(b"\x20\x09\x0b\x0c\x0d")]
    return len(worded) - len(set(worded))


_BASE = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, log_ppl double"


def _measures(texts: list[bytes], langs: list[str], models) -> list[pa.Array]:
    n = len(texts)
    words, repeats, chars, symbols, lines = (np.zeros(n, np.int64) for _ in range(5))
    ppl = np.full(n, np.nan)
    for i, hashes in words_by_text(texts):
        words[i], repeats[i] = len(hashes), repeated_words(hashes)
        raw = np.frombuffer(texts[i], np.uint8)
        chars[i] = np.count_nonzero(((raw & 0xC0) != 0x80) & ~_IS_BREAK[raw])
        symbols[i] = np.count_nonzero(_SYMBOL[raw])
        lines[i] = repeated_lines(texts[i])
    for lang in dict.fromkeys(langs):
        mine = [i for i, own in enumerate(langs) if own == lang and texts[i]]
        if not mine:
            continue
        model = models[lang]
        for group in batches([texts[i] for i in mine]):
            _, _, hashes, starts = grams_of([texts[mine[k]] for k in group])
            sums = np.add.reduceat(model.find(hashes).astype(np.float64), starts)
            sizes = np.diff(np.append(starts, len(hashes)))
            ppl[[mine[k] for k in group]] = -sums / sizes
    failed = (words < 10) | (100 * repeats > 20 * words)
    return [pa.array(x) for x in (words, chars, symbols, lines, repeats, failed)] + [pa.array(ppl, from_pandas=True)]


class SortedArray:
    """Sorted hashes (63 bits) of one language's 5-grams with their log-probabilities; where the hashes
    with given leading bits begin is kept beside them, so that a lookup is a step or two."""

    def __init__(self, hashes: np.ndarray, log_p: np.ndarray):
        self.hashes, self.log_p = hashes, log_p
        bits = max(int(len(hashes)).bit_length(), 1)
        self.shift = 63 - bits
        self.starts = np.searchsorted(hashes, np.arange(1 << bits) << self.shift).astype(np.int32)

    def find(self, wanted: np.ndarray) -> np.ndarray:
        """Log-probabilities of hashes that the array holds."""
        at = self.starts[wanted >> self.shift]
        todo = np.flatnonzero(self.hashes[at] != wanted)
        while len(todo):
            at[todo] += 1
            todo = todo[self.hashes[at[todo]] != wanted[todo]]
        return self.log_p[at]


def sorted_arrays(langs: pa.Array, hashes: np.ndarray, log_p: np.ndarray) -> dict[str, SortedArray]:
    """The sorted array of each language."""
    coded = langs.dictionary_encode()
    index = coded.indices.to_numpy(zero_copy_only=False)
    order = np.lexsort((hashes, index))
    edges = np.searchsorted(index[order], np.arange(len(coded.dictionary) + 1))
    return {lang: SortedArray(hashes[own], log_p[own]) for i, lang in enumerate(coded.dictionary.to_pylist()) for own in [order[edges[i] : edges[i + 1]]]}


def _hash_rows(it):
    for batch in it:
        if batch.num_rows:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(string_hashes(batch.column(1))), batch.column(2)], names=["lang", "hash", "log_p"])


def _packed_rows(it):
    """(lang, hashes, log_p): sorted runs as bytes."""
    for batch in it:
        langs = batch.column(0).dictionary_encode()
        index = langs.indices.to_numpy(zero_copy_only=False)
        for i, lang in enumerate(langs.dictionary.to_pylist()):
            own = np.flatnonzero(index == i)
            yield pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([batch.column(1).to_numpy()[own].tobytes()], pa.binary()), pa.array([batch.column(2).to_numpy()[own].tobytes()], pa.binary())], names=["lang", "hashes", "log_p"])


def gathered(model: DataFrame) -> list[tuple[str, bytes, bytes]]:
    """The arrays (lang, sorted hashes, log-probabilities) of a model of bounded size; sorted in the cluster."""
    hashed = model.select("lang", "gram", "log_p").mapInArrow(_hash_rows, "lang string, hash long, log_p float")
    n = int(model.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    runs = hashed.repartitionByRange(n, "lang", "hash").sortWithinPartitions("lang", "hash").mapInArrow(_packed_rows, "lang string, hashes binary, log_p binary").collect()
    parts: dict[str, tuple[list, list]] = {}
    for r in runs:
        for held, raw in zip(parts.setdefault(r["lang"], ([], [])), (r["hashes"], r["log_p"])):
            held.append(bytes(raw))
    return [(lang, b"".join(h), b"".join(p)) for lang, (h, p) in parts.items()]


#: The arrays of this worker process, which keeps the last ones, by the broadcast's number.
_arrays: dict[str, dict[str, SortedArray]] = {}


def _opened(name: str, blocks: list[tuple[str, bytes, bytes]]) -> dict[str, SortedArray]:
    if name not in _arrays:
        _arrays.clear()
        _arrays[name] = {lang: SortedArray(np.frombuffer(h, np.int64), np.frombuffer(p, np.float32)) for lang, h, p in blocks}
    return _arrays[name]


_NAMES = [f.split()[0] for f in _BASE.split(", ")]


def _measured(whole: pa.RecordBatch, lang: int, text: int, keep: list[int], models):
    """The columns `keep` of a batch with the measures of its texts, in parts of bounded size."""
    for batch in sliced(whole, text):
        out = _measures(utf8(batch.column(text)), batch.column(lang).to_pylist(), models)
        yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), *out], names=[*(batch.schema.names[k] for k in keep), *_NAMES])


def _scored(given: DataFrame, out: list[str], broadcast_rows: int) -> DataFrame:
    """The columns `out` of a table with __lang and __text and the measures by the model of all its texts, written
    to the shared folder."""
    spark = given.sparkSession
    dealt = given.select(F.lit(0).alias("chunk"), F.col("__lang").alias("lang"), F.col("__text").alias("text"))
    model, rows = settle_counted(train(count_grams(dealt)), "model")
    if rows > broadcast_rows:
        return settle(_scored_in_chunks(given, out, model), "scored")
    keep, lang, text = _places(given, out)
    held, name = spark.sparkContext.broadcast(gathered(model)), uuid.uuid4().hex

    def run(it):
        models = _opened(name, held.value)
        for batch in it:
            yield from _measured(batch, lang, text, keep, models)

    scored = settle(given.mapInArrow(trimmed(run), _schema(given, out)), "scored")
    held.destroy()
    give_back()
    return scored


def _places(given: DataFrame, out: list[str]) -> tuple[list[int], int, int]:
    return [given.columns.index(c) for c in out], given.columns.index("__lang"), given.columns.index("__text")


def _schema(given: DataFrame, out: list[str]) -> str:
    return ", ".join(f"`{c}` {given.schema[c].dataType.simpleString()}" for c in out) + f", {_BASE}"


def _scored_in_chunks(given: DataFrame, out: list[str], model: DataFrame) -> DataFrame:
    """The measures where the model is larger than what may be broadcast: documents are dealt into chunks,
    and each chunk meets the 5-grams that it holds."""
    names = given.columns
    size = given.agg(F.sum(F.octet_length("__text"))).first()[0] or 0
    chunks = max(CHUNKS, -(-int(size) // CHUNK))
    spread = [c for c in names if given.schema[c].dataType.simpleString() in ("bigint", "int", "string")]
    given = given.withColumn("__chunk", F.pmod(F.xxhash64(*spread), F.lit(chunks)).cast("int"))
    dealt = given.select(F.col("__chunk").alias("chunk"), F.col("__lang").alias("lang"), F.col("__text").alias("text")).repartition(chunks, "chunk")
    asked = count_grams(dealt).select("chunk", "lang", "gram").distinct()
    answers = asked.join(model, ["lang", "gram"]).select(F.col("chunk").alias("__chunk"), "lang", "gram", "log_p")
    schema = _schema(given, out)
    keep, lang, text = _places(given, out)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        models = sorted_arrays(right["lang"].combine_chunks(), string_hashes(right["gram"]), right["log_p"].to_numpy()) if right.num_rows else {}
        parts = [p for batch in left.to_batches() for p in _measured(batch, lang, text, keep, models)]
        return pa.Table.from_batches(parts) if parts else empty

    from pyspark.sql.pandas.types import to_arrow_schema

    empty = to_arrow_schema(given.sparkSession.createDataFrame([], schema).schema).empty_table()
    return given.groupBy("__chunk").cogroup(answers.groupBy("__chunk")).applyInArrow(run, schema)


def bands_of(scored: DataFrame, width: float) -> DataFrame:
    """(__lang, lower, upper): median -/+ width times the median absolute deviation (as a standard deviation), exact
    on a grid of 1/1000; of an even number of texts the lower middle one. Base-clean texts count once however
    often they are copied, so that copies don't narrow the band; the deviation is two steps of the grid at
    least. Needs __lang, __key, base_failed and log_ppl."""
    texts = scored.where("log_ppl IS NOT NULL AND NOT base_failed").select("__lang", "log_ppl", "__key").distinct()
    cells = settle(texts.groupBy("__lang", F.round(F.col("log_ppl") * GRID).cast("int").alias("cell")).agg(F.count("*").alias("n")), "cells")

    def middle(rows: DataFrame, name: str) -> DataFrame:
        """A language's rows are cells of the grid, of which there are a few thousand."""
        rows = rows.groupBy("__lang", "cell").agg(F.sum("n").alias("n"))
        whole = Window.partitionBy("__lang")
        rows = rows.withColumn("below", F.sum("n").over(whole.orderBy("cell"))).withColumn("half", F.floor((F.sum("n").over(whole) + 1) / 2))
        return rows.where("below >= half").groupBy("__lang").agg(F.min("cell").alias(name))

    medians = middle(cells, "m")
    off = cells.join(medians, "__lang").select("__lang", F.abs(F.col("cell") - F.col("m")).alias("cell"), "n")
    s = F.greatest(F.lit(1.4826) * F.col("s"), F.lit(2.0)) * F.lit(width)
    return medians.join(middle(off, "s"), "__lang").select("__lang", F.round((F.col("m") - s) / GRID, 6).alias("lower"), F.round((F.col("m") + s) / GRID, 6).alias("upper"))


def judge(docs: DataFrame, width: float = WIDTH, columns: list[str] | None = None, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The columns of `docs` (or of them `columns`) and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long),
    base_failed, log_ppl (null without text), lower, upper and kept. Needs text and lang; of columns with names
    of the results, the results stay.

    Null and empty texts have no words, fail the base rules and are not kept. A null lang is a
    language of its own (that of the empty string). Repeated rows get equal verdicts. Very long texts count
    whole. An empty table gives an empty result. `broadcast_rows`: largest model that is broadcast; it
    changes how scores are computed, not what they are."""
    clash = [*_NAMES, "lower", "upper", "kept"]
    names = [c for c in columns or docs.columns if c not in clash]
    rows = _judged(docs.select(*names, *_needed(docs)), [*names], width, broadcast_rows)
    return rows.select(*names, *_NAMES, "lower", "upper", "kept")


def _needed(docs: DataFrame) -> list[Column]:
    return [F.coalesce(docs["lang"].cast("string"), F.lit("")).alias("__lang"), docs["text"].alias("__text")]


def _judged(given: DataFrame, names: list[str], width: float, broadcast_rows: int) -> DataFrame:
    scored = _scored(given.withColumn("__key", F.xxhash64("__text")), [*names, "__lang", "__key"], broadcast_rows)
    bands = settle(bands_of(scored, width), "bands")
    # A row for each language, checked.
    bands = F.broadcast(bands) if bands.count() <= 100_000 else bands
    rows = scored.join(bands, "__lang", "left")
    low, high = F.coalesce("lower", F.lit(float("-inf"))), F.coalesce("upper", F.lit(float("inf")))
    fine = F.coalesce(F.col("log_ppl").between(low, high), F.lit(True)) & ~F.col("base_failed")
    return rows.select(*names, *_NAMES, low.alias("lower"), high.alias("upper"), fine.alias("kept"))


def reject(docs: DataFrame, width: float = WIDTH, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The documents that the base rules and the perplexity bands keep, with all their columns."""
    # Under plain names, so that columns of the results' names stay the documents' own; the text goes once.
    at = {c: "__text" if c == "text" else f"__{k}" for k, c in enumerate(docs.columns)}
    given = docs.select(*(docs[c].alias(n) for c, n in at.items() if c != "text"), *_needed(docs))
    kept = _judged(given, list(at.values()), width, broadcast_rows).where("kept")
    return kept.select(*(F.col(n).alias(c) for c, n in at.items()))
