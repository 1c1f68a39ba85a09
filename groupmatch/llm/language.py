"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Document frequencies come from all labelled training rows. The classifier is fitted on a bounded
sample of them (`per_lang` rows of each language, those with the smallest hash of doc_id) by follow-the-regularised-leader
with an elastic net, whose L1 part leaves a sparse weight table; a part of the sample that takes
no step sets the temperature which calibrates the probabilities.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .textops import mix, utf8

SLOT_BITS = 15
SLOTS = 1 << SLOT_BITS
UNKNOWN = "und"


def slot_counts(text: str) -> np.ndarray:
    """Count of each hashed character 1-, 2- and 3-gram of the lower-cased text, blank-padded."""
    points = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "replace"), np.uint32).astype(np.uint64)
    out = np.zeros(SLOTS, np.int64)
    for a in range(0, len(points), 1 << 20):
        part = points[a : a + (1 << 20) + 2]
        whole = len(part) if a + (1 << 20) >= len(points) else 1 << 20
        code = np.zeros(len(part), np.uint64)
        for n in (1, 2, 3):
            code = code[: len(part) - n + 1] * np.uint64(0x110001) + part[n - 1 :] + np.uint64(n)
            slots = mix(code[:whole]) >> np.uint64(64 - SLOT_BITS)
            out += np.bincount(slots.astype(np.int64), minlength=SLOTS)
    return out


def tfidf(slots: np.ndarray, counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = np.log1p(counts) * idf[slots]
    return x / max(float(np.sqrt(x @ x)), 1e-12)


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


@dataclass
class Model:
    langs: list[str]
    idf: np.ndarray
    weights: np.ndarray
    temperature: float = 1.0

    def logits(self, slots: np.ndarray, counts: np.ndarray) -> np.ndarray:
        return tfidf(slots, counts, self.idf) @ self.weights[slots]

    def predict(self, text: str) -> tuple[str, float]:
        counts = slot_counts(text)
        slots = np.flatnonzero(counts)
        p = _softmax(self.logits(slots, counts[slots]) / self.temperature)
        k = int(np.argmax(p))
        return self.langs[k], float(p[k])


def fit(rows, langs: list[str], idf: np.ndarray, epochs: int = 4, alpha: float = 1.0, beta: float = 1.0, l1: float = 1e-3, l2: float = 1e-3) -> Model:
    """FTRL-proximal with elastic net over rows (slots, counts, lang); every fifth row calibrates."""
    c = len(langs)
    index = {x: k for k, x in enumerate(langs)}
    z, n = np.zeros((SLOTS, c)), np.zeros((SLOTS, c))

    def weights(s):
        return np.where(np.abs(z[s]) <= l1, 0.0, -(z[s] - np.sign(z[s]) * l1) / ((beta + np.sqrt(n[s])) / alpha + l2))

    held = [r for k, r in enumerate(rows) if k % 5 == 4]
    steps = [r for k, r in enumerate(rows) if k % 5 != 4] or list(rows)
    for _ in range(epochs):
        for slots, counts, lang in steps:
            x, w = tfidf(slots, counts, idf), weights(slots)
            error = _softmax(x @ w)
            error[index[lang]] -= 1.0
            g = np.outer(x, error)
            sigma = (np.sqrt(n[slots] + g * g) - np.sqrt(n[slots])) / alpha
            z[slots] += g - sigma * w
            n[slots] += g * g
    model = Model(langs, idf, weights(np.arange(SLOTS)).astype(np.float64))
    if held and c > 1:
        logits = np.array([model.logits(s, k) for s, k, _ in held])
        truth = np.array([index[x] for _, _, x in held])
        grid = np.exp(np.linspace(np.log(0.05), np.log(20), 121))
        losses = [-np.mean(np.log(_softmax(logits / t)[np.arange(len(truth)), truth] + 1e-12)) for t in grid]
        model.temperature = float(grid[int(np.argmin(losses))])
    return model


def _sparse_rows(it):
    for batch in it:
        langs = batch.column(1).to_pylist()
        slots, counts = [], []
        for t in batch.column(0).to_pylist():
            c = slot_counts(t)
            s = np.flatnonzero(c)
            slots.append(s.astype(np.int32))
            counts.append(c[s])
        yield pa.RecordBatch.from_arrays([pa.array(slots, pa.list_(pa.int32())), pa.array(counts, pa.list_(pa.int64())), pa.array(langs, pa.string()), *(batch.column(k) for k in (2, 3, 4))], names=["slots", "counts", "lang", "hash", "doc_id", "text_hash"])


def _frequency_rows(it):
    df, rows = np.zeros(SLOTS, np.int64), 0
    for batch in it:
        for t in batch.column(0).to_pylist():
            df += slot_counts(t) > 0
            rows += 1
    if rows:
        used = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(used, -1).astype(np.int32)), pa.array(np.append(df[used], rows))], names=["slot", "n"])


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def train(labelled: DataFrame, per_lang: int = 500) -> Model | None:
    """A model from (doc_id, text, lang); None without usable rows.

    IDF and the set of languages use all of `labelled`; the weights are fitted on `per_lang` rows of each
    language, those with the smallest hash of doc_id (ties by doc_id and text). They are chosen by narrow rows;
    only the chosen texts are fetched."""
    usable = labelled.where("text IS NOT NULL AND lang IS NOT NULL").select("doc_id", "text", F.col("lang").cast("string").alias("lang"))
    counts = usable.select("text").mapInArrow(_frequency_rows, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toPandas()
    total = int(counts.loc[counts.slot < 0, "n"].sum())
    if not total:
        return None
    df = np.zeros(SLOTS)
    real = counts[counts.slot >= 0]
    df[real.slot.to_numpy()] = real.n.to_numpy()
    idf = np.log((1 + total) / (1 + df)) + 1
    order = ["hash", "doc_id", "text_hash"]
    given = usable.withColumn("hash", F.xxhash64("doc_id")).withColumn("text_hash", F.xxhash64("text"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(*order))
    chosen = given.select("lang", *order).withColumn("rank", rank).where(F.col("rank") <= per_lang)
    keys = chosen.select("lang", *(F.col(c).alias(f"c_{c}") for c in ("hash", "text_hash"))).distinct()
    # At most per_lang keys a language.
    picked = given.join(F.broadcast(keys.withColumnRenamed("lang", "c_lang")), (F.col("lang") == F.col("c_lang")) & (F.col("hash") == F.col("c_hash")) & (F.col("text_hash") == F.col("c_text_hash")), "left_semi")
    # A repeated row is as good as one of it; it can't come more often than there are places.
    picked = picked.groupBy("lang", *order).agg(F.first("text").alias("text")).select("text", "lang", *order)
    rows = picked.select("text", "lang", *order).mapInArrow(_sparse_rows, "slots array<int>, counts array<long>, lang string, hash long, doc_id long, text_hash long").toArrow().to_pylist()
    rows.sort(key=lambda r: (r["hash"], r["doc_id"] is None, r["doc_id"] or 0, r["text_hash"], r["lang"]))
    rows = [(np.array(r["slots"], np.int64), np.array(r["counts"]), r["lang"]) for r in rows]
    return fit(rows, sorted({x for _, _, x in rows}), idf)


def identify(docs: DataFrame, per_lang: int = 500) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every row; trained on rows that aren't held out.

    Null texts and texts without a letter are `und` with score 0, as is every row if no row can
    be learned from. A null doc_id isn't held out. Long texts count whole; repeated rows are
    judged each; an empty table gives an empty result."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"))
    model = train(docs.where(~held_out(F.col("doc_id"))), per_lang)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(it):
        model = held.value
        for batch in it:
            texts, letters = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            got = [model.predict(t) if model and ok else (UNKNOWN, 0.0) for t, ok in zip(texts, letters)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([x for x, _ in got], pa.string()), pa.array([float(p) for _, p in got])], names=["doc_id", "held_out", "lang_pred", "score"])

    lettered = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))
    given = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text", lettered.alias("letters"))
    return given.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
