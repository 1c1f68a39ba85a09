"""URL filters: rules by host and path, and a list of canonical URLs behind a blocked Bloom filter.

Each URL gives its canonical lookup keys (host suffixes times path prefixes). A split-block Bloom
filter of the listed keys passes possible hits; an exact join on those keys removes false positives.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from groupmatch.durable import settle

RULES = [("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block")]
#: Default list: canonical hosts and pages to block.
LISTED = ("ads-track.example.com/", "ads-track.example.net/", "cheap-pills.example.net/", "free-bets.example.net/", "spam-farm.example.net/", "casino-win.example.net/", "tionsh.example.net/en/404", "ththth.example.net/en/25")
WORDS = 8
MAX_BYTES = 64 << 20
#: The multipliers of split-block Bloom filters.
_SALTS = np.array([0x47B6137B, 0x44974D91, 0x8824AD5B, 0xA2B7289D, 0x705495C7, 0x2DF1424B, 0x9EFC4947, 0x5C6BFB31], np.uint32)


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"^(?s:.*?)://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"^(?s:.*?)://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules=None) -> Column:
    """The longest rule that fits, as struct(length, rule, verdict); null if none does."""
    fits = []
    for text, verdict in rules or RULES:
        own, slash, rest = text.partition("/")
        hit = ((host == own) | host.endswith("." + own)) & path.startswith(slash + rest)
        fits.append(F.when(hit, F.struct(F.lit(len(text)).alias("length"), F.lit(text).alias("rule"), F.lit(verdict).alias("verdict"))))
    return F.array_max(F.array_compact(F.array(*fits)))


def lookup_keys(host: str, path: str) -> list[str]:
    """Canonical keys, most specific first: the page without end slash, its folders, the host; for each
    host suffix of two labels or more."""
    labels = [x for x in host.rstrip(".").split(":")[0].split(".") if x]
    hosts = [".".join(labels[k:]) for k in range(max(1, len(labels) - 1))] if labels else []
    parts = [p for p in path.split("/") if p]
    paths = ["/" + "/".join(parts[:k]) for k in range(len(parts), -1, -1)]
    return [h + p for h in hosts for p in paths]


class BlockedBloom:
    """Split-block filter: a key sets one bit in each of the eight words of one block."""

    def __init__(self, words: np.ndarray):
        self.words = words

    @staticmethod
    def blocks_for(n: int, bits_per_key: int = 14) -> int:
        return int(min(max(1, -(-n * bits_per_key // 256)), MAX_BYTES // 32))

    @staticmethod
    def places(keys: list[str], blocks: int) -> tuple[np.ndarray, np.ndarray]:
        h = np.array([xxhash.xxh64_intdigest(k) for k in keys], np.uint64)
        block = ((h >> np.uint64(32)) * np.uint64(blocks) >> np.uint64(32)).astype(np.int64)
        low = (h & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        return block, np.uint32(1) << ((low[:, None] * _SALTS) >> np.uint32(27))

    def may_hold(self, keys: list[str]) -> np.ndarray:
        if not keys or not len(self.words):
            return np.zeros(len(keys), bool)
        block, bits = self.places(keys, len(self.words))
        return ((self.words[block] & bits) == bits).all(1)


def build_bloom(listed: DataFrame) -> BlockedBloom:
    """The filter of column `key`; words are or-ed in the cluster and at most MAX_BYTES come back."""
    blocks = BlockedBloom.blocks_for(listed.count())

    def run(it):
        for batch in it:
            keys = [k for k in batch.column(0).to_pylist() if k is not None]
            if keys:
                block, bits = BlockedBloom.places(keys, blocks)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(block * WORDS, WORDS) + np.tile(np.arange(WORDS), len(block))), pa.array(bits.reshape(-1).astype(np.int64))], names=["at", "bits"])

    words = np.zeros(blocks * WORDS, np.uint32)
    rows = listed.select("key").mapInArrow(run, "at long, bits long").groupBy("at").agg(F.bit_or("bits").alias("bits")).toArrow()
    words[rows["at"].to_numpy()] = rows["bits"].to_numpy().astype(np.uint32)
    return BlockedBloom(words.reshape(blocks, WORDS))


def listed_keys(spark: SparkSession, listed=LISTED) -> DataFrame:
    """Canonical keys (key) of a list of host/path texts or of a table with column `key`."""
    rows = listed if isinstance(listed, DataFrame) else spark.createDataFrame([(x,) for x in listed], "key string")
    return rows.where("key IS NOT NULL").select(F.lower(F.regexp_replace("key", "/+$", "/")).alias("key")).select(F.when(F.col("key").rlike("^[^/]*/$"), F.col("key")).otherwise(F.regexp_replace("key", "/$", "")).alias("key")).distinct()


def judge(pages: DataFrame, rules=None, listed=LISTED) -> DataFrame:
    """(page_id, host, path, rule, verdict, listed_key) of every row.

    verdict is the longest fitting rule's; without one `block` if a canonical key is listed, else
    `allow`. Null URLs and URLs without :// have empty host and path and are allowed. listed_key
    is the longest listed key, if looked up. Repeated rows are judged each, URLs of any length whole; an empty table
    gives an empty result."""
    spark = pages.sparkSession
    keys = listed_keys(spark, listed)
    held = spark.sparkContext.broadcast(build_bloom(keys))
    url = F.col("url")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), host_of(url).alias("host"), path_of(url).alias("path"))
    rows = rows.withColumn("fit", rule_of(F.col("host"), F.col("path"), rules))
    rows = rows.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), F.col("fit.verdict").alias("by_rule"))

    def possible(it):
        bloom = held.value
        for batch in it:
            per = [lookup_keys(h, p) if r is None else [] for h, p, r in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3)))]
            hit = bloom.may_hold([k for keys in per for k in keys]).tolist()
            at, out = 0, []
            for keys in per:
                out.append([k for k, ok in zip(keys, hit[at : at + len(keys)]) if ok])
                at += len(keys)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.list_(pa.string()))], names=[*batch.schema.names, "possible"])

    # Read several times below, so it is written once.
    rows = settle(rows.mapInArrow(possible, "page_id long, host string, path string, rule string, by_rule string, possible array<string>"), "urls")
    # The exact join is on distinct possible keys, so that a popular host is one row of it.
    hits = rows.select(F.explode("possible").alias("key")).distinct().join(keys, "key")
    name = F.concat("host", F.lit("\n"), "path")
    doubtful = rows.where(F.size("possible") > 0).select(name.alias("name"), F.explode("possible").alias("key")).distinct()
    found = doubtful.join(hits, "key").groupBy("name").agg(F.max_by("key", F.struct(F.length("key"), "key")).alias("listed_key"))
    clean, rest = rows.where(F.size("possible") == 0), rows.where(F.size("possible") > 0)
    judged = rest.withColumn("name", name).join(found, "name", "left").select("page_id", "host", "path", "rule", "by_rule", "listed_key")
    every = clean.select("page_id", "host", "path", "rule", "by_rule", F.lit(None).cast("string").alias("listed_key")).unionByName(judged)
    verdict = F.coalesce("by_rule", F.when(F.col("listed_key").isNotNull(), "block").otherwise("allow"))
    return every.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "listed_key")
