"""Data graphs built from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from groupmatch.durable import settle
from groupmatch.model import SocialGraph

_P = 2147483647


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mixed(x: Column) -> Column:
    """A reproducible number in 0..1 from an integer."""
    return ((x % F.lit(_P).cast("long")) * F.lit(48271).cast("long") % F.lit(_P).cast("long")) / F.lit(_P).cast("double")


def pseudo_random(vertices: DataFrame, edges: DataFrame) -> SocialGraph:
    """Scores in 0..1 drawn from ids: vertices (id, labels), edges (src, dst)."""
    small = lambda c: F.col(c) % F.lit(_P).cast("long")  # noqa: E731  so that products of large ids fit
    v = vertices.select("id", "labels", mixed(small("id") * 7919 + 17).alias("influence"))
    t = mixed(small("src") * 1000003 + small("dst") * 7919 + 101)
    r = mixed(small("src") * 1000033 + small("dst") * 104729 + 211)
    return SocialGraph(v, edges.select("src", "dst", t.alias("trust"), r.alias("intimacy")))


def _handed(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").where(F.col("l_linenumber") <= k).select("l_orderkey", "l_partkey", "l_linenumber", "l_returnflag")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    after = Window.partitionBy("l_partkey").orderBy("o_orderdate", "l_orderkey", "l_linenumber", "l_returnflag")
    rows = rows.select(F.col("o_custkey").alias("src"), F.lead("o_custkey").over(after).alias("dst"), "l_returnflag")
    return rows.where("dst IS NOT NULL AND src <> dst")


def handover(spark: SparkSession, sf_dir: str, k: int = 3) -> SocialGraph:
    """Customer to the customer of the next order line of the same part; `k` steers density."""
    v = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), F.array("c_mktsegment").alias("labels"))
    return pseudo_random(v, _handed(spark, sf_dir, k).select("src", "dst").distinct())


def handover_real(spark: SparkSession, sf_dir: str, k: int = 3) -> SocialGraph:
    """The same links with scores mined from the data and a second label, the region."""
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    places = nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    c = table(spark, sf_dir, "customer").join(places, F.col("c_nationkey") == F.col("n_nationkey"))
    v = c.select(F.col("c_custkey").alias("id"), F.array("c_mktsegment", "r_name").alias("labels"), ((F.col("c_acctbal") + 1000.0) / 11000.0).alias("influence"))
    kept = F.when(F.col("l_returnflag") == "R", 0.0).otherwise(1.0)
    e = _handed(spark, sf_dir, k).groupBy("src", "dst").agg((F.sum(kept) / F.count("*")).alias("trust"), F.count("*").alias("n"))
    return SocialGraph(v, e.select("src", "dst", "trust", F.least(F.lit(1.0), F.col("n") / F.lit(4.0)).alias("intimacy")))


def typed(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Customers, suppliers, parts, nations and regions; ids are kind * 10^13 + key."""
    t = lambda n: table(spark, sf_dir, n)
    at = lambda kind, c: (F.lit(kind * 10**13).cast("long") + F.col(c)).cast("long")
    parts = [
        t("customer").select(at(1, "c_custkey").alias("id"), F.array(F.lit("customer"), "c_mktsegment").alias("labels")),
        t("supplier").select(at(2, "s_suppkey").alias("id"), F.array(F.lit("supplier")).alias("labels")),
        t("part").select(at(3, "p_partkey").alias("id"), F.array(F.lit("part"), "p_type").alias("labels")),
        t("nation").select(at(4, "n_nationkey").alias("id"), F.array(F.lit("nation")).alias("labels")),
        t("region").select(at(5, "r_regionkey").alias("id"), F.array(F.lit("region"), "r_name").alias("labels")),
    ]
    lines = t("lineitem")
    ordered = lines.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    pairs = [
        ordered.select(at(1, "o_custkey").alias("src"), at(3, "l_partkey").alias("dst")),
        lines.select(at(3, "l_partkey").alias("src"), at(2, "l_suppkey").alias("dst")),
        t("customer").select(at(1, "c_custkey").alias("src"), at(4, "c_nationkey").alias("dst")),
        t("supplier").select(at(2, "s_suppkey").alias("src"), at(4, "s_nationkey").alias("dst")),
        t("nation").select(at(4, "n_nationkey").alias("src"), at(5, "n_regionkey").alias("dst")),
    ]
    v, e = parts[0], pairs[0]
    for x, y in zip(parts[1:], pairs[1:]):
        v, e = v.unionByName(x), e.unionByName(y)
    return pseudo_random(v, e.distinct())


def click(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """User to the next user within the same hour; labels are users' most frequent event types."""
    ev = table(spark, sf_dir, "events")
    kinds = ev.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.max_by("event_type", F.struct("n", "event_type")).alias("kind"))
    v = kinds.select(F.col("user_id").alias("id"), F.array("kind").alias("labels"))
    after = Window.partitionBy(F.date_trunc("hour", "ts")).orderBy("ts", "event_id")
    e = ev.select(F.col("user_id").alias("src"), F.lead("user_id").over(after).alias("dst")).where("dst IS NOT NULL AND src <> dst").distinct()
    return pseudo_random(v, e)


def similar(spark: SparkSession, sf_dir: str, top: int = 8, least: float = 0.15) -> SocialGraph:
    """Each vector to its `top` nearest by cosine, at least `least`; blocks of vectors meet, not rows.

    trust is the cosine, intimacy 1 / rank."""
    import numpy as np
    import pyarrow as pa

    from groupmatch.session import ship

    ship(spark)
    emb = table(spark, sf_dir, "embeddings").where("embedding IS NOT NULL").select("vec_id", F.col("embedding").cast("array<double>").alias("x"), "label")
    # Blocks of about 4,096 vectors, as many as the table needs.
    side = max(1, -(-emb.count() // 4096))
    block = F.pmod(F.xxhash64("vec_id"), F.lit(side)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(side - 1)))
    left = emb.select(block.alias("i"), every.alias("j"), F.lit(0).alias("s"), "vec_id", "x")
    right = emb.select(every.alias("i"), block.alias("j"), F.lit(1).alias("s"), "vec_id", "x")
    rows = left.unionByName(right)

    def near(t: pa.Table) -> pa.Table:
        s, ids = t["s"].to_numpy(), t["vec_id"].to_numpy()
        x = np.asarray(t["x"].combine_chunks().flatten()).reshape(len(ids), -1)
        a, b = x[s == 0], x[s == 1]
        left, right = ids[s == 0], ids[s == 1]
        # Folded left to right, so that the sums are reproducible.
        norm = lambda m: np.sqrt(np.add.accumulate(m * m, axis=1)[:, -1])
        src, dst, cos = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if len(a) and len(b):
            own, other = norm(a), norm(b)
            for at in range(0, len(a), 256):
                part = slice(at, at + 256)
                dot = np.zeros((len(a[part]), len(b)))
                for d in range(x.shape[1]):
                    dot += a[part, d][:, None] * b[:, d][None, :]
                c = dot / (own[part][:, None] * other[None, :])
                c[(c < least) | (left[part][:, None] == right[None, :])] = -2
                # The top few and all that tie with the last of them.
                bound = np.maximum(-np.partition(-c, min(top, c.shape[1]) - 1, axis=1)[:, min(top, c.shape[1]) - 1], -1)
                r, k = np.nonzero(c >= bound[:, None])
                src.append(left[part][r])
                dst.append(right[k])
                cos.append(c[r, k])
        return pa.table({"src": np.concatenate(src), "dst": np.concatenate(dst), "trust": np.concatenate(cos)})

    pairs = rows.groupBy("i", "j").applyInArrow(near, "src long, dst long, trust double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("trust"), "dst"))
    e = pairs.withColumn("rank", rank).where(F.col("rank") <= top).select("src", "dst", "trust", (F.lit(1.0) / F.col("rank")).alias("intimacy"))
    v = emb.select(F.col("vec_id").alias("id"), F.array(F.col("label").cast("string")).alias("labels"), mixed(F.col("vec_id") * 7919 + 17).alias("influence"))
    return SocialGraph(v, e)


def turns(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Turn to the next turn of its conversation; id is conv_id * 100000 + turn."""
    c = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 100000 + F.col("turn")).alias("id"), "conv_id", "turn", "role", F.length("text").alias("n"))
    after = Window.partitionBy("conv_id").orderBy("turn")
    e = c.select(F.col("id").alias("src"), F.lead("id").over(after).alias("dst"), F.col("n").alias("a"), F.lead("n").over(after).alias("b")).where("dst IS NOT NULL")
    ratio = F.least("a", "b") / F.greatest("a", "b", F.lit(1))
    v = c.select("id", F.array("role").alias("labels"), mixed(F.col("id") * 7919 + 17).alias("influence"))
    return SocialGraph(v, e.select("src", "dst", F.lit(1.0).alias("trust"), ratio.alias("intimacy")))


def links(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Page to every later page with a common outgoing link.

    Pairs of one link are spread over `salts` tasks by the earlier page, and each page counts once a link."""
    salts = 8
    p = table(spark, sf_dir, "pages")
    href = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("href")
    own = p.select("page_id", href)
    early = own.select("href", F.col("page_id").alias("src"), F.pmod(F.xxhash64("page_id"), F.lit(salts)).cast("int").alias("salt"))
    late = own.select("href", F.col("page_id").alias("dst"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    pairs = early.join(late, ["href", "salt"]).where("src < dst").select("src", "dst")
    n = own.groupBy("page_id").agg(F.count("*").alias("n"))
    e = pairs.groupBy("src", "dst").agg(F.count("*").alias("common")).join(n, F.col("src") == F.col("page_id")).select("src", "dst", (F.col("common") / F.col("n")).alias("trust"), F.lit(1.0).alias("intimacy"))
    lang = F.regexp_extract("url", r"://[^/]*/([a-z]{2})/", 1)
    return SocialGraph(p.select(F.col("page_id").alias("id"), F.array(lang).alias("labels"), mixed(F.col("page_id") * 7919 + 17).alias("influence")), e)


def _following(rows: DataFrame, group: str, order: str) -> DataFrame:
    """(src, dst): each value of `order` and the next one of its group. Ranges of (group, order) are dealt to
    tasks, so that a group of any size is split; the first of the next range follows the last of one."""
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    key = F.coalesce(F.concat(F.lit("="), F.col(group).cast("string")), F.lit("")).alias("key")
    dealt = rows.select(key, F.col(order).alias("src")).repartitionByRange(n, "key", "src").withColumn("part", F.spark_partition_id())
    dealt = settle(dealt, "ranges")
    firsts = dealt.groupBy("key", "part").agg(F.min("src").alias("first"))
    firsts = firsts.withColumn("following", F.lead("first").over(Window.partitionBy("key").orderBy("part"))).drop("first")
    inside = F.lead("src").over(Window.partitionBy("key", "part").orderBy("src"))
    found = dealt.withColumn("inside", inside).join(firsts, ["key", "part"])
    return found.select("src", F.coalesce("inside", "following").alias("dst")).where("dst IS NOT NULL")


def evidence(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Document to the next document of its source (in id order) and to benchmark items whose whole passage it
    holds, word by word; influence is the quality label, null where it is missing. Item ids are 10^13 + item_id.

    The first 8 words of a passage find the documents that may hold it (passages have as many at least)."""
    d = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    lab = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    b = table(spark, sf_dir, "benchmark")
    words = lambda c: F.regexp_extract_all(F.lower(c), F.lit("[^ \\t\\n\\r]+"), F.lit(0))
    grams = lambda w: F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - 7, F.lit(1))), lambda i: F.array_join(F.slice(w, i, 8), " "))
    whole = lambda c: F.concat(F.lit(" "), F.array_join(words(c), " "), F.lit(" "))
    keys = b.select((F.lit(10**13) + F.col("item_id")).alias("dst"), F.array_join(F.slice(words(F.col("text")), 1, 8), " ").alias("gram"))
    # The words are generated once per row; inlined into the lambda they would be split for every n-gram.
    split = d.select(F.col("doc_id").alias("src"), F.explode(F.array(words(F.col("text")))).alias("ws"))
    maybe = split.select("src", F.explode(F.array_distinct(grams(F.col("ws")))).alias("gram")).join(keys, "gram").select("src", "dst").distinct()
    passages = b.select((F.lit(10**13) + F.col("item_id")).alias("dst"), whole(F.col("text")).alias("passage"))
    held = maybe.join(passages, "dst").join(d.select(F.col("doc_id").alias("src"), "text"), "src").where(whole(F.col("text")).contains(F.col("passage"))).select("src", "dst").distinct()
    v = d.join(lab, "doc_id", "left").select(F.col("doc_id").alias("id"), F.array("lang", "source").alias("labels"), F.col("quality").cast("double").alias("influence"))
    items = b.select((F.lit(10**13) + F.col("item_id")).alias("id"), F.array(F.lit("item")).alias("labels"), F.lit(1.0).alias("influence"))
    g = pseudo_random(v.select("id", "labels"), held.unionByName(_following(d, "source", "doc_id")))
    return SocialGraph(v.unionByName(items), g.edges)


GRAPHS = {"handover": handover, "handover_real": handover_real, "typed": typed, "click": click, "similar": similar, "turns": turns, "links": links, "evidence": evidence}
