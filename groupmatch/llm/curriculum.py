"""Mixing sources to target weights along a time-varying curriculum, in DataFrame functions.

Each source has a share of the words to be taken and a schedule of its weight over training
time. The schedule's integral is its cumulative demand; inverting it gives the time at
which the middle of each document (in its source's order) is demanded, and range-sorting by that time
deals out the mixed order. A source's running totals are sums over hash buckets plus running totals
inside a bucket, so that no task holds a whole source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from groupmatch.durable import settle, settle_counted
from .textops import WORD

#: Weight of sources in code-point order, and intensity at even steps of time, both repeating.
WEIGHTS = (3.0, 1.0, 2.0)
SCHEDULES = ((0.5, 1.0, 1.5), (1.0, 1.0, 1.0), (1.5, 1.0, 0.5))
#: Rows that a hash bucket holds on average, and most bits of a bucket's number (all buckets of a source meet in one task).
BUCKET_ROWS, MOST_BITS = 64, 20


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def ranked(df: DataFrame, column: str, name: str = "rank") -> DataFrame:
    """Adds the 0-based position in the order of `column`, nulls last, without one task for all rows."""
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = settle(df.repartitionByRange(n, F.col(column).asc_nulls_last()).withColumn("__part", F.spark_partition_id()), "ranked")
    sizes = {r["__part"]: r["count"] for r in dealt.groupBy("__part").count().collect()}  # a row per partition
    before, offsets = 0, []
    for p in sorted(sizes):
        offsets += [F.lit(p), F.lit(before)]
        before += sizes[p]
    if not offsets:
        return df.withColumn(name, F.lit(0).cast("long"))
    local = F.row_number().over(Window.partitionBy("__part").orderBy(F.col(column).asc_nulls_last())) - 1
    return dealt.withColumn(name, (F.create_map(*offsets)[F.col("__part")] + local).cast("long")).drop("__part")


def targets(sources: DataFrame, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """(source, source_size) -> and position, weight, schedule, target.

    Weights share `share` times all sizes; a target stops at `cap` times its source's size and
    the excess is shared again among the others. A pass is one aggregate; sources stay in the cluster."""
    pick = lambda values, kind: F.element_at(F.array(*(kind(v) for v in values)), (F.col("position") % len(values)).cast("int") + 1)
    s = ranked(sources, "source", "position")
    s = s.withColumn("weight", pick(WEIGHTS, F.lit)).withColumn("schedule", pick(SCHEDULES, lambda v: F.array(*(F.lit(x) for x in v))))
    s = settle(s.withColumn("cap", F.col("source_size") * F.lit(cap)), "mix-sources")
    budget = float(s.agg(F.sum("source_size")).first()[0] or 0) * share
    level = 0.0
    while True:
        full = F.col("cap") <= F.col("weight") * F.lit(level)
        taken, weight = s.agg(F.sum(F.when(full, F.col("cap")).otherwise(0.0)), F.sum(F.when(full, 0.0).otherwise(F.col("weight")))).first()
        if not weight:
            break
        higher = (budget - taken) / weight
        if higher <= level:
            break
        level = higher
    return s.withColumn("target", F.least("cap", F.col("weight") * F.lit(level))).drop("cap")


def demanded_at(share: Column, schedule: Column, knots: int) -> Column:
    """Time in 0..1 at which `share` (0..1) of a source's words has been demanded.

    Intensity is linear between even knots; its integral is solved for time in each segment."""
    at = lambda k: F.element_at(schedule, k + 1)
    step = 1.0 / (knots - 1)
    areas = [(at(k) + at(k + 1)) * F.lit(step / 2) for k in range(knots - 1)]
    total = sum(areas[1:], areas[0])
    want = share * total
    out, before = F.lit(1.0), [F.lit(0.0)]
    for a in areas:
        before.append(before[-1] + a)
    for k in reversed(range(knots - 1)):
        rest = F.greatest(want - before[k], F.lit(0.0))
        slope = (at(k + 1) - at(k)) / F.lit(step)
        x = F.lit(2.0) * rest / (at(k) + F.sqrt(F.greatest(at(k) * at(k) + F.lit(2.0) * slope * rest, F.lit(0.0))))
        out = F.when(want <= before[k + 1], F.lit(k * step) + F.least(F.coalesce(x, F.lit(0.0)), F.lit(step))).otherwise(out)
    return out


def bucket_bits(rows: int) -> int:
    return min(MOST_BITS, max(6, (rows // BUCKET_ROWS).bit_length()))


def planned(docs: DataFrame, bits: int) -> DataFrame:
    """Rows with __size and __order (a hash) -> and source_size, target, start, taken, schedule.

    Both joins and the window are by one key without nulls, so that rows are dealt out once."""
    bucket = F.shiftrightunsigned("__order", 64 - bits).alias("__bucket")
    keyed = docs.withColumn("__key", F.coalesce(F.concat(F.lit("="), "source"), F.lit("")))
    sums = settle(keyed.select("__key", "source", bucket, "__size").groupBy("__key", "source", "__bucket").agg(F.sum("__size").alias("words")), "mix-buckets")
    sources = targets(sums.groupBy("__key", "source").agg(F.sum("words").alias("source_size"))).drop("source")
    per = Window.partitionBy("__key").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.withColumn("before", F.coalesce(F.sum("words").over(per), F.lit(0)))
    plan = settle(offsets.join(sources, "__key").select("__key", "__bucket", "before", "source_size", "target", "schedule"), "mix-plan")
    rows = keyed.withColumn("__bucket", bucket)
    inside = Window.partitionBy("__key", "__bucket").orderBy("__order", "doc_id", "__size").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("__local", F.coalesce(F.sum("__size").over(inside), F.lit(0))).join(plan, ["__key", "__bucket"])
    size, total = F.col("source_size"), F.round("target").cast("long")
    passes = F.when(size > 0, F.floor(total / size)).otherwise(0).cast("long")
    rows = rows.withColumn("start", F.col("before") + F.col("__local")).withColumn("passes", passes)
    last = F.least(F.greatest(total - F.col("passes") * size - F.col("start"), F.lit(0)), F.col("__size"))
    rows = rows.withColumn("last", last.cast("long")).withColumn("taken", F.col("passes") * F.col("__size") + F.col("last"))
    return rows.drop("__bucket", "__local", "__key", "before")


def _time(number: Column, words: Column) -> Column:
    middle = number * F.col("source_size") + F.col("start") + words / 2
    share = F.when(F.col("target") > 0, F.least(middle / F.col("target"), F.lit(1.0))).otherwise(0.0)
    return demanded_at(share, F.col("schedule"), len(SCHEDULES[0]))


def _order(doc_id: Column, text: Column) -> Column:
    return F.xxhash64(doc_id, text)


def mix(docs: DataFrame) -> DataFrame:
    """(doc_id, size, source_size, target, taken, position): a row for each document, range-sorted by position.

    position is the time in 0..1 of the document's first use, null if it isn't used. Null and
    blank texts have size 0 and take nothing; a null source is a source of its own, last in order.
    Repeated rows are taken each. The order within a source is a hash of doc_id and text."""
    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("__size"), _order(F.col("doc_id"), F.col("text")).alias("__order"))
    narrow, count = settle_counted(narrow, "mix-sizes")
    rows = planned(narrow, bucket_bits(count))
    first = F.when(F.col("passes") > 0, F.col("__size")).otherwise(F.col("last"))
    rows = rows.select("doc_id", F.col("__size").alias("size"), "source_size", "target", "taken", F.when(F.col("taken") > 0, _time(F.lit(0), first)).alias("position"))
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # Unused documents have no position; their numbers spread them.
    at = [F.col("position").asc_nulls_last(), F.col("doc_id")]
    return rows.repartitionByRange(n, *at).sortWithinPartitions(*at)


def train_order(docs: DataFrame) -> DataFrame:
    """The mix itself: each document as often as it is taken, range-sorted by training time.

    The one document of a source at which its target is reached gives its first words (joined by
    blanks); n_chars follows where it exists. Columns are those of `docs`."""
    names = docs.columns
    given = docs.select(F.struct(*names).alias("given"), F.col("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("__size"), _order(F.col("doc_id"), F.col("text")).alias("__order"))
    rows = planned(given, bucket_bits(docs.count())).where("taken > 0")
    copies = F.expr("CASE WHEN last > 0 THEN sequence(0L, passes) ELSE sequence(0L, passes - 1) END")
    rows = rows.withColumn("number", F.explode(copies)).withColumn("words", F.when(F.col("number") < F.col("passes"), F.col("__size")).otherwise(F.col("last")))
    rows = rows.where("words > 0").withColumn("time", _time(F.col("number"), F.col("words")))
    text = F.col("given.text")
    part = F.when(F.col("words") < F.col("__size"), F.array_join(F.slice(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.lit(1), F.col("words").cast("int")), " ")).otherwise(text)
    out = [part.alias(c) if c == "text" else F.col(f"given.`{c}`").alias(c) for c in names]
    rows = rows.select("time", "doc_id", "number", *[c.alias(f"__{k}") for k, c in enumerate(out)])
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartitionByRange(n, "time", "doc_id", "number").sortWithinPartitions("time", "doc_id", "number")
    final = [F.col(f"__{k}").alias(c) for k, c in enumerate(names)]
    if "n_chars" in names and "text" in names:
        final[names.index("n_chars")] = F.length(F.col(f"__{names.index('text')}")).cast(docs.schema["n_chars"].dataType).alias("n_chars")
    return rows.select(*final)
