"""Secret scans with corpus-wide ownership frequency, in DataFrame functions only.

Candidates are hashed; for each hash the distinct owners (and repositories) that hold it
are counted over the whole corpus. A value that many owners hold is a copied example; a
live-looking value of few owners is a credential. Base spans stay whatever the verdict; live
values beyond the base kinds add spans of kind `live`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from groupmatch.durable import settle

#: The base kinds in listed order, as (name, pattern, group of the value, least length).
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
KINDS = [("assign", ASSIGN, 2, 6), ("access", r"AKIA[A-Z0-9]{16,}", 0, 20), ("hex", r"[0-9a-f]{24,}", 0, 24)]
LIVE = r"[A-Za-z0-9+/_-]{32,}"
GUARD = r"""[A-Za-z0-9+/_-]{20,}|(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]"""
PLACEHOLDERS = r"(?i)example|changeme|placeholder|your|dummy|xxxx|sample|\*\*|0000000|1234567"
#: Values that are placeholders as a whole; other values of base kinds are masked unless many owners hold them.
NAMED = r"(?i)^(?:example|changeme|placeholder|dummy|sample|x{4,}|0{7,}|123456(?:7(?:8(?:90?)?)?)?|AKIA[A-Z0-9]*EXAMPLE|your(?:[_.-]?(?:own|api|access|key|secret|token|password|passwd|value|here))*)[._=/+-]*$"
MASK = "[SECRET]"
_SPAN = "struct<start:int,kind:int,end:int,hash:string,looks:boolean,named:boolean>"


def _spans(text: Column, kind: int, pattern: str, group: int, least: int) -> Column:
    """Leftmost non-overlapping matches with code-point positions: the pieces between the matches and
    the matches themselves give each start as a sum of lengths."""
    matches = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else matches
    pieces = F.split(text, pattern, -1)
    rows = F.arrays_zip(matches.alias("m"), values.alias("v"), F.slice(pieces, 1, F.size(matches)).alias("p"))

    def step(acc, x):
        start = acc["at"] + F.length(x["p"])
        end = start + F.length(x["m"])
        looks = (F.length(x["v"]) >= 16) & (F.size(F.array_distinct(F.split(x["v"], ""))) >= 10) & ~x["v"].rlike(PLACEHOLDERS)
        span = F.struct(start.alias("start"), F.lit(kind).alias("kind"), end.alias("end"), F.sha2(x["v"], 256).alias("hash"), looks.alias("looks"), x["v"].rlike(NAMED).alias("named"))
        return F.struct(end.alias("at"), F.when(F.length(x["v"]) >= least, F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    empty = F.array().cast(f"array<{_SPAN}>")
    found = F.aggregate(rows, F.struct(F.lit(0).alias("at"), empty.alias("out")), step)["out"]
    return F.when(text.rlike(pattern), found).otherwise(empty)


def candidates(text: Column) -> Column:
    """Base spans and further long tokens of digits and letters outside them, by (start, kind)."""
    empty = F.array().cast(f"array<{_SPAN}>")
    base = F.concat(*(_spans(text, k, p, g, n) for k, (_, p, g, n) in enumerate(KINDS)))
    more = F.filter(_spans(text, len(KINDS), LIVE, 0, 32), lambda x: x["looks"])
    return F.when(text.rlike(GUARD), F.array_sort(F.concat(base, more))).otherwise(empty)


def ownership(found: DataFrame) -> DataFrame:
    """(hash, n_owners, n_repositories) from rows (spans, owner, repository).

    Aggregated before each shuffle, finest first, so that a value in a third of all rows costs
    one row a task; null owners count as one owner."""
    rows = found.select(F.explode("spans.hash").alias("hash"), "owner", "repository").distinct()
    by_owner = rows.groupBy("hash", "owner").agg(F.count("*").alias("n"))
    return by_owner.groupBy("hash").agg(F.count("*").alias("n_owners"), F.sum("n").alias("n_repositories"))


def judged_spans(found: DataFrame, max_owners: int, short: bool = False) -> DataFrame:
    """(row, spans): the spans of each row with `live` set by ownership and looks; with `short`, ownership
    alone decides on base spans that aren't placeholders as a whole, so short values count too."""
    rows = found.where(F.size("spans") > 0).select("row", F.explode("spans").alias("s")).select("row", "s.*")
    seen = ownership(found.where(F.size("spans") > 0))
    looks = F.when(F.col("kind") < len(KINDS), ~F.col("named")).otherwise(F.col("looks")) if short else F.col("looks")
    judged = rows.join(seen, "hash").withColumn("live", looks & (F.col("n_owners") <= max_owners))
    span = F.struct("start", "kind", "end", "live", "n_owners", "n_repositories")
    return judged.groupBy("row").agg(F.array_sort(F.collect_list(span)).alias("judged"))


def _listed(spans: Column) -> Column:
    names = F.array(*(F.lit(k) for k, *_ in KINDS), F.lit("live"))
    return F.array_join(F.transform(spans, lambda x: F.concat(F.element_at(names, x["kind"] + 1), F.lit(":"), x["start"].cast("string"), F.lit(":"), x["end"].cast("string"))), ",")


def _accepted(judged: Column) -> Column:
    """Base spans, and live ones that no base span overlaps."""
    base = F.filter(judged, lambda x: x["kind"] < len(KINDS))
    extra = F.filter(judged, lambda x: (x["kind"] == len(KINDS)) & x["live"] & ~F.exists(base, lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"])))
    return F.array_sort(F.concat(base, extra))


def _found(docs: DataFrame, columns: list, owner: str, repository: str) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return settle(docs.select(*columns, F.col(owner).alias("owner"), F.col(repository).alias("repository"), candidates(text).alias("spans"), F.monotonically_increasing_id().alias("row")), "secrets")


def scan(docs: DataFrame, owner: str = "source", repository: str = "doc_id", max_owners: int = 2) -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_example.

    n_live: accepted spans judged live; n_example: spans held by more than `max_owners` owners.
    Null texts are empty: no spans, the digest of the empty string. Kinds may overlap each other.
    Repeated rows are scanned each and count once per owner and repository. A null owner is one owner."""
    found = _found(docs, [F.col("doc_id").cast("long").alias("doc_id")], owner, repository)
    joined = found.join(judged_spans(found, max_owners), "row", "left")
    spans = _accepted(F.coalesce("judged", F.array().cast("array<struct<start:int,kind:int,end:int,live:boolean,n_owners:bigint,n_repositories:bigint>>")))
    out = joined.select("doc_id", "spans", spans.alias("kept"))
    base = F.filter("spans", lambda x: x["kind"] < len(KINDS))
    of_kind = lambda k: lambda x: x["kind"] == k
    counts = [F.size(F.filter("spans", of_kind(k))).cast("long").alias(f"n_{name}") for k, (name, *_) in enumerate(KINDS)]
    return out.select(
        "doc_id", *counts, F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("kept")).alias("spans"),
        F.size(F.filter("kept", lambda x: x["live"])).cast("long").alias("n_live"),
        F.size(F.filter("kept", lambda x: x["n_owners"] > max_owners)).cast("long").alias("n_example"),
    )


def mask(docs: DataFrame, owner: str = "source", repository: str = "doc_id", max_owners: int = 2) -> DataFrame:
    """The documents with every live span replaced by a mask; n_chars follows where it exists. Base spans of few
    owners are live from their least length on, unless the whole value is a placeholder.

    Only documents that may hold a secret are written and joined; the others pass unchanged."""
    suspect = F.coalesce(F.col("text").rlike(GUARD), F.lit(False))
    names = docs.columns
    held = [F.struct(*(F.col(c) for c in names)).alias("given")]
    found = _found(docs.where(suspect), held, owner, repository)
    live = judged_spans(found, max_owners, short=True).select("row", F.filter("judged", lambda x: x["live"]).alias("live")).where(F.size("live") > 0)
    text = F.col("given.text")

    def step(acc, x):
        part = F.substring(text, acc["at"] + 1, x["start"] - acc["at"])
        fresh = F.struct(F.concat(acc["out"], part, F.lit(MASK)).alias("out"), x["end"].alias("at"))
        same = F.struct(acc["out"].alias("out"), F.greatest(acc["at"], x["end"]).alias("at"))
        return F.when(x["start"] >= acc["at"], fresh).otherwise(same)

    done = F.aggregate("live", F.struct(F.lit("").alias("out"), F.lit(0).alias("at")), step, lambda a: F.concat(a["out"], F.substring(text, a["at"] + 1, F.length(text))))
    masked = found.join(live, "row", "left").select("given", F.when(F.col("live").isNull(), text).otherwise(done).alias("new"))
    out = [F.col("new").alias(c) if c == "text" else F.length("new").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(f"given.`{c}`").alias(c) for c in names]
    return docs.where(~suspect).unionByName(masked.select(*out))
