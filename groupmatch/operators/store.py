"""Matched edges kept between matches: each start of an edge is expanded once, also if nothing was found."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from groupmatch.durable import settle_counted
from groupmatch.model import MatchOptions, PatternEdge, PatternNode

from . import paths


def fingerprint(e: PatternEdge, far: PatternNode, opt: MatchOptions, direction: str) -> str:
    """What an answer depends on besides its start: the edge's bound, minima and rule, the role at the other
    end, and the switches that change paths. Names and numbers of a pattern don't count."""
    for rule in (e.rule, far.rule):
        if rule is not None and any(map(callable, rule.params)):
            raise ValueError("a rule with a Python function has no lasting fingerprint")
    what = {
        "hops": e.max_hops, "minima": e.minima(), "rule": e.rule and asdict(e.rule),
        "labels": sorted(far.labels), "least": far.min_influence, "far_rule": far.rule and asdict(far.rule), "direction": direction,
        "switches": [opt.path_mode, opt.fold, opt.decay, opt.influence_span, opt.choose_first, opt.edge_mode],
    }
    return hashlib.sha256(json.dumps(what, sort_keys=True).encode()).hexdigest()


@dataclass
class PathStore:
    """Answers of one graph, as written tables. Starts are noted apart from paths, so that a start without any
    path counts as answered. `log` has a row for each request: (pattern, edge_no, requested, expanded, found)."""

    spark: SparkSession
    asked: dict[str, list[DataFrame]] = field(default_factory=dict)
    found: dict[str, list[DataFrame]] = field(default_factory=dict)
    ends: dict[str, str] = field(default_factory=dict)
    log: list[tuple] = field(default_factory=list)

    def answer(self, pattern: str, starts: DataFrame, edges: DataFrame, e: PatternEdge, far: PatternNode, targets: DataFrame, opt: MatchOptions, direction: str = "out") -> DataFrame:
        """The edge relation of `starts` (at): kept answers, and new ones for the starts that have none."""
        key = fingerprint(e, far, opt, direction)
        starts, requested = settle_counted(starts.select("at").distinct(), "starts")
        misses, expanded = starts, requested
        if self.asked.get(key):
            known = reduce(DataFrame.unionByName, self.asked[key])
            misses, expanded = settle_counted(starts.join(known, "at", "left_anti"), "misses")
        count = 0
        if expanded or key not in self.found:
            fresh, count = settle_counted(paths.match_edge(misses, edges, e, targets, opt, direction), "answers")
            # Paths first: a start must not count as answered before its paths are kept.
            self.found.setdefault(key, []).append(fresh)
            self.asked.setdefault(key, []).append(misses)
        self.log.append((pattern, e.no, requested, expanded, count))
        end = self.ends[key] = "v" if direction == "out" else "w"
        kept = reduce(DataFrame.unionByName, self.found[key])
        return kept.join(starts.select(F.col("at").alias(end)), end, "left_semi").select(*kept.columns)

    def requests(self) -> DataFrame:
        """(pattern, edge_no, requested, expanded, found) of every request so far."""
        return self.spark.createDataFrame(self.log, "pattern string, edge_no int, requested long, expanded long, found long")

    def empty_starts(self) -> DataFrame:
        """(fingerprint, empty): starts answered with no path, by edge."""
        out = []
        for key, asked in self.asked.items():
            ends = reduce(DataFrame.unionByName, self.found[key]).select(F.col(self.ends[key]).alias("at"))
            out.append(reduce(DataFrame.unionByName, asked).join(ends, "at", "left_anti").agg(F.count("*").alias("empty")).select(F.lit(key).alias("fingerprint"), "empty"))
        return reduce(DataFrame.unionByName, out)

    def forget(self, key: str | None = None) -> None:
        """Drop the answers of one fingerprint, or all; their files go once nothing reads them."""
        for kept in (self.asked, self.found):
            kept.pop(key, None) if key else kept.clear()
