"""Bounded path search and the choice of the best path of each pair."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from groupmatch.functions import aggregate as agg
from groupmatch.functions.membership import least_value, passes
from groupmatch.model import GroupPattern, MatchOptions, PatternEdge, SocialGraph

from .candidates import fits

_SLACK = 1e-9


def _floor(e: PatternEdge, name: str) -> float | None:
    minimum = e.minima().get(name)
    return None if minimum is None else least_value(minimum, e.rule)


def _floors(e: PatternEdge, opt: MatchOptions) -> dict[str, float]:
    """The least trust and intimacy of any data edge on an admissible path, where that follows from the edge's minima.

    Chosen before it is tested, a path may not leave early: it would let another path of its pair pass."""
    if not opt.eager_bounds or opt.edge_mode != "constrained" or opt.choose_first or opt.fold not in ("product", "min", "product_decay"):
        return {}
    floors = {k: _floor(e, k) for k in ("trust", "intimacy")}
    return {k: v for k, v in floors.items() if v is not None}


def useful_edges(g: SocialGraph, p: GroupPattern, opt: MatchOptions) -> DataFrame:
    """The scored edges that paths of the pattern's edges can hold: those above the smallest least values of all pattern
    edges and, where every path is one hop, those between candidates."""
    each = [_floors(e, opt) for e in p.edges]
    least = {k: min(f[k] for f in each) for k in ("trust", "intimacy") if each and all(k in f for f in each)}
    one_hop = opt.last_hop_filter and (opt.edge_mode == "edge" or all(e.max_hops == 1 for e in p.edges))
    ends = reduce(Column.__or__, map(fits, p.nodes)) if one_hop else None
    return g.scored_edges(least, ends)


def expand(starts: DataFrame, edges: DataFrame, e: PatternEdge, targets: DataFrame, opt: MatchOptions, direction: str = "out") -> DataFrame:
    """Paths of 1..max_hops hops between `starts` (keys..., at) and `targets` (at).

    One equi-join per hop; a path's end is a column beside it. `direction='in'` walks inverse
    edges and prepends, so that a path reads the same either way. With eager bounds an edge or prefix whose products
    already fall below the least passing value leaves at once (scores are at most 1)."""
    keys = [c for c in starts.columns if c != "at"]
    hops = 1 if opt.edge_mode == "edge" else e.max_hops
    floors = _floors(e, opt)
    out = direction == "out"
    near, far = ("src", "dst") if out else ("dst", "src")
    ready = edges
    for k, low in floors.items():
        ready = ready.where(F.col(k) >= F.lit(low))
    step = ready.select(F.col(near).alias("n_near"), F.col(far).alias("n_far"), F.col("trust").alias("n_trust"), F.col("intimacy").alias("n_intimacy"), F.col(f"{near}_influence").alias("n_first"), F.col(f"{far}_influence").alias("n_influence"))
    ends = targets.select(F.col("at").alias("end")).distinct()
    frontier, levels = None, []

    def glued(old: str, new: Column) -> Column:
        return F.concat(F.col(old), F.array(new)) if out else F.concat(F.array(new), F.col(old))

    for h in range(1, hops + 1):
        last = h == hops
        hop = step.join(ends, step.n_far == ends.end, "left_semi") if last and opt.last_hop_filter else step
        if frontier is None:
            pair = [F.col("n_near"), F.col("n_far")] if out else [F.col("n_far"), F.col("n_near")]
            scores = [F.col("n_first"), F.col("n_influence")] if out else [F.col("n_influence"), F.col("n_first")]
            frontier = starts.join(hop, starts["at"] == F.col("n_near")).select(*keys, F.col("n_far").alias("at"), F.array(*pair).alias("path"), F.array("n_trust").alias("ts"), F.array("n_intimacy").alias("rs"), F.array(*scores).alias("ps"), F.col("n_trust").alias("pt"), F.col("n_intimacy").alias("pr"))
        else:
            joined = frontier.join(hop, frontier["at"] == F.col("n_near"))
            if opt.path_mode == "simple":
                joined = joined.where(~F.array_contains("path", F.col("n_far")))
            frontier = joined.select(*keys, F.col("n_far").alias("at"), glued("path", F.col("n_far")).alias("path"), glued("ts", F.col("n_trust")).alias("ts"), glued("rs", F.col("n_intimacy")).alias("rs"), glued("ps", F.col("n_influence")).alias("ps"), (F.col("pt") * F.col("n_trust")).alias("pt"), (F.col("pr") * F.col("n_intimacy")).alias("pr"))
        if floors and opt.fold != "min":
            for k, c in (("trust", "pt"), ("intimacy", "pr")):
                if k in floors:
                    frontier = frontier.where(F.col(c) >= F.lit(floors[k] - _SLACK))
        levels.append(frontier)
    found = reduce(DataFrame.unionByName, levels)
    found = found.join(ends, found["at"] == ends["end"], "left_semi")
    return _aggregated(found, keys, e, opt)


def _aggregated(found: DataFrame, keys: list[str], e: PatternEdge, opt: MatchOptions) -> DataFrame:
    """Paths (keys..., v, w, path, hops, trust, intimacy, influence, worst)."""
    rows = found.select(
        *keys, F.element_at("path", 1).alias("v"), F.element_at("path", -1).alias("w"), "path", (F.size("path") - 1).alias("hops"),
        agg.fold(opt.fold, F.col("ts"), opt.decay).alias("trust"), agg.fold(opt.fold, F.col("rs"), opt.decay).alias("intimacy"),
        agg.influence(F.col("ps"), opt.influence_span).alias("influence"),
    )
    named = list(e.minima()) or ["trust", "intimacy", "influence"]
    worst = F.least(*named) if len(named) > 1 else F.col(named[0])
    rows = rows.withColumn("worst", worst)
    return rows if opt.choose_first or opt.edge_mode != "constrained" else admissible(rows, e)


def admissible(paths: DataFrame, e: PatternEdge) -> DataFrame:
    """Paths whose aggregates pass every constraint of the edge."""
    for k, minimum in e.minima().items():
        paths = paths.where(passes(F.col(k), minimum, e.rule))
    return paths


_PATH = ["path", "hops", "trust", "intimacy", "influence", "worst"]


def best(paths: DataFrame) -> DataFrame:
    """One path for each pair: the largest worst aggregate, then fewer hops, then the smaller path."""
    keys = [c for c in paths.columns if c not in _PATH]
    chosen = F.min_by(F.struct(*_PATH), F.struct((-F.col("worst")).alias("a"), F.col("hops").alias("b"), F.col("path").alias("c")))
    return paths.groupBy(*keys).agg(chosen.alias("p")).select(*keys, *(F.col(f"p.{c}").alias(c) for c in _PATH))


def match_edge(starts: DataFrame, edges: DataFrame, e: PatternEdge, targets: DataFrame, opt: MatchOptions, direction: str = "out") -> DataFrame:
    """The edge relation of one pattern edge: (keys..., v, w, best path)."""
    chosen = best(expand(starts, edges, e, targets, opt, direction))
    return admissible(chosen, e) if opt.choose_first and opt.edge_mode == "constrained" else chosen


def reach(starts: DataFrame, edges: DataFrame, e: PatternEdge, targets: DataFrame, opt: MatchOptions, direction: str = "out") -> DataFrame:
    """(keys..., v, w): the pairs that `match_edge` has a path for, without the paths; pairs of one hop may repeat where data edges do.

    Without constraints no path is made: where a walk leads from one vertex to another within the bound, a simple path does,
    so each hop only needs the ends reached so far."""
    keys = [c for c in starts.columns if c != "at"]
    constrained = opt.edge_mode == "constrained" and bool(e.minima())
    hops = 1 if opt.edge_mode == "edge" else e.max_hops
    if constrained and opt.choose_first:
        return match_edge(starts, edges, e, targets, opt, direction).select(*keys, "v", "w")
    if constrained and not keys and list(e.minima()) == ["influence"] and hops <= 3 and opt.influence_span == "all" and opt.path_mode == "simple":
        return _reach_by_influence(*((starts, targets) if direction == "out" else (targets, starts)), edges, e, hops)
    if constrained:
        found = expand(starts, edges, e, targets, opt, direction).select(*keys, "v", "w")
        return found if hops == 1 else found.distinct()
    near, far, first, last = ("src", "dst", "v", "w") if direction == "out" else ("dst", "src", "w", "v")
    step = edges.select(F.col(near).alias("n_near"), F.col(far).alias("n_far"))
    ends = targets.select(F.col("at").alias("end")).distinct()
    front, levels = starts.withColumn("own", F.col("at")), []
    for h in range(1, hops + 1):
        hop = step.join(ends, step.n_far == ends.end, "left_semi") if h == hops and opt.last_hop_filter else step
        front = front.join(hop, front["at"] == F.col("n_near")).select(*keys, "own", F.col("n_far").alias("at"))
        if opt.path_mode == "simple":
            front = front.where("own <> at")
        front = front if hops == 1 else front.distinct()
        levels.append(front)
    found = reduce(DataFrame.unionByName, levels)
    found = found.join(ends, found["at"] == ends["end"], "left_semi").select(*keys, F.col("own").alias(first), F.col("at").alias(last))
    return (found if hops == 1 else found.distinct()).select(*keys, "v", "w")


def _reach_by_influence(starts: DataFrame, targets: DataFrame, edges: DataFrame, e: PatternEdge, hops: int) -> DataFrame:
    """(v, w): `reach` for at most three hops where the mean influence of all vertices is the only constraint.

    Of the ways of two hops from one vertex to another the two of the largest sums do: a third hop goes back to the inner
    vertex of one of them at most. Sums grow from left to right, as those of whole paths, so a way that has the larger
    sum keeps it."""
    step = edges.groupBy(F.col("src").alias("near"), F.col("dst").alias("far")).agg(F.max("src_influence").alias("first"), F.max("dst_influence").alias("more"))
    step = step.where("first IS NOT NULL AND more IS NOT NULL")
    ends = targets.select(F.col("at").alias("far")).distinct()
    begun, levels = starts.select(F.col("at").alias("near")).distinct(), []

    def arrived(front: DataFrame, vertices: int) -> None:
        mean = F.col("sum") / F.lit(vertices)
        levels.append(front.where(passes(mean, e.min_influence, e.rule)).select("v", F.col("at").alias("w")))

    last = step.join(ends, "far", "left_semi")
    front = (last if hops == 1 else step).join(begun, "near", "left_semi").select(F.col("near").alias("v"), F.col("far").alias("at"), (F.lit(0.0) + F.col("first") + F.col("more")).alias("sum"))
    arrived(front, 2)
    if hops > 1:
        front = front.join((last if hops == 2 else step).select(F.col("near").alias("at"), "far", "more"), "at").where("far <> v")
        front = front.select("v", F.col("far").alias("at"), F.col("at").alias("inner"), (F.col("sum") + F.col("more")).alias("sum"))
        arrived(front, 3)
    if hops > 2:
        order = F.row_number().over(Window.partitionBy("v", "at").orderBy(F.desc("sum"), "inner"))
        front = front.withColumn("rank", order).where("rank <= 2")
        front = front.join(last.select(F.col("near").alias("at"), "far", "more"), "at").where("far <> v AND far <> inner")
        arrived(front.select("v", F.col("far").alias("at"), (F.col("sum") + F.col("more")).alias("sum")), 4)
    return reduce(DataFrame.unionByName, levels).join(ends.select(F.col("far").alias("w")), "w", "left_semi").select("v", "w").distinct()


def level_counts(starts: DataFrame, edges: DataFrame, e: PatternEdge, targets: DataFrame, opt: MatchOptions) -> DataFrame:
    """(hops, paths): paths that end in a target, by length."""
    return expand(starts, edges, e, targets, opt).groupBy("hops").agg(F.count("*").alias("paths"))
