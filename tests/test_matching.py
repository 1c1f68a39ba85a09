import itertools
import random

import pytest
from pyspark.sql import functions as F

from groupmatch.functions import membership
from groupmatch.model import MatchOptions, MembershipRule, SocialGraph
from groupmatch.model import pattern as P
from groupmatch.operators import baselines, explore, paths, simulate
from groupmatch.operators.store import PathStore


def graph(spark, labels, edges, scores=None):
    v = spark.createDataFrame([(i, [x], 1.0) for i, x in labels.items()], "id long, labels array<string>, influence double")
    rows = [(a, b, *(scores or {}).get((a, b), (1.0, 1.0))) for a, b in edges]
    return SocialGraph(v, spark.createDataFrame(rows, "src long, dst long, trust double, intimacy double"))


def groups(r):
    out = {}
    for x in r.members().collect():
        out.setdefault(x.leader, {}).setdefault(x.node, set()).add(x.v)
    return out


def test_membership(spark):
    df = spark.createDataFrame([(0.5, 1.0), (0.45, 0.9), (0.44, 0.88), (0.9, 1.0), (None, None)], "v double, degree double")
    rule = MembershipRule()
    for r in df.select("v", "degree", membership.ratio(F.col("v"), 0.5).alias("d"), membership.passes(F.col("v"), 0.5, rule).alias("p")).collect():
        assert r.d == r.degree and r.p == (r.v is not None and r.v >= 0.45)
    assert df.limit(1).select(membership.ratio(F.lit(0.0), 0.0)).first()[0] == 1.0


SHARED = ({1: "PM", 2: "PM", 3: "BA", 4: "SD", 5: "SD", 6: "ST", 7: "GD", 8: "GD"}, [(1, 4), (1, 5), (2, 4), (2, 5), (3, 7), (7, 4), (7, 8), (8, 5), (4, 6), (5, 6)])


@pytest.mark.parametrize("bound, sd", [(1, None), (2, {4}), (3, {4, 5})])
def test_shared_members(spark, bound, sd):
    g = graph(spark, *SHARED)
    p = P.pattern("f1", {x: x for x in ("PM", "BA", "SD", "ST")}, [("PM", "SD", 1), ("BA", "SD", bound), ("SD", "ST", 1)])
    want = {} if sd is None else {k: {"PM": {k}, "BA": {3}, "SD": sd, "ST": {6}} for k in (1, 2)}
    for s in ("plain", "combined"):
        assert groups(explore.match(g, p, s)) == want


def test_twin_cover_has_no_exact_match(spark):
    labels = dict(zip(range(1, 10), "ABBCCDDEE"))
    g = graph(spark, labels, [(1, 2), (1, 3), (1, 4), (1, 5), (2, 6), (2, 8), (3, 7), (3, 9), (4, 6), (4, 9), (5, 7), (5, 8)])
    p = P.pattern("f2", {x: x for x in "ABCDE"}, [("A", "B", 1), ("A", "C", 1), ("B", "D", 1), ("C", "D", 1), ("B", "E", 1), ("C", "E", 1)])
    r = explore.match(g, p)
    assert groups(r) == {1: {"A": {1}, "B": {2, 3}, "C": {4, 5}, "D": {6, 7}, "E": {8, 9}}} and r.links().count() == 12
    assert baselines.edge_join(g, p).count() == 0


def test_cascade(spark):
    labels = {1: "A", 11: "A", 2: "B", 3: "B", 4: "C", 5: "C", 6: "E", 7: "E", 8: "D"}
    g = graph(spark, labels, [(1, 2), (1, 3), (11, 3), (2, 4), (3, 5), (2, 6), (3, 7), (4, 8)])
    p = P.pattern("f3", {x: x for x in "ABCED"}, [("A", "B", 1), ("B", "C", 1), ("B", "E", 1), ("C", "D", 1)])
    assert groups(explore.match(g, p)) == {1: {"A": {1}, "B": {2}, "C": {4}, "E": {6}, "D": {8}}}


def test_far_source(spark):
    labels = {1: "PM", 2: "SD", 3: "ST", 4: "GD", 5: "BA", 6: "BA", 7: "GD", 8: "SD"}
    g = graph(spark, labels, [(1, 2), (2, 3), (4, 2), (5, 4), (6, 7), (7, 8), (8, 3)])
    p = P.pattern("f5", {x: x for x in ("PM", "BA", "GD", "SD", "ST")}, [("PM", "SD", 1), ("BA", "GD", 1), ("GD", "SD", 1), ("SD", "ST", 1)])
    for opt in (MatchOptions(), MatchOptions(reverse_chain=False)):
        assert groups(explore.match(g, p, "combined", opt)) == {1: {"PM": {1}, "BA": {5}, "GD": {4}, "SD": {2}, "ST": {3}}}


def test_path_choice(spark):
    scores = {(1, 3): (0.9, 0.7), (3, 2): (0.9, 0.6), (1, 4): (0.75, 0.75), (4, 2): (0.8, 0.8)}
    g = graph(spark, {1: "S", 2: "T", 3: "X", 4: "X"}, list(scores), scores)
    from groupmatch.model import PatternEdge

    e = PatternEdge(0, "S", "T", 2, 0.8, 0.4, None, None)
    at = lambda v: spark.createDataFrame([(v,)], "at long")
    best = lambda opt, e=e: [r.path for r in paths.match_edge(at(1), g.scored_edges(), e, at(2), opt).collect()]
    assert best(MatchOptions()) == [[1, 3, 2]]
    assert best(MatchOptions(choose_first=True, eager_bounds=False)) == []
    low = PatternEdge(0, "S", "T", 2, 0.4, 0.4, None, None)
    assert best(MatchOptions(), low) == best(MatchOptions(choose_first=True, eager_bounds=False), low) == [[1, 4, 2]]


def test_against_brute_force(spark):
    rng = random.Random(5)
    labels = {i: rng.choice("ABC") for i in range(14)}
    edges = sorted({(rng.randrange(14), rng.randrange(14)) for _ in range(40)} - {(i, i) for i in range(14)})
    scores = {e: (round(rng.random(), 2), round(rng.random(), 2)) for e in edges}
    g = graph(spark, labels, edges, scores)
    p = P.pattern("b", {x: x for x in "ABC"}, [("A", "B", 2), ("A", "C", 1), ("B", "C", 2)], 0.3)

    def linked(e, a, b):
        for k in range(e.max_hops):
            for mid in itertools.permutations(range(14), k):
                way = (a, *mid, b)
                hops = list(zip(way, way[1:]))
                if len(set(way)) == len(way) and all(h in scores for h in hops):
                    t = r = 1.0
                    for h in hops:
                        t, r = t * scores[h][0], r * scores[h][1]
                    if t >= 0.9 * 0.3 and r >= 0.9 * 0.3:
                        return True
        return False

    ok = {(e.no, a, b) for e in p.edges for a in range(14) for b in range(14) if labels[a] == e.src and labels[b] == e.dst and a != b and linked(e, a, b)}
    want = {}
    for leader in (i for i, x in labels.items() if x == "A"):
        s = {x: {i for i, y in labels.items() if y == x} for x in "ABC"} | {"A": {leader}}
        while True:
            new = {u: {v for v in vs if all(any((e.no, v, w) in ok for w in s[e.dst]) for e in p.out_edges(u)) and all(any((e.no, w, v) in ok for w in s[e.src]) for e in p.in_edges(u))} for u, vs in s.items()}
            if new == s:
                break
            s = new
        if all(s.values()):
            want[leader] = s
    for strategy in ("plain", "reverse", "cached", "combined", "local"):
        assert groups(explore.match(g, p, strategy)) == want, strategy
    held = {(x.node, x.v) for x in explore.match(g, p).members().select("node", "v").distinct().collect()}
    assert held <= {(x.node, x.v) for x in simulate.dual(g, p, "constrained").collect()} <= {(x.node, x.v) for x in simulate.child(g, p, "constrained").collect()}
    assert {x.leader for x in baselines.edge_join(g, p).collect()} <= set(want)


def test_store_expands_each_start_once(spark):
    # 2 reaches no SD: an answer without paths, which counts as answered.
    g = graph(spark, {1: "PM", 2: "PM", 3: "SD", 4: "ST"}, [(1, 3), (3, 4), (2, 1)])
    p = P.pattern("chain", {x: x for x in ("PM", "SD", "ST")}, [("PM", "SD", 1), ("SD", "ST", 1)])
    wide = P.pattern("wide", {x: x for x in ("PM", "SD", "ST")}, [("PM", "SD", 2), ("SD", "ST", 1)])
    kept = PathStore(spark)
    assert groups(explore.match(g, p, store=kept)) == groups(explore.match(g, p)) == {1: {"PM": {1}, "SD": {3}, "ST": {4}}}
    assert groups(explore.match(g, wide, store=kept)) == groups(explore.match(g, wide))
    # Requests of (edge, starts, expanded): a longer bound is another edge, the second edge is shared.
    assert [x[1:4] for x in kept.log] == [(0, 2, 2), (1, 1, 1), (0, 2, 2), (1, 1, 0)]
    assert sorted(r.empty for r in kept.empty_starts().collect()) == [0, 0, 1]
    with pytest.raises(ValueError):
        explore.match(g, p, "plain", store=kept)


TWO = P.pattern("two", {x: x for x in ("PM", "BA", "SD", "ST")}, [("PM", "SD", 2), ("BA", "SD", 3), ("SD", "ST", 2), ("PM", "ST", 3)], 0.3)
FAR = P.pattern("far", {x: x for x in ("PM", "BA", "GD", "SD")}, [("PM", "SD", 2), ("BA", "GD", 2), ("GD", "SD", 2), ("BA", "SD", 2)], 0.2)


def random_graph(spark, seed=11, n=30, m=130):
    rng = random.Random(seed)
    labels = {i: rng.choice(("PM", "BA", "SD", "ST", "GD")) for i in range(n)}
    edges = sorted({(a, b) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if a != b})
    return graph(spark, labels, edges, {e: (0.6 + 0.4 * rng.random(), 0.6 + 0.4 * rng.random()) for e in edges})


def test_plain_makes_no_pairs_of_leaders_and_candidates(spark, monkeypatch):
    g = random_graph(spark)
    want = {p.name: groups(explore.match(g, p)) for p in (TWO, FAR)}
    assert all(want.values())
    frame = type(g.vertices)
    monkeypatch.setattr(frame, "crossJoin", lambda *_: pytest.fail("all pairs were made"))
    for p in (TWO, FAR):
        assert groups(explore.match(g, p, "plain")) == want[p.name]
    with pytest.raises(ValueError):
        explore.match(g, TWO, "plain", MatchOptions(max_rows=3))


@pytest.fixture(scope="module")
def two(spark):
    g = random_graph(spark)
    g = SocialGraph(*(x.coalesce(1).localCheckpoint() for x in (g.vertices, g.edges)))
    return g, groups(explore.match(g, TWO))


def test_per_leader_baseline_makes_no_pairs(spark, two, monkeypatch):
    g, _ = two
    want = sorted(map(tuple, baselines.edge_join(g, TWO).collect()))
    monkeypatch.setattr(type(g.vertices), "crossJoin", lambda *_: pytest.fail("all pairs were made"))
    assert sorted(map(tuple, baselines.edge_join(g, TWO, per_leader=True).collect())) == want and want


def test_requests_of_plain_are_counted_without_making_them(two, monkeypatch):
    g, _ = two
    n = {x[0]: x[1] for x in g.vertices.groupBy(F.col("labels")[0]).count().collect()}
    monkeypatch.setattr(type(g.vertices), "crossJoin", lambda *_: pytest.fail("all pairs were made"))
    assert explore.match(g, TWO, "plain", count=True).work["requests"][1] == ("forward", n["PM"] * n["BA"])


def test_sizes_of_exact_groups_make_no_pairs(spark, monkeypatch):
    import __spark_entry__ as entry
    from groupmatch import queries

    g = graph(spark, {1: "AUTOMOBILE", 2: "BUILDING", 3: "MACHINERY", 4: "HOUSEHOLD", 5: "BUILDING"}, [(1, 3), (2, 3), (5, 3), (3, 4)])
    monkeypatch.setattr(queries, "_graph", lambda *_: g)
    monkeypatch.setattr(type(g.vertices), "crossJoin", lambda *_: pytest.fail("all pairs were made"))
    # PM 1, BA 2 and 5, SD 3, ST 4; PM->SD, BA->SD twice, SD->ST, PM->ST by way of 3.
    assert [tuple(x) for x in entry.queries()["exact_sizes_p2"](spark, "").collect()] == [(1, 5.0, 5.0)]


def no_balls(monkeypatch):
    from groupmatch.operators import locality

    monkeypatch.setattr(locality, "ball", lambda *_, **__: pytest.fail("a ball of data edges was made for each leader"))


def test_local_explores_what_the_pattern_reaches(two, monkeypatch):
    g, want = two
    no_balls(monkeypatch)
    assert groups(explore.match(g, TWO, "local")) == want


def test_local_with_one_source(two, monkeypatch):
    g, _ = two
    p = P.pattern("one", {x: x for x in ("PM", "BA", "SD")}, [("PM", "BA", 2), ("PM", "SD", 3), ("BA", "SD", 2)], 0.3)
    want = groups(explore.match(g, p))
    no_balls(monkeypatch)
    assert groups(explore.match(g, p, "local")) == want and want


def test_strong_simulation_follows_links(two, monkeypatch):
    g, want = two
    no_balls(monkeypatch)
    out = {}
    for x in simulate.strong(g, TWO, "constrained").collect():
        out.setdefault(x.leader, {}).setdefault(x.node, set()).add(x.v)
    assert out == want


def test_touched_leaders_without_balls(spark, monkeypatch):
    from groupmatch import streaming

    # A chain; only the leaders within the pattern's diameter of an end of the changed edge are touched.
    g = graph(spark, {i: "PM" if i % 2 else "SD" for i in range(12)}, [(i, i + 1) for i in range(11)])
    p = P.pattern("pair", {x: x for x in ("PM", "SD")}, [("PM", "SD", 2)])
    no_balls(monkeypatch)
    changed = g.edges.where("src = 5")
    assert {x.leader for x in streaming.touched_leaders(g, p, changed).collect()} == {3, 5, 7}


def test_minima_of_one_shape_are_matched_together(spark, monkeypatch):
    from groupmatch.operators import sweep

    # 1-2 passes both minima, 3-4 the lower one only.
    g = graph(spark, {1: "PM", 2: "SD", 3: "PM", 4: "SD"}, [(1, 2), (3, 4)], {(1, 2): (0.9, 0.9), (3, 4): (0.4, 0.9)})
    shape = lambda m: P.pattern("pair", {"PM": "PM", "SD": "SD"}, [("PM", "SD", 1)], m)
    got = sweep.members(g, {"low": shape(0.3), "high": shape(0.8)}).where("node = 'PM'").select("setting", "v").collect()
    assert sorted(map(tuple, got)) == [("high", 1), ("low", 1), ("low", 3)]


def test_requests_are_counted_without_making_groups(two, monkeypatch):
    from groupmatch.operators import prune

    g, _ = two
    want = {name: explore.match(g, TWO, name, count=True).work["requests"] for name in ("plain", "combined")}
    monkeypatch.setattr(prune, "cascade", lambda *_, **__: pytest.fail("groups were made"))
    assert explore.requests(g, TWO, ("plain", "combined")) == want and all(map(len, want.values()))


def test_edges_below_every_minimum_are_left_out_early(spark):
    from groupmatch.operators import paths

    g = graph(spark, {1: "PM", 2: "SD", 3: "SD", 4: "GD"}, [(1, 2), (1, 3), (1, 4)], {(1, 2): (0.9, 0.9), (1, 3): (0.2, 0.9), (1, 4): (0.9, 0.9)})
    ends = lambda p, opt=MatchOptions(): sorted(x.dst for x in paths.useful_edges(g, p, opt).collect())
    pair = lambda hops, m: P.pattern("pair", {"PM": "PM", "SD": "SD"}, [("PM", "SD", hops)], m)
    assert ends(pair(2, 0.5)) == [2, 4] and ends(pair(1, 0.5)) == [2]
    # Without minima, or where a path is chosen before it is tested, every score counts.
    assert ends(pair(2, None)) == [2, 3, 4] and ends(pair(2, 0.5), MatchOptions(choose_first=True)) == [2, 3, 4]


def test_local_hands_arrow_to_each_leader(two, monkeypatch):
    from pyspark.sql.pandas.group_ops import PandasCogroupedOps

    g, want = two
    monkeypatch.setattr(PandasCogroupedOps, "applyInPandas", lambda *_: pytest.fail("pandas frames were made for each leader"))
    assert groups(explore.match(g, TWO, "local")) == want


def test_members_need_no_paths(two, monkeypatch):
    from groupmatch.operators import paths

    g, want = two
    free = TWO.with_minimum(None)
    every = groups(explore.match(g, free))
    monkeypatch.setattr(paths, "best", lambda *_: pytest.fail("paths were chosen"))
    assert groups(explore.match(g, TWO, ends_only=True)) == want
    monkeypatch.setattr(paths, "expand", lambda *_: pytest.fail("paths were made"))
    assert groups(explore.match(g, free, ends_only=True)) == every and every


@pytest.mark.parametrize("seed", [1, 2])
def test_influence_needs_two_ways_to_each_vertex(spark, monkeypatch, seed):
    from groupmatch.operators import paths

    rng = random.Random(seed)
    score = {i: None if i == 3 else round(rng.random(), 2) for i in range(12)}
    v = spark.createDataFrame([(i, ["A" if i % 3 else "B"], x) for i, x in score.items()], "id long, labels array<string>, influence double")
    edges = sorted({(rng.randrange(12), rng.randrange(12)) for _ in range(30)})
    g = SocialGraph(v, spark.createDataFrame([(a, b, 0.1, 0.1) for a, b in edges], "src long, dst long, trust double, intimacy double"))
    at = lambda x: v.where(F.array_contains("labels", x)).select(F.col("id").alias("at"))
    ready, opt = g.scored_edges().coalesce(1).localCheckpoint(), MatchOptions()
    for hops in (1, 2, 3):
        p = P.pattern("pair", {"A": "A", "B": "B"}, [("A", "B", hops)], 0.6).only("influence")
        e = p.edges[0]
        want = sorted(map(tuple, paths.match_edge(at("A"), ready, e, at("B"), opt).select("v", "w").collect()))
        with monkeypatch.context() as m:
            m.setattr(paths, "expand", lambda *_, **__: pytest.fail("paths were made"))
            for way, ends in (("out", ("A", "B")), ("in", ("B", "A"))):
                assert sorted(map(tuple, paths.reach(at(ends[0]), ready, e, at(ends[1]), opt, way).collect())) == want, (hops, way)
    assert want


def test_trees_need_no_rounds_by_leader(spark, monkeypatch):
    from groupmatch.operators import prune

    # A leads; C and E hang on B, D on C, X on A. 3 lacks an E and 9 an X.
    labels = {1: "A", 11: "A", 2: "B", 3: "B", 4: "C", 5: "C", 6: "E", 8: "D", 9: "A", 10: "X"}
    g = graph(spark, labels, [(1, 2), (1, 3), (11, 3), (9, 2), (2, 4), (3, 5), (2, 6), (4, 8), (5, 8), (10, 1), (10, 11)])
    p = P.pattern("tree", {x: x for x in "ABCEDX"}, [("A", "B", 1), ("B", "C", 1), ("B", "E", 1), ("C", "D", 1), ("X", "B", 2)], None)
    want = groups(explore.match(g, p, "plain"))
    rounds = prune.cascade
    monkeypatch.setattr(prune, "cascade", lambda links, p, keys, *a, **b: pytest.fail("rounds by leader") if keys else rounds(links, p, keys, *a, **b))
    r = explore.match(g, p)
    assert groups(r) == want == {1: {"A": {1}, "B": {2}, "C": {4}, "E": {6}, "D": {8}, "X": {10}}, 9: {"A": {9}, "B": {2}, "C": {4}, "E": {6}, "D": {8}, "X": {10}}}
    assert sorted((x.leader, x.edge_no, x.v, x.w) for x in r.links().collect() if x.leader == 1) == [(1, 0, 1, 2), (1, 1, 2, 4), (1, 2, 2, 6), (1, 3, 4, 8), (1, 4, 10, 2)]


def test_minima_together_keep_no_paths(spark, monkeypatch):
    from groupmatch.operators import paths, sweep

    g = graph(spark, {1: "PM", 2: "SD", 3: "PM", 4: "SD"}, [(1, 2), (3, 4)], {(1, 2): (0.9, 0.9), (3, 4): (0.4, 0.9)})
    shape = lambda m: P.pattern("pair", {"PM": "PM", "SD": "SD"}, [("PM", "SD", 2)], m)
    monkeypatch.setattr(paths, "best", lambda *_: pytest.fail("paths were chosen"))
    got = sweep.members(g, {"low": shape(0.3), "high": shape(0.8)}).select("setting", "leader", "node", "v").collect()
    assert sorted(map(tuple, got)) == [("high", 1, "PM", 1), ("high", 1, "SD", 2), ("low", 1, "PM", 1), ("low", 1, "SD", 2), ("low", 3, "PM", 3), ("low", 3, "SD", 4)]
