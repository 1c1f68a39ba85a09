"""Group patterns: a small directed acyclic query graph with a leader, constraints and membership rules."""

from __future__ import annotations

import json
from collections import deque
from dataclasses import asdict, dataclass, field, replace


@dataclass(frozen=True)
class MembershipRule:
    """Turns a value and its minimum into a degree; `cut` is the least degree that passes."""

    kind: str = "ratio"
    cut: float = 0.9
    params: tuple = ()


RATIO = MembershipRule()


@dataclass(frozen=True)
class PatternNode:
    name: str
    labels: tuple[str, ...] = ()
    min_influence: float | None = None
    rule: MembershipRule | None = RATIO


@dataclass(frozen=True)
class PatternEdge:
    no: int
    src: str
    dst: str
    max_hops: int = 1
    min_trust: float | None = None
    min_intimacy: float | None = None
    min_influence: float | None = None
    rule: MembershipRule | None = RATIO

    @property
    def bit(self) -> int:
        return 1 << self.no

    def minima(self) -> dict[str, float]:
        """The constrained aggregates with their minima."""
        every = {"trust": self.min_trust, "intimacy": self.min_intimacy, "influence": self.min_influence}
        return {k: v for k, v in every.items() if v is not None}


@dataclass(frozen=True)
class MatchOptions:
    path_mode: str = "simple"  # or 'walk'
    fold: str = "product"  # 'product_decay', 'min', 'mean'
    decay: float = 0.5
    influence_span: str = "all"  # 'inner', 'no_source'
    choose_first: bool = False
    last_hop_filter: bool = True
    eager_bounds: bool = True
    global_reduce: bool = True
    reverse_chain: bool = True
    edge_mode: str = "constrained"  # 'edge', 'path'
    #: The reduction without leaders stops after a round that removes at most this share of the links.
    global_share: float = 0.1
    max_rounds: int | None = None
    #: Most pairs of leaders and candidates of a further source that strategy plain makes; None: any number.
    max_rows: int | None = None


@dataclass(frozen=True)
class GroupPattern:
    name: str
    leader: str
    nodes: tuple[PatternNode, ...]
    edges: tuple[PatternEdge, ...] = ()
    acyclic: bool = field(default=True)

    def __post_init__(self):
        self.validate()

    def node(self, name: str) -> PatternNode:
        return next(n for n in self.nodes if n.name == name)

    def index(self, name: str) -> int:
        return [n.name for n in self.nodes].index(name)

    def validate(self) -> None:
        names = [n.name for n in self.nodes]
        if len(set(names)) < len(names):
            raise ValueError("pattern node names repeat")
        if self.leader not in names:
            raise ValueError(f"the leader {self.leader} is not a pattern node")
        numbers = [e.no for e in self.edges]
        if len(set(numbers)) < len(numbers) or any(not 0 <= n < 63 for n in numbers):
            raise ValueError("edge numbers must differ and lie in 0..62")
        for e in self.edges:
            if e.src not in names or e.dst not in names:
                raise ValueError(f"edge {e.no} names an unknown node")
            if e.max_hops < 1:
                raise ValueError(f"edge {e.no} needs a hop bound of 1 or more")
        seen, todo = {self.leader}, deque([self.leader])
        while todo:
            u = todo.popleft()
            for e in self.edges:
                for a, b in ((e.src, e.dst), (e.dst, e.src)):
                    if a == u and b not in seen:
                        seen.add(b)
                        todo.append(b)
        if len(seen) < len(names):
            raise ValueError("the pattern is not connected")
        if self.acyclic:
            self.topological()
            if any(e.dst == self.leader for e in self.edges):
                raise ValueError("the leader has an incoming edge")

    def topological(self) -> list[str]:
        """Pattern nodes in topological order, the leader first."""
        waiting = {n.name: sum(e.dst == n.name for e in self.edges) for n in self.nodes}
        order: list[str] = []
        ready = [self.leader] if not waiting[self.leader] else []
        ready += [n.name for n in self.nodes if not waiting[n.name] and n.name != self.leader]
        while ready:
            u = ready.pop(0)
            order.append(u)
            for e in self.out_edges(u):
                waiting[e.dst] -= 1
                if not waiting[e.dst]:
                    ready.append(e.dst)
        if len(order) < len(self.nodes):
            raise ValueError("the pattern has a cycle")
        return order

    def out_edges(self, u: str) -> list[PatternEdge]:
        return [e for e in self.edges if e.src == u]

    def in_edges(self, u: str) -> list[PatternEdge]:
        return [e for e in self.edges if e.dst == u]

    def sources(self) -> list[str]:
        return [n.name for n in self.nodes if not self.in_edges(n.name)]

    def out_mask(self, u: str) -> int:
        return sum(e.bit for e in self.out_edges(u))

    def in_mask(self, u: str) -> int:
        return sum(e.bit for e in self.in_edges(u))

    def mask(self, u: str) -> int:
        return self.out_mask(u) | self.in_mask(u)

    def distances(self) -> dict[tuple[str, str], int]:
        """Undirected distances, each edge as long as its hop bound."""
        names = [n.name for n in self.nodes]
        d = {(a, b): 0 if a == b else 10**6 for a in names for b in names}
        for e in self.edges:
            for pair in ((e.src, e.dst), (e.dst, e.src)):
                d[pair] = min(d[pair], e.max_hops)
        for k in names:
            for a in names:
                for b in names:
                    d[a, b] = min(d[a, b], d[a, k] + d[k, b])
        return d

    def distance(self, a: str, b: str) -> int:
        return self.distances()[a, b]

    def diameter(self) -> int:
        return max(self.distances().values())

    def is_tree(self) -> bool:
        return len(self.edges) == len(self.nodes) - 1

    def hanging(self) -> list[tuple[PatternEdge, bool]]:
        """Edges to the outer nodes of trees that hang on the rest of the pattern, outermost first; True where the
        outer node is the edge's target. The leader is never an outer node, so of a tree all edges hang."""
        left, out = list(self.edges), []
        degree = lambda u: sum(u in (e.src, e.dst) for e in left)
        while found := next(((e, u == e.dst) for e in left for u in (e.dst, e.src) if u != self.leader and e.src != e.dst and degree(u) == 1), None):
            out.append(found)
            left.remove(found[0])
        return out

    def spanning_steps(self) -> list[tuple[PatternEdge, bool]]:
        """Edges that reach every node from the leader; True where an edge is followed forward."""
        seen, steps = {self.leader}, []
        while len(seen) < len(self.nodes):
            for e in self.edges:
                if (e.src in seen) != (e.dst in seen):
                    steps.append((e, e.src in seen))
                    seen |= {e.src, e.dst}
                    break
        return steps

    def with_minimum(self, minimum: float | None, cut: float | None = None, crisp: bool = False) -> GroupPattern:
        """The same shape with one minimum for all constraints."""
        rule = None if crisp else MembershipRule(cut=0.9 if cut is None else cut)
        nodes = tuple(replace(n, min_influence=minimum, rule=rule) for n in self.nodes)
        edges = tuple(replace(e, min_trust=minimum, min_intimacy=minimum, min_influence=minimum, rule=rule) for e in self.edges)
        return replace(self, nodes=nodes, edges=edges)

    def only(self, attribute: str) -> GroupPattern:
        """The ablation that keeps one constraint: 'node', 'trust', 'intimacy' or 'influence'."""
        nodes = tuple(n if attribute == "node" else replace(n, min_influence=None) for n in self.nodes)
        drop = [k for k in ("trust", "intimacy", "influence") if k != attribute]
        return replace(self, nodes=nodes, edges=tuple(replace(e, **{f"min_{k}": None for k in drop}) for e in self.edges))

    def with_hops(self, no: int, hops: int) -> GroupPattern:
        return replace(self, edges=tuple(replace(e, max_hops=hops) if e.no == no else e for e in self.edges))

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> GroupPattern:
        d = json.loads(text)

        def rule(x):
            return None if x is None else MembershipRule(x["kind"], x["cut"], tuple(x["params"]))

        nodes = tuple(PatternNode(n["name"], tuple(n["labels"]), n["min_influence"], rule(n["rule"])) for n in d["nodes"])
        edges = tuple(PatternEdge(**(e | {"rule": rule(e["rule"])})) for e in d["edges"])
        return cls(d["name"], d["leader"], nodes, edges, d["acyclic"])


def pattern(name: str, labels: dict[str, str | tuple], edges: list[tuple[str, str, int]], minimum: float | None = 0.5, leader: str | None = None, acyclic: bool = True) -> GroupPattern:
    """A pattern from a role -> label table and (from, to, hops) triples; the first role leads."""
    nodes = tuple(PatternNode(k, (v,) if isinstance(v, str) else tuple(v)) for k, v in labels.items())
    links = tuple(PatternEdge(i, a, b, h) for i, (a, b, h) in enumerate(edges))
    return GroupPattern(name, leader or next(iter(labels)), nodes, links, acyclic).with_minimum(minimum)


#: The market segments stand for professions.
_JOBS = {"PM": "AUTOMOBILE", "BA": "BUILDING", "SD": "MACHINERY", "ST": "HOUSEHOLD"}
_TWIN = {"A": "AUTOMOBILE", "B": "BUILDING", "C": "MACHINERY", "D": "HOUSEHOLD", "E": "FURNITURE"}
_TWINS = [("A", "B"), ("A", "C"), ("B", "D"), ("C", "D"), ("B", "E"), ("C", "E")]


def one_source(minimum: float | None = 0.5) -> GroupPattern:
    return pattern("one_source", _JOBS, [("PM", "BA", 2), ("PM", "SD", 3), ("BA", "SD", 2), ("SD", "ST", 2)], minimum)


def two_source(minimum: float | None = 0.5) -> GroupPattern:
    return pattern("two_source", _JOBS, [("PM", "SD", 2), ("BA", "SD", 3), ("SD", "ST", 2), ("PM", "ST", 3)], minimum)


def far_source(minimum: float | None = 0.5) -> GroupPattern:
    return pattern("far_source", _JOBS | {"GD": "FURNITURE"}, [("PM", "SD", 2), ("BA", "GD", 2), ("GD", "SD", 2), ("SD", "ST", 2)], minimum)


def full_team(minimum: float | None = 0.5) -> GroupPattern:
    roles = {"SA": "FURNITURE"} | _JOBS
    return pattern("full_team", roles, [("SA", "PM", 2), ("PM", "BA", 2), ("BA", "SD", 2), ("PM", "SD", 2), ("SD", "ST", 2)], minimum)


def twin_cover(minimum: float | None = 0.3, hops: int = 2) -> GroupPattern:
    return pattern("twin_cover", _TWIN, [(a, b, hops) for a, b in _TWINS], minimum)


def twin_mixed(minimum: float | None = 0.3) -> GroupPattern:
    return pattern("twin_mixed", _TWIN, [(a, b, h) for (a, b), h in zip(_TWINS, (2, 2, 1, 2, 2, 1))], minimum)


def chain(minimum: float | None = None) -> GroupPattern:
    return pattern("chain", {"system": "system", "user": "user", "assistant": "assistant"}, [("system", "user", 1), ("user", "assistant", 1)], minimum)
