"""The steps by which a pattern's edges are matched."""

from __future__ import annotations

from dataclasses import dataclass

from groupmatch.model.pattern import GroupPattern, PatternEdge


@dataclass(frozen=True)
class Step:
    """Forward: expand `edge` from its source's known matches. Backward: from its target's, over inverse
    edges. Scan: take every candidate of `node` for its matches."""

    kind: str
    node: str
    edge: PatternEdge | None = None

    def __str__(self):
        return f"{self.kind} {self.node}" + (f" [{self.edge.no}: {self.edge.src}->{self.edge.dst}]" if self.edge else "")


def steps(p: GroupPattern, reverse: bool, chain: bool = True) -> list[Step]:
    """Topological order; a further source is scanned, or with `reverse` found backward from a successor
    that already has matches (with `chain` also through nodes that don't have any yet)."""
    out, known, done = [], {p.leader}, set()

    def forward(u):
        for e in p.out_edges(u):
            if e.no not in done:
                out.append(Step("forward", u, e))
                done.add(e.no)
                known.add(e.dst)

    def backward(u) -> bool:
        for e in p.out_edges(u):
            if e.dst in known:
                out.append(Step("backward", u, e))
                done.add(e.no)
                known.add(u)
                return True
        if chain:
            for e in p.out_edges(u):
                if backward(e.dst):
                    out.append(Step("backward", u, e))
                    done.add(e.no)
                    known.add(u)
                    return True
        return False

    order = p.topological()
    for u in order:
        if u not in known:
            if not (reverse and backward(u)):
                out.append(Step("scan", u))
                known.add(u)
        forward(u)
    return out


def masks(p: GroupPattern, child_only: bool = False) -> dict[int, int]:
    """Edge bits that every match of a node must have, by the node's index."""
    return {p.index(n.name): p.out_mask(n.name) if child_only else p.mask(n.name) for n in p.nodes}


def explain(p: GroupPattern, reverse: bool, chain: bool = True) -> str:
    return "\n".join(str(s) for s in steps(p, reverse, chain))
