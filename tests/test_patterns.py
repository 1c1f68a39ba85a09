import pytest

from groupmatch.model import GroupPattern
from groupmatch.model import pattern as P
from groupmatch.plans.order import steps


def test_topology_and_masks():
    p = P.two_source()
    assert p.topological()[0] == "PM" and set(p.sources()) == {"PM", "BA"}
    assert p.out_mask("PM") == 0b1001 and p.in_mask("SD") == 0b0011
    assert p.diameter() == 5 and not p.is_tree() and P.far_source().is_tree()
    assert GroupPattern.from_json(p.to_json()) == p


@pytest.mark.parametrize(
    "edges",
    [[("a", "b", 1), ("b", "a", 1)], [("a", "b", 1)], [("b", "a", 1), ("b", "c", 1)], [("a", "x", 1), ("a", "b", 1), ("b", "c", 1)], [("a", "b", 0), ("b", "c", 1)]],
)
def test_bad_patterns(edges):
    with pytest.raises(ValueError):
        P.pattern("bad", {"a": "A", "b": "B", "c": "C"}, edges)


def test_reversal_plans():
    kinds = lambda p, r, c=True: [s.kind for s in steps(p, r, c)]
    assert "scan" in kinds(P.two_source(), False) and "backward" in kinds(P.two_source(), True)
    assert kinds(P.one_source(), True) == kinds(P.one_source(), False)
    assert kinds(P.far_source(), True).count("backward") == 2 and "scan" in kinds(P.far_source(), True, False)
