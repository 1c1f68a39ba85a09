"""DuckDB SQL written from the definitions, for the engine's queries."""

from __future__ import annotations

from groupmatch.functions.membership import least_value
from groupmatch.model import GroupPattern, PatternEdge

_P = 2147483647


def mixed(x: str) -> str:
    return f"((CAST(({x}) AS BIGINT) % {_P}) * 48271 % {_P}) / CAST({_P} AS DOUBLE)"


def scored(edges: str) -> str:
    """(src, dst, trust, intimacy) of edges (src, dst), drawn from ids."""
    a, b = f"(src % {_P})", f"(dst % {_P})"
    return f"SELECT src, dst, {mixed(f'{a} * 1000003 + {b} * 7919 + 101')} AS trust, {mixed(f'{a} * 1000033 + {b} * 104729 + 211')} AS intimacy FROM ({edges})"


def influence(key: str) -> str:
    return f"{mixed(f'({key} % {_P}) * 7919 + 17')} AS influence"


def graph(vertices: str, edges: str) -> str:
    """CTEs vtx (id, label, influence) and edg of any graph."""
    return f"vtx AS MATERIALIZED ({vertices}),\nedg AS MATERIALIZED ({edges})"


def handover(k: int = 3) -> str:
    """CTEs vtx (id, label, influence) and edg (src, dst, trust, intimacy) of handover(k)."""
    return f"""vtx AS (SELECT c_custkey AS id, c_mktsegment AS label, {mixed('c_custkey * 7919 + 17')} AS influence FROM customer),
raw AS (SELECT o_custkey AS src, lead(o_custkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, l_orderkey, l_linenumber, l_returnflag) AS dst, l_returnflag
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_linenumber <= {k}),
edg AS MATERIALIZED (SELECT src, dst, {mixed('src * 1000003 + dst * 7919 + 101')} AS trust, {mixed('src * 1000033 + dst * 104729 + 211')} AS intimacy
  FROM (SELECT DISTINCT src, dst FROM raw WHERE dst IS NOT NULL AND src <> dst))"""


def candidates(p: GroupPattern) -> str:
    parts = []
    for n in p.nodes:
        tests = [f"label = '{x}'" for x in n.labels]
        if n.min_influence is not None:
            tests.append(f"influence >= {least_value(n.min_influence, n.rule)!r}")
        parts.append(f"SELECT '{n.name}' AS node, id AS v FROM vtx WHERE {' AND '.join(tests) or 'TRUE'}")
    return "cnd AS MATERIALIZED (" + " UNION ALL ".join(parts) + ")"


def relation(e: PatternEdge, name: str, constrained: bool = True, hops: int | None = None) -> str:
    """CTEs ending in `name` (v, w, path, hops, trust, intimacy, influence, worst): best admissible paths."""
    hops = hops or e.max_hops
    out = [f"{name}_1 AS (SELECT src AS v, dst AS w, [src, dst] AS path, 1 AS hops, trust, intimacy, 0.0::DOUBLE + a.influence + b.influence AS s FROM edg JOIN cnd ON v = src AND node = '{e.src}' JOIN vtx a ON a.id = src JOIN vtx b ON b.id = dst)"]
    for h in range(2, hops + 1):
        out.append(f"{name}_{h} AS (SELECT v, dst AS w, list_append(path, dst) AS path, {h} AS hops, p.trust * g.trust AS trust, p.intimacy * g.intimacy AS intimacy, s + b.influence AS s FROM {name}_{h - 1} p JOIN edg g ON g.src = p.w JOIN vtx b ON b.id = dst WHERE NOT list_contains(path, dst))")
    named = list(e.minima()) if constrained else []
    worst = named or ["trust", "intimacy", "influence"]
    tests = " AND ".join(f"{k} >= {least_value(m, e.rule)!r}" for k, m in e.minima().items()) if constrained and named else "TRUE"
    union = " UNION ALL ".join(f"SELECT * FROM {name}_{h}" for h in range(1, hops + 1))
    worst_sql = f"least({', '.join(worst)})" if len(worst) > 1 else worst[0]
    out.append(f"{name}_f AS (SELECT *, {worst_sql} AS worst FROM (SELECT p.v, p.w, path, hops, trust, intimacy, s / (hops + 1) AS influence FROM ({union}) p JOIN cnd c ON c.v = p.w AND c.node = '{e.dst}') WHERE {tests})")
    out.append(f"{name} AS MATERIALIZED (SELECT x.* FROM (SELECT arg_min({{'v': v, 'w': w, 'path': path, 'hops': hops, 'trust': trust, 'intimacy': intimacy, 'influence': influence, 'worst': worst}}, {{'a': -worst, 'b': hops, 'c': path}}) AS x FROM {name}_f GROUP BY v, w))")
    return ",\n".join(out)


def relations(p: GroupPattern, constrained: bool = True, one_hop: bool = False) -> str:
    return ",\n".join(relation(e, f"e{e.no}", constrained, 1 if one_hop else None) for e in p.edges)


def fixpoint(p: GroupPattern, rounds: int, child_only: bool = False, leader: bool = True) -> str:
    """CTEs s_<node>_<round>, each round a semi-join per pattern edge; the last round is `members`."""
    out = []
    key = "leader, " if leader else ""
    if leader:
        out.append(f"s_{p.leader}_0 AS (SELECT v AS leader, v AS x FROM cnd WHERE node = '{p.leader}')")
        for e, forward in p.spanning_steps():
            a, b, near, far = (e.src, e.dst, "v", "w") if forward else (e.dst, e.src, "w", "v")
            out.append(f"s_{b}_0 AS (SELECT DISTINCT leader, {far} AS x FROM s_{a}_0 JOIN e{e.no} ON {near} = x)")
    else:
        out += [f"s_{n.name}_0 AS (SELECT v AS x FROM cnd WHERE node = '{n.name}')" for n in p.nodes]
    for r in range(1, rounds + 1):
        for n in p.nodes:
            tests = []
            for e in p.edges:
                same = " AND t.leader = s.leader" if leader else ""
                if e.src == n.name:
                    tests.append(f"EXISTS (SELECT 1 FROM e{e.no} l JOIN s_{e.dst}_{r - 1} t ON t.x = l.w WHERE l.v = s.x{same})")
                if e.dst == n.name and not child_only:
                    tests.append(f"EXISTS (SELECT 1 FROM e{e.no} l JOIN s_{e.src}_{r - 1} t ON t.x = l.v WHERE l.w = s.x{same})")
            out.append(f"s_{n.name}_{r} AS MATERIALIZED (SELECT {key}x FROM s_{n.name}_{r - 1} s WHERE {' AND '.join(tests) or 'TRUE'})")
    union = " UNION ALL ".join(f"SELECT {key}'{n.name}' AS node, x AS v FROM s_{n.name}_{rounds}" for n in p.nodes)
    return ",\n".join(out) + f",\nmembers AS MATERIALIZED ({union})"


def groups(p: GroupPattern, tail: str, rounds: int = 5, k: int = 3, data: str | None = None) -> str:
    return f"WITH {data or handover(k)},\n{candidates(p)},\n{relations(p)},\n{fixpoint(p, rounds)}\n{tail}"


def members(p: GroupPattern, rounds: int = 5) -> str:
    return groups(p, "SELECT leader, node, v FROM members", rounds)


def links(p: GroupPattern) -> str:
    """The links CTE body: relations between members of one leader."""
    return " UNION ALL ".join(f"SELECT a.leader, {e.no} AS edge_no, l.* FROM e{e.no} l JOIN members a ON a.node = '{e.src}' AND a.v = l.v JOIN members b ON b.node = '{e.dst}' AND b.v = l.w AND b.leader = a.leader" for e in p.edges)


def assignments(p: GroupPattern, select: str, injective: bool = False) -> str:
    """Assignments as one join of the relations."""
    names = [n.name for n in p.nodes]
    frm = ", ".join(f"e{e.no}" for e in p.edges)
    at: dict[str, str] = {}
    tests = []
    for e in p.edges:
        for u, c in ((e.src, "v"), (e.dst, "w")):
            if u in at:
                tests.append(f"e{e.no}.{c} = {at[u]}")
            else:
                at[u] = f"e{e.no}.{c}"
    if injective:
        tests += [f"{at[a]} <> {at[b]}" for i, a in enumerate(names) for b in names[:i]]
    worst = f"least({', '.join(f'e{e.no}.worst' for e in p.edges)})"
    cols = ", ".join(f"{at[u]} AS {u}" for u in names)
    return f"WITH {handover()},\n{candidates(p)},\n{relations(p)},\nasg AS (SELECT {at[p.leader]} AS leader, {cols}, {worst} AS worst FROM {frm} WHERE {' AND '.join(tests) or 'TRUE'})\n{select}"


def simulation(p: GroupPattern, mode: str, child_only: bool, rounds: int = 8) -> str:
    q = p if mode == "constrained" else p.with_minimum(None)
    body = f"WITH {handover()},\n{candidates(q)},\n{relations(q, mode == 'constrained', mode == 'edge')},\n{fixpoint(q, rounds, child_only, False)}"
    return body + f"\nSELECT node, v FROM members WHERE (SELECT count(DISTINCT node) FROM members) = {len(p.nodes)}"
