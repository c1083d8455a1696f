"""Schema and propagation graphs: plain driver-side sets, no data."""

from __future__ import annotations

from .model import DatabaseSpec

Edge = tuple[str, str, str]  # source relation, foreign key column, target relation


def schema_graph(spec: DatabaseSpec) -> list[Edge]:
    return [(f.source, "+".join(f.columns), f.target) for f in spec.fks]


def degrees(spec: DatabaseSpec) -> dict[str, tuple[int, int]]:
    """relation -> (foreign keys leaving, foreign keys entering)."""
    edges = schema_graph(spec)
    return {n: (sum(e[0] == n for e in edges), sum(e[2] == n for e in edges)) for n in spec.relations}


def propagation_graph(spec: DatabaseSpec) -> list[Edge]:
    """Surrogate foreign keys only; a relation with a declared natural key passes nothing on."""
    return [(f.source, f.columns[0], f.target) for f in spec.sfks() if not spec.relations[f.target].declared_nk]


def restricted(spec: DatabaseSpec) -> list[Edge]:
    """Of the propagation graph, the edges whose column is part of the source's potential key."""
    return [e for e in propagation_graph(spec) if e[1] in spec.relations[e[0]].potential_key()]


def layers(nodes: list[str], edges: list[Edge]) -> list[list[str]]:
    """Relations in the order of cleaning: a layer refers to earlier layers only. Raises on a cycle."""
    left, out = set(nodes), []
    while left:
        free = sorted(n for n in left if not any(e[0] == n and e[2] in left for e in edges))
        if not free:
            raise ValueError(f"cycle among {sorted(left)}")
        out.append(free)
        left -= set(free)
    return out


def cycles(nodes: list[str], edges: list[Edge]) -> list[list[str]]:
    """Groups of relations that refer to each other in a circle (a self-reference counts)."""
    reach = {n: {e[2] for e in edges if e[0] == n} for n in nodes}
    for k in nodes:
        for n in nodes:
            if k in reach[n]:
                reach[n] |= reach[k]
    found = {tuple(sorted({n} | {m for m in reach[n] if n in reach.get(m, ())})) for n in nodes if n in reach[n]}
    return [list(f) for f in sorted(found)]


def review_order(spec: DatabaseSpec, small: int = 15, few: int = 2) -> list[tuple[str, int]]:
    """(relation, group): leaves of the propagation graph first, then small relations with few keys, then the rest."""
    out = {e[0] for e in propagation_graph(spec)}
    n_fks = {n: sum(f.source == n for f in spec.fks) for n in spec.relations}
    group = {n: 1 if n not in out else 2 if len(r.columns) < small and n_fks[n] <= few else 3 for n, r in spec.relations.items()}
    return sorted(group.items(), key=lambda x: (x[1], x[0]))
