"""Functional dependency theory on attribute sets (driver side; nothing here reads data)."""

from __future__ import annotations

from itertools import combinations

FD = tuple[frozenset[str], str]


def fd(left: str, right: str) -> FD:
    return frozenset(left.split()), right


def closure(attributes: frozenset[str], fds: list[FD]) -> frozenset[str]:
    out, grown = set(attributes), True
    while grown:
        new = {a for left, a in fds if left <= out} - out
        grown = bool(new)
        out |= new
    return frozenset(out)


def implies(fds: list[FD], other: FD) -> bool:
    return other[1] in closure(other[0], fds)


def is_superkey(attributes: frozenset[str], relation: frozenset[str], fds: list[FD]) -> bool:
    return closure(attributes, fds) >= relation


def is_key(attributes: frozenset[str], relation: frozenset[str], fds: list[FD]) -> bool:
    return is_superkey(attributes, relation, fds) and not any(is_superkey(attributes - {a}, relation, fds) for a in attributes)


def candidate_keys(relation: frozenset[str], fds: list[FD]) -> list[frozenset[str]]:
    """All minimal keys, by growing size; attributes on no right side are in every key."""
    core = relation - {a for _, a in fds}
    rest, found = sorted(relation - core), []
    for size in range(len(rest) + 1):
        for more in combinations(rest, size):
            key = core | set(more)
            if not any(k <= key for k in found) and is_superkey(key, relation, fds):
                found.append(frozenset(key))
    return found
