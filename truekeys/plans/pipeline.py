"""The three blocks end to end, with the time of each."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame

from ..operators import chase, decompose, profile, propagate, reduce, stability
from .model import Database, ExpertDecisions
from .staging import staged


@dataclass
class Result:
    db: Database  # the cleaned database, histories included
    suppressed: propagate.Suppressed
    profiles: DataFrame
    roles: dict[str, dict[str, str]] = field(default_factory=dict)
    seconds: dict[str, float] = field(default_factory=dict)


def run(db: Database, decisions: ExpertDecisions | None = None, restricted: bool = False, include_declared_nk: bool = False, functions: dict[str, Callable[[Column], Column]] | None = None) -> Result:
    """Profiles; suppression along the graph; stability, chase, decomposition and reduction. Blocks are materialised.

    A graph with cycles is cleaned over its key columns alone, or to a fixpoint where these are in a circle too.
    functions: scores by name, for rules ``model``.  Ties of rules go to the row with the least surrogate key it had
    before cleaning, and to the least value in relations without one.
    """
    decisions = decisions or ExpertDecisions()
    db = Database(decisions.apply(db.spec), db.tables)
    if decisions.interest:
        db = db.restrict(decisions.interest)
    clock, seconds = time.perf_counter(), {}
    profiles = staged(profile.rrp_database(db))
    seconds["profiles"], clock = time.perf_counter() - clock, time.perf_counter()

    done = propagate.clean(db, restricted, lineage=True)
    cleaned = Database(db.spec, {n: staged(t) for n, t in done.db.tables.items()})
    done.db = cleaned
    seconds["suppression"], clock = time.perf_counter() - clock, time.perf_counter()

    out, roles = {}, {}
    for n, t in cleaned.tables.items():
        r = db.spec.relations[n]
        attributes = list(r.remaining())
        key = list(r.potential_key())
        if (r.nk or (include_declared_nk and r.declared_nk)) and attributes:
            found = stability.classify(stability.profile(t, key, attributes), 0.0, decisions.stable.get(n, []), decisions.unstable.get(n, []))
            roles[n] = {x["attribute"]: x["role"] for x in found.collect()}  # one row an attribute
        historised = [a for a, x in roles.get(n, {}).items() if x == "AtbN"] if n in decisions.completing else []
        if historised:
            past = decompose.split(cleaned, n, [a for a in attributes if a not in historised], historised, decisions.completing[n])[1]
            out[f"{n}_history"] = staged(past)
        conflicting = [a for a in attributes if a in roles.get(n, {}) and a not in historised]  # no history of theirs was asked for
        if conflicting:
            order = propagate.LINEAGE + r.sks[0] if r.sks and propagate.LINEAGE + r.sks[0] in t.columns else None
            t = chase.decided(t, key, conflicting, order, decisions.rules.get(n, {}), functions or {})
        t = t.drop(*historised)
        out[n] = staged(reduce.relation(t, r.sks))
    seconds["normalise and reduce"] = time.perf_counter() - clock
    return Result(Database(db.spec, out), done, profiles, roles, {k: round(v, 3) for k, v in seconds.items()})
