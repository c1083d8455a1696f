"""Suppression: surrogate keys collapse to their class, and every foreign key that points to them follows."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import graph
from ..plans.model import Database
from ..plans.staging import discard, staged
from .equivalence import representatives, sk_map

LINEAGE = "__orig_"


def apply_map(df: DataFrame, column: str, mapping: DataFrame) -> DataFrame:
    """The column rewritten by (sk, rep); values that are null or not in the map stay.

    The map is a left join side: Spark broadcasts it if its measured size allows, and shuffles otherwise.
    """
    m = mapping.select(F.col("sk").alias("_sk"), F.col("rep").alias("_rep"))
    return df.join(m, F.col(column) == F.col("_sk"), "left").withColumn(column, F.coalesce("_rep", column)).drop("_sk", "_rep")


def collapse_key(df: DataFrame, sks: str | list[str], key: list[str] | tuple[str, ...], policy: str = "min", order: str | None = None, nulls: str = "equal") -> DataFrame:
    """Every surrogate key by its class's representative; rows and other columns stay."""
    maps = [(s, sk_map(df, s, key, nulls) if policy == "min" else representatives(df, s, key, policy, order)) for s in ([sks] if isinstance(sks, str) else sks)]
    for s, m in maps:
        df = apply_map(df, s, m)
    return df


repoint_fk = apply_map


@dataclass
class Suppressed:
    db: Database
    maps: dict[tuple[str, str], DataFrame]  # (relation, surrogate key) -> (sk, rep)
    order: list[list[str]] = field(default_factory=list)


def with_lineage(db: Database) -> Database:
    """Copies of surrogate keys and surrogate foreign keys as they were before cleaning."""
    out = {}
    for n, t in db.tables.items():
        kept = [*db.spec.relations[n].sks, *dict.fromkeys(f.columns[0] for f in db.spec.sfks() if f.source == n)]
        out[n] = t.withColumns({LINEAGE + c: F.col(c) for c in kept})
    return Database(db.spec, out)


def without_lineage(db: Database) -> Database:
    return Database(db.spec, {n: t.drop(*(c for c in t.columns if c.startswith(LINEAGE))) for n, t in db.tables.items()})


def suppress(db: Database, restricted: bool = False, lineage: bool = False) -> Suppressed:
    """The database without artificial unicity: one visit a relation, from referenced ones towards referencing ones.

    restricted: the order follows only foreign keys inside potential keys, which may be free of cycles where the whole
    graph is not; the others are rewritten at the end, as they affect no class.  Maps are written to the shared folder,
    so plans stay short and each incoming foreign key reads the same map.
    """
    spec = db.spec
    edges = graph.restricted(spec) if restricted else graph.propagation_graph(spec)
    order = graph.layers(list(spec.relations), edges)
    now = dict((with_lineage(db) if lineage else db).tables)
    maps: dict[tuple[str, str], DataFrame] = {}
    done: set[tuple[str, str]] = set()

    def follow(source: str, column: str, target: str) -> None:
        fk = next(f for f in spec.sfks() if f.source == source and f.columns[0] == column and f.target == target)
        now[source] = apply_map(now[source], column, maps[target, fk.target_columns[0]])
        done.add((source, column))

    def mapped(name: str) -> None:
        """Maps of a relation, whose references are clean by now."""
        for sk in spec.relations[name].sks:
            maps[name, sk] = staged(sk_map(now[name], sk, spec.relations[name].potential_key()))

    for layer in order:
        own = [n for n in layer if not spec.relations[n].declared_nk]
        with ThreadPoolExecutor(max_workers=8) as pool:  # relations of a layer do not wait for each other
            list(pool.map(mapped, own))
        for name in own:
            for sk in spec.relations[name].sks:
                now[name] = apply_map(now[name], sk, maps[name, sk])
            for e in edges:
                if e[2] == name:
                    follow(*e)
    for e in graph.propagation_graph(spec):
        if (e[0], e[1]) not in done:
            follow(*e)
    return Suppressed(Database(spec, now), maps, order)


def fixpoint(db: Database, max_rounds: int | None = None, lineage: bool = False) -> Suppressed:
    """For graphs with cycles: collapse and follow, all relations at a time, until no map changes anything.

    Equivalence is defined inductively, so iterating from "all different" reaches the least solution; each round either
    merges classes or ends, after at most as many rounds as the longest chain of references.  With ``max_rounds``, a
    chain that needs more raises.  A round rewrites only the relations that a map of it touches.
    """
    spec, now = db.spec, dict((with_lineage(db) if lineage else db).tables)
    edges = graph.propagation_graph(spec)
    total: dict[tuple[str, str], DataFrame] = {}
    for done in count():
        maps = {(n, sk): staged(sk_map(t, sk, spec.relations[n].potential_key())) for n, t in now.items() if not spec.relations[n].declared_nk for sk in spec.relations[n].sks}
        maps = {k: m for k, m in maps.items() if not m.isEmpty()}
        if not maps:
            break
        if done == max_rounds:
            raise RuntimeError(f"fixpoint: keys still change after {max_rounds} rounds")
        before, touched = dict(now), set()
        for (n, sk), m in maps.items():
            now[n] = apply_map(now[n], sk, m)
            touched.add(n)
            total[n, sk] = staged(apply_map(total[n, sk], "rep", m).unionByName(m)) if (n, sk) in total else m
        for source, column, target in edges:
            m = maps.get((target, next(f.target_columns[0] for f in spec.sfks() if (f.source, f.columns[0], f.target) == (source, column, target))))
            if m is not None:
                now[source] = apply_map(now[source], column, m)
                touched.add(source)
        for n in touched:
            now[n] = staged(now[n])
        if done:  # the tables of the first round are the caller's
            discard(*(before[n] for n in touched))
    for n, t in now.items():
        for sk in spec.relations[n].sks:
            total.setdefault((n, sk), t.select(F.col(sk).alias("sk"), F.col(sk).alias("rep")).limit(0))
    return Suppressed(Database(spec, now), total)


def clean(db: Database, restricted: bool = False, lineage: bool = False) -> Suppressed:
    """suppress() where the graph is free of cycles, or the graph of key columns is; fixpoint() where neither is."""
    nodes = list(db.spec.relations)
    if not restricted and not graph.cycles(nodes, graph.propagation_graph(db.spec)):
        return suppress(db, False, lineage)
    if not graph.cycles(nodes, graph.restricted(db.spec)):
        return suppress(db, True, lineage)
    return fixpoint(db, lineage=lineage)
