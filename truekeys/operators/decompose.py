"""Normalisation: stable attributes stay with the entity, unstable ones move to a history."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.model import Database, DatabaseSpec, ForeignKey
from . import verify
from .propagate import LINEAGE


def stable_part(df: DataFrame, sks: list[str], key: list[str], stable: list[str]) -> DataFrame:
    return df.select(*dict.fromkeys([*sks, *key, *stable])).distinct()


def history(df: DataFrame, sks: list[str], key: list[str], completing: list[str], unstable: list[str], carry_key: bool = True) -> DataFrame:
    return df.select(*dict.fromkeys([*sks, *(key if carry_key else []), *completing, *unstable])).distinct()


def path(spec: DatabaseSpec, relation: str, o: str) -> list[tuple[str, ForeignKey, bool]]:
    """(relation, key, whether the key points back) of every step from the relation to that of the completing attribute.

    ``other.column`` takes the one shortest path of foreign keys; ``a[key]/b[key].column`` names the steps, and their key
    columns where two relations share several.  More than one way to go raises.
    """
    *steps, last = o.rsplit(".", 1)[0].split("/")
    names = [re.fullmatch(r"(\w+)(?:\[(\w+)\])?", s).groups() for s in (*steps, last)]

    def hops(here: str, there: str, key: str | None) -> list[tuple[str, ForeignKey, bool]]:
        return [(there, f, f.source == there) for f in spec.fks if (f.source, f.target) in ((here, there), (there, here)) and (key is None or key in f.columns)]

    def only(found: list, what: str) -> list:
        if len(found) != 1:
            raise ValueError(f"{len(found)} ways from {relation} to {what}: name the steps and their keys")
        return found[0]

    here, out = relation, []
    for there, key in names:
        ways = [[h] for h in hops(here, there, key)]
        if not ways and key is None:
            reached = [[h] for n in spec.relations for h in hops(here, n, None)]
            while reached and not ways:
                reached = [[*w, h] for w in reached for n in spec.relations if n != here and n not in {x[0] for x in w} for h in hops(w[-1][0], n, None)]
                ways = [w for w in reached if w[-1][0] == there]
        out += only(ways, there)
        here = there
    return out


def o_column(db: Database, relation: str, o: str) -> str:
    """The name that the completing attribute has in the completed relation."""
    column = o.rsplit(".", 1)[-1]
    return column if "." not in o or column not in db.tables[relation].columns else "o_" + column


def completed(db: Database, relation: str, o: str) -> DataFrame:
    """The relation with the completing attribute joined in along foreign keys, over keys as they were before cleaning.

    Cleaned keys would pair every version of an entity with every event of it; lineage keys pair each with its own.
    Rows without a partner stay, with a null: none of their values may be lost.
    """
    out = db.tables[relation]
    if "." not in o:
        return out
    before = lambda t, c: LINEAGE + c if LINEAGE + c in t.columns else c
    steps, here, prefix = path(db.spec, relation, o), out, ""
    for i, (name, fk, back) in enumerate(steps):
        there = db.tables[name]
        ours, theirs = (fk.target_columns, fk.columns) if back else (fk.columns, fk.target_columns)
        renamed = there.select(*(F.col(c).alias(f"_{i}_{c}") for c in there.columns))
        match = reduce(lambda a, b: a & b, [F.col(prefix + before(here, a)) == F.col(f"_{i}_" + before(there, b)) for a, b in zip(ours, theirs, strict=True)])
        out, here, prefix = out.join(renamed, match, "left"), there, f"_{i}_"
    return out.select(*db.tables[relation].columns, F.col(prefix + o.rsplit(".", 1)[-1]).alias(o_column(db, relation, o)))


def split(db: Database, relation: str, stable: list[str], unstable: list[str], candidates: list[str], carry_key: bool = True) -> tuple[DataFrame, DataFrame, str]:
    """(stable part, history, completing attribute): the first candidate that makes (surrogate key, it) a key.

    Rows that the candidate's relation knows nothing of have a null there and count in the check of the key.
    """
    r = db.spec.relations[relation]
    sks, key = list(r.sks), list(r.potential_key())
    for o in candidates:
        column = o_column(db, relation, o)
        out = history(completed(db, relation, o), sks, key, [column], unstable, carry_key)
        if verify.is_key(out, [sks[0], column]):
            return stable_part(db.tables[relation], sks, key, stable), out, o
    raise ValueError(f"no candidate completes the key of {relation}: {candidates}")


def suggest(db: Database, relation: str) -> list[str]:
    """Temporal columns of the relation, then of relations one foreign key away."""
    def temporal(name: str, prefix: str = "") -> list[str]:
        return [prefix + f.name for f in db.tables[name].schema if isinstance(f.dataType, T.DateType | T.TimestampType | T.TimestampNTZType) and not f.name.startswith(LINEAGE)]

    near = [f.source if f.target == relation else f.target for f in db.spec.sfks() if relation in (f.source, f.target)]
    return temporal(relation) + [c for n in dict.fromkeys(near) for c in temporal(n, n + ".")]


def compacted(df: DataFrame, sk: str, o: str, values: list[str]) -> DataFrame:
    """Only the versions of a history that differ from the one before."""
    order = Window.partitionBy(sk).orderBy(o)
    same = F.row_number().over(order) > 1
    for v in values:
        same = same & F.lag(v).over(order).eqNullSafe(F.col(v))
    return df.withColumn("_same", same).where(~F.col("_same")).drop("_same")


def validity(df: DataFrame, sk: str, o: str) -> DataFrame:
    """The history with valid_from and valid_to (null: still valid)."""
    return df.withColumnRenamed(o, "valid_from").withColumn("valid_to", F.lead("valid_from").over(Window.partitionBy(sk).orderBy("valid_from")))
