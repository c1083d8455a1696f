"""Checks: keys, inclusion, absence of artificial unicity, equal contents."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canon import fingerprint
from ..plans.model import Database, DatabaseSpec
from .equivalence import class_key


def violations(df: DataFrame, key: list[str] | tuple[str, ...]) -> DataFrame:
    """n_groups: values of the key that more than one row has."""
    return df.groupBy(fingerprint(df, key).alias("_k")).count().where("count > 1").agg(F.count(F.lit(1)).alias("n_groups"))


def is_key(df: DataFrame, key: list[str] | tuple[str, ...]) -> bool:
    return df.groupBy(fingerprint(df, key).alias("_k")).count().where("count > 1").limit(1).isEmpty()


def orphans(source: DataFrame, columns: list[str], target: DataFrame, target_columns: list[str]) -> DataFrame:
    """Rows of source whose non-null reference is not found in target."""
    there = target.select(*(F.col(c).alias(f"_t{i}") for i, c in enumerate(target_columns))).distinct()
    match = reduce(lambda a, b: a & b, [F.col(c) == F.col(f"_t{i}") for i, c in enumerate(columns)])
    return source.dropna(subset=columns).join(there, match, "left_anti")


def fk_report(db: Database) -> DataFrame:
    """fk, n_orphans of every foreign key."""
    parts = []
    for f in db.spec.fks:
        lost = orphans(db.tables[f.source], list(f.columns), db.tables[f.target], list(f.target_columns))
        parts.append(lost.agg(F.count(F.lit(1)).alias("n_orphans")).select(F.lit(f"{f.source}.{'+'.join(f.columns)}").alias("fk"), "n_orphans"))
    return reduce(DataFrame.unionByName, parts)


def unique_keys(db: Database, keys: dict[str, tuple[str, ...]]) -> set[str]:
    """The relations whose key has no null and no repeat."""
    whole = lambda k: F.when(reduce(lambda a, b: a & b, [F.col(c).isNotNull() for c in k]), F.struct(*k))
    parts = [db.tables[n].agg(F.count(F.lit(1)).alias("n"), F.countDistinct(whole(k)).alias("dv")).select(F.lit(n).alias("relation"), "n", "dv") for n, k in keys.items()]
    return {r["relation"] for r in reduce(DataFrame.unionByName, parts).where("n = dv").collect()}


def without_orphans(db: Database) -> set[str]:
    """The foreign keys without orphans; each value is looked up once, however many rows have it."""
    parts = []
    for f in db.spec.fks:
        lost = orphans(db.tables[f.source].select(*f.columns).distinct(), list(f.columns), db.tables[f.target], list(f.target_columns))
        parts.append(lost.agg(F.count(F.lit(1)).alias("k")).select(F.lit(f"{f.source}.{'+'.join(f.columns)}").alias("fk"), "k"))
    return {r["fk"] for r in reduce(DataFrame.unionByName, parts).collect() if not r["k"]} if parts else set()


def borne_out(db: Database) -> DatabaseSpec:
    """The specification without surrogate keys that repeat in the tables and foreign keys that have orphans there."""
    relations = dict(db.spec.relations)
    for i in range(max((len(r.sks) for r in relations.values()), default=0)):
        keys = {n: (r.sks[i],) for n, r in db.spec.relations.items() if len(r.sks) > i}
        good = unique_keys(db, keys)
        relations |= {n: replace(relations[n], sks=tuple(s for s in relations[n].sks if s != k[0])) for n, k in keys.items() if n not in good}
    held = without_orphans(db)
    return DatabaseSpec(relations, tuple(f for f in db.spec.fks if f"{f.source}.{'+'.join(f.columns)}" in held))


def no_au(db: Database) -> DataFrame:
    """relation, n_rows, n_keys, n_classes: keys equal classes where no artificial unicity is left."""
    parts = []
    for n, t in db.tables.items():
        r = db.spec.relations[n]
        if r.sks:
            counts = t.agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct(r.sks[0]).alias("n_keys"), F.countDistinct(class_key(t, r.sks[0], r.potential_key())).alias("n_classes"))
            parts.append(counts.select(F.lit(n).alias("relation"), "n_rows", "n_keys", "n_classes", (F.col("n_keys") > F.col("n_classes")).alias("suffers")))
    return reduce(DataFrame.unionByName, parts)


def reencode(db: Database) -> DataFrame:
    """relation, kind, columns, holds of every constraint that can be declared again: primary, unique, not null, foreign."""
    parts = []

    def add(name: str, kind: str, columns: str, holds: DataFrame) -> None:
        parts.append(holds.select(F.lit(name).alias("relation"), F.lit(kind).alias("kind"), F.lit(columns).alias("columns"), "holds"))

    for n, t in db.tables.items():
        r = db.spec.relations[n]
        for kind, key in (*(("primary", (s,)) for s in r.sks[:1]), *(("unique", (s,)) for s in r.sks[1:]), ("unique", r.potential_key())):
            add(n, kind, "+".join(key), violations(t, key).select((F.col("n_groups") == 0).alias("holds")))
        for s in r.sks:
            add(n, "not null", s, t.agg((F.count_if(F.col(s).isNull()) == 0).alias("holds")))
    for f in db.spec.fks:
        lost = orphans(db.tables[f.source], list(f.columns), db.tables[f.target], list(f.target_columns))
        add(f.source, "foreign", "+".join(f.columns), lost.limit(1).agg((F.count(F.lit(1)) == 0).alias("holds")))
    return reduce(DataFrame.unionByName, parts)


def same_content(a: DataFrame, b: DataFrame) -> DataFrame:
    """n_rows of b, n_missing from b, n_extra in b, as bags."""
    missing, extra = a.exceptAll(b).agg(F.count(F.lit(1)).alias("n_missing")), b.exceptAll(a).agg(F.count(F.lit(1)).alias("n_extra"))
    return b.agg(F.count(F.lit(1)).alias("n_rows")).crossJoin(missing).crossJoin(extra)  # one row each
