"""Deterministic pollution: row twins under new surrogate keys, copied columns, drifting values.

Which rows get a twin is read off md5('seed|relation|key'), so every engine picks the same rows without a shuffle, and
whether a parent has a twin can be told from the reference alone.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.model import Database, DatabaseSpec, ForeignKey, Relation

NEW = "new_id"


@dataclass(frozen=True)
class Settings:
    df: float = 0.3
    seed: int = 42
    select: str = "bernoulli"  # or "exact"
    fk_policy: str = "follow"  # or "original", "spread"


def threshold(share: float) -> str:
    """The first eight hexadecimal digits below which a hash is chosen."""
    return f"{min(int(share * 2**32), 2**32 - 1):08x}"


def _pk_text(columns: tuple[str, ...]) -> Column:
    return F.concat_ws("|", *(F.col(c).cast("string") for c in columns))


def hashed(name: str, text: Column, s: Settings, salt: str = "") -> Column:
    return F.left(F.md5(F.concat(F.lit(f"{s.seed}{salt}|{name}|"), text)), F.lit(8))


def twin_count(n: int, share: float) -> int:
    """share * n, halves rounded down."""
    hundredths = round(share * 100) * n
    return hundredths // 100 + (hundredths % 100 > 50)


def _exact(df: DataFrame, name: str, pk: tuple[str, ...], s: Settings) -> DataFrame:
    """Rows with the lowest hashes, as many as the share asks for (a global rank; bernoulli is the way for large data)."""
    n = twin_count(df.count(), s.df)
    rank = F.row_number().over(Window.orderBy(hashed(name, _pk_text(pk), s), *pk))
    return df.withColumn("_r", rank).where(F.col("_r") <= n).drop("_r")


def rows(db: Database, pks: dict[str, tuple[str, ...]], s: Settings = Settings()) -> Database:
    """Every relation with twins and a surrogate key new_id; foreign keys point to the parents' new_id.

    pks: the original keys. new_id is 2 * key + copy for one integer key, else md5 of key and copy.
    """
    single = {n for n, pk in pks.items() if len(pk) == 1}
    out: dict[str, DataFrame] = {}
    for n, t in db.tables.items():
        pk = pks[n]
        twins = _exact(t, n, pk, s) if s.select == "exact" else t.where(hashed(n, _pk_text(pk), s) < threshold(s.df))
        both = t.withColumn("_copy", F.lit(0)).unionByName(twins.withColumn("_copy", F.lit(1)))
        new = F.col(pk[0]).cast("long") * 2 + F.col("_copy") if n in single else F.md5(F.concat(_pk_text(pk), F.lit("|"), F.col("_copy").cast("string")))
        own_text = _pk_text(pk)
        both = both.withColumn(NEW, new).withColumn("_own", own_text)
        for f in db.spec.fks:
            if f.source == n and f.target in single:
                c = f.columns[0]
                parent_twin = hashed(f.target, F.col(c).cast("string"), s) < threshold(s.df)
                side = {"original": F.lit(False), "follow": F.col("_copy") == 1, "spread": hashed(n, F.concat("_own", F.lit(f"|{c}|"), F.col("_copy").cast("string")), s, "s") < "80000000"}[s.fk_policy]
                both = both.withColumn(c, F.col(c).cast("long") * 2 + F.when(side & parent_twin, 1).otherwise(0))
        out[n] = both.select(NEW, *t.columns)
    return Database(polluted_spec(db.spec, pks), out)


def polluted_spec(spec: DatabaseSpec, pks: dict[str, tuple[str, ...]]) -> DatabaseSpec:
    rel = {n: replace(r, sks=(NEW,), nk=r.nk or pks[n], declared_nk=None, columns=()) for n, r in spec.relations.items()}
    return DatabaseSpec(rel, tuple(ForeignKey(f.source, f.columns, f.target, (NEW,)) for f in spec.fks if len(f.columns) == 1))


def columns(db: Database, times: int) -> Database:
    """All columns outside keys and foreign keys copied under new names, so that there are ``times`` as many."""
    out = {}
    for n, t in db.tables.items():
        r = db.spec.relations[n]
        fixed = {*r.sks, *r.potential_key(), *(c for f in db.spec.fks if f.source == n for c in f.columns)}
        own = [c for c in t.columns if c not in fixed]
        out[n] = t.select("*", *(F.col(c).alias(f"{c}__{k}") for k in range(2, times + 1) for c in own))
    return Database(db.spec, out)


def drift(df: DataFrame, pk: str, s: Settings = Settings(), share: float = 0.5, other_share: float = 0.125, amount: str = "c_acctbal", label: str = "c_mktsegment", other: str = "DRIFTED") -> DataFrame:
    """Changed values in the twins of a polluted relation: amount + 1 in a share of them, another label in fewer."""
    twin = F.col(NEW) % 2 == 1
    h = hashed("drift", F.col(pk).cast("string"), s)
    return df.withColumn(amount, F.when(twin & (h < threshold(share)), F.col(amount) + 1.0).otherwise(F.col(amount))).withColumn(label, F.when(twin & (h < threshold(other_share)), F.lit(other)).otherwise(F.col(label)))


def spec_for(name: str, sk: str, nk: tuple[str, ...] | None) -> Relation:
    return Relation(name, (sk,), nk)
