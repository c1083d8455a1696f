"""Classes of surrogate values that stand for the same entity.

Rows with equal potential keys (whose foreign keys are clean already) belong together, null being equal to null.  The
map holds only values that change, so its size is the redundancy, not the relation.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.canon import fingerprint

Key = list[str] | tuple[str, ...]


def class_key(df: DataFrame, sk: str, key: Key, nulls: str = "equal") -> Column:
    """The grouping key of a row.  nulls='distinct': a row with a null in the key is a class alone.

    An empty key tells nothing, so every row is a class alone.
    """
    if not key:
        return F.sha2(F.concat(F.lit("row:"), F.col(sk).cast("string")), 256)
    own = fingerprint(df, key)
    if nulls == "distinct":
        missing = F.greatest(*(F.col(c).isNull().cast("int") for c in key), F.lit(0)) == 1
        own = F.when(missing, F.sha2(F.concat(F.lit("row:"), F.col(sk).cast("string")), 256)).otherwise(own)
    return own


def pairs(df: DataFrame, sk: str, key: Key) -> DataFrame:
    """(sk_a, sk_b): every pair of artificially unique duplicates, read off the definition; for small relations."""
    keyed = df.select(F.col(sk), class_key(df, sk, key).alias("_k"))
    a, b = keyed.select(F.col(sk).alias("sk_a"), "_k"), keyed.select(F.col(sk).alias("sk_b"), "_k")
    return a.join(b, "_k").where("sk_a < sk_b").select("sk_a", "sk_b").distinct()


def classes(df: DataFrame, sk: str, key: Key) -> DataFrame:
    """rep, members (sorted), size of every class; collects members, so for classes of bounded size."""
    keyed = df.select(F.col(sk), class_key(df, sk, key).alias("_k"))
    grouped = keyed.groupBy("_k").agg(F.min(sk).alias("rep"), F.sort_array(F.collect_set(sk)).alias("members"))
    return grouped.select("rep", "members", F.size("members").cast("long").alias("size"))


def sk_map(df: DataFrame, sk: str, key: Key, nulls: str = "equal", plan: str = "join") -> DataFrame:
    """(sk, rep) for the values that are not the least of their class.

    plan: 'join' aggregates minima with map-side combining and joins them back, which no class is too large for;
    'explode' shuffles once and needs bounded classes; 'window' shuffles once and sorts.
    """
    keyed = df.where(F.col(sk).isNotNull()).select(F.col(sk).alias("sk"), class_key(df, sk, key, nulls).alias("_k"))
    if plan == "window":
        out = keyed.withColumn("rep", F.min("sk").over(Window.partitionBy("_k")))
    elif plan == "explode":
        grouped = keyed.groupBy("_k").agg(F.min("sk").alias("rep"), F.collect_set("sk").alias("all")).where("size(all) > 1")
        out = grouped.select(F.explode("all").alias("sk"), "rep")
    else:
        shared = keyed.groupBy("_k").agg(F.min("sk").alias("rep"), F.max("sk").alias("_last")).where("rep <> _last").drop("_last")
        out = keyed.join(shared, "_k")
    return out.where("sk <> rep").select("sk", "rep").distinct()


def representatives(df: DataFrame, sk: str, key: Key, policy: str = "min", order: str | None = None) -> DataFrame:
    """(sk, rep) under another policy: 'earliest' by an order column, 'fullest' (fewest nulls), ties to the least value."""
    if policy == "min":
        return sk_map(df, sk, key)
    rank = F.struct(F.col(order), F.col(sk)) if policy == "earliest" else F.struct(sum(F.col(c).isNull().cast("int") for c in df.columns), F.col(sk))
    keyed = df.select(F.col(sk).alias("sk"), class_key(df, sk, key).alias("_k"), rank.alias("_r"))
    best = keyed.groupBy("_k").agg(F.min_by("sk", "_r").alias("rep"))
    return keyed.join(best, "_k").where("sk <> rep").select("sk", "rep").distinct()
