"""How much artificial unicity there is, and what removing it changes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import Database
from .equivalence import class_key


def au(df: DataFrame, sk: str, key: list[str] | tuple[str, ...]) -> DataFrame:
    """n, classes, au = 1 - classes / n (0 for an empty relation), kept_ratio = classes / n."""
    out = df.agg(F.count(F.lit(1)).alias("n"), F.countDistinct(class_key(df, sk, key)).alias("classes"))
    kept = F.when(F.col("n") == 0, F.lit(1.0)).otherwise(F.col("classes") / F.col("n"))
    return out.select("n", "classes", F.round(1 - kept, 6).alias("au"), F.round(kept, 6).alias("kept_ratio"))


def suffers(df: DataFrame, sk: str, key: list[str] | tuple[str, ...]) -> DataFrame:
    """One row: whether two different surrogate values belong to one class."""
    keyed = df.select(F.col(sk), class_key(df, sk, key).alias("_k")).groupBy("_k").agg(F.min(sk).alias("a"), F.max(sk).alias("b"))
    return keyed.where("a <> b").limit(1).agg((F.count(F.lit(1)) > 0).alias("suffers"))


def report(db: Database) -> DataFrame:
    """au of every relation with a surrogate key, and the total weighted by rows."""
    parts = [au(t, r.sks[0], r.potential_key()).select(F.lit(n).alias("relation"), "n", "classes") for n, t in db.tables.items() if (r := db.spec.relations[n]).sks]
    every = reduce(DataFrame.unionByName, parts)
    total = every.agg(F.sum("n").alias("n"), F.sum("classes").alias("classes")).select(F.lit("(all)").alias("relation"), "n", "classes")
    ratio = F.when(F.col("n") == 0, F.lit(0.0)).otherwise(1 - F.col("classes") / F.col("n"))
    return every.unionByName(total).withColumn("au", F.round(ratio, 6))


def reduction_rate(before: int, after: int) -> float:
    return round(1 - after / before, 6) if before else 0.0


def reduction(before: Database, after: Database) -> DataFrame:
    """relation, rows_before, rows_after, reduction_rate."""
    def sizes(db: Database, name: str) -> DataFrame:
        return reduce(DataFrame.unionByName, [t.agg(F.count(F.lit(1)).alias(name)).select(F.lit(n).alias("relation"), name) for n, t in db.tables.items()])

    both = sizes(before, "rows_before").join(sizes(after, "rows_after"), "relation")
    rate = F.when(F.col("rows_before") == 0, F.lit(0.0)).otherwise(1 - F.col("rows_after") / F.col("rows_before"))
    return both.withColumn("reduction_rate", F.round(rate, 6))


def key_census(db: Database) -> dict[str, float]:
    """Shares of relations with a surrogate key, and of those without any natural key."""
    rel = list(db.spec.relations.values())
    with_sk = [r for r in rel if r.sks]
    return {"relations": len(rel), "with_sk": len(with_sk), "sk_without_nk": sum(not (r.nk or r.declared_nk) for r in with_sk)}


def distortion(dirty: DataFrame, clean: DataFrame, column: str) -> DataFrame:
    """Mean, median, deviation and rows of a column before and after: what redundancy does to plain statistics."""
    def stats(df: DataFrame, name: str) -> DataFrame:
        return df.agg(F.count(column).alias("n"), F.round(F.avg(column), 6).alias("mean"), F.round(F.median(column), 6).alias("median"), F.round(F.stddev_samp(column), 6).alias("deviation")).select(F.lit(name).alias("state"), "*")

    return stats(dirty, "dirty").unionByName(stats(clean, "clean"))
