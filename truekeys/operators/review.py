"""What is shown to the expert: small, reproducible samples and counterexamples."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canon import fingerprint


def sample(df: DataFrame, n: int, key: list[str]) -> DataFrame:
    """n rows by a hash of the key: the same rows every time."""
    return df.orderBy(F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in key))), *key).limit(n)


def counterexamples(df: DataFrame, key: list[str] | tuple[str, ...], attribute: str | None = None) -> DataFrame:
    """Rows that share a key; with an attribute, only where they disagree on it."""
    keyed = df.withColumn("_k", fingerprint(df, key))
    groups = keyed.groupBy("_k").agg(F.count(F.lit(1)).alias("n"), *([F.min(attribute).alias("a"), F.max(attribute).alias("b"), F.count(attribute).alias("c")] if attribute else []))
    bad = groups.where("n > 1" if attribute is None else "a <> b or (c > 0 and c < n)").select("_k")
    return keyed.join(bad, "_k", "left_semi").drop("_k")


def effort(relations: int, low: float = 3, high: float = 12) -> tuple[float, float]:
    """Hours of an expert's time for a number of relations, at minutes a relation."""
    return round(relations * low / 60, 2), round(relations * high / 60, 2)
