"""Stability of attributes: the least share of rows to take away for key -> attribute to hold."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.canon import comparable, fingerprint

Key = list[str] | tuple[str, ...]


def holds(df: DataFrame, left: Key, right: str) -> DataFrame:
    """One row: whether left -> right holds; one shuffle, equality null-safe."""
    g = df.groupBy(fingerprint(df, left).alias("_k")).agg(F.min(right).alias("a"), F.max(right).alias("b"), F.count(right).alias("c"), F.count(F.lit(1)).alias("n"))
    return g.where("a <> b or (c > 0 and c < n)").limit(1).agg((F.count(F.lit(1)) == 0).alias("holds"))


def g3(df: DataFrame, left: Key, right: str) -> DataFrame:
    """n, kept, g3: by definition, each group of left keeps the rows of its most frequent value of right."""
    per = df.groupBy(fingerprint(df, left).alias("_k"), comparable(df, right).alias("_v")).agg(F.count(F.lit(1)).alias("c"))
    best = per.groupBy("_k").agg(F.max("c").alias("best"), F.sum("c").alias("rows"))
    out = best.agg(F.coalesce(F.sum("rows"), F.lit(0)).alias("n"), F.coalesce(F.sum("best"), F.lit(0)).alias("kept"))
    return out.select("n", "kept", F.round(F.when(F.col("n") == 0, F.lit(0.0)).otherwise(1 - F.col("kept") / F.col("n")), 6).alias("g3"))


def _row_hash(df: DataFrame, attributes: list[str]) -> Column:
    """One 64-bit hash of all the attributes of a row, nulls told apart by position."""
    parts = []
    for a in attributes:
        own = comparable(df, a)
        parts += [F.isnull(a), own + F.lit(0.0) if isinstance(df.schema[a].dataType, T.FloatType | T.DoubleType) else own]
    return F.xxhash64(*parts)


def conflict_groups(df: DataFrame, key: Key, attributes: list[str]) -> DataFrame:
    """_k, _n of the groups whose rows differ in some attribute.

    Rows are compared by one hash of all attributes, so the width of the shuffle does not grow with their number.
    """
    keyed = df.select(fingerprint(df, key).alias("_k"), _row_hash(df, attributes).alias("_h"))
    groups = keyed.groupBy("_k").agg(F.count(F.lit(1)).alias("_n"), F.min("_h").alias("_a"), F.max("_h").alias("_b"))
    return groups.where("_a <> _b").select("_k", "_n")


def conflict_rows(df: DataFrame, key: Key, attributes: list[str], extra: dict[str, Column] | None = None) -> DataFrame:
    """_k, _n, the attributes and the extra columns of the rows in conflicting groups."""
    extra = extra or {}
    keyed = df.withColumn("_k", fingerprint(df, key)).select("_k", *attributes, *(c.alias(n) for n, c in extra.items()))
    return keyed.join(conflict_groups(df, key, attributes), "_k")


def conflict_values(df: DataFrame, key: Key, attributes: list[str], extra: dict[str, Column] | None = None) -> DataFrame:
    """_k, attribute, value (as text) of the rows in conflicting groups."""
    extra = extra or {}
    cells = F.array(*(F.struct(F.lit(a).alias("attribute"), text_of(df, a).alias("value")) for a in attributes))
    return conflict_rows(df, key, attributes, extra).select("_k", "_n", *extra, F.inline(cells))


def conflict_counts(df: DataFrame, key: Key, attributes: list[str]) -> DataFrame:
    """attribute, n_conflicts: keys with more than one value of the attribute."""
    values = conflict_values(df, key, attributes).select("_k", "attribute", "value").distinct()
    bad = values.groupBy("_k", "attribute").count().where("count > 1").groupBy("attribute").agg(F.count(F.lit(1)).alias("n_conflicts"))
    every = df.sparkSession.createDataFrame([(a,) for a in attributes], "attribute string")
    return every.join(bad, "attribute", "left").select("attribute", F.coalesce("n_conflicts", F.lit(0).cast("long")).alias("n_conflicts"))


#: Options under which nested values survive the way to JSON and back: microseconds are kept.
NESTED = {"timestampFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSSXXX", "timestampNTZFormat": "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"}


def text_of(df: DataFrame, a: str) -> Column:
    """The attribute as text, alike for values that Spark groups as one."""
    kind = df.schema[a].dataType
    if isinstance(kind, T.MapType):
        return F.to_json(F.map_from_entries(F.sort_array(F.map_entries(F.col(a)))), NESTED)
    if isinstance(kind, T.ArrayType | T.StructType):
        return F.to_json(F.col(a), NESTED)
    own = F.col(a) + F.lit(0.0).cast(kind) if isinstance(kind, T.FloatType | T.DoubleType) else F.col(a)
    return own.cast("string")


def profile(df: DataFrame, key: Key, attributes: list[str]) -> DataFrame:
    """attribute, stability of all attributes in two phases.

    Groups of one row, or of rows that agree, lose nothing, so only conflicting groups are counted value by value: the
    relation is shuffled once, as two hashes a row whatever the number of attributes, and the rest is in proportion to
    conflicts.
    """
    counts = conflict_values(df, key, attributes).groupBy("_k", "attribute", "value").agg(F.count(F.lit(1)).alias("c"))
    lost = counts.groupBy("_k", "attribute").agg((F.sum("c") - F.max("c")).alias("lost")).groupBy("attribute").agg(F.sum("lost").alias("lost"))
    every = df.sparkSession.createDataFrame([(a,) for a in attributes], "attribute string")
    n = df.agg(F.count(F.lit(1)).alias("n"))
    out = F.broadcast(every).join(lost, "attribute", "left").crossJoin(F.broadcast(n))  # one row
    share = F.when(F.col("n") == 0, F.lit(0.0)).otherwise(F.coalesce("lost", F.lit(0)) / F.col("n"))
    return out.select("attribute", F.round(share, 6).alias("stability"))


def normalised(stabilities: DataFrame, au: DataFrame) -> DataFrame:
    """attribute, stability, ratio = stability / au in 0..1: near 1 where even equal keys never agree."""
    ratio = F.when(F.col("au") == 0, F.lit(0.0)).otherwise(F.col("stability") / F.col("au"))
    return stabilities.crossJoin(F.broadcast(au.select("au"))).select("attribute", "stability", F.round(ratio, 6).alias("ratio"))


def nk_risk(stabilities: DataFrame, au: DataFrame, near: float = 0.9) -> DataFrame:
    """One row: attributes, unstable ones near the bound, and whether the natural key itself looks wrong (most are)."""
    r = normalised(stabilities, au)
    return r.agg(F.count(F.lit(1)).alias("attributes"), F.count_if(F.col("ratio") >= near).alias("near_bound"), (F.count_if(F.col("ratio") >= near) * 2 > F.count(F.lit(1))).alias("nk_suspect"))


def red_line_hint(rrp: DataFrame, nk_values: int, attributes: list[str]) -> DataFrame:
    """Attributes with more distinct values than the key: surely unstable, with no further reading."""
    return rrp.where(F.col("attribute").isin(*attributes)).select("attribute", "dv", (F.col("dv") > nk_values).alias("above_line"))


def classify(stabilities: DataFrame, threshold: float = 0.0, stable: list[str] = (), unstable: list[str] = ()) -> DataFrame:
    """attribute, stability, role: AtbN (unstable) above the threshold, else AtbC; the expert's word comes first."""
    a = F.col("attribute")
    role = F.when(a.isin(*stable or [""]), "AtbC").when(a.isin(*unstable or [""]), "AtbN").when(F.col("stability") > threshold, "AtbN").otherwise("AtbC")
    return stabilities.select("attribute", "stability", role.alias("role"))
