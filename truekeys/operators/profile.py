"""Redundancy profiles: distinct, null and repeated values of attributes, alone and in combination."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.canon import comparable
from ..plans.model import Database, Relation

#: Up to so many columns are counted in one aggregate; each distinct count multiplies the rows of that one.
ONE_PASS = 8


def arp(df: DataFrame, columns: str | list[str], rsd: float | None = None) -> DataFrame:
    """attribute, n, dv, nv, ov of a column or a combination; a combination with a null part counts as null.

    rsd: relative error of an approximate distinct count, which needs no expansion and shuffles kilobytes.
    """
    names = [columns] if isinstance(columns, str) else list(columns)
    values = [comparable(df, c) for c in names]
    some_null = reduce(lambda a, b: a | b, [F.col(c).isNull() for c in names])
    dv = F.approx_count_distinct(F.when(~some_null, F.struct(*values)), rsd) if rsd else F.countDistinct(*values)
    out = df.agg(F.count(F.lit(1)).alias("n"), dv.alias("dv"), F.count_if(some_null).alias("nv"))
    return out.select(F.lit("+".join(names)).alias("attribute"), "n", "dv", "nv", (F.col("n") - F.col("dv") - F.col("nv")).alias("ov"))


def rrp(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """The profiles of all columns, one row each.

    Few columns: one aggregate.  More: one narrow two-step aggregate a column (values pre-aggregated on the map side),
    which scans only that column; Spark runs them side by side.
    """
    columns = columns or df.columns
    if len(columns) > ONE_PASS:
        parts = []
        for c in columns:
            own = df.groupBy(comparable(df, c).alias("v")).agg(F.count(F.lit(1)).alias("k"))
            one = own.agg(F.coalesce(F.sum("k"), F.lit(0)).alias("n"), F.count("v").alias("dv"), F.coalesce(F.sum(F.when(F.col("v").isNull(), F.col("k"))), F.lit(0)).alias("nv"))
            parts.append(one.select(F.lit(c).alias("attribute"), "n", "dv", "nv", (F.col("n") - F.col("dv") - F.col("nv")).alias("ov")))
        return reduce(DataFrame.unionByName, parts)
    aggs = [F.count(F.lit(1)).alias("n")]
    for i, c in enumerate(columns):
        aggs += [F.countDistinct(comparable(df, c)).alias(f"d{i}"), F.count_if(F.col(c).isNull()).alias(f"z{i}")]
    rows = F.array(*(F.struct(F.lit(c).alias("attribute"), F.col("n"), F.col(f"d{i}").alias("dv"), F.col(f"z{i}").alias("nv"), (F.col("n") - F.col(f"d{i}") - F.col(f"z{i}")).alias("ov")) for i, c in enumerate(columns)))
    return df.agg(*aggs).select(F.inline(rows))


def categories(relation: Relation, fk_columns: set[str]) -> dict[str, str]:
    keys = {*relation.sks, *(relation.declared_nk or ())}
    return {c: "K" if c in keys else "FK" if c in fk_columns else "RA" for c in relation.columns}


def layout(profile: DataFrame, relation: Relation, fk_columns: set[str]) -> DataFrame:
    """The profile with category and place: keys first, then remaining attributes by falling dv, foreign keys last."""
    kind = F.create_map(*(F.lit(x) for pair in categories(relation, fk_columns).items() for x in pair))
    out = profile.withColumn("category", kind[F.col("attribute")])
    order = Window.orderBy(F.expr("case category when 'K' then 1 when 'RA' then 2 else 3 end"), F.desc("dv"), "attribute")
    return out.withColumn("position", F.row_number().over(order))  # one row a column


def rrp_database(db: Database) -> DataFrame:
    parts = [rrp(t).select(F.lit(n).alias("relation"), "*") for n, t in db.tables.items()]
    return reduce(DataFrame.unionByName, parts)


def lines(df: DataFrame, nk: list[str]) -> DataFrame:
    """size_line, nk_line and their gap: a first estimate of the redundancy."""
    return arp(df, nk).select("attribute", F.col("n").alias("size_line"), F.col("dv").alias("nk_line"), (F.col("n") - F.col("dv")).alias("gap"))


def compare(before: DataFrame, after: DataFrame) -> DataFrame:
    """Two profiles side by side by attribute."""
    names = ("dv", "nv", "ov")
    a = before.select("attribute", *(F.col(c).alias(f"{c}_before") for c in names))
    b = after.select("attribute", *(F.col(c).alias(f"{c}_after") for c in names))
    return a.join(b, "attribute", "full")


def sk_candidates(profile: DataFrame, relation: Relation, fk_columns: set[str], generated: set[str] = frozenset(), almost: float = 0.99) -> DataFrame:
    """Columns that may be surrogate keys, and why: declared as generated, declared key, or (almost) unique."""
    kinds = categories(relation, fk_columns)
    kind = F.create_map(*(F.lit(x) for pair in kinds.items() for x in pair))
    single = set(relation.sks) | ({relation.declared_nk[0]} if relation.declared_nk and len(relation.declared_nk) == 1 else set())
    near = (F.col("nv") == 0) & (F.col("dv") >= F.lit(almost) * F.col("n")) & (F.col("n") > 0)
    reason = F.when(F.col("attribute").isin(*generated or {""}), "generated").when(F.col("attribute").isin(*single or {""}), "declared key").when(near & (F.col("dv") == F.col("n")), "unique").when(near, "almost unique")
    return profile.select("attribute", "n", "dv", kind[F.col("attribute")].alias("category"), reason.alias("reason")).where("reason is not null")


def nk_candidates(df: DataFrame, columns: list[str] | None = None, max_width: int | None = None, near: float = 0.9) -> DataFrame:
    """Combinations whose distinct values come near the size, for the expert; supersets of a unique one are left out.

    Widths go up to ``max_width`` (none: until nothing is left to try).  A combination has at most the product of its
    columns' distinct values; where that falls short of the bound it is not counted.
    """
    from itertools import combinations
    from math import prod

    from .baselines import distinct_counts

    columns, n, unique, rows, single = columns or df.columns, df.count(), [], [], {}
    for width in range(1, (max_width or len(columns)) + 1):
        level = [c for c in combinations(columns, width) if not any(set(u) <= set(c) for u in unique)]
        if not level:
            break
        if single:
            level = [c for c in level if prod(single[x] for x in c) >= near * n]
        counts = distinct_counts(df, level)
        if width == 1:
            single = {c: dv for (c,), dv in zip(level, counts, strict=True)}
        for c, dv in zip(level, counts, strict=True):
            if dv == n:
                unique.append(c)
            if n and dv >= near * n:
                rows.append(("+".join(c), n, dv))
    return df.sparkSession.createDataFrame(rows, "attributes string, n long, dv long")
