"""Conflict resolution: key -> attribute is made to hold for every stable attribute.

All dependencies of a relation share their left side and no right side is part of it, so one pass is the fixpoint.
Only conflicting groups are resolved; a null yields to any value.  Rules that compare values (min, max, first, longest,
latest) aggregate each attribute in its own type; rules that count or look at a value (majority, priority, validated,
expert, model) see it as text, in the column ``value``, and bring the chosen one back to its type.
"""

from __future__ import annotations

import json
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.canon import fingerprint
from .stability import NESTED, conflict_rows, conflict_values, text_of

Key = list[str] | tuple[str, ...]
COMPARING = ("min", "max", "first", "longest", "latest")


def conflicts(df: DataFrame, key: Key, attribute: str, order: str) -> DataFrame:
    """Key columns, n_values and the values (by frequency, then first occurrence) of every group that disagrees."""
    per = df.groupBy(*key, attribute).agg(F.count(F.lit(1)).alias("c"), F.min(order).alias("f"))
    grouped = per.groupBy(*key).agg(F.count(F.lit(1)).alias("n_values"), F.array_sort(F.collect_list(F.struct((-F.col("c")).alias("c"), F.col("f"), F.col(attribute).alias("v")))).alias("s"))
    return grouped.where("n_values > 1").select(*key, "n_values", F.transform("s", lambda x: F.coalesce(x["v"].cast("string"), F.lit("NULL"))).alias("values"))


def _compared(df: DataFrame, a: str, rule: str) -> Column:
    """Aggregate over a group's rows (_f: order, _o: the column of 'latest'); nulls of the attribute take no part."""
    v = F.col(a)
    own = text_of(df, a) if isinstance(df.schema[a].dataType, T.MapType) else v
    if rule == "min":
        return F.min_by(v, own)
    if rule == "max":
        return F.max_by(v, own)
    if rule == "first":
        return F.min_by(v, F.when(v.isNotNull(), F.struct(F.col("_f"), own.alias("v"))))
    if rule == "latest":
        return F.max_by(v, F.when(v.isNotNull(), F.struct(F.col("_o"), own.alias("v"))))
    return F.max_by(v, F.when(v.isNotNull(), F.struct(F.length(text_of(df, a)).alias("l"), own.alias("v"))))


def _counted(rule: str, predicate: str | None, priority: tuple[str, ...]) -> Column:
    """Aggregate over (value, c rows, f first order value) that picks the value to keep; ties to the earliest row, then
    to the least value."""
    usual = [(-F.col("c")).alias("c"), F.col("f"), F.col("value")]
    if rule == "majority":
        return F.min_by("value", F.struct(*usual))
    if rule == "priority":
        return F.min_by("value", F.struct(_place(priority), *usual))
    if rule == "validated":
        fails = F.when(F.expr(predicate or "true"), F.lit(0)).otherwise(F.lit(1))
        return F.min_by("value", F.struct(fails.alias("fails"), *usual))
    raise ValueError(f"no such rule: {rule}")


def _place(priority: tuple[str, ...]) -> Column:
    """Place of the value in the list, last if it is not in it."""
    at = F.array_position(F.array(*(F.lit(p) for p in priority)) if priority else F.array(F.lit("")), F.col("value"))
    return F.when(at > 0, at).otherwise(F.lit(len(priority) + 1)).alias("place")


def _extra(order: str | None, latest: str | None = None) -> dict[str, Column]:
    return {"_f": F.col(order) if order else F.lit(None).cast("long"), "_o": F.col(latest) if latest else F.lit(None).cast("string")}


def _counts(df: DataFrame, key: Key, attributes: list[str], order: str | None) -> DataFrame:
    """_k, attribute, value, c, f of the conflicting groups, without nulls."""
    values = conflict_values(df, key, attributes, _extra(order)).where("value is not null")
    return values.groupBy("_k", "attribute", "value").agg(F.count(F.lit(1)).alias("c"), F.min("_f").alias("f"))


def _wide(df: DataFrame, attributes: list[str], chosen: DataFrame) -> DataFrame:
    """(_k, attribute, value) -> _k and one column for each attribute, in its own type."""

    def typed(a: str, value: Column) -> Column:
        kind = df.schema[a].dataType
        return F.from_json(value, kind, NESTED) if isinstance(kind, T.ArrayType | T.MapType | T.StructType) else value.cast(kind)

    wide = chosen.groupBy("_k").agg(*(F.max(F.when(F.col("attribute") == a, F.col("value"))).alias(f"_new_{i}") for i, a in enumerate(attributes)))
    return wide.select("_k", *(typed(a, F.col(f"_new_{i}")).alias(f"_new_{i}") for i, a in enumerate(attributes)))


def resolution(df: DataFrame, key: Key, attributes: list[str], order: str | None, rule: str = "majority", latest: str | None = None, predicate: str | None = None, priority: tuple[str, ...] = ()) -> DataFrame:
    """_k, _new_0, _new_1, ...: what each conflicting group keeps of each attribute.

    order: a column of any orderable type that says which row came first; without one, ties go to the least value.
    """
    if rule == "latest" and not latest:
        raise ValueError("the rule 'latest' needs the column that tells which row is the latest")
    if rule in COMPARING:
        rows = conflict_rows(df, key, attributes, _extra(order, latest))
        return rows.groupBy("_k").agg(*(_compared(df, a, rule).alias(f"_new_{i}") for i, a in enumerate(attributes)))
    per = _counts(df, key, attributes, order)
    return _wide(df, attributes, per.groupBy("_k", "attribute").agg(_counted(rule, predicate, priority).alias("value")))


def apply(df: DataFrame, key: Key, attributes: list[str], resolved: DataFrame) -> DataFrame:
    """df with the resolved values in the groups that have one."""
    out = df.withColumn("_k", fingerprint(df, key)).join(resolved, "_k", "left")
    new = {a: F.coalesce(F.col(f"_new_{i}"), F.col(a)).alias(a) for i, a in enumerate(attributes)}
    return out.select(*(new.get(c, F.col(c)) for c in df.columns))


def resolve(df: DataFrame, key: Key, attributes: list[str], order: str | None = None, rule: str = "majority", latest: str | None = None, predicate: str | None = None, priority: tuple[str, ...] = ()) -> DataFrame:
    return apply(df, key, attributes, resolution(df, key, attributes, order, rule, latest, predicate, priority))


def resolve_by_list(df: DataFrame, key: Key, attribute: str, chosen: DataFrame, order: str | None = None) -> DataFrame:
    """The expert's values where there is one (chosen: the key columns and ``value``), else the majority."""
    usual = _counts(df, key, [attribute], order).groupBy("_k", "attribute").agg(_counted("majority", None, ()).alias("value"))
    own = chosen.select(*(F.col(k).cast(df.schema[k].dataType).alias(k) for k in key), F.col("value").cast("string").alias("_own"))
    own = own.select(fingerprint(own, key).alias("_k"), "_own")
    return apply(df, key, [attribute], _wide(df, [attribute], usual.join(own, "_k", "left").select("_k", "attribute", F.coalesce("_own", "value").alias("value"))))


def resolve_by_model(df: DataFrame, key: Key, attribute: str, score: Column, order: str | None = None) -> DataFrame:
    """The value with the best score of a caller's (pandas) function of the column ``value``; ties to the least value."""
    scored = _counts(df, key, [attribute], order).withColumn("_s", score)
    best = scored.groupBy("_k", "attribute").agg(F.min_by("value", F.struct((-F.col("_s")).alias("s"), F.col("value"))).alias("value"))
    return apply(df, key, [attribute], _wide(df, [attribute], best))


def decided(df: DataFrame, key: Key, attributes: list[str], order: str | None, rules: dict[str, str | dict], functions: dict[str, Callable[[Column], Column]]) -> DataFrame:
    """The attributes resolved by the expert's rules: a name, or a dictionary with ``rule`` and its parameters.

    latest: ``by`` (a column); validated: ``predicate`` (SQL on ``value``); priority: ``values``; expert: ``values``, a
    list of {"key": [...], "value": ...}; model: ``function``, a name in ``functions``.  Without a rule: majority.
    """
    groups: dict[str, list[str]] = {}
    for a in attributes:
        rule = rules.get(a, "majority")
        groups.setdefault(json.dumps({"rule": rule} if isinstance(rule, str) else rule, sort_keys=True, default=str), []).append(a)
    parsed = [(json.loads(text), own) for text, own in groups.items()]
    by = {f"_by_{r['by']}": F.col(r["by"]) for r, _ in parsed if r.get("by")}
    out = df.withColumns(by) if by else df  # as they were, whatever is resolved before
    for rule, own in parsed:
        name = rule["rule"]
        if name == "expert":
            for a in own:
                kinds = ", ".join(f"`{k}` string" for k in key)
                rows = [(*(None if x is None else str(x) for x in r["key"]), None if r["value"] is None else str(r["value"])) for r in rule["values"]]
                out = resolve_by_list(out, key, a, df.sparkSession.createDataFrame(rows, f"{kinds}, value string"), order)
        elif name == "model":
            for a in own:
                out = resolve_by_model(out, key, a, functions[rule["function"]](F.col("value")), order)
        else:
            out = resolve(out, key, own, order, name, f"_by_{rule['by']}" if rule.get("by") else None, rule.get("predicate"), tuple(rule.get("values", ())))
    return out.select(*df.columns)
