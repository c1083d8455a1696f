"""User-defined functions: only where callers bring their own code; built-in expressions are the default path."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf


@F.pandas_udf(T.StringType())
def majority(values: pd.Series) -> str:
    """The most frequent value, ties to the least."""
    counts = values.dropna().value_counts()
    return min(counts[counts == counts.max()].index) if len(counts) else None


@udtf(returnType=T.StructType([T.StructField("sk", T.LongType()), T.StructField("valid_from", T.TimestampNTZType()), T.StructField("value", T.DoubleType())]))
class Compacted:
    """Versions that differ from the one before, for a table partitioned by sk and ordered by time."""

    def __init__(self) -> None:
        self.last: tuple | None = None

    def eval(self, row) -> Iterator[tuple]:  # noqa: ANN001
        now = (row["sk"], row["value"])
        if now != self.last:
            self.last = now
            yield row["sk"], row["valid_from"], row["value"]


@udtf(returnType=T.StructType([T.StructField("attribute", T.StringType()), T.StructField("n", T.LongType()), T.StructField("dv", T.LongType()), T.StructField("nv", T.LongType())]))
class Profiled:
    """Rows, distinct and null values of each attribute of a table of (attribute, value, k) that is ordered by value.

    k counts equal rows folded before.  Only the last value is held; a caller may cut an attribute into parts by its
    values and add up the results.
    """

    def __init__(self) -> None:
        self.attribute: str | None = None
        self.last: object = None
        self.n = self.dv = self.nv = 0

    def eval(self, row) -> None:  # noqa: ANN001
        self.attribute, now, k = row["attribute"], row["value"], row["k"]
        self.n += k
        if now is None:
            self.nv += k
        elif now != self.last:
            self.last, self.dv = now, self.dv + 1

    def terminate(self) -> Iterator[tuple]:
        if self.n:
            yield self.attribute, self.n, self.dv, self.nv


def register(spark: SparkSession) -> None:
    """tk_canon and tk_url as SQL functions, tk_majority as an aggregate, tk_compacted and tk_profiled as table functions."""
    spark.sql("create or replace temporary function tk_canon(s string) returns string return trim(regexp_replace(lower(s), '[^a-z0-9]+', ' '))")
    spark.udf.register("tk_majority", majority)
    spark.udtf.register("tk_compacted", Compacted)
    spark.udtf.register("tk_profiled", Profiled)
