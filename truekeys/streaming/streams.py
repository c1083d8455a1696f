"""Streams: profiles over windows, incremental key maps, following of foreign keys.

Event time arrives as a timestamp without zone, which watermarks do not take, so it is cast under a UTC session.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.query import StreamingQuery

from ..functions.canon import fingerprint
from ..operators.equivalence import sk_map
from ..operators.propagate import apply_map


def source(spark: SparkSession, folder: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def event_time(df: DataFrame, column: str = "ts", late: str = "10 minutes") -> DataFrame:
    return df.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, late)


def tumbling(df: DataFrame, by: str, value: str, size: str = "1 day", slide: str | None = None, column: str = "ts") -> DataFrame:
    """Rows, null values and approximate distinct values by window; works on streams and on batches."""
    return df.groupBy(F.window(column, size, slide), by).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col(value).isNull()).alias("nv"), F.approx_count_distinct(value).alias("dv"))


def sessions(df: DataFrame, by: str, gap: str = "30 minutes", column: str = "ts") -> DataFrame:
    return df.groupBy(F.session_window(column, gap), by).agg(F.count(F.lit(1)).alias("n"))


def without_repeats(df: DataFrame, key: list[str]) -> DataFrame:
    """Rows whose key was not seen within the watermark."""
    return df.dropDuplicatesWithinWatermark(key)


def follow(df: DataFrame, fk: str, mapping: DataFrame) -> DataFrame:
    """A stream's foreign keys by a stored map."""
    return apply_map(df, fk, mapping)


def joined(a: DataFrame, b: DataFrame, key: str, column: str = "ts", within: str = "1 hour") -> DataFrame:
    """Two streams of events with equal keys at most ``within`` apart."""
    left, right = a.alias("a"), b.withColumnRenamed(column, "_ts").withColumnRenamed(key, "_key").alias("b")
    near = F.expr(f"a.{key} = b._key and b._ts between a.{column} and a.{column} + interval {within}")
    return left.join(right, near)


class Levels:
    """Rows added batch by batch as written tables; tables of one rank are merged into one of the next.

    A row is rewritten as often as the number of batches can be halved, and there are as many tables as that.
    """

    def __init__(self, write: Callable[[DataFrame, int], DataFrame], merge: Callable[[DataFrame], DataFrame], sign: int) -> None:
        self.write, self.merge, self.sign = write, merge, sign
        self.tables: list[tuple[int, DataFrame]] = []
        self.written = 0

    def add(self, rows: DataFrame) -> None:
        rank = 0
        while self.tables and self.tables[-1][0] == rank:
            rows, rank = self.tables.pop()[1].unionByName(rows), rank + 1
        kept = self.write(self.merge(rows) if rank else rows, self.sign * (self.written + 1))
        self.written += 1
        self.tables.append((rank, kept))

    def all(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [x for _, x in self.tables])


class StoredMap:
    """An incrementally kept map: the first surrogate value of a class is its representative until a smaller one comes.

    Each batch writes the classes that are new to it or whose representative falls, and nothing else; the stored levels
    are merged now and then.  A batch that is delivered twice changes nothing.  Revisions say which representative
    replaced which.  ``write`` stores a table under a number (positive: state, negative: revisions) and gives it back.
    """

    def __init__(self, sk: str, key: list[str], write: Callable[[DataFrame, int], DataFrame]) -> None:
        self.sk, self.key = sk, key
        self._levels = Levels(write, lambda x: x.groupBy("_k").agg(F.min("rep").alias("rep")), 1)
        self._revised = Levels(write, lambda x: x, -1)

    @property
    def state(self) -> DataFrame | None:
        """(_k, rep) of every class seen."""
        return self._levels.all().groupBy("_k").agg(F.min("rep").alias("rep")) if self._levels.tables else None

    @property
    def revisions(self) -> list[DataFrame]:
        return [x for _, x in self._revised.tables]

    def update(self, batch: DataFrame, number: int | None = None) -> None:
        new = batch.groupBy(fingerprint(batch, self.key).alias("_k")).agg(F.min(self.sk).alias("rep"))
        if not self._levels.tables:
            self._levels.add(new)
            return
        asked = self._levels.all().join(new.select("_k"), "_k", "left_semi").groupBy("_k").agg(F.min("rep").alias("was"))
        changed = new.join(asked, "_k", "left").where("was is null or rep < was")
        self._revised.add(changed.where("was is not null").select("_k", "was", "rep"))
        self._levels.add(changed.select("_k", "rep"))

    def sink(self, live: DataFrame, checkpoint: str) -> StreamingQuery:
        """Feeds the map from a stream, batch by batch, until what is available is read."""
        return each_batch(live, self.update, checkpoint)

    def mapping(self, rows: DataFrame) -> DataFrame:
        """(sk, rep) of the rows under the current state."""
        keyed = rows.select(F.col(self.sk).alias("sk"), fingerprint(rows, self.key).alias("_k"))
        return keyed.join(self.state, "_k").where("sk <> rep").select("sk", "rep").distinct()


def each_batch(live: DataFrame, work: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Runs ``work`` on every micro-batch, where batch operators such as exact distinct counts are allowed."""
    return live.writeStream.foreachBatch(work).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def batch_map(rows: DataFrame, sk: str, key: list[str]) -> DataFrame:
    return sk_map(rows, sk, key)


def first_seen(df: DataFrame, key: str, sk: str) -> DataFrame:
    """A custom stateful operator: for each key the least surrogate value so far, a row whenever it falls."""
    def step(k: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        known = state.get[0] if state.exists else None
        least = min((int(b[sk].min()) for b in batches), default=known)
        if known is None or least < known:
            state.update((least,))
            yield pd.DataFrame({key: [k[0]], "rep": [least], "was": [known]}).astype({"was": "Int64"})

    kind = df.schema[key].dataType.simpleString()
    return df.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, rep long, was long", "least long", "append", "NoTimeout")
