"""Plumbing shared by the operators: document blocks, gapless ranks, and packed posting exchanges.

Three of the operators ask one question of the whole corpus: "which of my keys (anchors, windows, lines, signature
coordinates) also occur elsewhere, and where first?".  They answer it with the same three steps, which keep a hot key
harmless and move few bytes:

1. documents are dealt into blocks by a hash of ``doc_id`` and text; a block folds its own repeats, so that a key which a third
   of all documents hold costs one posting a block, not one a document;
2. postings travel as packed numpy columns, one row for each (block, key shard), and a shard decides on its keys;
3. verdicts travel back to the block, which is cogrouped with its documents.  Every pass reads the documents from the
   same exchange (Spark reuses it), so texts are shuffled once.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged as staged  # noqa: PLC0414  the operators take it from here

#: Documents in one block, and documents whose postings one key shard receives, on average; bytes of a block's texts.
BLOCK_ROWS, SHARD_ROWS, BLOCK_BYTES = 1024, 4096, 24_000_000
POSTING = "_shard int, _block int, c0 binary, c1 binary, c2 binary"


def counts(docs: DataFrame) -> tuple[int, int]:
    """(blocks, shards) for the number of rows and the bytes of their texts.

    Both grow with the input, so what a task holds stays bounded: a block has ``BLOCK_ROWS`` documents or ``BLOCK_BYTES``
    of text on average, whichever is less.  A block reaches as many shards as it has keys at most, so with many shards
    its packed rows get short; from 4 million rows on, blocks grow up to 8-fold in rows (never in bytes) and shards up
    to 16-fold to keep them worth packing.
    """
    own = F.octet_length("text").cast("long") if "text" in docs.columns else F.lit(0)
    n, size = docs.agg(F.count(F.lit(1)), F.sum(own)).first()
    factor = max(1.0, math.sqrt(n / 4_000_000))
    blocks = max(math.ceil(n / (BLOCK_ROWS * min(8.0, factor))), math.ceil((size or 0) / BLOCK_BYTES))
    return max(1, blocks), max(1, math.ceil(n / (SHARD_ROWS * min(16.0, factor))), math.ceil((size or 0) / (4 * BLOCK_BYTES)))


def with_block(docs: DataFrame, blocks: int, by: tuple[str, ...] = ("doc_id", "text")) -> DataFrame:
    """docs with a block that depends on id and text, so that one id (or none) is no hot block.

    Only rows that are alike in both meet in one block whatever their number.
    """
    return docs.withColumn("_block", F.pmod(F.xxhash64(*by), F.lit(blocks)).cast("int"))


def carried(docs: DataFrame, keep: bool) -> tuple[DataFrame, list[str], str]:
    """(docs with the other columns under safe names, those names, their schema text) for operators that pass rows on."""
    others = [c for c in docs.columns if c not in ("doc_id", "text")] if keep else []
    renamed = docs.select("doc_id", "text", *(F.col(f"`{c}`").alias(f"_keep{i}") for i, c in enumerate(others)))
    return renamed, [f"_keep{i}" for i in range(len(others))], "".join(f", _keep{i} {docs.schema[c].dataType.simpleString()}" for i, c in enumerate(others))


def passed_on(docs: DataFrame, result: DataFrame, text: Column) -> DataFrame:
    """The rows of docs with another text (and its n_chars, if docs has that), from a result with carried columns."""
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    new = {"doc_id": F.col("doc_id"), "text": text.alias("text")} | {c: F.col(f"_keep{i}").alias(c) for i, c in enumerate(others)}
    if "n_chars" in others:
        new["n_chars"] = F.length(text).cast(docs.schema["n_chars"].dataType).alias("n_chars")
    return result.select(*(new[c] for c in docs.columns))


def scatter(block: int, key: np.ndarray, columns: list[np.ndarray], shards: int) -> pa.Table:
    """Postings of one block as packed rows, one for each shard that gets any. key: uint64, chooses the shard."""
    shard = (key % np.uint64(shards)).astype(np.uint16 if shards <= 1 << 16 else np.int64)
    order = np.argsort(shard, kind="stable")
    return packed(shard[order], [c[order] for c in columns], "_shard", {"_block": block})


def packed(group: np.ndarray, columns: list[np.ndarray], name: str, fixed: dict[str, int]) -> pa.Table:
    """One row for each run of equal values in the sorted ``group``, with the columns' bytes."""
    used, starts = np.unique(group, return_index=True)
    ends = np.append(starts[1:], len(group))
    out = {name: pa.array(used.astype(np.int32))} | {k: pa.array(np.full(len(used), v, np.int32)) for k, v in fixed.items()}
    for i in range(3):
        out[f"c{i}"] = pa.array([columns[i][s:e].tobytes() for s, e in zip(starts, ends, strict=True)] if i < len(columns) else [None] * len(used), pa.binary())
    return pa.table({k: out[k] for k in ("_shard", "_block", "c0", "c1", "c2")})


def unpacked(table: pa.Table, kinds: list[str], owner: str) -> tuple[np.ndarray, list[np.ndarray]]:
    """The postings of all rows of the table, and for each the value of its row's ``owner`` column."""
    columns = []
    for i, kind in enumerate(kinds):
        columns.append(np.frombuffer(b"".join(x or b"" for x in table.column(f"c{i}").to_pylist()), dtype=kind))
    width = np.dtype(kinds[0]).itemsize
    lengths = np.array([len(x or b"") // width for x in table.column("c0").to_pylist()], np.int64)
    return np.repeat(table.column(owner).to_numpy().astype(np.int64), lengths), columns


def empty(schema: pa.Schema | None = None) -> pa.Table:
    schema = schema or pa.schema([("_shard", pa.int32()), ("_block", pa.int32()), ("c0", pa.binary()), ("c1", pa.binary()), ("c2", pa.binary())])
    return schema.empty_table()


def range_bucket(df: DataFrame, column: str, rows: int, most: int = 200_000, knots: int = 32) -> Column:
    """A bucket number that rises with the numeric column, with about ``rows`` rows in each of at most ``most`` buckets.

    Knots at approximate quantiles keep buckets even when ids are not; between two knots buckets are equally wide.
    Null is bucket -1.
    """
    n, q = df.agg(F.count(column), F.percentile_approx(column, [i / knots for i in range(knots + 1)], 2000)).first()
    marks = sorted({float(x) for x in q or [0]})
    steps = max(1, math.ceil(min(max(1, n / rows), most) / max(1, len(marks) - 1)))
    x, out = F.col(column).cast("double"), None
    for i in reversed(range(max(1, len(marks) - 1))):
        low, high = marks[i], marks[min(i + 1, len(marks) - 1)]
        wide = max((high - low) / steps, 1e-300)
        own = (F.lit(i * steps) + F.greatest(F.lit(0), F.least(F.lit(steps - 1), F.floor((x - low) / wide)))).cast("int")
        out = own if out is None else F.when(x < high, own).otherwise(out)
    return F.when(F.col(column).isNull(), F.lit(-1)).otherwise(out)


def ranked(df: DataFrame, group: str, order: list[str], name: str, rows: int = 16384) -> DataFrame:
    """df with gapless numbers from 0 within each group, by ``order`` (its first column numeric).

    A group may hold any share of the rows: numbers are counted inside range buckets, and each bucket starts at the
    running total of those before it.
    """
    from pyspark.sql import Window

    dealt = df.withColumn("_bucket", range_bucket(df, order[0], rows))
    before = Window.partitionBy(group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = dealt.groupBy(group, "_bucket").count().select(group, "_bucket", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_base"))
    own = Window.partitionBy(group, "_bucket").orderBy(*order)
    return dealt.withColumn("_own", F.row_number().over(own)).join(base, [group, "_bucket"]).withColumn(name, F.col("_base") + F.col("_own") - 1).drop("_bucket", "_own", "_base")
