"""Connected components by alternating stars; links and labels stay distributed."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.staging import discard, staged


def connected_components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int | None = None) -> DataFrame:
    """links(a, b) -> node, root: every linked node with the smallest node of its component.

    Each round hangs the neighbours of a node under the smallest one known, first the larger neighbours, then the
    smaller; a component of n nodes becomes one star in O(log n) rounds.  Minima are pre-aggregated on the map side
    and joined back, so a hub costs one row a task, and a skewed join can be split.  With ``max_rounds``, links that
    need more raise.
    """
    edges = staged(links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct())
    seen = _mark(edges)
    for done in count():
        if not seen[0]:
            break
        if done == max_rounds:
            raise RuntimeError(f"connected_components: links still change after {max_rounds} rounds")
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(small, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        before, edges = edges, staged(moved.unionByName(small.select("u", F.col("m").alias("v"))).distinct())
        discard(before)
        now = _mark(edges)
        if now == seen:
            break
        seen = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def _mark(edges: DataFrame) -> tuple[int, int]:
    """Row count and an order-free checksum: equal for equal sets of links."""
    n, h = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return n, int(h or 0)
