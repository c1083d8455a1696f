"""Plug-in matching: pairs from any matcher become classes by transitive closure."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged
from .components import connected_components


def candidate_pairs(df: DataFrame, sk: str, block: Column, value: str, alike: Callable[[Column, Column], Column]) -> DataFrame:
    """(a, b) with a < b inside a block where ``alike`` holds; equal values are folded first, so copies are not paired.

    Blocks must be small by construction: the caller's blocking key bounds them.
    """
    distinct = df.select(F.col(value).alias("v"), block.alias("_b"), sk).groupBy("_b", "v").agg(F.min(sk).alias("k"))
    a, b = distinct.select("_b", F.col("v").alias("va"), F.col("k").alias("a")), distinct.select("_b", F.col("v").alias("vb"), F.col("k").alias("b"))
    near = a.join(b, "_b").where("a < b").where(alike(F.col("va"), F.col("vb"))).select("a", "b")
    copies = df.select(F.col(value).alias("v"), block.alias("_b"), F.col(sk).alias("b")).join(distinct.select("_b", "v", F.col("k").alias("a")), ["_b", "v"]).where("a < b").select("a", "b")
    return near.unionByName(copies).distinct()


def shingle_set(text: Column, width: int) -> Column:
    """Distinct hashes of runs of ``width`` lower-case words of letters and digits; fewer words are one run."""
    words = F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[a-z0-9]+"), 0)

    def runs(w: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(w) - (width - 1)))
        return F.when(F.size(w) > 0, F.array_sort(F.array_distinct(F.transform(starts, lambda i: F.xxhash64(F.array_join(F.slice(w, i, width), " "))))))

    return F.transform(F.array(words), runs)[0]  # bound once: an expression repeated in a lambda would be evaluated anew


def minhash_pairs(df: DataFrame, sk: str, text: str, width: int = 5, similar: float = 0.8, bands: int = 32, rows: int = 2) -> DataFrame:
    """Links (a, b) whose closure holds all pairs with sets of word shingles of a Jaccard similarity of at least ``similar``.

    Equal sets are folded first, so copies are linked to the least key only.  Signatures are cut into bands; sets that
    share a band are candidates, and each link is confirmed on the whole sets.  A pair at the threshold is missed with
    probability (1 - similar ** rows) ** bands: 6e-15 as it is.  First every set is compared with the least key of each
    of its bands, which joins a group of near copies with as many comparisons as it has members.  Where a band still
    holds several components, those outside its largest one are compared with the rest of the band.
    """
    sets = staged(df.select(F.col(sk).alias("k"), shingle_set(F.col(text), width).alias("s")).where("s is not null"))
    keyed = sets.withColumn("h", F.sha2(F.array_join(F.col("s").cast("array<string>"), ","), 256))
    first = staged(keyed.groupBy("h").agg(F.min("k").alias("k"), F.first("s").alias("s")))
    least = lambda i: F.array_min(F.transform("s", lambda x: F.xxhash64(x, F.lit(i))))
    keys = F.array(*(F.xxhash64(F.lit(b), *(least(b * rows + r) for r in range(rows))) for b in range(bands)))
    posted = staged(first.select("k", F.size("s").alias("n"), F.explode(keys).alias("band")))

    def confirmed(pairs: DataFrame) -> DataFrame:
        both = pairs.distinct().join(first.select(F.col("k").alias("a"), F.col("s").alias("sa")), "a").join(first.select(F.col("k").alias("b"), F.col("s").alias("sb")), "b")
        common = F.size(F.array_intersect("sa", "sb"))
        return staged(both.where(common >= similar * (F.size("sa") + F.size("sb") - common)).select("a", "b"))

    close = F.least("na", "nb") >= similar * F.greatest("na", "nb")
    heads = posted.groupBy("band").agg(F.min(F.struct(F.col("k").alias("a"), F.col("n").alias("na"))).alias("head")).select("band", "head.*")
    star = confirmed(posted.select("band", F.col("k").alias("b"), F.col("n").alias("nb")).join(heads, "band").where("a < b").where(close).select("a", "b"))

    roots = connected_components(star).select(F.col("node").alias("k"), "root")
    rooted = staged(posted.join(roots, "k", "left").withColumn("root", F.coalesce("root", "k")))
    parts = rooted.groupBy("band", "root").agg(F.count(F.lit(1)).alias("size"))
    open_bands = parts.groupBy("band").agg(F.count(F.lit(1)).alias("parts"), F.max_by("root", F.struct("size", "root")).alias("largest")).where("parts > 1").select("band", "largest")
    left = staged(rooted.join(open_bands, "band"))
    x = left.where("root <> largest").select("band", F.col("k").alias("x"), F.col("n").alias("na"), F.col("root").alias("rx"))
    y = left.select("band", F.col("k").alias("y"), F.col("n").alias("nb"), F.col("root").alias("ry"))
    rest = confirmed(x.join(y, "band").where("rx <> ry").where(close).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))

    copies = keyed.select("h", F.col("k").alias("b")).join(first.select("h", F.col("k").alias("a")), "h").where("a < b").select("a", "b")
    return star.unionByName(rest).unionByName(copies)


def classes_from_pairs(df: DataFrame, sk: str, pairs: DataFrame) -> DataFrame:
    """(sk, rep) of every row: pairs closed transitively, with the least key of each class as its representative."""
    roots = connected_components(pairs).select(F.col("node").alias(sk), "root")
    return df.select(sk).join(roots, sk, "left").select(F.col(sk).alias("sk"), F.coalesce("root", sk).alias("rep"))
