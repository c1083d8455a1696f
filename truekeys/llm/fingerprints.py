"""Canonical exact fingerprints, with DataFrame functions only.

A text is brought to a canonical form (compatibility normalisation, full case folding, blanks folded to one), and its
fingerprint is 128 bits of chained xxhash64 of that form.  Documents with equal hashes are then compared byte by byte:
each bucket's least and greatest canonical text must be the same.  Edited texts, which only this operator makes, are
compared with each other and with the documents in the same buckets by the SHA-256 of their canonical forms.  If a
bucket fails, its fingerprints get that SHA-256 appended, so texts that differ never share one.  Likeness of two exact fingerprints is 1 or 0.

The next document (ascending doc_id) is found without a global sort: documents are dealt into range buckets of ids, the
first document of each bucket is lent to the bucket before it, and a window looks one row ahead.

Defined results: a null text is an empty one; equal ids are ordered by text; a null id comes first; a single document is
its own next; other columns are ignored.  Normalisation and folding call the ICU library that Spark ships, by the SQL
function reflect, and only for texts with characters beyond ASCII.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .exchange import range_bucket, staged

#: Hashes of repeated texts (16 bytes each) that are broadcast at most; beyond that the join shuffles.
BROADCAST_HASHES = 1_000_000
BUCKET_ROWS = 512


def folded(text: Column) -> Column:
    """Compatibility normalisation around full case folding; for ASCII both come down to lower case."""

    def nfkc(c: Column) -> Column:
        return F.reflect(F.lit("com.ibm.icu.text.Normalizer"), F.lit("compose"), c, F.lit(True))

    full = nfkc(F.reflect(F.lit("com.ibm.icu.lang.UCharacter"), F.lit("foldCase"), nfkc(text), F.lit(True)))
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(full)


def canonical(text: Column) -> Column:
    return F.btrim(F.regexp_replace(folded(text), r"[\s\p{Z}]+", " "))


def _hashes(df: DataFrame, canon: str, a: str, b: str) -> DataFrame:
    return df.withColumns({a: F.xxhash64(canon), b: F.xxhash64(F.lit(1), canon)})


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text (never null), next_text: the text of the next document, after the last one that of the first."""
    plain = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    dealt = plain.withColumn("_bucket", range_bucket(plain, "doc_id", BUCKET_ROWS))
    firsts = dealt.groupBy("_bucket").agg(F.min("doc_id").alias("_first"))
    whole = Window.orderBy("_bucket")  # one row a bucket, at most as many as range_bucket allows
    lent = firsts.select("_bucket", "_first", F.coalesce(F.lag("_bucket").over(whole), F.max("_bucket").over(Window.partitionBy())).alias("_to"))
    heads = dealt.join(F.broadcast(lent), "_bucket").where(F.col("doc_id").eqNullSafe(F.col("_first"))).groupBy("_to").agg(F.min(F.struct("doc_id", "text")).alias("r"))
    both = dealt.withColumn("_lent", F.lit(0)).unionByName(heads.select(F.col("r.doc_id").alias("doc_id"), F.col("r.text").alias("text"), F.col("_to").alias("_bucket"), F.lit(1).alias("_lent")))
    ahead = Window.partitionBy("_bucket").orderBy("_lent", "doc_id", "text")
    return both.withColumn("next_text", F.lead("text").over(ahead)).where("_lent = 0").select("doc_id", "text", "next_text")


def edited(text: Column, n: Column, following: Column) -> Column:
    """The last quarter (rounded down) replaced by as many characters of the following text, or all of it."""
    k = F.floor(n / 4).cast("int")
    return F.concat(F.substr(text, F.lit(1), n.cast("int") - k), F.substr(following, F.lit(1), k))


def impure_buckets(docs: DataFrame, hashes: DataFrame) -> DataFrame:
    """Hashes (a, b) that documents with different canonical texts share: byte comparison inside equal buckets."""
    again = hashes.groupBy("a", "b").count().where("count > 1").select("a", "b")
    small = again.limit(BROADCAST_HASHES + 1).count() <= BROADCAST_HASHES
    texts = _hashes(docs.select(canonical(F.coalesce("text", F.lit(""))).alias("canon")), "canon", "a", "b")
    members = texts.join(F.broadcast(again) if small else again, ["a", "b"], "left_semi")
    return members.groupBy("a", "b").agg(F.min("canon").alias("low"), F.max("canon").alias("high")).where("low <> high").select("a", "b")


def impure_digests(rows: DataFrame) -> DataFrame:
    """Hashes (a, b) that texts, edited ones included, of different SHA-256 share."""
    edited_too = rows.select("a", "b", "sha").unionByName(rows.select(F.col("ea").alias("a"), F.col("eb").alias("b"), F.col("edited_sha").alias("sha")))
    return edited_too.groupBy("a", "b").agg(F.min("sha").alias("low"), F.max("sha").alias("high")).where("low <> high").select("a", "b")


def fingerprint(a: str, b: str, sha: str, impure: Column) -> Column:
    wide = F.lower(F.concat(F.lpad(F.hex(a), 16, "0"), F.lpad(F.hex(b), 16, "0")))
    return F.when(impure, F.concat(wide, F.lit(":"), F.col(sha))).otherwise(wide)


def fingerprints(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    docs = docs.select("doc_id", "text")
    pairs = with_next(docs).withColumns({"n_chars": F.length("text").cast("long"), "canon": canonical(F.col("text"))})
    pairs = pairs.withColumn("edited", edited(F.col("text"), F.col("n_chars"), F.col("next_text")))
    pairs = pairs.withColumns({"edited_canon": canonical(F.col("edited")), "next_canon": canonical(F.col("next_text"))})
    pairs = _hashes(_hashes(pairs, "canon", "a", "b"), "edited_canon", "ea", "eb")
    rows = staged(
        pairs.select(
            "doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "a", "b", "ea", "eb",
            F.sha2(F.col("canon").cast("binary"), 256).alias("sha"), F.sha2(F.col("edited_canon").cast("binary"), 256).alias("edited_sha"),
            (F.col("canon") == F.col("edited_canon")).cast("double").alias("near_edited"), (F.col("canon") == F.col("next_canon")).cast("double").alias("near_next"),
        )
    )
    flagged = staged(impure_buckets(docs, rows.select("a", "b")).unionByName(impure_digests(rows)).distinct())
    own = other = F.lit(False)
    if not flagged.isEmpty():
        mark = lambda x, y, name: flagged.select(F.col("a").alias(x), F.col("b").alias(y), F.lit(True).alias(name))
        rows = rows.join(mark("a", "b", "own"), ["a", "b"], "left").join(mark("ea", "eb", "other"), ["ea", "eb"], "left")
        own, other = F.col("own").isNotNull(), F.col("other").isNotNull()
    return rows.select("doc_id", "n_chars", "edited_sha256", fingerprint("a", "b", "sha", own).alias("fingerprint"), fingerprint("ea", "eb", "edited_sha", other).alias("edited_fingerprint"), "near_edited", "near_next")
