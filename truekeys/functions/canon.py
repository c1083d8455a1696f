"""Canonical forms: two values are alike if their canonical forms are equal, so any likeness used is transitive."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Accented Latin letters and their plain ones.
ACCENTED, PLAIN = "àâäáãåçèéêëìíîïñòóôöõùúûüýÿÀÂÄÁÃÅÇÈÉÊËÌÍÎÏÑÒÓÔÖÕÙÚÛÜÝ", "aaaaaaceeeeiiiinooooouuuuyyAAAAAACEEEEIIIINOOOOOUUUUY"


def text(c: Column) -> Column:
    """Lower case, accents and punctuation off, blanks folded."""
    return F.trim(F.regexp_replace(F.lower(F.translate(c, ACCENTED, PLAIN)), "[^a-z0-9]+", " "))


def url(c: Column) -> Column:
    """Without scheme, leading www. or m., query, fragment and closing slash; lower case host and path."""
    bare = F.regexp_replace(F.lower(F.trim(c)), r"^[a-z]+://", "")
    bare = F.regexp_replace(F.regexp_replace(bare, r"^(www|m)\.", ""), r"[?#].*$", "")
    return F.regexp_replace(bare, r"/+$", "")


def date(c: Column) -> Column:
    """A date from day-month-year with dashes or slashes, or year-month-day; null if none fits."""
    return F.coalesce(*(F.try_to_timestamp(c, F.lit(f)) for f in ("dd-MM-yyyy", "dd/MM/yyyy", "yyyy-MM-dd"))).cast("date")


def comparable(df: DataFrame, name: str) -> Column:
    """A form of the column that can be grouped: maps become arrays of entries by key."""
    c = F.col(name)
    return F.sort_array(F.map_entries(c)) if isinstance(df.schema[name].dataType, T.MapType) else c


def part(c: Column, kind: T.DataType) -> Column:
    """The value as text that differs exactly where Spark's grouping tells two values of the type apart; null is 'n'.

    Texts are prefixed with their length in bytes, so parts can be put end to end.  Timestamps are counted in
    microseconds, -0.0 is 0.0 at any depth, and strings and binaries are taken byte by byte; a string type of another
    collation, in which texts of different bytes can be equal, is refused.
    """
    if isinstance(kind, T.StructType):
        own = F.when(c.isNotNull(), F.concat(F.lit("{"), *(part(c.getField(f.name), f.dataType) for f in kind.fields), F.lit("}")))
    elif isinstance(kind, T.ArrayType):
        own = F.concat(F.lit("["), F.array_join(F.transform(c, lambda x: part(x, kind.elementType)), ""), F.lit("]"))
    elif isinstance(kind, T.MapType):
        entry = lambda e: F.concat(part(e["key"], kind.keyType), part(e["value"], kind.valueType))
        own = F.concat(F.lit("<"), F.array_join(F.array_sort(F.transform(F.map_entries(c), entry)), ""), F.lit(">"))
    else:
        if isinstance(kind, T.StringType) and kind.collation != "UTF8_BINARY":
            raise TypeError(f"texts of collation {kind.collation} have no form by bytes; bring them to a canonical form first")
        if isinstance(kind, T.FloatType | T.DoubleType):
            c = c + F.lit(0.0).cast(kind)
        elif isinstance(kind, T.TimestampType):
            c = F.unix_micros(c)
        elif isinstance(kind, T.BinaryType):
            c = F.hex(c)
        shown = c.cast("string")
        own = F.concat(F.octet_length(shown).cast("string"), F.lit(":"), shown)
    return F.coalesce(own, F.lit("n"))


def fingerprint(df: DataFrame, columns: list[str] | tuple[str, ...]) -> Column:
    """256 bits of the columns' values: one narrow, never-null grouping and join key for any number of columns.

    Null is a value of its own, which makes equality null-safe; two rows have one key exactly if Spark's own grouping
    by the columns (maps as sets of entries) would put them together.
    """
    return F.sha2(F.concat(F.lit(""), *(part(F.col(c), df.schema[c].dataType) for c in columns)), 256)
