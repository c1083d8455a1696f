"""Licence scans by sentence rules.

A text is cut into sentences (at line ends, and at full stops and the like before a blank), each is normalised to lower
case words, and known sentences become identifiers.  Licence rules are ordered sequences of identifiers; a rule matches
where its sequence stands in a text's identifiers without a known sentence between.  A second reading joins the lines of
a paragraph first, for licence texts that are wrapped; paragraphs end at lines without words, and a title or copyright
line is a sentence of its own.  A tag line (SPDX-License-Identifier) is one sentence.  Sentences and rules are read from
licences.tsv.  The first matching rule in the order of the list names the
licence; longer sequences stand first, so a full licence text outranks a notice in it.

All steps are DataFrame functions.  Defined results: a null or empty text has no sentences and no licence; rows are
scanned one by one; other columns are ignored.
"""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Identifiers of tag sentences begin here; they follow the order of the names in the file.
TAGS = 1000


def _table() -> tuple[dict[int, str], tuple[tuple[str, tuple[int, ...]], ...]]:
    """(sentences by identifier, ordered rules) of the file beside this module."""
    sentences, rules, names = {}, [], []
    for line in Path(__file__).with_name("licences.tsv").read_text(encoding="utf-8").splitlines():
        kind, *rest = line.split("\t")
        if kind == "S":
            sentences[int(rest[0])] = rest[1]
        elif kind == "R":
            rules.append((rest[0], tuple(map(int, rest[1].split()))))
        elif kind == "N":
            names.append(rest[0])
    tags = {TAGS + i: n for i, n in enumerate(names)}
    return sentences | {i: f"SPDX-License-Identifier {n}" for i, n in tags.items()}, (*rules, *((n, (i,)) for i, n in tags.items()))


#: Known sentences by identifier; (licence, sequence of identifiers), of which the first match names the licence.
SENTENCES, RULES = _table()


def normal(sentence: str) -> str:
    """What the column expressions make of a sentence."""
    kept = "".join(c if c in LOWER or c.isdigit() and c.isascii() else " " for c in sentence.translate(str.maketrans(UPPER, LOWER)))
    return " ".join(kept.split())


KNOWN = {normal(s): i for i, s in SENTENCES.items()}
if len(KNOWN) < len(SENTENCES):
    raise ValueError("two sentences of licences.tsv are alike once normalised")

TAG = "SPDX-License-Identifier:"


def _identifiers(text: Column) -> Column:
    """The identifiers of the known sentences, in the order of the text."""
    known = F.create_map(*(F.lit(x) for pair in KNOWN.items() for x in pair))
    tagged = F.when(text.contains(TAG), F.regexp_replace(text, TAG + r"[ \t]*", TAG.removesuffix(":") + " ")).otherwise(text)
    cut = F.split(F.regexp_replace(tagged, r"([.!?;:])[ \t\r]+", "$1\n"), "\n")
    firsts = sorted({n.split(" ")[0] for n in KNOWN})

    def lookup(s: Column) -> Column:
        return F.try_element_at(known, F.trim(F.regexp_replace(F.translate(s, UPPER, LOWER), "[^a-z0-9]+", " ")))

    # only sentences that begin like a known one are normalised
    start = r"(?i)^[^a-z0-9]*(" + "|".join(firsts) + r")([^a-z0-9]|$)"
    return F.filter(F.transform(F.filter(cut, lambda s: s.rlike(start)), lookup), lambda i: i.isNotNull())


MARKS = r"[ \t\r*#/;>|-]*"
COPYRIGHT = rf"(?im)^({MARKS}(?:copyright[ \t:,]*(?:\(c\)|©|&copy;|<|\[|[0-9]{{4}})|(?:\(c\)|©)[ \t]*[0-9]{{4}})[^\n]*)$"
ADDRESS = r" +(https?://[^ \n]+)"
TITLE = rf"(?im)(\A|\n{MARKS}\n)({MARKS}(?:[a-z0-9.\"'&+-]+[ \t]+){{0,6}}licen[sc]e(?:[ \t]*\([^)\n]*\))?(?:,?[ \t]+v(?:ersion)?[ \t]*[0-9.]+)?[ \t\r:]*)$"


def _joined(text: Column) -> Column:
    """The lines of each paragraph joined; title and copyright lines are paragraphs, and addresses are lines."""
    apart = F.regexp_replace(F.regexp_replace(text, COPYRIGHT, "\n\n$1\n\n"), TITLE, "$1$2\n\n")
    whole = F.array_join(F.transform(F.split(apart, rf"\n(?:{MARKS}\n)+"), lambda p: F.regexp_replace(p, r"\r?\n", " ")), "\n")
    return F.when(whole.contains("://"), F.regexp_replace(whole, ADDRESS, "\n$1\n")).otherwise(whole)


def _listed(ids: Column) -> Column:
    return F.concat(F.lit(","), F.array_join(ids.cast("array<string>"), ","), F.lit(","))


def licence_scan(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_sentences (known ones), sentence_ids, licence (null if none), n_rules (matches)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = docs.select("doc_id", _identifiers(text).alias("a"), _identifiers(_joined(text)).alias("b"))
    listed = lines.withColumns({"la": _listed(F.col("a")), "lb": _listed(F.col("b"))})
    hits = [F.col("la").contains(f",{','.join(map(str, ids))},") | F.col("lb").contains(f",{','.join(map(str, ids))},") for _, ids in RULES]
    licence = F.coalesce(*(F.when(h, F.lit(name)) for h, (name, _) in zip(hits, RULES, strict=True)))
    longer = F.size("b") > F.size("a")
    return listed.select(
        "doc_id",
        F.greatest(F.size("a"), F.size("b")).cast("long").alias("n_sentences"),
        F.when(longer, F.col("lb")).otherwise(F.col("la")).alias("sentence_ids"),
        licence.alias("licence"),
        sum(h.cast("long") for h in hits).alias("n_rules"),
    )


def oracle() -> str:
    """The same in DuckDB SQL for texts without blank, title and copyright lines; it joins the whole text."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    known = "MAP {" + ", ".join(f"{quote(k)}: {i}" for k, i in KNOWN.items()) + "}"

    def ids(text: str) -> str:
        tagged = f"regexp_replace({text}, '{TAG}[ \\t]*', '{TAG.removesuffix(':')} ', 'g')"
        cut = f"string_split(regexp_replace({tagged}, '([.!?;:])[ \\t\\r]+', '\\1' || chr(10), 'g'), chr(10))"
        norm = f"trim(regexp_replace(translate(s, '{UPPER}', '{LOWER}'), '[^a-z0-9]+', ' ', 'g'))"
        return f"list_filter(list_transform({cut}, lambda s: known[{norm}]), lambda i: i is not null)"

    has = [f"(contains(la, ',{','.join(map(str, i))},') or contains(lb, ',{','.join(map(str, i))},'))" for _, i in RULES]
    return f"""
with k as (select {known} as known),
d as (select doc_id, {ids("coalesce(text, '')")} as a, {ids(f"regexp_replace(regexp_replace(coalesce(text, ''), chr(13) || '?' || chr(10), ' ', 'g'), '{ADDRESS}', chr(10) || '{chr(92)}1' || chr(10), 'g')")} as b from documents, k),
e as (select doc_id, a, b, ',' || array_to_string(a, ',') || ',' as la, ',' || array_to_string(b, ',') || ',' as lb from d)
select doc_id, cast(greatest(len(a), len(b)) as bigint) as n_sentences, case when len(b) > len(a) then lb else la end as sentence_ids,
  coalesce({", ".join(f"case when {h} then '{n}' end" for h, (n, _) in zip(has, RULES, strict=True))}) as licence,
  cast({" + ".join(f"{h}::INT" for h in has)} as bigint) as n_rules from e"""
