"""Stability, decomposition, conflict resolution, reduction."""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import canon
from ..operators import analytics, chase, decompose, matching, metrics, pollute, profile, propagate, reduce, stability, verify
from ..plans.model import Database
from ..plans.staging import staged
from ..sources.io import union_all
from .block1 import g3_sql
from .block2 import URL, au_sql, text_db
from .registry import COLUMNS, NKS, ORDER, borne_out_sql, once, poll_sql, polluted, query, star, suppressed, t, with_clean


def stability_sql(table: str, key: str, attributes: tuple[str, ...]) -> str:
    return " union all ".join(f"select '{a}' as attribute, g3 as stability from ({g3_sql(table, key, a)})" for a in attributes)


DOC = ("lang", "source", "n_chars")
PART = ("p_brand", "p_type", "p_size", "p_retailprice")
LINE = ("l_partkey", "l_suppkey", "l_quantity", "l_returnflag", "l_shipdate")


@query("stability_documents", stability_sql("documents", "text", DOC))
def stability_documents(spark: SparkSession, folder: str) -> DataFrame:
    return stability.profile(t(spark, folder, "documents"), ["text"], list(DOC))


@query("stability_part_pname", stability_sql("part", "p_name", PART))
def stability_part_pname(spark: SparkSession, folder: str) -> DataFrame:
    return stability.profile(t(spark, folder, "part"), ["p_name"], list(PART))


# Twins of customer whose values drift: the experiments' twins are exact, so conflicts need changes of their own.

_LIMITS = pollute.threshold(0.5), pollute.threshold(0.125)
_DRIFT = f"""drift as (select new_id, c_custkey, c_name, c_nationkey,
  c_acctbal + case when new_id % 2 = 1 and left(md5('42|drift|' || c_custkey), 8) < '{_LIMITS[0]}' then 1.0 else 0.0 end as c_acctbal,
  case when new_id % 2 = 1 and left(md5('42|drift|' || c_custkey), 8) < '{_LIMITS[1]}' then 'DRIFTED' else c_mktsegment end as c_mktsegment from poll_customer)"""
_DRIFTED = f"""with {poll_sql()}, {_DRIFT},
map_region as (select new_id as old, min(new_id) over (partition by r_name) as rep from poll_region),
ref_nation as (select p.new_id, p.n_name, m.rep as n_regionkey from poll_nation p left join map_region m on p.n_regionkey = m.old),
map_nation as (select new_id as old, min(new_id) over (partition by n_name, n_regionkey) as rep from ref_nation),
ref as (select d.new_id as orig, d.c_custkey, d.c_name, m.rep as c_nationkey, d.c_acctbal, d.c_mktsegment from drift d left join map_nation m on d.c_nationkey = m.old),
cust as (select min(orig) over (partition by c_name, c_nationkey) as new_id, * from ref),
ord as (select o.new_id, o.o_orderkey, o.o_custkey as orig, o.o_orderdate from poll_orders o),
full_history as (select distinct c.new_id, c.c_name, c.c_nationkey, o.o_orderdate, c.c_acctbal from cust c left join ord o on c.orig = o.orig)
"""


@once
def drifted(spark: SparkSession, folder: str) -> Database:
    """The polluted star with drifting customer twins, after suppression, with lineage."""
    db = polluted(spark, folder)
    db.tables["customer"] = pollute.drift(db.tables["customer"], "c_custkey")
    small = Database(db.spec.restrict(["region", "nation", "customer", "orders"]), {n: db.tables[n] for n in ("region", "nation", "customer", "orders")})
    out = propagate.suppress(small, lineage=True).db
    return Database(out.spec, {n: staged(x) for n, x in out.tables.items()})


KEY = list(NKS["customer"])


@query("stability_customer_drift", _DRIFTED + stability_sql("cust", "c_name, c_nationkey", ("c_acctbal", "c_mktsegment")))
def stability_customer_drift(spark: SparkSession, folder: str) -> DataFrame:
    return stability.profile(drifted(spark, folder).tables["customer"], KEY, ["c_acctbal", "c_mktsegment"])


@query("stability_vs_redline", "select attribute, dv, dv > (select count(distinct p_name) from part) as above_line from (" + " union all ".join(f"select '{a}' as attribute, count(distinct {a}) as dv from part" for a in PART) + ")")
def stability_vs_redline(spark: SparkSession, folder: str) -> DataFrame:
    p = t(spark, folder, "part")
    line = profile.lines(p, ["p_name"]).first()["nk_line"]
    return stability.red_line_hint(profile.rrp(p, list(PART)), line, list(PART))


def risk_sql(table: str, key: str, attributes: tuple[str, ...]) -> str:
    return f"with s as ({stability_sql(table, key, attributes)}), a as ({au_sql(table, key)}), r as (select case when au = 0 then 0 else round(stability / au, 6) end as ratio from s, a) select count(*) as attributes, count(*) filter (where ratio >= 0.9) as near_bound, 2 * count(*) filter (where ratio >= 0.9) > count(*) as nk_suspect from r"


@query("nk_risk_lineitem", risk_sql("lineitem", "l_orderkey, l_linenumber", LINE))
def nk_risk_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    d, key = t(spark, folder, "lineitem"), ["l_orderkey", "l_linenumber"]
    return stability.nk_risk(stability.profile(d, key, list(LINE)), metrics.au(d, "l_partkey", key))


@query("nk_risk_part", risk_sql("part", "p_name", PART))
def nk_risk_part(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "part")
    return stability.nk_risk(stability.profile(d, ["p_name"], list(PART)), metrics.au(d, "p_partkey", ["p_name"]))


@query("stability_normalised_documents", f"with s as ({stability_sql('documents', 'text', DOC)}), a as ({au_sql('documents', 'text')}) select attribute, stability, case when au = 0 then 0.0 else round(stability / au, 6) end as ratio from s, a")
def stability_normalised_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents")
    return stability.normalised(stability.profile(d, ["text"], list(DOC)), metrics.au(d, "doc_id", ["text"]))


@query("classify_documents", f"select attribute, stability, case when stability > 0 then 'AtbN' else 'AtbC' end as role from ({stability_sql('documents', 'text', DOC)})")
def classify_documents(spark: SparkSession, folder: str) -> DataFrame:
    return stability.classify(stability.profile(t(spark, folder, "documents"), ["text"], list(DOC)))


@query("classify_override_documents", f"select attribute, stability, case when attribute = 'source' then 'AtbC' when attribute = 'lang' then 'AtbN' when stability > 0 then 'AtbN' else 'AtbC' end as role from ({stability_sql('documents', 'text', DOC)})")
def classify_override_documents(spark: SparkSession, folder: str) -> DataFrame:
    return stability.classify(stability.profile(t(spark, folder, "documents"), ["text"], list(DOC)), 0.0, ["source"], ["lang"])


@query("split_stable_customer", _DRIFTED + "select distinct new_id, c_name, c_nationkey, c_custkey, c_mktsegment from cust")
def split_stable_customer(spark: SparkSession, folder: str) -> DataFrame:
    return decompose.stable_part(drifted(spark, folder).tables["customer"], ["new_id"], KEY, ["c_custkey", "c_mktsegment"])


def _history(spark: SparkSession, folder: str) -> DataFrame:
    db = drifted(spark, folder)
    return decompose.history(decompose.completed(db, "customer", "orders.o_orderdate"), ["new_id"], KEY, ["o_orderdate"], ["c_acctbal"])


@query("split_history_customer", _DRIFTED + "select * from full_history")
def split_history_customer(spark: SparkSession, folder: str) -> DataFrame:
    return _history(spark, folder)


@query("history_key_violations", _DRIFTED + "select count(*) as n_groups from (select new_id, o_orderdate from full_history group by all having count(*) > 1)")
def history_key_violations(spark: SparkSession, folder: str) -> DataFrame:
    return verify.violations(_history(spark, folder), ["new_id", "o_orderdate"])


_ONE = ", one_a_day as (select new_id, o_orderdate, min(c_acctbal) as c_acctbal from full_history group by new_id, o_orderdate) "


def _one_a_day(spark: SparkSession, folder: str) -> DataFrame:
    return _history(spark, folder).groupBy("new_id", "o_orderdate").agg(F.min("c_acctbal").alias("c_acctbal"))


@query("history_compacted_customer", _DRIFTED + _ONE + "select new_id, o_orderdate, c_acctbal from (select *, lag(c_acctbal) over w as before, row_number() over w as r from one_a_day window w as (partition by new_id order by o_orderdate nulls first)) where r = 1 or before is distinct from c_acctbal")
def history_compacted_customer(spark: SparkSession, folder: str) -> DataFrame:
    return decompose.compacted(_one_a_day(spark, folder), "new_id", "o_orderdate", ["c_acctbal"])


@query("history_validity", _DRIFTED + _ONE + "select new_id, o_orderdate as valid_from, lead(o_orderdate) over (partition by new_id order by o_orderdate nulls first) as valid_to, c_acctbal from one_a_day")
def history_validity(spark: SparkSession, folder: str) -> DataFrame:
    return decompose.validity(_one_a_day(spark, folder), "new_id", "o_orderdate")


@query("history_array_customer", _DRIFTED + _ONE + "select new_id, count(*) as n_versions, array_to_string(list(cast(round(c_acctbal, 2) as varchar) order by o_orderdate nulls first), ';') as versions from (select new_id, o_orderdate, cast(c_acctbal as decimal(18,2)) as c_acctbal from one_a_day) group by new_id")
def history_array_customer(spark: SparkSession, folder: str) -> DataFrame:
    own = _one_a_day(spark, folder).withColumn("c_acctbal", F.col("c_acctbal").cast("decimal(18,2)"))
    grouped = own.groupBy("new_id").agg(F.count(F.lit(1)).alias("n_versions"), F.array_sort(F.collect_list(F.struct("o_orderdate", "c_acctbal"))).alias("h"))
    return grouped.select("new_id", "n_versions", F.array_join(F.transform("h", lambda x: x["c_acctbal"].cast("string")), ";").alias("versions"))


@query("split_documents_source", "select distinct min(doc_id) over (partition by text) as doc_id, cast(row_number() over (partition by text order by doc_id) as int) as copy_no, source from documents")
def split_documents_source(spark: SparkSession, folder: str) -> DataFrame:
    """The completing attribute is in the relation: the number of the copy."""
    from pyspark.sql import Window

    key = canon.fingerprint(t(spark, folder, "documents"), ["text"])
    d = t(spark, folder, "documents").withColumn("k", key).withColumn("copy_no", F.row_number().over(Window.partitionBy("k").orderBy("doc_id"))).drop("k")
    return decompose.history(propagate.collapse_key(d, "doc_id", ["text"]), ["doc_id"], ["text"], ["copy_no"], ["source"], carry_key=False)


@query("chase_conflicts_documents", "with p as (select text, source, count(*) as c, min(doc_id) as f from documents group by text, source) select md5(text) as text_md5, count(*) as n_values, array_to_string(list(source order by c desc, f), ',') as \"values\" from p group by text having count(*) > 1")
def chase_conflicts_documents(spark: SparkSession, folder: str) -> DataFrame:
    return chase.conflicts(t(spark, folder, "documents"), ["text"], "source", "doc_id").select(F.md5(F.col("text").cast("binary")).alias("text_md5"), "n_values", F.array_join("values", ",").alias("values"))


_PICKS = {
    "majority": "c desc, f",
    "min": "c_mktsegment",
    "max": "c_mktsegment desc",
    "first": "f",
    "longest": "length(c_mktsegment) desc, c_mktsegment desc",
    "validated": "case when c_mktsegment <> 'DRIFTED' then 0 else 1 end, c desc, f",
}


def chase_sql(order: str) -> str:
    per = "select c_name, c_nationkey, c_mktsegment, count(*) as c, min(orig) as f from cust group by all"
    return _DRIFTED + f"select c.orig as orig_id, c.new_id, b.v as c_mktsegment from cust c join (select c_name, c_nationkey, first(c_mktsegment order by {order}) as v from ({per}) group by all) b on c.c_name = b.c_name and c.c_nationkey = b.c_nationkey"


for _rule, _order in _PICKS.items():

    @query("chase_customer_segment" if _rule == "majority" else f"chase_rule_{_rule}", chase_sql(_order))
    def _chase(spark: SparkSession, folder: str, rule: str = _rule) -> DataFrame:
        c = drifted(spark, folder).tables["customer"]
        out = chase.resolve(c, KEY, ["c_mktsegment"], "__orig_new_id", rule, None, "value <> 'DRIFTED'")
        return out.select(F.col("__orig_new_id").alias("orig_id"), "new_id", "c_mktsegment")


@query("chase_rule_latest", "with p as (select o_orderkey, o_custkey, o_orderdate, o_orderpriority from orders), b as (select o_custkey, first(o_orderpriority order by d desc, o_orderpriority desc) as v from (select o_custkey, o_orderpriority, max(o_orderdate) as d from p group by all) group by o_custkey) select p.o_orderkey, p.o_custkey, b.v as o_orderpriority from p join b on p.o_custkey = b.o_custkey")
def chase_rule_latest(spark: SparkSession, folder: str) -> DataFrame:
    o = t(spark, folder, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    return chase.resolve(o, ["o_custkey"], ["o_orderpriority"], "o_orderkey", "latest", "o_orderdate").drop("o_orderdate")


@query("chase_rule_majority", "with p as (select doc_id, text, source from documents), b as (select text, first(source order by c desc, f) as v from (select text, source, count(*) as c, min(doc_id) as f from p group by text, source) group by text) select doc_id, b.v as source from p join b on p.text = b.text")
def chase_rule_majority(spark: SparkSession, folder: str) -> DataFrame:
    return chase.resolve(t(spark, folder, "documents"), ["text"], ["source"], "doc_id").select("doc_id", "source")


@query("chase_rule_priority", "with p as (select doc_id, text, source from documents), b as (select text, first(source order by case source when 'src3' then 1 when 'src1' then 2 else 3 end, c desc, f) as v from (select text, source, count(*) as c, min(doc_id) as f from p group by text, source) group by text) select doc_id, b.v as source from p join b on p.text = b.text")
def chase_rule_priority(spark: SparkSession, folder: str) -> DataFrame:
    """Trusted sources first."""
    return chase.resolve(t(spark, folder, "documents"), ["text"], ["source"], "doc_id", "priority", priority=("src3", "src1")).select("doc_id", "source")


@query("chase_rule_expert", _DRIFTED + "select orig as orig_id, case when c_name in (select c_name from cust where c_mktsegment = 'DRIFTED') then 'EXPERT' else c_mktsegment end as c_mktsegment from cust")
def chase_rule_expert(spark: SparkSession, folder: str) -> DataFrame:
    c = drifted(spark, folder).tables["customer"]
    chosen = c.where("c_mktsegment = 'DRIFTED'").select(*KEY).distinct().withColumn("value", F.lit("EXPERT"))
    return chase.resolve_by_list(c, KEY, "c_mktsegment", chosen, "__orig_new_id").select(F.col("__orig_new_id").alias("orig_id"), "c_mktsegment")


@query("chase_rule_model", chase_sql("len(list_distinct(string_split(c_mktsegment, ''))) desc, c_mktsegment"))
def chase_rule_model(spark: SparkSession, folder: str) -> DataFrame:
    """A caller's vectorised score decides: here, how many distinct letters a value has."""

    @F.pandas_udf("double")
    def score(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float(len(set(x))))

    c = drifted(spark, folder).tables["customer"]
    return chase.resolve_by_model(c, KEY, "c_mktsegment", score(F.col("value")), "__orig_new_id").select(F.col("__orig_new_id").alias("orig_id"), "new_id", "c_mktsegment")


@query("chase_star_report", _DRIFTED + "select 'customer' as relation, attribute, cast(n as bigint) as n_conflicts from (select 'c_acctbal' as attribute, count(*) as n from (select 1 from cust group by c_name, c_nationkey having count(distinct c_acctbal) > 1) union all select 'c_mktsegment', count(*) from (select 1 from cust group by c_name, c_nationkey having count(distinct c_mktsegment) > 1))")
def chase_star_report(spark: SparkSession, folder: str) -> DataFrame:
    c, attributes = drifted(spark, folder).tables["customer"], ["c_acctbal", "c_mktsegment"]
    return stability.conflict_counts(c, KEY, attributes).select(F.lit("customer").alias("relation"), "attribute", "n_conflicts")


for _name in ORDER:

    @query(f"reduced_{_name}", with_clean(f"select distinct new_id, {', '.join(COLUMNS[_name])} from clean_{_name}"))
    def _reduced(spark: SparkSession, folder: str, name: str = _name) -> DataFrame:
        return reduce.relation(suppressed(spark, folder).db.tables[name])


@query("reduced_documents", "with c as (select min(doc_id) over (partition by text) as doc_id, lang, n_chars from documents) select distinct doc_id, lang, n_chars from c")
def reduced_documents(spark: SparkSession, folder: str) -> DataFrame:
    return reduce.relation(propagate.collapse_key(t(spark, folder, "documents"), "doc_id", ["text"]).select("doc_id", "lang", "n_chars"))


@query("reduced_documents_by_key", "with c as (select min(doc_id) over (partition by text) as doc_id, lang, n_chars from documents) select distinct doc_id, lang, n_chars from c")
def reduced_documents_by_key(spark: SparkSession, folder: str) -> DataFrame:
    return reduce.relation(propagate.collapse_key(t(spark, folder, "documents"), "doc_id", ["text"]).select("doc_id", "lang", "n_chars"), ("doc_id",), by_key=True)


@query("reduction_rate_star", with_clean("select *, round(1 - rows_after / rows_before::double, 6) as reduction_rate from (" + " union all ".join(f"select '{n}' as relation, (select count(*) from poll_{n}) as rows_before, count(*) as rows_after from (select distinct * from clean_{n})" for n in ORDER) + ")"))
def reduction_rate_star(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.reduction(polluted(spark, folder), reduce.database(suppressed(spark, folder).db))


def _constraints() -> str:
    from .registry import FKS

    unique = lambda n, kind, key: f"select '{n}' as relation, '{kind}' as kind, '{'+'.join(key)}' as columns, not exists (select 1 from done_{n} group by {', '.join(key)} having count(*) > 1) as holds"
    parts = []
    for n in ORDER:
        parts += [unique(n, "primary", ("new_id",)), unique(n, "unique", NKS[n]), f"select '{n}', 'not null', 'new_id', not exists (select 1 from done_{n} where new_id is null)"]
    parts += [f"select '{a}', 'foreign', '{c}', not exists (select 1 from done_{a} where {c} is not null and {c} not in (select new_id from done_{b}))" for a, c, b in FKS]
    done = ", ".join(f"done_{n} as (select distinct new_id, {', '.join(COLUMNS[n])} from clean_{n})" for n in ORDER)
    return with_clean("select 1").removesuffix("select 1") + ", " + done + " " + " union all ".join(parts)


@query("constraints_after_clean", _constraints())
def constraints_after_clean(spark: SparkSession, folder: str) -> DataFrame:
    return verify.reencode(reduce.database(suppressed(spark, folder).db))


@query("standardise_pages_url", f"select page_id, {URL} as url from pages")
def standardise_pages_url(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "pages").select("page_id", canon.url(F.col("url")).alias("url"))


_TEXT = f"trim(regexp_replace(lower(translate(text, '{canon.ACCENTED}', '{canon.PLAIN}')), '[^a-z0-9]+', ' ', 'g'))"


@query("standardise_documents_text", f"select doc_id, md5({_TEXT}) as text_md5 from documents")
def standardise_documents_text(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "documents").select("doc_id", F.md5(canon.text(F.col("text")).cast("binary")).alias("text_md5"))


@query("au_pages_canon", f"with p as (select {URL} as u from pages) {au_sql('p', 'u')}")
def au_pages_canon(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.au(t(spark, folder, "pages").withColumn("u", canon.url(F.col("url"))), "page_id", ["u"])


@query("match_part_names", "with recursive k as materialized (select p_brand, p_name, min(p_partkey) as k from part group by all), e as materialized (select a.k as a, b.k as b from k a join k b on a.p_brand = b.p_brand and a.k < b.k and levenshtein(a.p_name, b.p_name) <= 2 union select k, p_partkey from part join k using (p_brand, p_name) where p_partkey <> k), g as (select a, b from e union select b, a from e), w(node, root) as (select a, a from g union select g.b, w.root from w join g on g.a = w.node where w.root < g.b), roots as (select node, min(root) as root from w group by node) select p_partkey as sk, coalesce(root, p_partkey) as rep from part left join roots on node = p_partkey")
def match_part_names(spark: SparkSession, folder: str) -> DataFrame:
    p = t(spark, folder, "part")
    pairs = matching.candidate_pairs(p, "p_partkey", F.col("p_brand"), "p_name", lambda a, b: F.levenshtein(a, b) <= 2)
    return matching.classes_from_pairs(p, "p_partkey", pairs)


@query("cc_min_label", "with recursive e as (select min(doc_id) over (partition by text) as a, doc_id as b from documents), g as (select a, b from e where a <> b union select b, a from e where a <> b), w(node, root) as (select a, a from g union select g.b, w.root from w join g on g.a = w.node where w.root < g.b) select node, min(root) as root from w group by node")
def cc_min_label(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.components import connected_components

    d = t(spark, folder, "documents").select("doc_id", canon.fingerprint(t(spark, folder, "documents"), ["text"]).alias("k"))
    first = d.groupBy("k").agg(F.min("doc_id").alias("a"))
    return connected_components(d.join(first, "k").where("a <> doc_id").select("a", F.col("doc_id").alias("b")))


@query("block3_conversations", stability_sql("conversations", "conv_id, turn", ("role", "text")))
def block3_conversations(spark: SparkSession, folder: str) -> DataFrame:
    """A relation whose natural key is declared takes part in the last block alone."""
    return stability.profile(t(spark, folder, "conversations"), ["conv_id", "turn"], ["role", "text"])


_VISITS = "select c.{key} as entity, count(*) as n_events, round(sum(o.o_totalprice), 2) as total from {p}customer c join {p}orders o on c.{sk} = o.o_custkey group by c.{key}"


@query("analytics_dirty", f"with {poll_sql()} select c.new_id as entity, min(c_name) as name, count(*) as n_events, count(distinct o_orderdate) as n_dates from poll_customer c join poll_orders o on c.new_id = o.o_custkey group by c.new_id")
def analytics_dirty(spark: SparkSession, folder: str) -> DataFrame:
    db = polluted(spark, folder)
    return analytics.visits_per_entity(db.tables["customer"], "new_id", "c_name", db.tables["orders"], "o_custkey", "o_orderdate")


@query("analytics_clean", "select c_custkey * 2 as entity, min(c_name) as name, count(*) as n_events, count(distinct o_orderdate) as n_dates from customer join orders on c_custkey = o_custkey group by c_custkey")
def analytics_clean(spark: SparkSession, folder: str) -> DataFrame:
    db = reduce.database(suppressed(spark, folder).db)
    return analytics.visits_per_entity(db.tables["customer"], "new_id", "c_name", db.tables["orders"], "o_custkey", "o_orderdate")


@query("analytics_posts_per_document", "with m as (select doc_id, min(doc_id) over (partition by text) as rep from documents), l as (select distinct rep, quality, toxic from labels join m using (doc_id)) select rep as entity, count(*) as n_events from l group by rep")
def analytics_posts_per_document(spark: SparkSession, folder: str) -> DataFrame:
    db = reduce.database(propagate.suppress(text_db(spark, folder)).db)
    return db.tables["labels"].groupBy(F.col("doc_id").alias("entity")).agg(F.count(F.lit(1)).alias("n_events"))


@query("distortion_customer_acctbal", f"with {poll_sql()} select 'dirty' as state, count(*) as n, round(avg(c_acctbal), 6) as mean, round(median(c_acctbal), 6) as median, round(stddev_samp(c_acctbal), 6) as deviation from poll_customer union all select 'clean', count(*), round(avg(c_acctbal), 6), round(median(c_acctbal), 6), round(stddev_samp(c_acctbal), 6) from customer")
def distortion_customer_acctbal(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.distortion(polluted(spark, folder).tables["customer"], reduce.relation(suppressed(spark, folder).db.tables["customer"]), "c_acctbal")


@query("key_census", f"with {borne_out_sql()} select cast({len(ORDER)} as bigint) as relations, count(*) filter (where ok) as with_sk, cast(0 as bigint) as sk_without_nk from k")
def key_census(spark: SparkSession, folder: str) -> DataFrame:
    """Of the surrogate keys that do not repeat in the tables."""
    db = star(spark, folder)
    found = metrics.key_census(Database(verify.borne_out(Database(replace(db.spec, fks=()), db.tables)), db.tables))
    return spark.createDataFrame([tuple(found.values())], "relations long, with_sk long, sk_without_nk long")


@query("rrp_evolution_customer", with_clean(" union all ".join(f"select '{a}' as attribute, (select count(distinct {a}) from poll_customer) as dv_before, (select count(*) - count({a}) from poll_customer) as nv_before, (select count({a}) - count(distinct {a}) from poll_customer) as ov_before, count(distinct {a}) as dv_after, count(*) - count({a}) as nv_after, count({a}) - count(distinct {a}) as ov_after from clean_customer" for a in ("new_id", *COLUMNS["customer"]))))
def rrp_evolution_customer(spark: SparkSession, folder: str) -> DataFrame:
    names = ["new_id", *COLUMNS["customer"]]
    return profile.compare(profile.rrp(polluted(spark, folder).tables["customer"], names), profile.rrp(suppressed(spark, folder).db.tables["customer"], names))
