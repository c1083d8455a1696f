"""Artificial unicity: classes, propagation, levels."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import canon
from ..operators import equivalence, metrics, propagate, verify
from ..plans import graph
from ..plans.model import Database, DatabaseSpec, ForeignKey, Relation
from ..sources.io import union_all
from .registry import COLUMNS, NKS, ORDER, PKS, borne_out_sql, clean_sql, poll_sql, polluted, query, star, suppressed, t, with_clean

URL = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(lower(trim(url)), '^[a-z]+://', ''), '^(www|m)\\.', ''), '[?#].*$', ''), '/+$', '')"


@query("au_pairs_documents", "select a.doc_id as sk_a, b.doc_id as sk_b from documents a join documents b on a.text is not distinct from b.text and a.doc_id < b.doc_id")
def au_pairs_documents(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.pairs(t(spark, folder, "documents"), "doc_id", ["text"])


@query("au_pairs_pages_canon", f"with p as (select page_id, {URL} as u from pages) select a.page_id as sk_a, b.page_id as sk_b from p a join p b on a.u = b.u and a.page_id < b.page_id")
def au_pairs_pages_canon(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.pairs(t(spark, folder, "pages").withColumn("u", canon.url(F.col("url"))), "page_id", ["u"])


@query("au_chain_customer_orders", with_clean("select 'orders' as relation, count(*) as n, count(distinct (o_custkey, o_orderdate, o_totalprice)) as classes, (select count(distinct (o_custkey, o_orderdate, o_totalprice)) from poll_orders) as classes_alone from clean_orders"))
def au_chain_customer_orders(spark: SparkSession, folder: str) -> DataFrame:
    cleaned, raw = suppressed(spark, folder).db.tables["orders"], polluted(spark, folder).tables["orders"]
    alone = metrics.au(raw, "new_id", NKS["orders"]).select(F.col("classes").alias("classes_alone"))
    return metrics.au(cleaned, "new_id", NKS["orders"]).select(F.lit("orders").alias("relation"), "n", "classes").crossJoin(alone)  # one row each


@query("au_flags_all", " union all ".join(f"select '{n}' as relation, (select count(*) from {n}) > (select count(*) from (select distinct {k} from {n})) as suffers" for n, k in (("region", "r_name"), ("customer", "c_name"), ("supplier", "s_name"), ("orders", "o_custkey, o_orderdate"), ("documents", "text"), ("benchmark", "text"))))
def au_flags_all(spark: SparkSession, folder: str) -> DataFrame:
    keys = (("region", "r_regionkey", ["r_name"]), ("customer", "c_custkey", ["c_name"]), ("supplier", "s_suppkey", ["s_name"]), ("orders", "o_orderkey", ["o_custkey", "o_orderdate"]), ("documents", "doc_id", ["text"]), ("benchmark", "item_id", ["text"]))
    return union_all([metrics.suffers(t(spark, folder, n), sk, k).select(F.lit(n).alias("relation"), "suffers") for n, sk, k in keys])


@query("sk_classes_documents", "select min(doc_id) as rep, array_to_string(list_sort(list(doc_id)), ',') as members, count(*) as size from documents group by text")
def sk_classes_documents(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.classes(t(spark, folder, "documents"), "doc_id", ["text"]).select("rep", F.array_join(F.col("members").cast("array<string>"), ",").alias("members"), "size")


def map_sql(table: str, sk: str, key: str) -> str:
    return f"select {sk} as sk, rep from (select {sk}, min({sk}) over (partition by {key}) as rep from {table}) where {sk} <> rep"


@query("sk_map_documents", map_sql("documents", "doc_id", "text"))
def sk_map_documents(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.sk_map(t(spark, folder, "documents"), "doc_id", ["text"])


@query("sk_map_documents_explode", map_sql("documents", "doc_id", "text"))
def sk_map_documents_explode(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.sk_map(t(spark, folder, "documents"), "doc_id", ["text"], plan="explode")


@query("sk_map_documents_window", map_sql("documents", "doc_id", "text"))
def sk_map_documents_window(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.sk_map(t(spark, folder, "documents"), "doc_id", ["text"], plan="window")


@query("sk_map_part", map_sql("part", "p_partkey", "p_name"))
def sk_map_part(spark: SparkSession, folder: str) -> DataFrame:
    return equivalence.sk_map(t(spark, folder, "part"), "p_partkey", ["p_name"])


@query("collapse_documents", "select min(doc_id) over (partition by text) as doc_id, lang, source, n_chars from documents")
def collapse_documents(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.collapse_key(t(spark, folder, "documents"), "doc_id", ["text"]).select("doc_id", "lang", "source", "n_chars")


@query("collapse_documents_fullest", "select first_value(doc_id) over (partition by text order by case when s is null then 1 else 0 end, doc_id) as doc_id, lang, s as source from (select *, case when doc_id % 3 = 0 then null else source end as s from documents)")
def collapse_documents_fullest(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents").withColumn("source", F.when(F.col("doc_id") % 3 != 0, F.col("source")))
    return propagate.collapse_key(d, "doc_id", ["text"], policy="fullest").select("doc_id", "lang", "source")


@query("collapse_documents_earliest", "select first_value(doc_id) over (partition by text order by n_chars, doc_id) as doc_id, n_chars from documents")
def collapse_documents_earliest(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.collapse_key(t(spark, folder, "documents"), "doc_id", ["text"], policy="earliest", order="n_chars").select("doc_id", "n_chars")


@query("collapse_two_keys_customer", "with p as (select c_custkey, md5(cast(c_custkey as varchar)) as tag, c_nationkey, c_mktsegment from customer) select min(c_custkey) over w as c_custkey, min(tag) over w as tag, c_nationkey, c_mktsegment from p window w as (partition by c_nationkey, c_mktsegment)")
def collapse_two_keys_customer(spark: SparkSession, folder: str) -> DataFrame:
    c = t(spark, folder, "customer").select("c_custkey", F.md5(F.col("c_custkey").cast("string")).alias("tag"), "c_nationkey", "c_mktsegment")
    return propagate.collapse_key(c, ["c_custkey", "tag"], ["c_nationkey", "c_mktsegment"])


_PART = COLUMNS["part"][1:]


@query("collapse_part_restkey", f"select min(p_partkey) over (partition by {', '.join(_PART)}) as p_partkey, {', '.join(_PART)} from part")
def collapse_part_restkey(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.collapse_key(t(spark, folder, "part"), "p_partkey", Relation("part", ("p_partkey",), columns=COLUMNS["part"]).potential_key())


def au_sql(table: str, key: str) -> str:
    return f"select count(*) as n, count(distinct ({key})) as classes, round(1 - count(distinct ({key})) / count(*)::double, 6) as au, round(count(distinct ({key})) / count(*)::double, 6) as kept_ratio from {table}"


@query("au_part_restkey", au_sql("part", ", ".join(_PART)))
def au_part_restkey(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.au(t(spark, folder, "part"), "p_partkey", _PART)


@query("au_documents_text", au_sql("documents", "text"))
def au_documents_text(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.au(t(spark, folder, "documents"), "doc_id", ["text"])


@query("au_lineitem_false_nk", au_sql("lineitem", "l_orderkey, l_linenumber"))
def au_lineitem_false_nk(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.au(t(spark, folder, "lineitem"), "l_partkey", ["l_orderkey", "l_linenumber"])


_NULLED = "(select o_orderkey, case when o_custkey % 5 = 0 then null else o_custkey end as k, o_orderpriority as p from orders)"


def _nulled(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "orders").select("o_orderkey", F.when(F.col("o_custkey") % 5 != 0, F.col("o_custkey")).alias("k"), F.col("o_orderpriority").alias("p"))


@query("collapse_nulls_equal", f"select min(o_orderkey) over (partition by k, p) as o_orderkey, k, p from {_NULLED}")
def collapse_nulls_equal(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.collapse_key(_nulled(spark, folder), "o_orderkey", ["k", "p"])


@query("collapse_nulls_distinct", f"select case when k is null or p is null then o_orderkey else min(o_orderkey) over (partition by k, p) end as o_orderkey, k, p from {_NULLED}")
def collapse_nulls_distinct(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.collapse_key(_nulled(spark, folder), "o_orderkey", ["k", "p"], nulls="distinct")


@query("repoint_labels", "with m as (select doc_id, min(doc_id) over (partition by text) as rep from documents) select coalesce(m.rep, l.doc_id) as doc_id, quality, toxic from labels l left join m on l.doc_id = m.doc_id")
def repoint_labels(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.repoint_fk(t(spark, folder, "labels"), "doc_id", equivalence.sk_map(t(spark, folder, "documents"), "doc_id", ["text"]))


@query("repoint_two_fks", "with m as (select c_custkey, min(c_custkey) over (partition by c_nationkey) as rep from customer), n as (select count(*) as k from customer), tr as (select o_orderkey as tid, o_custkey as a, (o_custkey + 7) % k as b from orders, n) select tid, coalesce(x.rep, a) as from_cust, coalesce(y.rep, b) as to_cust from tr left join m x on a = x.c_custkey left join m y on b = y.c_custkey")
def repoint_two_fks(spark: SparkSession, folder: str) -> DataFrame:
    c, o = t(spark, folder, "customer"), t(spark, folder, "orders")
    n = c.count()
    tr = o.select(F.col("o_orderkey").alias("tid"), F.col("o_custkey").alias("from_cust"), ((F.col("o_custkey") + 7) % n).alias("to_cust"))
    m = equivalence.sk_map(c, "c_custkey", ["c_nationkey"])
    for fk in ("from_cust", "to_cust"):
        tr = propagate.repoint_fk(tr, fk, m)
    return tr


@query("propagation_graph_star", f"with {borne_out_sql()} select source, fk, target from e")
def propagation_graph_star(spark: SparkSession, folder: str) -> DataFrame:
    """Of the keys and foreign keys that the tables bear out."""
    return spark.createDataFrame(graph.propagation_graph(verify.borne_out(star(spark, folder))), "source string, fk string, target string")


@query("propagation_graph_restricted", f"with {borne_out_sql()} select source, fk, target from e where (source, fk) in (('orders', 'o_custkey'), ('lineitem', 'l_orderkey'), ('lineitem', 'l_partkey'), ('lineitem', 'l_suppkey'))")
def propagation_graph_restricted(spark: SparkSession, folder: str) -> DataFrame:
    spec = verify.borne_out(star(spark, folder))
    names = {"nation": ("n_name",), "customer": ("c_name",), "supplier": ("s_name",)}
    alone = DatabaseSpec({n: Relation(n, r.sks, names.get(n, r.nk)) for n, r in spec.relations.items()}, spec.fks)
    return spark.createDataFrame(graph.restricted(alone), "source string, fk string, target string")


@query("propagation_layers_star", f"with recursive {borne_out_sql()}, d(relation, l) as (select unnest([{', '.join(repr(n) for n in ORDER)}]), 1 union all select e.source, d.l + 1 from e join d on e.target = d.relation) select relation, cast(max(l) as int) as layer from d group by relation")
def propagation_layers_star(spark: SparkSession, folder: str) -> DataFrame:
    spec = verify.borne_out(star(spark, folder))
    found = graph.layers(list(spec.relations), graph.propagation_graph(spec))
    return spark.createDataFrame([(n, i + 1) for i, own in enumerate(found) for n in own], "relation string, layer int")


@query("fixpoint_self_reference", "select 2 * c_custkey as id, c_name, case when c_custkey >= 10 then 2 * (c_custkey // 10) end as boss from customer, (values (0), (1)) v(copy)")
def fixpoint_self_reference(spark: SparkSession, folder: str) -> DataFrame:
    """A chain of managers with twins: equal names under equivalent managers are one person, at any depth."""
    c = t(spark, folder, "customer").select("c_custkey", "c_name", F.when(F.col("c_custkey") >= 10, F.floor(F.col("c_custkey") / 10)).alias("boss"))
    twins = c.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).select((F.col("c_custkey") * 2 + F.col("copy")).alias("id"), "c_name", (F.col("boss") * 2 + F.col("copy")).alias("boss"))
    spec = DatabaseSpec({"staff": Relation("staff", ("id",), ("c_name", "boss"))}, (ForeignKey("staff", ("boss",), "staff", ("id",)),))
    return propagate.fixpoint(Database(spec, {"staff": twins})).db.tables["staff"]


for _name in ORDER:

    @query(f"suppress_star_{_name}", with_clean(f"select new_id, {', '.join(COLUMNS[_name])} from clean_{_name}"))
    def _suppress(spark: SparkSession, folder: str, name: str = _name) -> DataFrame:
        return suppressed(spark, folder).db.tables[name].select("new_id", *COLUMNS[name])


TEXT = DatabaseSpec({"documents": Relation("documents", ("doc_id",), ("text",)), "labels": Relation("labels", (), ("doc_id",))}, (ForeignKey("labels", ("doc_id",), "documents", ("doc_id",)),))


def text_db(spark: SparkSession, folder: str) -> Database:
    return Database(TEXT, {n: t(spark, folder, n) for n in TEXT.relations})


@query("suppress_text_labels", "with m as (select doc_id, min(doc_id) over (partition by text) as rep from documents) select distinct m.rep as doc_id, quality, toxic from labels l join m on l.doc_id = m.doc_id")
def suppress_text_labels(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.suppress(text_db(spark, folder)).db.tables["labels"].distinct()


def _levels(select: str, prefix: str) -> str:
    return " union all ".join(select.format(n=n, p=prefix, k=", ".join(NKS[n])) for n in ORDER)


@query("au_level_star_df30", with_clean(_levels("select '{n}' as relation, count(*) as n, count(distinct ({k})) as classes, round(1 - count(distinct ({k})) / count(*)::double, 6) as au, round(count(distinct ({k})) / count(*)::double, 6) as kept_ratio from {p}_{n}", "clean")))
def au_level_star_df30(spark: SparkSession, folder: str) -> DataFrame:
    db = suppressed(spark, folder).db
    return union_all([metrics.au(x, "new_id", NKS[n]).select(F.lit(n).alias("relation"), "*") for n, x in db.tables.items()])


@query("au_level_star_local", f"with {poll_sql()} " + _levels("select '{n}' as relation, count(*) as n, count(distinct ({k})) as classes, round(1 - count(distinct ({k})) / count(*)::double, 6) as au, round(count(distinct ({k})) / count(*)::double, 6) as kept_ratio from {p}_{n}", "poll"))
def au_level_star_local(spark: SparkSession, folder: str) -> DataFrame:
    return union_all([metrics.au(x, "new_id", NKS[n]).select(F.lit(n).alias("relation"), "*") for n, x in polluted(spark, folder).tables.items()])


_REPORT = _levels("select '{n}' as relation, count(*) as n, count(distinct ({k})) as classes from {p}_{n}", "clean")


@query("au_report_star", with_clean(f"select relation, n, classes, round(1 - classes / n::double, 6) as au from (select * from ({_REPORT}) union all select '(all)', cast(sum(n) as bigint), cast(sum(classes) as bigint) from ({_REPORT}))"))
def au_report_star(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.report(suppressed(spark, folder).db)


@query("theorem_no_au_star", with_clean(_levels("select '{n}' as relation, count(*) as n_rows, count(distinct new_id) as n_keys, count(distinct ({k})) as n_classes, count(distinct new_id) > count(distinct ({k})) as suffers from {p}_{n}", "clean")))
def theorem_no_au_star(spark: SparkSession, folder: str) -> DataFrame:
    return verify.no_au(suppressed(spark, folder).db)


@query("suppress_restricted_star", with_clean("select new_id, l_orderkey, l_partkey, l_suppkey, l_linenumber, l_shipdate from clean_lineitem"))
def suppress_restricted_star(spark: SparkSession, folder: str) -> DataFrame:
    return propagate.suppress(polluted(spark, folder), restricted=True).db.tables["lineitem"].select("new_id", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate")


__all__ = ["PKS", "clean_sql", "star"]
