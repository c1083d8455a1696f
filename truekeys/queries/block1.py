"""Theory, profiles and elicitation."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, profile, review, stability, verify
from ..plans import fdtheory, graph
from ..plans.model import Database, DatabaseSpec, Relation
from ..sources.io import union_all
from .registry import COLUMNS, ORDER, STAR, TABLES, borne_out_sql, query, sets_sql, star, t

SCHEMAS = {
    "region": "r_regionkey r_name",
    "nation": "n_nationkey n_name n_regionkey",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment",
    "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props",
    "documents": "doc_id text lang source n_chars",
    "embeddings": "vec_id embedding label",
    "pages": "page_id url html",
    "benchmark": "item_id text",
    "labels": "doc_id quality toxic",
    "conversations": "conv_id turn role text",
}


def arp_sql(table: str, column: str, relation: bool = False) -> str:
    first = f"'{table}' as relation, " if relation else ""
    return f"select {first}'{column}' as attribute, count(*) as n, count(distinct {column}) as dv, count(*) - count({column}) as nv, count({column}) - count(distinct {column}) as ov from {table}"


def rrp_sql(table: str, relation: bool = False) -> str:
    return " union all ".join(arp_sql(table, c, relation) for c in SCHEMAS[table].split())


for _name in TABLES:

    @query(f"rrp_{_name}", rrp_sql(_name))
    def _rrp(spark: SparkSession, folder: str, name: str = _name) -> DataFrame:
        return profile.rrp(t(spark, folder, name))


@query("rrp_database", " union all ".join(rrp_sql(n, True) for n in TABLES))
def rrp_database(spark: SparkSession, folder: str) -> DataFrame:
    return profile.rrp_database(Database(DatabaseSpec({n: Relation(n) for n in TABLES}), {n: t(spark, folder, n) for n in TABLES}))


@query("fd_holds_documents", "select 'text->' || a as dependency, holds from (select 'lang' as a, not exists (select 1 from documents group by text having count(distinct lang) > 1) as holds union all select 'source', not exists (select 1 from documents group by text having count(distinct source) > 1) union all select 'n_chars', not exists (select 1 from documents group by text having count(distinct n_chars) > 1))")
def fd_holds_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents")
    return union_all([stability.holds(d, ["text"], a).select(F.lit(f"text->{a}").alias("dependency"), "holds") for a in ("lang", "source", "n_chars")])


def g3_sql(table: str, x: str, a: str) -> str:
    return f"select cast(sum(k) as bigint) as n, cast(sum(b) as bigint) as kept, round(1 - sum(b) / sum(k)::double, 6) as g3 from (select sum(c) as k, max(c) as b from (select {x}, {a}, count(*) as c from {table} group by {x}, {a}) group by {x})"


@query("g3_documents_source", g3_sql("documents", "text", "source"))
def g3_documents_source(spark: SparkSession, folder: str) -> DataFrame:
    return stability.g3(t(spark, folder, "documents"), ["text"], "source")


@query("g3_part_pname", g3_sql("part", "p_name", "p_brand"))
def g3_part_pname(spark: SparkSession, folder: str) -> DataFrame:
    return stability.g3(t(spark, folder, "part"), ["p_name"], "p_brand")


def closure_sql(table: str, columns: list[str], of: tuple[str, ...], implied: tuple[tuple[str, str], ...]) -> str:
    """Closures, keys and implications counted straight from the table: X determines A if A adds no distinct row to X."""
    sets = [c for k in range(1, len(columns) + 1) for c in combinations(sorted(columns), k)]
    counts = " union all ".join(f"select '{' '.join(c)}' as s, (select count(*) from (select distinct {', '.join(c)} from {table})) as dv" for c in sets)
    pairs = ", ".join(f"('{' '.join(a)}', '{' '.join(b)}')" for b in sets for a in sets if set(a) < set(b))
    dv = lambda c: f"(select dv from d where s = '{' '.join(sorted(set(c)))}')"
    rows = [f"select 'closure of {x}' as item, concat_ws(' ', {', '.join(f'case when {dv([x, a])} = {dv([x])} then {a!r} end' for a in sorted(columns))}) as attributes" for x in of]
    rows += [f"select 'candidate key', s from d where dv = {dv(columns)} and s not in (select large from p join d u on small = u.s where u.dv = {dv(columns)})"]
    rows += [f"select '{x} -> {a}', cast({dv([*x.split(), a])} = {dv(x.split())} as varchar)" for x, a in implied]
    return f"with d as ({counts}), p as (select * from (values {pairs}) v(small, large)) {' union all '.join(rows)}"


_IMPLIED = (("c_name c_nationkey", "c_acctbal"), ("c_nationkey", "c_mktsegment"))


@query("fd_closure_demo", closure_sql("customer", SCHEMAS["customer"].split(), ("c_custkey", "c_nationkey"), _IMPLIED))
def fd_closure_demo(spark: SparkSession, folder: str) -> DataFrame:
    """Inference from the minimal dependencies found in the table; the SQL counts each answer directly."""
    r = frozenset(SCHEMAS["customer"].split())
    fds = [(frozenset(x), a) for x, a, _ in baselines.fds(t(spark, folder, "customer"), sorted(r), max_left=len(r) - 1)]
    show = lambda s: " ".join(sorted(s))
    rows = [(f"closure of {x}", show(fdtheory.closure(frozenset([x]), fds))) for x in ("c_custkey", "c_nationkey")]
    rows += [("candidate key", show(k)) for k in fdtheory.candidate_keys(r, fds)]
    rows += [(f"{x} -> {a}", str(fdtheory.implies(fds, fdtheory.fd(x, a))).lower()) for x, a in _IMPLIED]
    return spark.createDataFrame(rows, "item string, attributes string")


@query("fk_orphans_star", " union all ".join(f"select '{f.source}.{f.columns[0]}' as fk, count(*) as n_orphans from {f.source} where {f.columns[0]} is not null and {f.columns[0]} not in (select {f.target_columns[0]} from {f.target})" for f in STAR.fks))
def fk_orphans_star(spark: SparkSession, folder: str) -> DataFrame:
    return verify.fk_report(star(spark, folder))


@query("schema_graph_degrees", "select relation, cast(l as int) as leaving, cast(e as int) as entering from (values ('region', 0, 1), ('nation', 1, 2), ('customer', 1, 1), ('supplier', 1, 1), ('part', 0, 1), ('orders', 1, 1), ('lineitem', 3, 0)) v(relation, l, e)")
def schema_graph_degrees(spark: SparkSession, folder: str) -> DataFrame:
    return spark.createDataFrame([(n, *d) for n, d in graph.degrees(STAR).items()], "relation string, leaving int, entering int")


@query("arp_customer_acctbal", arp_sql("customer", "c_acctbal"))
def arp_customer_acctbal(spark: SparkSession, folder: str) -> DataFrame:
    return profile.arp(t(spark, folder, "customer"), "c_acctbal")


@query("arp_events_value", arp_sql("events", "value"))
def arp_events_value(spark: SparkSession, folder: str) -> DataFrame:
    return profile.arp(t(spark, folder, "events"), "value")


@query("arp_composite_lineitem", "select 'l_orderkey+l_linenumber' as attribute, count(*) as n, count(distinct (l_orderkey, l_linenumber)) as dv, count(*) filter (where l_orderkey is null or l_linenumber is null) as nv, count(*) - count(distinct (l_orderkey, l_linenumber)) - count(*) filter (where l_orderkey is null or l_linenumber is null) as ov from lineitem")
def arp_composite_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    return profile.arp(t(spark, folder, "lineitem"), ["l_orderkey", "l_linenumber"])


@query("arp_nested_embeddings", arp_sql("embeddings", "embedding"))
def arp_nested_embeddings(spark: SparkSession, folder: str) -> DataFrame:
    return profile.arp(t(spark, folder, "embeddings"), "embedding")


@query("arp_json_events", "select 'k' as attribute, count(*) as n, count(distinct k) as dv, count(*) - count(k) as nv, count(k) - count(distinct k) as ov from (select json_extract_string(props, '$.k') as k from events)")
def arp_json_events(spark: SparkSession, folder: str) -> DataFrame:
    return profile.arp(t(spark, folder, "events").select(F.get_json_object("props", "$.k").alias("k")), "k")


@query("arp_approx_lineitem", "select 'l_orderkey' as attribute, count(*) as n, count(*) - count(l_orderkey) as nv, true as near, true as merged_near from lineitem")
def arp_approx_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    """The sketched profile, and whether it and a sketch merged from groups lie within 5 % of the exact count."""
    d = t(spark, folder, "lineitem")
    sketch = d.groupBy("l_returnflag").agg(F.hll_sketch_agg("l_orderkey").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("merged"))
    both = profile.arp(d, "l_orderkey", rsd=0.01).crossJoin(sketch).crossJoin(profile.arp(d, "l_orderkey").select(F.col("dv").alias("exact")))  # one row each
    within = lambda c: F.abs(F.col(c) - F.col("exact")) <= 0.05 * F.col("exact")
    return both.select("attribute", "n", "nv", within("dv").alias("near"), within("merged").alias("merged_near"))


@query("rrp_layout_orders", f"select attribute, n, dv, nv, ov, category, cast(row_number() over (order by case category when 'K' then 1 when 'RA' then 2 else 3 end, dv desc, attribute) as int) as position from (select *, case attribute when 'o_orderkey' then 'K' when 'o_custkey' then 'FK' else 'RA' end as category from ({rrp_sql('orders')}))")
def rrp_layout_orders(spark: SparkSession, folder: str) -> DataFrame:
    db = star(spark, folder)
    return profile.layout(profile.rrp(db.tables["orders"]), db.spec.relations["orders"], {"o_custkey"})


@query("rrp_lines_documents", "select 'text' as attribute, count(*) as size_line, count(distinct text) as nk_line, count(*) - count(distinct text) as gap from documents")
def rrp_lines_documents(spark: SparkSession, folder: str) -> DataFrame:
    return profile.lines(t(spark, folder, "documents"), ["text"])


def candidates_sql(table: str, keys: str, fks: str) -> str:
    return f"select '{table}' as relation, attribute, n, dv, case when attribute in ({keys}) then 'K' when attribute in ({fks}) then 'FK' else 'RA' end as category, case when attribute in ({keys}) then 'declared key' when nv = 0 and n > 0 and dv = n then 'unique' when nv = 0 and n > 0 and dv >= 0.99 * n then 'almost unique' end as reason from ({rrp_sql(table)})"


_KEYS = {"customer": ("'c_custkey'", "'c_nationkey'"), "supplier": ("'s_suppkey'", "'s_nationkey'"), "orders": ("'o_orderkey'", "'o_custkey'"), "part": ("'p_partkey'", "''"), "nation": ("'n_nationkey'", "'n_regionkey'"), "region": ("'r_regionkey'", "''")}


@query("sk_candidates_all", "select * from (" + " union all ".join(candidates_sql(n, *k) for n, k in _KEYS.items()) + ") where reason is not null")
def sk_candidates_all(spark: SparkSession, folder: str) -> DataFrame:
    db = star(spark, folder)
    fks = {n: {c for f in STAR.fks if f.source == n for c in f.columns} for n in _KEYS}
    return union_all([profile.sk_candidates(profile.rrp(db.tables[n]), db.spec.relations[n], fks[n]).select(F.lit(n).alias("relation"), "*") for n in _KEYS])


@query("nk_candidates_lineitem", f"select columns as attributes, n, dv from ({sets_sql('lineitem', COLUMNS['lineitem'], 2, 'dv >= 0.7 * n')})")
def nk_candidates_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    return profile.nk_candidates(t(spark, folder, "lineitem"), list(COLUMNS["lineitem"]), 2, 0.7)


@query("review_order", f"with {borne_out_sql()}, g as (select relation, case when relation not in (select source from e) then 1 when (select count(*) from f where source = relation) <= 2 then 2 else 3 end as g from (select unnest([{', '.join(repr(n) for n in ORDER)}]) as relation)) select relation, cast(g as int) as review_group, cast(row_number() over (order by g, relation) as int) as position from g")
def review_order(spark: SparkSession, folder: str) -> DataFrame:
    """By the keys and foreign keys that the tables bear out."""
    rows = graph.review_order(verify.borne_out(star(spark, folder)))
    return spark.createDataFrame([(n, g, i + 1) for i, (n, g) in enumerate(rows)], "relation string, review_group int, position int")


@query("counterexamples_lineitem_nk", "select l_orderkey, l_linenumber, l_partkey, l_suppkey from lineitem where (l_orderkey, l_linenumber) in (select (l_orderkey, l_linenumber) from lineitem group by l_orderkey, l_linenumber having count(*) > 1)")
def counterexamples_lineitem_nk(spark: SparkSession, folder: str) -> DataFrame:
    return review.counterexamples(t(spark, folder, "lineitem"), ["l_orderkey", "l_linenumber"]).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


@query("counterexamples_documents_source", "select doc_id, source from documents where text in (select text from documents group by text having count(distinct source) > 1)")
def counterexamples_documents_source(spark: SparkSession, folder: str) -> DataFrame:
    return review.counterexamples(t(spark, folder, "documents"), ["text"], "source").select("doc_id", "source")
