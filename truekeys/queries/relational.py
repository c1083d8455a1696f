"""The relational operators that the method is made of, each on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import canon, udf
from ..operators import equivalence
from ..streaming import streams
from .block1 import rrp_sql
from .registry import COLUMNS, poll_sql, polluted, query, t

REST = COLUMNS["part"][1:]


@query("proj_restkey_part", f"select {', '.join(REST)} from part")
def proj_restkey_part(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "part").drop("p_partkey")


@query("proj_case_roles", "select o_orderkey, case when o_totalprice > 100000 then 'large' when o_totalprice > 10000 then 'medium' else 'small' end as size, try_cast(substr(o_orderpriority, 1, 1) as int) as priority from orders")
def proj_case_roles(spark: SparkSession, folder: str) -> DataFrame:
    size = F.when(F.col("o_totalprice") > 100000, "large").when(F.col("o_totalprice") > 10000, "medium").otherwise("small")
    return t(spark, folder, "orders").select("o_orderkey", size.alias("size"), F.substring("o_orderpriority", 1, 1).try_cast("int").alias("priority"))


@query("filter_predicates_orders", "select o_orderkey from orders where o_totalprice between 1000 and 200000 and o_orderstatus in ('O', 'F') and o_orderpriority like '%-%' and regexp_matches(o_orderpriority, '^[12]') and o_custkey is not null")
def filter_predicates_orders(spark: SparkSession, folder: str) -> DataFrame:
    o = t(spark, folder, "orders")
    return o.where(o.o_totalprice.between(1000, 200000) & o.o_orderstatus.isin("O", "F") & o.o_orderpriority.like("%-%") & o.o_orderpriority.rlike("^[12]") & o.o_custkey.isNotNull()).select("o_orderkey")


@query("filter_nullsafe", "select o_orderkey from (select o_orderkey, case when o_custkey % 3 = 0 then null else o_custkey % 3 end as k from orders) where k is not distinct from null")
def filter_nullsafe(spark: SparkSession, folder: str) -> DataFrame:
    k = F.when(F.col("o_custkey") % 3 != 0, F.col("o_custkey") % 3)
    return t(spark, folder, "orders").where(k.eqNullSafe(F.lit(None))).select("o_orderkey")


@query("having_duplicate_keys_lineitem", "select l_orderkey, l_linenumber, count(*) as n from lineitem group by l_orderkey, l_linenumber having count(*) > 1")
def having_duplicate_keys_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.count(F.lit(1)).alias("n")).where("n > 1")


@query("join_smj_orders_customer", "select o_orderkey, c_name from orders left join customer on o_custkey = c_custkey")
def join_smj_orders_customer(spark: SparkSession, folder: str) -> DataFrame:
    o, c = t(spark, folder, "orders"), t(spark, folder, "customer")
    return o.join(c.hint("merge"), o.o_custkey == c.c_custkey, "left").select("o_orderkey", "c_name")


@query("join_shuffled_hash_orders", "select o_orderkey, c_mktsegment from orders join customer on o_custkey = c_custkey")
def join_shuffled_hash_orders(spark: SparkSession, folder: str) -> DataFrame:
    o, c = t(spark, folder, "orders"), t(spark, folder, "customer")
    return o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).select("o_orderkey", "c_mktsegment")


@query("join_inner_star", "select r_name, count(*) as n, count(distinct c_custkey) as customers from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")
def join_inner_star(spark: SparkSession, folder: str) -> DataFrame:
    o, c, n, r = (t(spark, folder, x) for x in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("c_custkey").alias("customers"))


@query("join_nullsafe_keys", "with a as (select distinct case when c_nationkey % 4 = 0 then null else c_nationkey end as k from customer), b as (select distinct case when s_nationkey % 4 = 0 then null else s_nationkey end as k from supplier) select a.k from a join b on a.k is not distinct from b.k")
def join_nullsafe_keys(spark: SparkSession, folder: str) -> DataFrame:
    a = t(spark, folder, "customer").select(F.when(F.col("c_nationkey") % 4 != 0, F.col("c_nationkey")).alias("k")).distinct()
    b = t(spark, folder, "supplier").select(F.when(F.col("s_nationkey") % 4 != 0, F.col("s_nationkey")).alias("k2")).distinct()
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).select("k")


@query("join_semi_conflicts", "select doc_id from documents where text in (select text from documents group by text having count(distinct source) > 1)")
def join_semi_conflicts(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents").select("doc_id", "source", canon.fingerprint(t(spark, folder, "documents"), ["text"]).alias("k"))
    bad = d.groupBy("k").agg(F.min("source").alias("a"), F.max("source").alias("b")).where("a <> b")
    return d.join(bad, "k", "left_semi").select("doc_id")


@query("join_anti_orphans", "select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_custkey is not null)")
def join_anti_orphans(spark: SparkSession, folder: str) -> DataFrame:
    c, o = t(spark, folder, "customer"), t(spark, folder, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@query("join_full_rrp", f"with a as ({rrp_sql('customer')}), b as ({rrp_sql('supplier')}) select coalesce(x, y) as name, a.dv as dv_customer, b.dv as dv_supplier from (select *, substr(attribute, 3) as x from a) a full join (select *, substr(attribute, 3) as y from b) b on x = y")
def join_full_rrp(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.profile import rrp

    side = lambda n: rrp(t(spark, folder, n)).select(F.expr("substr(attribute, 3)").alias("name"), F.col("dv").alias(f"dv_{n}"))
    return side("customer").join(side("supplier"), "name", "full")


@query("join_cross_rules", "select r_name, rule from region cross join (values ('majority'), ('min')) v(rule)")
def join_cross_rules(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "region").select("r_name").crossJoin(spark.createDataFrame([("majority",), ("min",)], "rule string"))  # a few rows by two


_VERSIONS = "v as (select o_custkey as sk, o_orderdate as valid_from, max(o_totalprice) as price from orders group by all), h as (select *, lead(valid_from) over (partition by sk order by valid_from) as valid_to from v), e as (select event_id, user_id, ts from events)"


def versions(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.decompose import validity

    o = t(spark, folder, "orders")
    v = o.groupBy(F.col("o_custkey").alias("sk"), F.col("o_orderdate").alias("valid_from")).agg(F.max("o_totalprice").alias("price"))
    return validity(v.withColumnRenamed("valid_from", "o"), "sk", "o")


@query("join_interval_history", f"with {_VERSIONS} select event_id, sk, price from e join h on user_id = sk and ts >= valid_from and (valid_to is null or ts < valid_to)")
def join_interval_history(spark: SparkSession, folder: str) -> DataFrame:
    h, e = versions(spark, folder), t(spark, folder, "events")
    inside = (e.user_id == h.sk) & (e.ts >= h.valid_from) & (h.valid_to.isNull() | (e.ts < h.valid_to))
    return e.join(h, inside).select("event_id", "sk", "price")


@query("join_asof_history", f"with {_VERSIONS} select e.event_id, v.price from e asof left join v on e.user_id = v.sk and e.ts >= v.valid_from")
def join_asof_history(spark: SparkSession, folder: str) -> DataFrame:
    """As-of join: both sides in one sorted stream by key, the last version carried forward; one shuffle."""
    h, e = versions(spark, folder), t(spark, folder, "events")
    both = h.select("sk", F.col("valid_from").alias("at"), F.lit(0).alias("side"), "price", F.lit(None).cast("long").alias("event_id")).unionByName(e.select(F.col("user_id").alias("sk"), F.col("ts").alias("at"), F.lit(1).alias("side"), F.lit(None).cast("double").alias("price"), "event_id"))
    carried = F.last("price", ignorenulls=True).over(Window.partitionBy("sk").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("price", carried).where("side = 1").select("event_id", "price")


@query("join_lateral_latest", "select c_custkey, d as latest from customer left join (select o_custkey, max(o_orderdate) as d from orders group by o_custkey) on c_custkey = o_custkey where d is not null")
def join_lateral_latest(spark: SparkSession, folder: str) -> DataFrame:
    c, o = t(spark, folder, "customer"), t(spark, folder, "orders")
    latest = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).select(F.max("o_orderdate").alias("latest"))
    return c.lateralJoin(latest).where("latest is not null").select("c_custkey", "latest")


@query("agg_min_per_class", "select p_name, min(p_partkey) as rep, count(*) as n from part group by p_name")
def agg_min_per_class(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "part").groupBy("p_name").agg(F.min("p_partkey").alias("rep"), F.count(F.lit(1)).alias("n"))


@query("agg_filter_nulls", "select count(*) filter (where c_acctbal < 0) as negative, count(*) filter (where c_nationkey is null) as nv from customer")
def agg_filter_nulls(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").agg(F.count_if(F.col("c_acctbal") < 0).alias("negative"), F.count_if(F.col("c_nationkey").isNull()).alias("nv"))


@query("agg_conflict_groups", "select count(*) as n_groups from (select 1 from part group by p_name having count(distinct p_brand) > 1)")
def agg_conflict_groups(spark: SparkSession, folder: str) -> DataFrame:
    g = t(spark, folder, "part").groupBy("p_name").agg(F.min("p_brand").alias("a"), F.max("p_brand").alias("b"))
    return g.where("a <> b").agg(F.count(F.lit(1)).alias("n_groups"))


_MAJORITY = "with p as (select p_name, p_brand, count(*) as c, min(p_partkey) as f from part group by all) select p_name, first(p_brand order by c desc, f) as brand from p group by p_name"


@query("agg_majority_source", _MAJORITY)
def agg_majority_source(spark: SparkSession, folder: str) -> DataFrame:
    per = t(spark, folder, "part").groupBy("p_name", "p_brand").agg(F.count(F.lit(1)).alias("c"), F.min("p_partkey").alias("f"))
    return per.groupBy("p_name").agg(F.max_by("p_brand", F.struct(F.col("c"), (-F.col("f")).alias("f"))).alias("brand"))


@query("udaf_majority_brand", "with p as (select p_name, p_brand, count(*) as c from part group by all) select p_name, first(p_brand order by c desc, p_brand) as brand from p group by p_name")
def udaf_majority_brand(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "part").groupBy("p_name").agg(udf.majority("p_brand").alias("brand"))


@query("agg_statistics_acctbal", "select c_mktsegment, round(median(c_acctbal), 4) as median, round(stddev_samp(c_acctbal), 4) as deviation, round(avg(c_acctbal), 4) as mean from customer group by c_mktsegment")
def agg_statistics_acctbal(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").groupBy("c_mktsegment").agg(F.round(F.median("c_acctbal"), 4).alias("median"), F.round(F.stddev_samp("c_acctbal"), 4).alias("deviation"), F.round(F.avg("c_acctbal"), 4).alias("mean"))


@query("agg_percentiles_acctbal", "select c_mktsegment, round(quantile_cont(c_acctbal, 0.25), 4) as q1, round(quantile_cont(c_acctbal, 0.9), 4) as p90 from customer group by c_mktsegment")
def agg_percentiles_acctbal(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").groupBy("c_mktsegment").agg(F.round(F.percentile("c_acctbal", F.lit(0.25)), 4).alias("q1"), F.round(F.percentile("c_acctbal", F.lit(0.9)), 4).alias("p90"))


@query("agg_histogram_acctbal", "select cast(floor((c_acctbal + 1000) / 1000) as bigint) as bar, count(*) as n, min(c_acctbal) as low, max(c_acctbal) as high from customer where c_acctbal is not null group by all")
def agg_histogram_acctbal(spark: SparkSession, folder: str) -> DataFrame:
    """Bars of equal width, counted where the rows are."""
    c = t(spark, folder, "customer").where("c_acctbal is not null")
    return c.groupBy(F.floor((F.col("c_acctbal") + 1000) / 1000).alias("bar")).agg(F.count(F.lit(1)).alias("n"), F.min("c_acctbal").alias("low"), F.max("c_acctbal").alias("high"))


_AU = "count(*) as n, round(1 - count(distinct text) / count(*)::double, 6) as au from documents group by"


def _au(grouped):  # noqa: ANN001, ANN202
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.round(1 - F.countDistinct("text") / F.count(F.lit(1)), 6).alias("au"))


@query("au_rollup_lang_source", f"select lang, source, {_AU} rollup(lang, source)")
def au_rollup_lang_source(spark: SparkSession, folder: str) -> DataFrame:
    return _au(t(spark, folder, "documents").rollup("lang", "source"))


@query("au_cube_documents", f"select lang, source, {_AU} cube(lang, source)")
def au_cube_documents(spark: SparkSession, folder: str) -> DataFrame:
    return _au(t(spark, folder, "documents").cube("lang", "source"))


@query("au_gsets_orders", "select o_orderstatus, o_orderpriority, cast(grouping_id(o_orderstatus, o_orderpriority) as bigint) as gid, count(*) as n, count(distinct o_custkey) as dv from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def au_gsets_orders(spark: SparkSession, folder: str) -> DataFrame:
    o = t(spark, folder, "orders")
    return o.groupingSets([[o.o_orderstatus], [o.o_orderpriority], []], o.o_orderstatus, o.o_orderpriority).agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"), F.countDistinct("o_custkey").alias("dv"))


@query("rrp_unpivot_nation", "unpivot (select count(distinct n_nationkey) as n_nationkey, count(distinct n_name) as n_name, count(distinct n_regionkey) as n_regionkey from nation) on n_nationkey, n_name, n_regionkey into name attribute value dv")
def rrp_unpivot_nation(spark: SparkSession, folder: str) -> DataFrame:
    names = ["n_nationkey", "n_name", "n_regionkey"]
    return t(spark, folder, "nation").agg(*(F.countDistinct(c).alias(c) for c in names)).unpivot([], names, "attribute", "dv")


@query("pivot_roles", "select lang, count(*) filter (where doc_id % 2 = 0) as even, count(*) filter (where doc_id % 2 = 1) as odd from documents group by lang")
def pivot_roles(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents").withColumn("parity", F.when(F.col("doc_id") % 2 == 0, "even").otherwise("odd"))
    return d.groupBy("lang").pivot("parity", ["even", "odd"]).agg(F.count(F.lit(1))).fillna(0)


@query("win_min_rep_documents", "select doc_id, min(doc_id) over (partition by text) as rep from documents")
def win_min_rep_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents")
    return d.select("doc_id", F.min("doc_id").over(Window.partitionBy(canon.fingerprint(d, ["text"]))).alias("rep"))


@query("win_rank_rrp", f"select attribute, dv, cast(rank() over w as int) as r, cast(dense_rank() over w as int) as dr, cast(ntile(2) over (order by dv desc, attribute) as int) as half, round(percent_rank() over w, 6) as pr from ({rrp_sql('orders')}) window w as (order by dv desc)")
def win_rank_rrp(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.profile import rrp

    w = Window.orderBy(F.desc("dv"))  # one row a column
    return rrp(t(spark, folder, "orders")).select("attribute", "dv", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(2).over(Window.orderBy(F.desc("dv"), "attribute")).alias("half"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("win_rownumber_local_dedup", f"with {poll_sql()} select new_id, c_custkey from poll_customer qualify row_number() over (partition by c_name, c_nationkey order by new_id) = 1")
def win_rownumber_local_dedup(spark: SparkSession, folder: str) -> DataFrame:
    w = Window.partitionBy("c_name", "c_nationkey").orderBy("new_id")
    return polluted(spark, folder).tables["customer"].withColumn("r", F.row_number().over(w)).where("r = 1").select("new_id", "c_custkey")


@query("win_running_dups_orders", "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row) as so_far, round(avg(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row), 4) as moving from orders")
def win_running_dups_orders(spark: SparkSession, folder: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(spark, folder, "orders").select("o_orderkey", F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"), F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("moving"))


@query("win_range_7d_events", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 604800000000 preceding and current row) as n_7d from events")
def win_range_7d_events(spark: SparkSession, folder: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-604_800_000_000, 0)
    return t(spark, folder, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n_7d"))


@query("topk_classes_documents", "select min(doc_id) as rep, count(*) as size from documents group by text order by size desc, rep limit 10")
def topk_classes_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents")
    return d.groupBy(canon.fingerprint(d, ["text"]).alias("k")).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("size")).select("rep", "size").orderBy(F.desc("size"), "rep").limit(10)


@query("topk_per_class", "select doc_id, lang from documents qualify row_number() over (partition by lang order by n_chars desc, doc_id) <= 3")
def topk_per_class(spark: SparkSession, folder: str) -> DataFrame:
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return t(spark, folder, "documents").withColumn("r", F.row_number().over(w)).where("r <= 3").select("doc_id", "lang")


@query("set_union_polluted", "select 'customer' as relation, c_custkey as k from customer union all select 'supplier', s_suppkey from supplier")
def set_union_polluted(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").select(F.lit("customer").alias("relation"), F.col("c_custkey").alias("k")).unionByName(t(spark, folder, "supplier").select(F.col("s_suppkey").alias("k"), F.lit("supplier").alias("relation")))


@query("set_intersect_nations", "select c_nationkey as k from customer intersect select s_nationkey from supplier")
def set_intersect_nations(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).intersect(t(spark, folder, "supplier").select("s_nationkey"))


@query("set_except_all_nations", "select c_nationkey as k from customer except all select s_nationkey from supplier")
def set_except_all_nations(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(t(spark, folder, "supplier").select("s_nationkey"))


@query("set_intersect_all_nations", "select c_nationkey as k from customer intersect all select s_nationkey from supplier")
def set_intersect_all_nations(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(t(spark, folder, "supplier").select("s_nationkey"))


@query("fn_normalise_part_name", "select p_partkey, trim(regexp_replace(lower(p_name), '[^a-z0-9]+', ' ', 'g')) as name, upper(p_brand) as brand from part")
def fn_normalise_part_name(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "part").select("p_partkey", canon.text(F.col("p_name")).alias("name"), F.upper("p_brand").alias("brand"))


@query("fn_levenshtein_brand", "with b as (select distinct p_brand as b from part) select x.b as a, y.b as b, levenshtein(x.b, y.b) as d from b x join b y on x.b < y.b and levenshtein(x.b, y.b) <= 1")
def fn_levenshtein_brand(spark: SparkSession, folder: str) -> DataFrame:
    b = t(spark, folder, "part").select(F.col("p_brand").alias("b")).distinct()  # a few brands
    return b.withColumnRenamed("b", "a").join(b, F.col("a") < F.col("b")).withColumn("d", F.levenshtein("a", "b").cast("long")).where("d <= 1")


_CODES = "translate(upper(p_name), 'AEIOUYHWBFPVCGJKQSXZDTLMNR', '00000077111122222222334556')"
for _digit in "0123456":
    _CODES = f"regexp_replace({_CODES}, '{_digit}+', '{_digit}', 'g')" if _digit != "0" else f"replace({_CODES}, '7', '')"


@query("fn_soundex_part_name", f"select distinct p_name as word, left(p_name, 1).upper() || rpad(left(replace(substr({_CODES}, 2), '0', ''), 3), 3, '0') as sound from (select split_part(p_name, ' ', 1) as p_name from part) where p_name <> '' and upper(left(p_name, 1)) not in ('H', 'W')")
def fn_soundex_part_name(spark: SparkSession, folder: str) -> DataFrame:
    """How the first words of names sound (the oracle's rule needs a first letter that has a code)."""
    word = F.split_part("p_name", F.lit(" "), F.lit(1))
    w = t(spark, folder, "part").select(word.alias("word")).distinct().where("word <> '' and upper(left(word, 1)) not in ('H', 'W')")
    return w.select("word", F.soundex("word").alias("sound"))


@query("fn_collate_brand", "select min(b) as least, count(*) as n from (select case when p_partkey % 2 = 0 then upper(p_brand) else p_brand end as b from part) group by lower(b)")
def fn_collate_brand(spark: SparkSession, folder: str) -> DataFrame:
    """Brands that differ in case only are one value under a collation without case."""
    b = F.when(F.col("p_partkey") % 2 == 0, F.upper("p_brand")).otherwise(F.col("p_brand"))
    return t(spark, folder, "part").select(b.alias("b")).groupBy(F.collate("b", "UTF8_LCASE").alias("c")).agg(F.min("b").alias("least"), F.count(F.lit(1)).alias("n")).select("least", "n")


@query("fn_variant_events", "select event_type, count(distinct cast(json_extract(props, '$.k') as bigint)) as dv, sum(cast(json_extract(props, '$.k') as bigint))::bigint as total from events group by event_type")
def fn_variant_events(spark: SparkSession, folder: str) -> DataFrame:
    k = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return t(spark, folder, "events").groupBy("event_type").agg(F.countDistinct(k).alias("dv"), F.sum(k).alias("total"))


@query("fn_variant_schema_events", "select event_type, 'OBJECT<k: BIGINT>' as shape from events group by event_type")
def fn_variant_schema_events(spark: SparkSession, folder: str) -> DataFrame:
    """The schema that all values of an attribute share, found by an aggregate over all rows."""
    return t(spark, folder, "events").groupBy("event_type").agg(F.schema_of_variant_agg(F.try_parse_json("props")).alias("shape"))


@query("fn_parse_dates", "select o_orderkey, cast(o_orderdate as date) as day from orders")
def fn_parse_dates(spark: SparkSession, folder: str) -> DataFrame:
    """Dates written in three ways are read back to the same day."""
    o = t(spark, folder, "orders")
    shape = F.element_at(F.array(*(F.date_format("o_orderdate", f) for f in ("dd-MM-yyyy", "dd/MM/yyyy", "yyyy-MM-dd"))), (F.col("o_orderkey") % 3 + 1).cast("int"))
    return o.select("o_orderkey", canon.date(shape).alias("day"))


@query("fn_trunc_orders", "select o_orderkey, cast(date_trunc('month', o_orderdate) as date) as month, cast(o_orderdate + interval 1 month as date) as next from orders")
def fn_trunc_orders(spark: SparkSession, folder: str) -> DataFrame:
    return t(spark, folder, "orders").select("o_orderkey", F.trunc("o_orderdate", "month").alias("month"), F.add_months("o_orderdate", 1).alias("next"))


@query("fn_md5_sample", "select doc_id from documents order by md5(cast(doc_id as varchar)), doc_id limit 20")
def fn_md5_sample(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.review import sample

    return sample(t(spark, folder, "documents"), 20, ["doc_id"]).select("doc_id")


@query("fn_array_class_members", "with c as (select list_sort(list(p_partkey)) as m from part group by p_name, p_brand) select m[1] as rep, len(m) as size, m[len(m)] as last, list_contains(m, 1) as has_one from c where len(m) > 1")
def fn_array_class_members(spark: SparkSession, folder: str) -> DataFrame:
    c = equivalence.classes(t(spark, folder, "part"), "p_partkey", ["p_name", "p_brand"]).where("size > 1")
    return c.select("rep", "size", F.array_max("members").alias("last"), F.array_contains("members", F.lit(1).cast("long")).alias("has_one"))


@query("fn_map_canonical", "select count(*) as n, count(distinct (case when o_orderkey % 2 = 0 then 'a' else 'b' end, o_orderstatus, o_orderpriority)) as dv, cast(0 as bigint) as nv, count(*) - count(distinct (case when o_orderkey % 2 = 0 then 'a' else 'b' end, o_orderstatus, o_orderpriority)) as ov from orders")
def fn_map_canonical(spark: SparkSession, folder: str) -> DataFrame:
    """A map column is profiled by its entries in key order, whatever order they were written in."""
    from ..operators.profile import arp

    pair = F.struct(F.when(F.col("o_orderkey") % 2 == 0, "a").otherwise("b").alias("k"), F.col("o_orderstatus").alias("s"))
    twice = F.create_map(F.lit("x"), pair["k"], F.lit("y"), pair["s"], F.lit("z"), F.col("o_orderpriority"))
    other = F.create_map(F.lit("z"), F.col("o_orderpriority"), F.lit("y"), pair["s"], F.lit("x"), pair["k"])
    o = t(spark, folder, "orders").select(F.when(F.col("o_custkey") % 2 == 0, twice).otherwise(other).alias("m"))
    return arp(o, "m").drop("attribute")


@query("udtf_history", "with v as (select o_custkey as sk, o_orderdate as valid_from, cast(count(*) as double) as value from orders group by all) select sk, valid_from, value from (select *, lag(value) over w as b, row_number() over w as r from v window w as (partition by sk order by valid_from)) where r = 1 or b is distinct from value")
def udtf_history(spark: SparkSession, folder: str) -> DataFrame:
    udf.register(spark)
    o = t(spark, folder, "orders")
    o.groupBy(F.col("o_custkey").alias("sk"), F.col("o_orderdate").alias("valid_from")).agg(F.count(F.lit(1)).cast("double").alias("value")).createOrReplaceTempView("tk_versions")
    return spark.sql("select * from tk_compacted(table(tk_versions) partition by sk order by valid_from)")


@query("udtf_profile_orders", " union all ".join(f"select '{c}' as attribute, count(*) as n, count(distinct {c}) as dv, count(*) - count({c}) as nv from orders" for c in COLUMNS["orders"]))
def udtf_profile_orders(spark: SparkSession, folder: str) -> DataFrame:
    """Profiles by a table function: equal values are folded first, and each attribute is cut into parts by its values."""
    udf.register(spark)
    names = list(COLUMNS["orders"])
    long = t(spark, folder, "orders").select(*(F.col(c).cast("string").alias(c) for c in names)).unpivot([], names, "attribute", "value")
    long.groupBy("attribute", "value").agg(F.count(F.lit(1)).alias("k")).withColumn("part", F.pmod(F.xxhash64("value"), F.lit(64))).createOrReplaceTempView("tk_values")
    parts = spark.sql("select * from tk_profiled(table(tk_values) partition by (attribute, part) order by value)")
    return parts.groupBy("attribute").agg(*(F.sum(c).alias(c) for c in ("n", "dv", "nv")))


@query("sql_udf_canon", "select p_partkey, trim(regexp_replace(lower(p_name), '[^a-z0-9]+', ' ', 'g')) as name from part")
def sql_udf_canon(spark: SparkSession, folder: str) -> DataFrame:
    udf.register(spark)
    t(spark, folder, "part").createOrReplaceTempView("tk_part")
    return spark.sql("select p_partkey, tk_canon(p_name) as name from tk_part")


@query("stream_tumbling_events", "select time_bucket(interval 1 day, ts) as starts, event_type, count(*) as n, count(*) - count(value) as nv from events group by all")
def stream_tumbling_events(spark: SparkSession, folder: str) -> DataFrame:
    out = streams.tumbling(t(spark, folder, "events"), "event_type", "value")
    return out.select(F.col("window.start").alias("starts"), "event_type", "n", "nv")


@query("stream_sliding_events", "select s as starts, event_type, count(*) as n from (select unnest([time_bucket(interval 12 hours, ts), time_bucket(interval 12 hours, ts) - interval 12 hours]) as s, event_type from events) group by all")
def stream_sliding_events(spark: SparkSession, folder: str) -> DataFrame:
    out = streams.tumbling(t(spark, folder, "events"), "event_type", "value", "1 day", "12 hours")
    return out.select(F.col("window.start").alias("starts"), "event_type", "n")


@query("stream_session_events", "with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 1 day then 0 else 1 end as fresh from events), s as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as g from e) select user_id, min(ts) as starts, count(*) as n from s group by user_id, g")
def stream_session_events(spark: SparkSession, folder: str) -> DataFrame:
    out = streams.sessions(t(spark, folder, "events"), "user_id", "1 day")
    return out.select("user_id", F.col("session_window.start").alias("starts"), "n")
