"""Baselines: discovery of keys, dependencies and inclusions; deduplication without propagation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, metrics, verify
from ..plans.model import Database
from ..sources.io import union_all
from .registry import COLUMNS, FKS, NKS, ORDER, poll_sql, polluted, query, sets_sql, star, t


def ucc_sql(table: str, columns: tuple[str, ...], width: int) -> str:
    return f"select columns from ({sets_sql(table, columns, width, 'dv = n')})"


@query("ucc_lineitem", ucc_sql("lineitem", COLUMNS["lineitem"], 3))
def ucc_lineitem(spark: SparkSession, folder: str) -> DataFrame:
    """Minimal keys of at most three columns, of all columns of the widest relation."""
    found = baselines.uccs(t(spark, folder, "lineitem"), list(COLUMNS["lineitem"]), max_width=3)
    return spark.createDataFrame([("+".join(c),) for c in found], "columns string")


@query("ucc_customer", ucc_sql("customer", COLUMNS["customer"], 2))
def ucc_customer(spark: SparkSession, folder: str) -> DataFrame:
    found = baselines.uccs(t(spark, folder, "customer"), max_width=2)
    return spark.createDataFrame([("+".join(c),) for c in found], "columns string")


@query("ucc_accuracy", f"with f as ({ucc_sql('customer', COLUMNS['customer'], 2)}) select count(*) as found, coalesce(round(count(*) filter (where columns = 'c_name') / nullif(count(*), 0)::double, 6), 0.0) as \"precision\", case when count(*) filter (where columns = 'c_name') > 0 then 1.0 else 0.0 end::double as recall from f")
def ucc_accuracy(spark: SparkSession, folder: str) -> DataFrame:
    a = baselines.key_accuracy(baselines.uccs(t(spark, folder, "customer"), max_width=2), ("c_name",))
    return spark.createDataFrame([(a["found"], a["precision"], a["recall"])], "found long, precision double, recall double")


def fd_sql(table: str, columns: list[str]) -> str:
    """Minimal dependencies with one or two columns on the left."""
    from itertools import combinations

    lefts = [c for k in (1, 2) for c in combinations(columns, k)]
    tests = [(x, a) for x in lefts for a in columns if a not in x]
    rows = " union all ".join(f"select '{'+'.join(x)}' as lhs, '{a}' as rhs, (select count(*) from (select distinct {', '.join(x)} from {table})) = (select count(*) from (select distinct {', '.join(x)}, {a} from {table})) as ok" for x, a in tests)
    pairs = ", ".join(f"('{'+'.join(x)}', '{'+'.join(y)}')" for x in lefts for y in lefts if set(x) < set(y))
    return f"with f as ({rows}), p as (select * from (values {pairs}) v(small, large)) select lhs, rhs from f where ok and not exists (select 1 from p join f g on p.small = g.lhs where p.large = f.lhs and g.rhs = f.rhs and g.ok)"


@query("fds_part", fd_sql("part", list(COLUMNS["part"])))
def fds_part(spark: SparkSession, folder: str) -> DataFrame:
    return spark.createDataFrame([("+".join(x), a) for x, a, _ in baselines.fds(t(spark, folder, "part"))], "lhs string, rhs string")


@query("fds_nation", fd_sql("nation", list(COLUMNS["nation"])))
def fds_nation(spark: SparkSession, folder: str) -> DataFrame:
    return spark.createDataFrame([("+".join(x), a) for x, a, _ in baselines.fds(t(spark, folder, "nation"))], "lhs string, rhs string")


_IND = {"region": ["r_regionkey"], "nation": ["n_nationkey", "n_regionkey"], "customer": ["c_custkey", "c_nationkey"], "supplier": ["s_suppkey", "s_nationkey"], "part": ["p_partkey"], "orders": ["o_orderkey", "o_custkey"], "events": ["user_id"], "documents": ["doc_id"], "labels": ["doc_id"], "conversations": ["conv_id"]}
_IND_PAIRS = [(f"{a}.{x}", a, x, f"{b}.{y}", b, y) for a, xs in _IND.items() for x in xs for b, ys in _IND.items() for y in ys if (a, x) != (b, y)]


@query("inds_star", "select dependent, referenced from (" + " union all ".join(f"select '{p}' as dependent, '{q}' as referenced, not exists (select {x} from {a} where {x} is not null except select {y} from {b}) as ok" for p, a, x, q, b, y in _IND_PAIRS) + ") where ok")
def inds_star(spark: SparkSession, folder: str) -> DataFrame:
    from ..plans.model import DatabaseSpec, Relation

    db = Database(DatabaseSpec({n: Relation(n) for n in _IND}), {n: t(spark, folder, n) for n in _IND})
    return baselines.unary_inds(db, _IND)


@query("baseline_distinct_star", f"with {poll_sql()} " + " union all ".join(f"select '{n}' as relation, count(*) as n_rows, (select count(*) from (select distinct * from poll_{n})) as n_distinct from poll_{n}" for n in ORDER))
def baseline_distinct_star(spark: SparkSession, folder: str) -> DataFrame:
    return baselines.distinct_only(polluted(spark, folder))


@query("baseline_local_dedup_orphans", f"with {poll_sql()}, " + ", ".join(f"loc_{n} as (select * from poll_{n} qualify row_number() over (partition by {', '.join(NKS[n])} order by new_id) = 1)" for n in ORDER) + " select * from (" + " union all ".join(f"select '{a}.{c}' as fk, (select count(*) from loc_{a} s where not exists (select 1 from loc_{b} p where p.new_id = s.{c})) as n_orphans" for a, c, b in FKS) + ")")
def baseline_local_dedup_orphans(spark: SparkSession, folder: str) -> DataFrame:
    return verify.fk_report(_first_of_each(polluted(spark, folder)))


def _first_of_each(db: Database) -> Database:
    """Local deduplication that keeps, of each class, the row with the least key."""
    from pyspark.sql import Window

    out = {}
    for n, x in db.tables.items():
        own = Window.partitionBy(*NKS[n]).orderBy("new_id")
        out[n] = x.withColumn("_r", F.row_number().over(own)).where("_r = 1").drop("_r")
    return Database(db.spec, out)


@query("baseline_local_dedup_sizes", f"with {poll_sql()} " + " union all ".join(f"select '{n}' as relation, count(distinct ({', '.join(NKS[n])})) as n_left, (select count(*) from {n}) as n_true from poll_{n}" for n in ORDER))
def baseline_local_dedup_sizes(spark: SparkSession, folder: str) -> DataFrame:
    db, true = baselines.local_dedup(polluted(spark, folder)), star(spark, folder)
    return union_all([x.agg(F.count(F.lit(1)).alias("n_left")).crossJoin(true.tables[n].agg(F.count(F.lit(1)).alias("n_true"))).select(F.lit(n).alias("relation"), "*") for n, x in db.tables.items()])


@query("baseline_attr_match_part", f"with {poll_sql()} select count(*) as n, count(distinct (p_name, p_brand, p_type)) as classes, round(1 - count(distinct (p_name, p_brand, p_type)) / count(*)::double, 6) as au, round(count(distinct (p_name, p_brand, p_type)) / count(*)::double, 6) as kept_ratio from poll_part")
def baseline_attr_match_part(spark: SparkSession, folder: str) -> DataFrame:
    return baselines.attribute_match(polluted(spark, folder).tables["part"], "new_id", ["p_name", "p_brand", "p_type"])


@query("baseline_vs_propagation", f"with {poll_sql()}, x as (" + " union all ".join(f"select '{n}' as relation, count(*) as n, count(distinct ({', '.join(NKS[n])})) as alone, (select count(*) from {n}) as with_propagation from poll_{n}" for n in ORDER) + ") select relation, n, alone, with_propagation, round(1 - alone / n::double, 6) as au_alone, round(1 - with_propagation / n::double, 6) as au_propagated from x")
def baseline_vs_propagation(spark: SparkSession, folder: str) -> DataFrame:
    """Artificial unicity found with and without propagation."""
    from .registry import suppressed

    raw, clean = polluted(spark, folder), suppressed(spark, folder).db
    parts = []
    for n in ORDER:
        a = metrics.au(raw.tables[n], "new_id", NKS[n]).select("n", F.col("classes").alias("alone"), F.col("au").alias("au_alone"))
        b = metrics.au(clean.tables[n], "new_id", NKS[n]).select(F.col("classes").alias("with_propagation"), F.col("au").alias("au_propagated"))
        parts.append(a.crossJoin(b).select(F.lit(n).alias("relation"), "n", "alone", "with_propagation", "au_alone", "au_propagated"))
    return union_all(parts)
