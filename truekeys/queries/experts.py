"""Rules that an expert gives for whole runs, histories along paths of keys, keys of awkward types, long chains."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import decompose, equivalence, matching, propagate
from ..plans import pipeline
from ..plans.model import Database, DatabaseSpec, ExpertDecisions, ForeignKey, Relation
from ..plans.staging import staged
from .block3 import _DRIFTED, KEY, drifted
from .registry import once, query, t

# Runs of the pipeline on the drifting customers (references clean, twins not yet merged), one rule for two or three
# attributes of different types.

_SEEN = _DRIFTED + ", own as (select *, cast(orig % 7 as int) as seen from cust)"
_ATTRIBUTES = ("c_acctbal", "c_mktsegment", "seen")


@once
def _customers(spark: SparkSession, folder: str) -> DataFrame:
    c = drifted(spark, folder).tables["customer"]
    return staged(c.select(F.col("__orig_new_id").alias("new_id"), "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", (F.col("__orig_new_id") % 7).cast("int").alias("seen")))


def _run(spark: SparkSession, folder: str, rules: dict, sk: str | None = "new_id", hashed: bool = False, **kw) -> DataFrame:  # noqa: ANN003
    c = _customers(spark, folder)
    if hashed:
        c = c.withColumn("new_id", F.md5(F.col("new_id").cast("string").cast("binary")))
    if sk is None:
        c = c.drop("new_id")
    spec = DatabaseSpec({"customer": Relation("customer", (sk,) if sk else (), tuple(KEY))})
    decisions = ExpertDecisions.from_json(ExpertDecisions(rules={"customer": rules}).to_json())
    return pipeline.run(Database(spec, {"customer": c}), decisions, **kw).db.tables["customer"]


def _runs_sql(picks: dict[str, str], sk: str = "min(orig) as new_id, ", first: str = "min(orig)") -> str:
    """One row an entity; picks: attribute -> order in which its first value (c rows, f first, o latest) is kept."""
    parts = [f"{a}_of as (select c_name, c_nationkey, first({a} order by {order}) as {a} from (select c_name, c_nationkey, {a}, cast({a} as varchar) as value, count(*) as c, {first} as f, max(seen) as o from own group by c_name, c_nationkey, {a}) group by c_name, c_nationkey)" for a, order in picks.items()]
    joins = " ".join(f"join {a}_of using (c_name, c_nationkey)" for a in picks)
    return _SEEN + ", " + ", ".join(parts) + f" select {sk}c_name, c_nationkey, {', '.join(f'any_value({a}_of.{a}) as {a}' for a in picks)} from own {joins} group by c_name, c_nationkey"


_MAJORITY = "c desc, f, value"


@query("chase_mixed_types", _runs_sql({"c_acctbal": "c_acctbal", "c_mktsegment": "c_mktsegment", "seen": "seen"}))
def chase_mixed_types(spark: SparkSession, folder: str) -> DataFrame:
    """The least value of a double, a string and an integer at once."""
    return _run(spark, folder, dict.fromkeys(_ATTRIBUTES, "min"))


@query("chase_hash_key", _runs_sql(dict.fromkeys(_ATTRIBUTES, _MAJORITY), "min(md5(cast(orig as varchar))) as new_id, ", "min(md5(cast(orig as varchar)))"))
def chase_hash_key(spark: SparkSession, folder: str) -> DataFrame:
    """The default rule where surrogate keys are texts."""
    return _run(spark, folder, {}, hashed=True)


@query("chase_no_surrogate", _runs_sql(dict.fromkeys(_ATTRIBUTES, "c desc, value"), ""))
def chase_no_surrogate(spark: SparkSession, folder: str) -> DataFrame:
    """The default rule in a relation without a surrogate key."""
    return _run(spark, folder, {}, None)


@query("chase_pipeline_latest", _runs_sql({"c_acctbal": "o desc, c_acctbal desc", "c_mktsegment": "o desc, c_mktsegment desc", "seen": "seen desc"}))
def chase_pipeline_latest(spark: SparkSession, folder: str) -> DataFrame:
    return _run(spark, folder, {"c_acctbal": {"rule": "latest", "by": "seen"}, "c_mktsegment": {"rule": "latest", "by": "seen"}, "seen": "max"})


@query("chase_pipeline_priority", _runs_sql({"c_acctbal": _MAJORITY, "c_mktsegment": "case c_mktsegment when 'DRIFTED' then 1 when 'BUILDING' then 2 else 3 end, " + _MAJORITY, "seen": "case seen when 5 then 1 when 3 then 2 else 3 end, " + _MAJORITY}))
def chase_pipeline_priority(spark: SparkSession, folder: str) -> DataFrame:
    return _run(spark, folder, {"c_mktsegment": {"rule": "priority", "values": ["DRIFTED", "BUILDING"]}, "seen": {"rule": "priority", "values": ["5", "3"]}})


@query("chase_pipeline_validated", _runs_sql({"c_acctbal": "case when c_acctbal >= 1000 then 0 else 1 end, " + _MAJORITY, "c_mktsegment": "case when c_mktsegment <> 'BUILDING' and c_mktsegment <> 'DRIFTED' then 0 else 1 end, " + _MAJORITY, "seen": _MAJORITY}))
def chase_pipeline_validated(spark: SparkSession, folder: str) -> DataFrame:
    return _run(spark, folder, {"c_acctbal": {"rule": "validated", "predicate": "cast(value as double) >= 1000"}, "c_mktsegment": {"rule": "validated", "predicate": "value not in ('BUILDING', 'DRIFTED')"}})


_FIRST = "(select c_name from own group by c_name, c_nationkey having count(distinct {a}) > 1 order by c_name limit 3)"


@query("chase_pipeline_expert", _runs_sql({"c_acctbal": _MAJORITY, "c_mktsegment": _MAJORITY, "seen": _MAJORITY}).replace(" select min(orig)", f", named as (select (select list(c_name) from {_FIRST.format(a='c_acctbal')}) as a, (select list(c_name) from {_FIRST.format(a='c_mktsegment')}) as b) select min(orig)").replace("any_value(c_acctbal_of.c_acctbal)", "case when list_contains((select a from named), c_name) then -1.5 else any_value(c_acctbal_of.c_acctbal) end").replace("any_value(c_mktsegment_of.c_mktsegment)", "case when list_contains((select b from named), c_name) then 'EXPERT' else any_value(c_mktsegment_of.c_mktsegment) end"))
def chase_pipeline_expert(spark: SparkSession, folder: str) -> DataFrame:
    """The expert names a balance and a segment for three entities each (a hand-written list), majority for the others."""

    def named(a: str, value: object) -> dict:
        rows = _customers(spark, folder).groupBy(*KEY).agg(F.countDistinct(a).alias("n")).where("n > 1").orderBy("c_name").limit(3).collect()
        return {"rule": "expert", "values": [{"key": [r[k] for k in KEY], "value": value} for r in rows]}

    return _run(spark, folder, {"c_acctbal": named("c_acctbal", -1.5), "c_mktsegment": named("c_mktsegment", "EXPERT")})


@query("chase_pipeline_model", _runs_sql({"c_acctbal": _MAJORITY, "c_mktsegment": "length(c_mktsegment) desc, c_mktsegment", "seen": "cast(value as int) % 4 desc, value"}))
def chase_pipeline_model(spark: SparkSession, folder: str) -> DataFrame:
    """Scores of the caller's: here, the length of a text and the remainder of a number."""
    functions = {"long": F.length, "remainder": lambda v: v.cast("int") % 4}
    return _run(spark, folder, {"c_mktsegment": {"rule": "model", "function": "long"}, "seen": {"rule": "model", "function": "remainder"}}, functions=functions)


# Histories: entities without any event, and completing attributes along a path of keys.

_PART = _DRIFTED + ", some_orders as (select * from ord where orig % 5 <> 0)"


def _childless(spark: SparkSession, folder: str) -> Database:
    """The drifting customers, where one in five has no order; lineitem hangs on the orders."""
    db = drifted(spark, folder)
    orders = db.tables["orders"].where(F.col(propagate.LINEAGE + "o_custkey") % 5 != 0)
    return Database(db.spec, db.tables | {"orders": orders})


@query("split_history_childless", _PART + " select distinct c.new_id, c.c_name, c.c_nationkey, o.o_orderdate, c.c_acctbal from cust c left join some_orders o on c.orig = o.orig")
def split_history_childless(spark: SparkSession, folder: str) -> DataFrame:
    """Entities without any event keep their values, under a completing attribute that is not known."""
    db = _childless(spark, folder)
    return decompose.history(decompose.completed(db, "customer", "orders.o_orderdate"), ["new_id"], KEY, ["o_orderdate"], ["c_acctbal"])


@query("history_recovers_values", _PART + " select count(*) as n_values, cast(0 as bigint) as n_lost from (select distinct new_id, c_acctbal from cust)")
def history_recovers_values(spark: SparkSession, folder: str) -> DataFrame:
    """Every (entity, value) of an unstable attribute is found in the history."""
    db = _childless(spark, folder)
    own = db.tables["customer"].select("new_id", "c_acctbal").distinct()
    there = split_history_childless(spark, folder).select("new_id", "c_acctbal").distinct().withColumn("found", F.lit(1))
    return own.join(there, ["new_id", "c_acctbal"], "left").agg(F.count(F.lit(1)).alias("n_values"), F.count_if(F.col("found").isNull()).alias("n_lost"))


@query("history_path_customer", _DRIFTED + ", days as (select o.orig, l.l_shipdate from ord o left join poll_lineitem l on l.l_orderkey = o.o_orderkey_id) select distinct c.new_id, d.l_shipdate, c.c_acctbal from cust c left join days d on c.orig = d.orig".replace("o.o_orderkey_id", "o.new_id"))
def history_path_customer(spark: SparkSession, folder: str) -> DataFrame:
    """The completing attribute is two foreign keys away: customer, its orders, their items."""
    from .registry import polluted

    db = drifted(spark, folder)
    every = polluted(spark, folder)
    tables = db.tables | {"lineitem": every.tables["lineitem"]}
    wide = Database(every.spec.restrict([*db.tables, "lineitem"]), tables)
    out = decompose.completed(wide, "customer", "orders/lineitem[l_orderkey].l_shipdate")
    return decompose.history(out, ["new_id"], [], ["l_shipdate"], ["c_acctbal"])


# Keys of awkward types, long chains, matchers.


@query("sk_map_events_micros", "select event_id as sk, rep from (select event_id, min(event_id) over (partition by user_id % 4, event_id % 5, extract(minute from ts), event_id % 3) as rep from events) where event_id <> rep")
def sk_map_events_micros(spark: SparkSession, folder: str) -> DataFrame:
    """Natural keys that differ in microseconds only."""
    e = t(spark, folder, "events")
    base = F.lit("2024-01-01 00:00:00").cast("timestamp_ntz")
    made = e.select("event_id", (F.col("user_id") % 4).alias("u"), (F.col("event_id") % 5).cast("int").alias("part"), F.timestamp_add("MICROSECOND", (F.col("event_id") % 3).cast("int"), F.timestamp_add("MINUTE", F.minute("ts"), base)).alias("at"))
    return equivalence.sk_map(made, "event_id", ["u", "part", "at"])


_LEVELS = 32


@query("fixpoint_long_chain", f"with recursive chain(id, name, boss, rep, level) as (select copy, 'n0', cast(null as bigint), cast(0 as bigint), 0 from (values (cast(0 as bigint)), (cast(1 as bigint))) v(copy) union all select id + 2, 'n' || (level + 1), id, cast(2 * (level + 1) as bigint), level + 1 from chain where level + 1 < {_LEVELS}) select rep as id, name, case when level > 0 then rep - 2 end as boss from chain")
def fixpoint_long_chain(spark: SparkSession, folder: str) -> DataFrame:
    """A chain of managers with twins at each of its levels: one level becomes equal in each round."""
    rows = [(2 * k + copy, f"n{k}", 2 * (k - 1) + copy if k else None) for k in range(_LEVELS) for copy in (0, 1)]
    spec = DatabaseSpec({"staff": Relation("staff", ("id",), ("name", "boss"))}, (ForeignKey("staff", ("boss",), "staff", ("id",)),))
    return propagate.clean(Database(spec, {"staff": spark.createDataFrame(rows, "id long, name string, boss long").coalesce(1)})).db.tables["staff"]


_SHINGLES = "select doc_id, list_distinct(list_transform(generate_series(1, greatest(1, len(w) - 4)), lambda i: array_to_string(w[i:i + 4], ' '))) as s from (select doc_id, regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9]+') as w from documents) where len(w) > 0"
_CLOSED = "g as (select a, b from e union select b, a from e), w(node, root) as (select a, a from g union select g.b, w.root from w join g on g.a = w.node where w.root < g.b), roots as (select node, min(root) as root from w group by node)"


@query("match_documents_minhash", f"with recursive s as materialized ({_SHINGLES}), c as materialized (select s, min(doc_id) as doc_id from s group by s), p as materialized (select doc_id, unnest(s) as x, len(s) as n from c), f as materialized (select a.doc_id as a, b.doc_id as b from p a join p b on a.x = b.x and a.doc_id < b.doc_id group by a.doc_id, b.doc_id, a.n, b.n having count(*) >= 0.8 * (a.n + b.n - count(*))), e as materialized (select a, b from f union select c.doc_id, s.doc_id from s join c on s.s = c.s where s.doc_id <> c.doc_id), {_CLOSED} select d.doc_id as sk, coalesce(root, d.doc_id) as rep from documents d left join roots on node = d.doc_id")
def match_documents_minhash(spark: SparkSession, folder: str) -> DataFrame:
    """Documents of similar shingle sets are one class: candidates by banded signatures, confirmed on whole sets."""
    d = t(spark, folder, "documents")
    return matching.classes_from_pairs(d, "doc_id", matching.minhash_pairs(d, "doc_id", "text"))
