"""Registry of queries and oracles, and the database that the experiments use."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession

from ..operators import pollute, propagate
from ..plans.model import Database, DatabaseSpec, ForeignKey, Relation
from ..plans.staging import staged
from ..sources.io import parquet

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def t(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return parquet(spark, folder, name)


def once(f: Callable) -> Callable:
    """Results that several queries share: written tables, kept by session and arguments."""
    kept: dict[tuple, object] = {}

    @wraps(f)
    def call(spark: SparkSession, *args):  # noqa: ANN002, ANN202
        key = (spark.sparkContext.applicationId, *args)
        if key not in kept:
            kept[key] = f(spark, *args)
        return kept[key]

    return call


#: The star as it is given: its keys are surrogate keys, potential keys are as an expert would tag them.
PKS = {"region": ("r_regionkey",), "nation": ("n_nationkey",), "customer": ("c_custkey",), "supplier": ("s_suppkey",), "part": ("p_partkey",), "orders": ("o_orderkey",), "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate")}
NKS = {"region": ("r_name",), "nation": ("n_name", "n_regionkey"), "customer": ("c_name", "c_nationkey"), "supplier": ("s_name", "s_nationkey"), "part": ("p_partkey",), "orders": ("o_custkey", "o_orderdate", "o_totalprice"), "lineitem": PKS["lineitem"]}
FKS = (("nation", "n_regionkey", "region"), ("customer", "c_nationkey", "nation"), ("supplier", "s_nationkey", "nation"), ("orders", "o_custkey", "customer"), ("lineitem", "l_orderkey", "orders"), ("lineitem", "l_partkey", "part"), ("lineitem", "l_suppkey", "supplier"))
STAR = DatabaseSpec({n: Relation(n, PKS[n] if len(PKS[n]) == 1 else (), NKS[n]) for n in PKS}, tuple(ForeignKey(a, (c,), b, PKS[b]) for a, c, b in FKS))
ORDER = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")
COLUMNS = {
    "region": ("r_regionkey", "r_name"),
    "nation": ("n_nationkey", "n_name", "n_regionkey"),
    "customer": ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"),
    "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal"),
    "part": ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"),
    "orders": ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"),
    "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"),
}
#: Where a key column is also a foreign key, the original value is needed to tell relations apart after pollution.


def star(spark: SparkSession, folder: str) -> Database:
    return Database(STAR, {n: t(spark, folder, n) for n in ORDER})


def polluted(spark: SparkSession, folder: str, df: float = 0.3, policy: str = "follow", select: str = "bernoulli", times: int = 1) -> Database:
    out = pollute.rows(star(spark, folder), PKS, pollute.Settings(df, 42, select, policy))
    return pollute.columns(out, times) if times > 1 else out


@once
def suppressed(spark: SparkSession, folder: str, df: float = 0.3, policy: str = "follow", times: int = 1) -> propagate.Suppressed:
    out = propagate.suppress(polluted(spark, folder, df, policy, times=times), lineage=True)
    out.db = Database(out.db.spec, {n: staged(x) for n, x in out.db.tables.items()})
    return out


# Oracle text: pollution and suppression as common table expressions.


def pk_sql(name: str) -> str:
    return "concat_ws('|', " + ", ".join(f"cast({c} as varchar)" for c in PKS[name]) + ")"


def poll_sql(df: float = 0.3, policy: str = "follow", names: tuple[str, ...] = ORDER) -> str:
    """poll_<relation> expressions: new_id and the columns, foreign keys rewritten."""
    limit, out = pollute.threshold(df), []
    for n in names:
        pk, fks = pk_sql(n), {c: b for a, c, b in FKS if a == n}
        new = f"cast({PKS[n][0]} as bigint) * 2 + cp" if len(PKS[n]) == 1 else f"md5({pk} || '|' || cp)"
        cols = []
        for c in COLUMNS[n]:
            if c in fks:
                twin = f"left(md5('42|{fks[c]}|' || {c}), 8) < '{limit}'"
                side = {"original": "false", "follow": "cp = 1", "spread": f"left(md5('42s|{n}|' || {pk} || '|{c}|' || cp), 8) < '80000000'"}[policy]
                cols.append(f"cast({c} as bigint) * 2 + (case when {side} and {twin} then 1 else 0 end) as {c}")
            else:
                cols.append(c)
        out.append(f"poll_{n} as (select {new} as new_id, {', '.join(cols)} from (select *, 0 as cp from {n} union all select *, 1 as cp from {n} where left(md5('42|{n}|' || {pk}), 8) < '{limit}'))")
    return ",\n".join(out)


def borne_out_sql() -> str:
    """k (relation, key, ok), f (source, fk, target) of foreign keys without orphans, e: those of f to a unique key."""
    k = " union all ".join(f"select '{n}' as relation, '{c[0]}' as key, (select count(*) = count(distinct {c[0]}) from {n}) as ok" for n, c in PKS.items() if len(c) == 1)
    f = " union all ".join(f"select '{a}' as source, '{c}' as fk, '{b}' as target, not exists (select {c} from {a} where {c} is not null except select {PKS[b][0]} from {b}) as ok" for a, c, b in FKS)
    return f"k as ({k}), f as (select source, fk, target from ({f}) where ok), e as (select f.* from f join k on target = relation where k.ok)"


def sets_sql(table: str, columns: tuple[str, ...], width: int, where: str) -> str:
    """columns, n, dv of the sets of at most ``width`` columns for which ``where`` holds and no proper subset is unique."""
    sets = [c for k in range(1, width + 1) for c in combinations(columns, k)]
    counts = " union all ".join(f"select '{'+'.join(c)}' as columns, count(*) as n, count(distinct ({', '.join(c)})) as dv from {table}" for c in sets)
    pairs = ", ".join(f"('{'+'.join(a)}', '{'+'.join(b)}')" for b in sets for k in range(1, len(b)) for a in combinations(b, k))
    return f"with s as ({counts}), p as (select * from (values {pairs}) v(small, large)) select columns, n, dv from s where {where} and columns not in (select large from p join s u on small = u.columns where u.dv = u.n)"


def clean_sql(names: tuple[str, ...] = ORDER) -> str:
    """After poll_sql: ref_<relation> (foreign keys followed), map_<relation> (old, rep), clean_<relation>."""
    out = []
    for n in names:
        fks = {c: b for a, c, b in FKS if a == n}
        cols = [f"m{i}.rep as {c}" if (i := list(fks).index(c) if c in fks else -1) >= 0 else f"p.{c}" for c in COLUMNS[n]]
        joins = " ".join(f"left join map_{b} m{i} on p.{c} = m{i}.old" for i, (c, b) in enumerate(fks.items()))
        out.append(f"ref_{n} as (select p.new_id, {', '.join(cols)} from poll_{n} p {joins})")
        out.append(f"map_{n} as (select new_id as old, min(new_id) over (partition by {', '.join(NKS[n])}) as rep from ref_{n})")
        out.append(f"clean_{n} as (select m.rep as new_id, {', '.join('r.' + c for c in COLUMNS[n])} from ref_{n} r join map_{n} m on r.new_id = m.old)")
    return ",\n".join(out)


def with_clean(select: str, df: float = 0.3, policy: str = "follow") -> str:
    return f"with {poll_sql(df, policy)},\n{clean_sql()}\n{select}"
