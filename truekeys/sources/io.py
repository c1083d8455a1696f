"""Tables in and out, declared constraints, specifications."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.model import Database, DatabaseSpec, ForeignKey, Relation


def parquet(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def open_database(spark: SparkSession, folder: str, spec: DatabaseSpec) -> Database:
    return Database(spec, {n: parquet(spark, folder, n) for n in spec.relations})


def read(spark: SparkSession, path: str, kind: str, schema: T.StructType | str) -> DataFrame:
    """CSV, JSON or ORC with a given schema (none is ever inferred)."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else getattr(reader, kind)(path)


def write(df: DataFrame, path: str, kind: str, mode: str = "errorifexists") -> None:
    writer = df.write.mode(mode)
    writer.option("header", True).csv(path) if kind == "csv" else getattr(writer, kind)(path)


def jdbc_options(url: str, table: str, column: str | None = None, bounds: tuple[int, int] | None = None, parts: int = 16, fetch: int = 10_000) -> dict[str, str]:
    """Options of a partitioned read from a relational database."""
    out = {"url": url, "dbtable": table, "fetchsize": str(fetch)}
    if column and bounds:
        out |= {"partitionColumn": column, "lowerBound": str(bounds[0]), "upperBound": str(bounds[1]), "numPartitions": str(parts)}
    return out


def jdbc(spark: SparkSession, **options: str) -> DataFrame:
    return spark.read.format("jdbc").options(**options).load()


def spec_from_catalog(constraints: DataFrame) -> DatabaseSpec:
    """Declared constraints to a specification.

    constraints: table_name, constraint_name, kind (PRIMARY KEY, UNIQUE, FOREIGN KEY), column_name, position, and for
    foreign keys ref_table, ref_column; generated: whether the column's values are generated.  A generated single-column
    key is a surrogate key; any other primary key is a declared natural key.
    """
    rows = sorted((r.asDict() for r in constraints.collect()), key=lambda r: (r["table_name"], r["constraint_name"], r["position"]))  # schema-sized
    groups: dict[tuple[str, str, str], list[dict]] = {}
    for r in rows:
        groups.setdefault((r["table_name"], r["constraint_name"], r["kind"]), []).append(r)
    rel = {n: Relation(n) for n in dict.fromkeys(r["table_name"] for r in rows)}
    fks = []
    for (table, _, kind), cols in groups.items():
        names = tuple(c["column_name"] for c in cols)
        old = rel[table]
        if kind == "FOREIGN KEY":
            fks.append(ForeignKey(table, names, cols[0]["ref_table"], tuple(c["ref_column"] for c in cols)))
        elif len(names) == 1 and cols[0]["generated"]:
            rel[table] = Relation(table, (*old.sks, *names), old.nk, old.declared_nk)
        elif old.declared_nk is None:
            rel[table] = Relation(table, old.sks, old.nk, names)
    return DatabaseSpec(rel, tuple(fks))


def constraint_rows(spec: DatabaseSpec) -> list[tuple[str, str, str]]:
    """(relation, kind, columns) of a specification."""
    out = [(n, "surrogate", s) for n, r in spec.relations.items() for s in r.sks]
    out += [(n, "natural", "+".join(r.declared_nk)) for n, r in spec.relations.items() if r.declared_nk]
    return sorted(out + [(f.source, "foreign", f"{'+'.join(f.columns)}->{f.target}") for f in spec.fks])


def save(db: Database, folder: str, maps: dict[tuple[str, str], DataFrame] | None = None) -> None:
    """A new copy of the database, its specification and its key maps; never in place."""
    spark = next(iter(db.tables.values())).sparkSession
    for n, t in db.tables.items():
        t.write.parquet(f"{folder}/{n}.parquet")
    for (n, sk), m in (maps or {}).items():
        m.write.parquet(f"{folder}/_maps/{n}.{sk}.parquet")
    spark.createDataFrame([(db.spec.to_json(),)], "spec string").coalesce(1).write.text(f"{folder}/_spec")


def save_bucketed(db: Database, prefix: str, keys: dict[str, str], buckets: int) -> None:
    """New tables in the catalog, each in buckets of one key and sorted by it, so that joins by it shuffle no side.

    Relations that are to be joined need the same number of buckets; rows are dealt to them before they are written,
    which keeps one file a bucket.
    """
    for n, c in keys.items():
        dealt = db.tables[n].repartition(buckets, c)
        dealt.write.bucketBy(buckets, c).sortBy(c).saveAsTable(prefix + n)


def load(spark: SparkSession, folder: str) -> Database:
    text = "\n".join(r[0] for r in spark.read.text(f"{folder}/_spec", wholetext=True).collect())
    return open_database(spark, folder, DatabaseSpec.from_json(text))


def apply_delta(clean: DataFrame, delta: DataFrame, sk: str) -> DataFrame:
    """Rows of the delta replace those with the same key; the others are added."""
    return clean.join(delta.select(sk), sk, "left_anti").select(clean.columns).unionByName(delta.select(clean.columns))


def register(db: Database, prefix: str = "") -> None:
    """Temporary views, for SQL over everything."""
    for n, t in db.tables.items():
        t.createOrReplaceTempView(prefix + n)


def union_all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def null_safe(a: DataFrame, b: DataFrame, columns: list[str]) -> F.Column:
    return reduce(lambda x, y: x & y, [a[c].eqNullSafe(b[c]) for c in columns])
