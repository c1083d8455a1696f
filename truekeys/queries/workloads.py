"""The experiments: pollution, recovery of the original, the worked example."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import chase, decompose, metrics, pollute, profile, propagate, reduce, stability, verify
from ..plans.model import Database, DatabaseSpec, ForeignKey, Relation
from ..sources import io
from ..sources.io import union_all
from .registry import COLUMNS, FKS, ORDER, PKS, ORACLES, borne_out_sql, once, pk_sql, poll_sql, polluted, query, star, suppressed, t

LEVELS = (0.1, 0.2, 0.3, 0.4, 0.5)


def _sizes_sql() -> str:
    parts = []
    for n in ORDER:
        parts.append(f"select '{n}' as relation, 0.0 as df, count(*) as n_rows from {n}")
        for d in LEVELS:
            parts.append(f"select '{n}', {d}, count(*) + count(*) filter (where left(md5('42|{n}|' || {pk_sql(n)}), 8) < '{pollute.threshold(d)}') from {n}")
    return f"select relation, cast(df as double) as df, n_rows from ({' union all '.join(parts)})"


@query("polluted_sizes", _sizes_sql())
def polluted_sizes(spark: SparkSession, folder: str) -> DataFrame:
    count = F.count(F.lit(1)).alias("n_rows")
    parts = [x.agg(count).select(F.lit(n).alias("relation"), F.lit(0.0).alias("df"), "n_rows") for n, x in star(spark, folder).tables.items()]
    for d in LEVELS:
        parts += [x.agg(count).select(F.lit(n).alias("relation"), F.lit(d).alias("df"), "n_rows") for n, x in polluted(spark, folder, d).tables.items()]
    return union_all(parts)


@query("polluted_sizes_exact", "select relation, n_rows, n_rows + (n_rows * 30 // 100) + (case when n_rows * 30 % 100 > 50 then 1 else 0 end) as n_polluted from (" + " union all ".join(f"select '{n}' as relation, count(*) as n_rows from {n}" for n in ("region", "nation", "customer", "supplier", "part")) + ")")
def polluted_sizes_exact(spark: SparkSession, folder: str) -> DataFrame:
    names = ("region", "nation", "customer", "supplier", "part")
    small = Database(star(spark, folder).spec.restrict(list(names)), {n: t(spark, folder, n) for n in names})
    out = pollute.rows(small, PKS, pollute.Settings(0.3, 42, "exact"))
    return union_all([small.tables[n].agg(F.count(F.lit(1)).alias("n_rows")).crossJoin(out.tables[n].agg(F.count(F.lit(1)).alias("n_polluted"))).select(F.lit(n).alias("relation"), "*") for n in names])


def _columns(n: str) -> str:
    return ", ".join(COLUMNS[n])


for _name in ("customer", "orders"):

    @query(f"polluted_{_name}_df30", f"with {poll_sql()} select new_id, {_columns(_name)} from poll_{_name}")
    def _polluted(spark: SparkSession, folder: str, name: str = _name) -> DataFrame:
        return polluted(spark, folder).tables[name]


@query("polluted_bernoulli", f"with {poll_sql(0.5)} select new_id, {_columns('supplier')} from poll_supplier")
def polluted_bernoulli(spark: SparkSession, folder: str) -> DataFrame:
    return polluted(spark, folder, 0.5).tables["supplier"]


for _policy in ("original", "follow", "spread"):

    @query(f"polluted_fk_{_policy}", f"with {poll_sql(0.3, _policy)} select new_id, {_columns('lineitem')} from poll_lineitem")
    def _fk(spark: SparkSession, folder: str, policy: str = _policy) -> DataFrame:
        return polluted(spark, folder, 0.3, policy).tables["lineitem"]


for _times in (2, 3):
    _copies = ", ".join(f"{c} as {c}__{k}" for k in range(2, _times + 1) for c in ("c_custkey", "c_acctbal", "c_mktsegment"))

    @query(f"polluted_columns_x{_times}", f"with {poll_sql()} select new_id, {_columns('customer')}, {_copies} from poll_customer")
    def _wide(spark: SparkSession, folder: str, times: int = _times) -> DataFrame:
        return polluted(spark, folder, times=times).tables["customer"]


def roundtrip(spark: SparkSession, folder: str, df: float, policy: str = "follow", times: int = 1) -> DataFrame:
    """relation, n_rows, n_missing, n_extra of the cleaned database against the original, foreign keys told by value."""
    found = suppressed(spark, folder, df, policy, times)
    db, parts = reduce.database(found.db), []
    for n in ORDER:
        own = db.tables[n]
        for i, (a, c, b) in enumerate(FKS):
            if a == n:  # the parent's original key, through the cleaned surrogate key
                parent = db.tables[b].select(F.col("new_id").alias(f"_p{i}"), F.col(PKS[b][0]).alias(f"_v{i}"))
                own = own.join(parent, F.col(c) == F.col(f"_p{i}")).withColumn(c, F.col(f"_v{i}")).drop(f"_p{i}", f"_v{i}")
        original = t(spark, folder, n).select(*COLUMNS[n])
        copies = [c for c in own.columns if "__" in c]
        back = own.select(*(F.col(c).cast(original.schema[c].dataType) for c in COLUMNS[n]), *copies)
        for c in copies:  # a copy that differs from its column shows as an extra row
            back = back.withColumn(c.split("__")[0], F.when(F.col(c).eqNullSafe(F.col(c.split("__")[0])), F.col(c.split("__")[0])))
        parts.append(verify.same_content(original, back.select(*COLUMNS[n])).select(F.lit(n).alias("relation"), "*"))
    return union_all(parts)


_BACK = " union all ".join(f"select '{n}' as relation, count(*) as n_rows, cast(0 as bigint) as n_missing, cast(0 as bigint) as n_extra from {n}" for n in ORDER)

for _d in LEVELS:

    @query(f"roundtrip_df{round(_d * 100)}", _BACK)
    def _round(spark: SparkSession, folder: str, d: float = _d) -> DataFrame:
        return roundtrip(spark, folder, d)


for _times in (2, 3):

    @query(f"roundtrip_x{_times}", _BACK)
    def _round_wide(spark: SparkSession, folder: str, times: int = _times) -> DataFrame:
        return roundtrip(spark, folder, 0.3, "follow", times)


@query("roundtrip_spread", _BACK)
def roundtrip_spread(spark: SparkSession, folder: str) -> DataFrame:
    return roundtrip(spark, folder, 0.3, "spread")


# The worked example: a clinic with animals, their microchips and appointments.

#: The three relations of the published example, with its columns in its order.
ANIMAL = [
    (744, "canine", "greyhound", "Gunter", 611, "M", "15-07-2014", 27.0, "Greyh. Mix", "227f1df55c"),
    (746, "canine", "labrador", "Coco", 613, "F", None, 41.0, "H Large Dog", "c59a2c0744"),
    (747, "feline", "siamese", "Izzy", 614, "F", "18-01-2018", 4.2, "Indoor Cat", "9d5faf7fa6"),
    (749, "canine", "greyhound", "Gunter", 616, "M", "15-07-2014", 25.8, "Urinary", "ded5f4207a"),
    (750, "feline", "siamese", "Izzy", 617, "F", "01-01-2018", 4.1, "Indoor Cat", "d33673d97d"),
    (752, "canine", "labrador", "Coco", 619, "F", None, 41.0, "H Large Dog", "4745dd610e"),
    (753, "canine", "greyhound", "Gunter", 620, "M", "15-07-2014", 26.0, "Urinary", "f41e45bf6e"),
]
APPOINTMENT = [
    (370, 744, "08-02-2022", "10:00", "sick pet"),
    (372, 746, "20-04-2022", "15:00", "surgery"),
    (373, 747, "10-05-2022", "11:30", "injured pet"),
    (375, 749, "20-07-2022", "16:00", "annual visit"),
    (376, 750, "20-07-2022", "14:30", "annual visit"),
    (378, 752, "16-08-2022", "12:00", "surgery follow-up"),
    (379, 753, "09-09-2022", "17:00", "sick pet"),
]
MICROCHIP = [
    (611, 744982769, "09-04-2015"),
    (613, 713356552, "18-11-2018"),
    (614, 576918144, "23-06-2018"),
    (616, 744982769, "04-09-2015"),
    (617, 576918144, "23-06-2018"),
    (619, 713356552, "18-11-2018"),
    (620, 744982769, "09-04-2015"),
]
CLINIC = DatabaseSpec(
    {"microchip": Relation("microchip", ("id_microchip",), ("number",)), "animal": Relation("animal", ("id_animal", "hash_id"), ("id_microchip",)), "appointment": Relation("appointment", ("id_appointment",), ("id_animal", "date", "time"))},
    (ForeignKey("animal", ("id_microchip",), "microchip", ("id_microchip",)), ForeignKey("appointment", ("id_animal",), "animal", ("id_animal",))),
)
TRAITS = ["species", "breed", "name", "gender", "dob", "weight", "food"]


def clinic(spark: SparkSession) -> Database:
    def table(rows: list[tuple], schema: str, day: str) -> DataFrame:
        read = spark.createDataFrame(rows, schema)
        return read.withColumn(day, F.to_date(day, "dd-MM-yyyy"))

    return Database(
        CLINIC,
        {
            "microchip": table(MICROCHIP, "id_microchip int, number long, implant_date string", "implant_date"),
            "animal": table(ANIMAL, "id_animal int, species string, breed string, name string, id_microchip int, gender string, dob string, weight double, food string, hash_id string", "dob"),
            "appointment": table(APPOINTMENT, "id_appointment int, id_animal int, date string, time string, main_reason string", "date"),
        },
    )


@once
def clinic_suppressed(spark: SparkSession) -> propagate.Suppressed:
    return propagate.suppress(clinic(spark), lineage=True)


def _values(rows: list[tuple], names: str) -> str:
    show = lambda x: "null" if x is None else str(x).lower() if isinstance(x, bool) else repr(x) if isinstance(x, str) else str(x)
    return f"select * from (values {', '.join('(' + ', '.join(map(show, r)) + ')' for r in rows)}) v({names})"


@query("worked_example_profile", "select relation, attribute, cast(dv as bigint) as dv, cast(nv as bigint) as nv, cast(ov as bigint) as ov from (" + _values([("animal", "id_animal", 7, 0, 0), ("animal", "hash_id", 7, 0, 0), ("animal", "id_microchip", 7, 0, 0), ("animal", "species", 2, 0, 5), ("animal", "breed", 3, 0, 4), ("animal", "name", 3, 0, 4), ("animal", "gender", 2, 0, 5), ("animal", "dob", 3, 2, 2), ("animal", "weight", 6, 0, 1), ("animal", "food", 4, 0, 3), ("microchip", "id_microchip", 7, 0, 0), ("microchip", "number", 3, 0, 4), ("microchip", "implant_date", 4, 0, 3), ("appointment", "id_appointment", 7, 0, 0), ("appointment", "id_animal", 7, 0, 0), ("appointment", "date", 6, 0, 1), ("appointment", "time", 7, 0, 0), ("appointment", "main_reason", 5, 0, 2)], "relation, attribute, dv, nv, ov") + ")")
def worked_example_profile(spark: SparkSession, folder: str) -> DataFrame:
    return profile.rrp_database(clinic(spark)).drop("n")


@query("worked_example_levels", "select relation, cast(n as bigint) as n, cast(classes as bigint) as classes, au from (" + _values([("microchip", 7, 3, 0.571429), ("animal", 7, 3, 0.571429), ("appointment", 7, 7, 0.0), ("(all)", 21, 13, 0.380952)], "relation, n, classes, au") + ")")
def worked_example_levels(spark: SparkSession, folder: str) -> DataFrame:
    return metrics.report(clinic_suppressed(spark).db).withColumn("au", F.col("au"))


@query("worked_example_suppressed", "select cast(id_animal as int) as id_animal, hash_id, cast(id_microchip as int) as id_microchip, weight::double as weight from (" + _values([(744, "227f1df55c", 611, 27.0), (746, "4745dd610e", 613, 41.0), (747, "9d5faf7fa6", 614, 4.2), (744, "227f1df55c", 611, 25.8), (747, "9d5faf7fa6", 614, 4.1), (746, "4745dd610e", 613, 41.0), (744, "227f1df55c", 611, 26.0)], "id_animal, hash_id, id_microchip, weight") + ")")
def worked_example_suppressed(spark: SparkSession, folder: str) -> DataFrame:
    return clinic_suppressed(spark).db.tables["animal"].select("id_animal", "hash_id", "id_microchip", "weight")


@query("worked_example_stability", "select attribute, stability::double as stability, role from (" + _values([("species", 0.0, "AtbC"), ("breed", 0.0, "AtbC"), ("name", 0.0, "AtbC"), ("gender", 0.0, "AtbC"), ("dob", 0.142857, "AtbC"), ("weight", 0.428571, "AtbN"), ("food", 0.142857, "AtbN")], "attribute, stability, role") + ")")
def worked_example_stability(spark: SparkSession, folder: str) -> DataFrame:
    return stability.classify(stability.profile(clinic_suppressed(spark).db.tables["animal"], ["id_microchip"], TRAITS), stable=["dob"])


def clinic_clean(spark: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(animals, history, microchips) after decomposition, conflict resolution and reduction."""
    db = clinic_suppressed(spark).db
    _, past, _ = decompose.split(db, "animal", ["species", "breed", "name", "gender", "dob"], ["weight", "food"], ["appointment.date"], carry_key=False)
    pets = chase.resolve(db.tables["animal"].drop("weight", "food"), ["id_microchip"], ["dob"], "__orig_id_animal")
    chips = chase.resolve(db.tables["microchip"], ["number"], ["implant_date"], "__orig_id_microchip")
    return reduce.relation(pets), past, reduce.relation(chips)


@query("worked_example_clean", "select cast(id_animal as int) as id_animal, name, cast(dob as date) as dob, hash_id, cast(id_microchip as int) as id_microchip from (" + _values([(744, "Gunter", "2014-07-15", "227f1df55c", 611), (746, "Coco", None, "4745dd610e", 613), (747, "Izzy", "2018-01-18", "9d5faf7fa6", 614)], "id_animal, name, dob, hash_id, id_microchip") + ")")
def worked_example_clean(spark: SparkSession, folder: str) -> DataFrame:
    return clinic_clean(spark)[0].select("id_animal", "name", "dob", "hash_id", "id_microchip")


@query("worked_example_history", "select cast(id_animal as int) as id_animal, cast(date as date) as date, weight::double as weight, food from (" + _values([(744, "2022-02-08", 27.0, "Greyh. Mix"), (746, "2022-04-20", 41.0, "H Large Dog"), (747, "2022-05-10", 4.2, "Indoor Cat"), (744, "2022-07-20", 25.8, "Urinary"), (747, "2022-07-20", 4.1, "Indoor Cat"), (744, "2022-09-09", 26.0, "Urinary")], "id_animal, date, weight, food") + ")")
def worked_example_history(spark: SparkSession, folder: str) -> DataFrame:
    return decompose.compacted(clinic_clean(spark)[1], "id_animal", "date", ["weight", "food"]).select("id_animal", "date", "weight", "food")


@query("worked_example_visits", "select state, cast(entity as int) as entity, cast(n as bigint) as n_events from (" + _values([("dirty", e, 1) for e in (744, 746, 747, 749, 750, 752, 753)] + [("clean", 744, 3), ("clean", 746, 2), ("clean", 747, 2)], "state, entity, n") + ")")
def worked_example_visits(spark: SparkSession, folder: str) -> DataFrame:
    from ..operators.analytics import visits_per_entity

    raw, clean = clinic(spark), clinic_suppressed(spark).db
    a = visits_per_entity(raw.tables["animal"], "id_animal", "name", raw.tables["appointment"], "id_animal", "date").select(F.lit("dirty").alias("state"), "entity", "n_events")
    b = visits_per_entity(clinic_clean(spark)[0], "id_animal", "name", clean.tables["appointment"], "id_animal", "date").select(F.lit("clean").alias("state"), "entity", "n_events")
    return a.unionByName(b)


# Sources.

def catalog(spark: SparkSession, folder: str) -> DataFrame:
    """Constraints of the star, as a database would list them, as far as the tables bear them out."""
    db = star(spark, folder)
    unique = verify.unique_keys(db, PKS)
    held = verify.without_orphans(db)
    rows = [(n, "pk", "PRIMARY KEY", c, i + 1, None, None, len(k) == 1) for n, k in PKS.items() if n in unique for i, c in enumerate(k)]
    rows += [(a, f"fk_{c}", "FOREIGN KEY", c, 1, b, PKS[b][0], False) for a, c, b in FKS if f"{a}.{c}" in held]
    return spark.createDataFrame(rows, "table_name string, constraint_name string, kind string, column_name string, position int, ref_table string, ref_column string, generated boolean")


@query("ddl_constraints_to_spec", f"with {borne_out_sql()} select relation, 'surrogate' as kind, key as columns from k where ok union all select 'lineitem', 'natural', '{'+'.join(PKS['lineitem'])}' where (select count(*) from lineitem) = (select count(*) from (select distinct {', '.join(PKS['lineitem'])} from lineitem where {' and '.join(c + ' is not null' for c in PKS['lineitem'])})) union all select source, 'foreign', fk || '->' || target from f")
def ddl_constraints_to_spec(spark: SparkSession, folder: str) -> DataFrame:
    return spark.createDataFrame(io.constraint_rows(io.spec_from_catalog(catalog(spark, folder))), "relation string, kind string, columns string")


@query("io_csv_roundtrip_nation", "select * from nation")
def io_csv_roundtrip_nation(spark: SparkSession, folder: str) -> DataFrame:
    import uuid

    from ..plans.staging import shared_folder

    n = t(spark, folder, "nation")
    path = f"{shared_folder(spark)}/csv-{uuid.uuid4().hex}"
    io.write(n, path, "csv")
    return io.read(spark, path, "csv", n.schema)


@query("delta_apply_documents", "select doc_id, case when doc_id % 10 = 0 then 'delta' else source end as source, n_chars from documents union all select -1, 'new', 0")
def delta_apply_documents(spark: SparkSession, folder: str) -> DataFrame:
    d = t(spark, folder, "documents").select("doc_id", "source", "n_chars")
    delta = d.where("doc_id % 10 = 0").withColumn("source", F.lit("delta")).unionByName(spark.createDataFrame([(-1, "new", 0)], "doc_id long, source string, n_chars long"))
    return io.apply_delta(d, delta, "doc_id")


@query("sql_au_documents", "select lang, round(1 - count(distinct text) / count(*)::double, 6) as au from documents group by lang")
def sql_au_documents(spark: SparkSession, folder: str) -> DataFrame:
    spec = DatabaseSpec({"documents": Relation("documents", ("doc_id",), ("text",))})
    io.register(io.open_database(spark, folder, spec), "tk_")
    return spark.sql("select lang, round(1 - count(distinct text) / count(*), 6) as au from tk_documents group by lang")


__all__ = ["ORACLES"]
