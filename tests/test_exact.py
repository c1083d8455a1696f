"""Exactness of class keys, histories, rules and staged tables."""

import datetime as dt
import decimal
import itertools
import os
import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from truekeys.functions import canon
from truekeys.operators import baselines, chase, decompose, equivalence, profile, propagate
from truekeys.operators.components import connected_components
from truekeys.plans import pipeline, staging
from truekeys.plans.model import Database, DatabaseSpec, ExpertDecisions, ForeignKey, Relation

A, B = dt.datetime(2020, 1, 1, 0, 0, 0, 123456), dt.datetime(2020, 1, 1, 0, 0, 0, 123999)
VALUES = {
    "int": [0, 1, -1, None],
    "string": ["", "a", "A", "1", "n", "1:a", None],
    "binary": [b"", b"\xff", b"\xfe", b"a", None],
    "double": [0.0, -0.0, float("nan"), float("inf"), 0.1, 0.1 + 1e-17, 0.30000000000000004, None],
    "float": [0.0, -0.0, float("nan"), 0.5, None],
    "decimal(20,4)": [decimal.Decimal("1.0000"), decimal.Decimal("1.0001"), None],
    "boolean": [True, False, None],
    "date": [dt.date(2020, 1, 1), dt.date(2020, 1, 2), None],
    "timestamp": [A, B, A.replace(microsecond=0), None],
    "timestamp_ntz": [A, B, None],
    "array<double>": [[0.0], [-0.0], [], [None], [0.0, None], None],
    "array<string>": [["a", "b"], ["ab"], ["a", None, "b"], ["", ""], [""], None],
    "struct<a:double,b:array<timestamp_ntz>>": [(0.0, [A]), (-0.0, [A]), (0.0, [B]), (None, None), None],
}


@pytest.mark.parametrize("kind", VALUES)
def test_fingerprints_group_as_spark_does(spark, kind):
    own = VALUES[kind]
    df = spark.createDataFrame([(i, v, w) for i, (v, w) in enumerate(itertools.product(own, own[:3]))], f"id int, v {kind}, w {kind}")
    native = df.groupBy("v", "w").agg(F.sort_array(F.collect_list("id")).alias("ids")).collect()
    ours = df.groupBy(canon.fingerprint(df, ["v", "w"]).alias("k")).agg(F.sort_array(F.collect_list("id")).alias("ids")).collect()
    assert sorted(r.ids for r in ours) == sorted(r.ids for r in native)


def test_fingerprints_of_maps_are_of_their_entries(spark):
    df = spark.createDataFrame([({"a": -0.0, "b": 1.0},), ({"b": 1.0, "a": 0.0},), ({"a": 0.0},), ({},), (None,)], "m map<string,double>")
    assert df.select(canon.fingerprint(df, ["m"]).alias("k")).distinct().count() == 4


def test_microseconds_keep_entities_apart(spark):
    df = spark.createDataFrame([(1, A), (2, B), (3, B)], "id int, at timestamp")
    assert [tuple(r) for r in equivalence.sk_map(df, "id", ["at"]).collect()] == [(3, 2)]


def test_rules_keep_every_type(spark):
    rows = [("k", 2, "b", 1.5, A, [1, 2], {"x": 1}, 1), ("k", 10, "a", -0.0, B, [3], {"x": 2}, 2), ("k", None, None, None, None, None, None, 3), ("l", 7, "z", 0.0, A, [1], {}, 4)]
    df = spark.createDataFrame(rows, "k string, i int, s string, d double, t timestamp, a array<int>, m map<string,int>, id int")
    own = ["i", "s", "d", "t", "a", "m"]

    def pick(rule, **kw):
        rows = [tuple(r) for r in chase.resolve(df, ["k"], own, rule=rule, **kw).where("k = 'k'").select(*own).collect()]
        assert all(r == rows[0] for r in rows)
        return rows[0]

    assert pick("min") == (2, "a", -0.0, A, [1, 2], {"x": 1}) and pick("max") == (10, "b", 1.5, B, [3], {"x": 2})
    assert pick("first", order="id") == rows[0][1:7] and pick("latest", latest="id") == rows[1][1:7]
    assert pick("majority", order="id") == rows[0][1:7]
    with pytest.raises(ValueError):
        chase.resolve(df, ["k"], ["i"], rule="latest")
    assert chase.resolve(df, ["k"], ["i", "s"], rule="majority").schema == df.schema


def test_text_keys_and_no_keys_are_chased(spark):
    df = spark.createDataFrame([("ff", "x", 2), ("aa", "x", 1), ("bb", "y", 5)], "id string, k string, a int")
    for sks, ids in ((("id",), {"aa", "bb"}), ((), None)):
        spec = DatabaseSpec({"r": Relation("r", sks, ("k",))})
        out = pipeline.run(Database(spec, {"r": df if sks else df.drop("id")})).db.tables["r"].collect()
        assert {(r.k, r.a) for r in out} == {("x", 1), ("y", 5)} and len(out) == 2
        assert ids is None or {r.id for r in out} == ids


def graph_of_events(spark):
    spec = DatabaseSpec(
        {"who": Relation("who", ("id",), ("name",)), "visit": Relation("visit", ("vid",), ("who", "n")), "bill": Relation("bill", ("bid",), ("visit", "day"))},
        (ForeignKey("visit", ("who",), "who", ("id",)), ForeignKey("visit", ("host",), "who", ("id",)), ForeignKey("bill", ("visit",), "visit", ("vid",))),
    )
    tables = {
        "who": spark.createDataFrame([(1, "a", "w1"), (2, "a", "w2"), (3, "b", "w9")], "id int, name string, w string"),
        "visit": spark.createDataFrame([(10, 1, 3, 1), (11, 2, 3, 2)], "vid int, who int, host int, n int"),
        "bill": spark.createDataFrame([(100, 10, 5), (101, 11, 6)], "bid int, visit int, day int"),
    }
    return Database(spec, tables)


def test_histories_keep_entities_without_events(spark):
    db = graph_of_events(spark)
    decisions = ExpertDecisions(completing={"who": ["visit[who]/bill.day"]})
    out = pipeline.run(db, decisions).db
    past = {(r.id, r.day, r.w) for r in out.tables["who_history"].collect()}
    assert past == {(1, 5, "w1"), (1, 6, "w2"), (3, None, "w9")}
    assert set(out.tables["who"].columns) == {"id", "name"}


def test_ambiguous_paths_are_refused(spark):
    db = propagate.with_lineage(graph_of_events(spark))
    for o in ("visit.n", "bill.day", "nowhere.x"):
        with pytest.raises(ValueError):
            decompose.completed(db, "who", o)
    assert decompose.completed(db, "bill", "visit.n").count() == 2 and decompose.completed(db, "bill", "visit/who[host].name").count() == 2


def test_cyclic_graphs_run_end_to_end(spark):
    depth = 3
    staff = [(2 * k + copy, f"n{k}", 2 * (k - 1) + copy if k else None, k if copy else 9) for k in range(depth) for copy in (0, 1)]
    spec = DatabaseSpec({"staff": Relation("staff", ("id",), ("name", "boss"))}, (ForeignKey("staff", ("boss",), "staff", ("id",)),))
    db = Database(spec, {"staff": spark.createDataFrame(staff, "id long, name string, boss long, pay int").coalesce(1)})
    out = pipeline.run(db, ExpertDecisions(rules={"staff": {"pay": "min"}})).db.tables["staff"]
    assert sorted(tuple(r) for r in out.collect()) == [(0, "n0", None, 0), (2, "n1", 0, 1), (4, "n2", 2, 2)]


def test_staged_tables_go(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(staging, "shared_folder", lambda s: f"file://{tmp_path}")
    with staging.scratch(spark):
        t = staging.staged(spark.range(3))
        assert t.count() == 3 and len(os.listdir(tmp_path)) == 1
        staging.discard(t, spark.range(2))
        assert os.listdir(tmp_path) == []
        assert connected_components(spark.createDataFrame([(k, k + 1) for k in range(9)], "a long, b long")).count() == 10
        assert len(os.listdir(tmp_path)) == 1
    assert os.listdir(tmp_path) == []


def test_a_cluster_needs_a_shared_folder():
    class Session:
        class conf:  # noqa: N801
            get = staticmethod(lambda name, default: default)

        class sparkContext:  # noqa: N801
            master = "spark://host:7077"

            @staticmethod
            def getConf():
                return {}

    with pytest.raises(RuntimeError):
        staging.shared_folder(Session)


def test_minimal_keys_of_any_width_against_brute_force(spark):
    rng = random.Random(3)
    names = list("abcde")
    rows = list({tuple(rng.choice([None, 0, 1, 2]) for _ in names) for _ in range(60)})
    df = spark.createDataFrame(rows, ", ".join(f"{c} int" for c in names))
    unique = [c for k in range(1, 6) for c in combinations(range(5), k) if len({tuple(r[i] for i in c) for r in rows}) == len(rows)]
    minimal = {"".join(names[i] for i in c) for c in unique if not any(set(u) < set(c) for u in unique)}
    assert {"".join(c) for c in baselines.uccs(df)} == minimal
    shown = {r["attributes"].replace("+", ""): r["dv"] for r in profile.nk_candidates(df, near=0.5).collect()}
    dv = {c: len({tuple(r[i] for i in c) for r in rows}) for k in range(1, 6) for c in combinations(range(5), k)}
    assert shown == {"".join(names[i] for i in c): d for c, d in dv.items() if d >= 0.5 * len(rows) and not any(set(u) < set(c) for u in unique)}


def test_a_repeat_in_few_rows_refutes_and_its_absence_does_not(spark):
    df = spark.createDataFrame([(i, i // 2, i % 2) for i in range(50)], "k int, half int, odd int")
    repeats = baselines.repeats_in(df, df.columns, rows=20)
    assert not repeats(("k",)) and repeats(("half",)) and repeats(("odd",)) and not repeats(("half", "odd"))
    assert baselines.uccs(df) == [("k",), ("half", "odd")]
    assert baselines.uccs(df.limit(0)) == [("k",), ("half",), ("odd",)]


def test_large_tables_give_the_same_keys_by_slices_and_rows_that_agree(spark, monkeypatch):
    rng = random.Random(5)
    names = list("abcdef")
    rows = [(i // 2, rng.choice([None, *range(40)]), rng.choice([0.0, -0.0, 1.0, float("nan"), None]), rng.randrange(30), i % 2, rng.randrange(12)) for i in range(400)]
    rows += [(rows[7][0], *rows[8][1:])]  # one repeat that hardly any slice holds
    df = spark.createDataFrame(rows, "a int, b int, c double, d int, e int, f int")
    few, grouped = baselines.few_codes, []
    monkeypatch.setattr(baselines, "few_codes", lambda df, columns: few(df, columns, 3))
    agree = baselines.LargeTable._rows_that_agree
    monkeypatch.setattr(baselines.LargeTable, "_rows_that_agree", lambda self, names: grouped.append(names) or agree(self, names))
    value = lambda v: "nan" if v != v else v
    plain = [tuple(value(v) for v in r) for r in rows]
    unique = [c for k in range(1, 7) for c in combinations(range(6), k) if len({tuple(r[i] for i in c) for r in plain}) == len(rows)]
    minimal = {"".join(names[i] for i in c) for c in unique if not any(set(u) < set(c) for u in unique)}
    assert {"".join(c) for c in baselines.uccs(df, rows=100)} == minimal
    assert grouped and {"".join(c) for c in baselines.uccs(df)} == minimal
