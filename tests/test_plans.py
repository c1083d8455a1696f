"""Plans: what is read, how often it is shuffled, and that it stays in the JVM."""

import re

import pytest

from truekeys.operators import equivalence, metrics, profile, propagate, stability
from truekeys.queries import ORACLES, QUERIES

SMALL = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def read(text):
    return {c for m in re.findall(r"ReadSchema: struct<([^>]*)>", text) for c in re.findall(r"(\w+):", m)}


def test_a_map_reads_key_columns_only(spark):
    d = spark.read.parquet(f"{SMALL}/customer.parquet")
    p = plan(equivalence.sk_map(d, "c_custkey", ["c_name"]))
    assert read(p) == {"c_custkey", "c_name"} and "PushedFilters: [IsNotNull(c_custkey)]" in p
    assert plan(equivalence.sk_map(d, "c_custkey", ["c_name"], plan="window")).count("Exchange hashpartitioning") == 2
    assert "partial_min" in p


def test_stability_reads_once_narrow(spark):
    d = spark.read.parquet(f"{SMALL}/part.parquet")
    p = plan(stability.conflict_groups(d, ["p_name"], ["p_brand", "p_type", "p_size"]))
    assert p.count("Exchange hashpartitioning") == 1 and read(p) == {"p_name", "p_brand", "p_type", "p_size"} and "HashAggregate" in p


def test_profiles_read_their_column(spark):
    d = spark.read.parquet(f"{SMALL}/lineitem.parquet")
    assert read(plan(profile.arp(d, "l_orderkey"))) == {"l_orderkey"}
    assert "Expand" not in plan(profile.rrp(d)) and "Expand" not in plan(profile.arp(d, "l_orderkey", rsd=0.05))


@pytest.mark.parametrize("name", ["au_documents_text", "sk_map_documents", "stability_documents", "g3_part_pname", "chase_rule_majority", "join_asof_history", "theorem_no_au_star"])
def test_no_python_in_the_main_path(spark, name):
    assert not re.search("Python|Pandas|Arrow|MapIn", plan(QUERIES[name](spark, SMALL)))


def test_following_a_key_is_one_join(spark):
    c, o = spark.read.parquet(f"{SMALL}/customer.parquet"), spark.read.parquet(f"{SMALL}/orders.parquet")
    m = equivalence.sk_map(c, "c_custkey", ["c_name"])
    assert propagate.repoint_fk(o, "o_custkey", m).columns[0:2] == ["o_orderkey", "o_custkey"] or "o_custkey" in propagate.repoint_fk(o, "o_custkey", m).columns
    assert metrics.au(c, "c_custkey", ["c_name"]).first().au == 0


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 200
