"""The registered queries return the columns that their contracts name, over all rows."""

import pytest

from truekeys.llm.queries import ORACLES, QUERIES

SMALL = "/root/testdata/sf0.001"
COLUMNS = {
    "op1": "doc_id:bigint n_tokens:bigint ids_crc32:bigint",
    "op2": "doc_id:bigint held_out:boolean score:double predicted:int",
    "op3": "doc_id:bigint piece:int start:bigint length:bigint ids_crc32:bigint sequence_id:bigint offset:bigint",
    "op4": "doc_id:bigint size:bigint text_crc32:bigint law:string shard:int slot:bigint grown_shard:int",
    "op5": "doc_id:bigint n_chars:bigint edited_sha256:string fingerprint:string edited_fingerprint:string near_edited:double near_next:double",
    "op6": "doc_id:bigint n_words:bigint n_removed:bigint kept_sha256:string",
    "op7": "doc_id:bigint n_sentences:bigint licence:string",
    "op8": "doc_id:bigint n_shingles:bigint component_id:bigint kept:boolean",
    "op9": "doc_id:bigint n_lines:bigint n_dropped:bigint kept_sha256:string",
    "op10": "doc_id:bigint n_words:bigint word_chars:bigint n_symbols:bigint n_dup_lines:bigint n_repeat_words:bigint base_failed:boolean kept:boolean",
}


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_columns_and_rows(spark, name):
    out = QUERIES[name](spark, SMALL)
    kinds = dict(out.dtypes)
    assert all(kinds[c.split(":")[0]] == c.split(":")[1] for c in COLUMNS[name.split("_")[0]].split())
    assert out.select("doc_id").distinct().count() == 200


def test_names():
    assert sorted(int(n.split("_")[0][2:]) for n in QUERIES) == list(range(1, 11)) and set(ORACLES) <= set(QUERIES)
