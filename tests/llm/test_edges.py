"""Every operator and the pipeline on tables that no one should have to clean first."""

import collections
import math
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F
from tests_support import brute_lines, brute_near, brute_windows
from xxhash import xxh3_64_intdigest

from truekeys.llm import exchange, fingerprints, licences, line_dedup, minhash, packing, quality_classifier, quality_rules, sentencepiece_codec, sharding, substring_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _block int, quality int, score double, x int, `a b` string"
WORDS = ["".join(random.Random(i).choice("bdkaeioulmn") for _ in range(5)) for i in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def ugly_rows():
    """One id on a third of the rows, no id on some, nulls in every column, equal rows, one text of two million bytes."""
    rng = random.Random(11)
    shared = prose(rng, 40)
    rows = [(7, prose(rng, 30) + "\n" + shared) for _ in range(40)]
    rows += [(None, prose(rng, 25)) for _ in range(10)] + [(None, None), (None, ""), (8, None), (9, ""), (9, ""), (10, "   \n "), (-(1 << 62), "least"), (1 << 62, "largest id of them")]
    rows += [(100 + i, prose(rng, 60)) for i in range(40)] + [(200, shared + " " + shared), (201, shared), (201, shared)]
    rows.append((300, prose(rng, 330_000)))
    return rows


@pytest.fixture(scope="module")
def ugly(spark):
    rows = [(i, t, None if i is None else "en", None, len(t or "") if i else None, 3, None, None, -1, "q") for i, t in ugly_rows()]
    return spark.createDataFrame(rows, SCHEMA).repartition(6)


OPERATORS = {
    "op1": sentencepiece_codec.round_trip,
    "op2": lambda d: quality_classifier.classify(d, quality_classifier.Model(np.zeros(1 << 18, np.float32), 0.5)),
    "op3": packing.pack,
    "op4": sharding.shard_documents,
    "op5": fingerprints.fingerprints,
    "op6": substring_dedup.substring_dedup,
    "op7": licences.licence_scan,
    "op8": minhash.near_duplicates,
    "op9": line_dedup.line_dedup,
    "op10": quality_rules.quality_rules,
}


@pytest.mark.parametrize("name", OPERATORS)
def test_ugly_tables_give_a_result_for_every_row(spark, ugly, name):
    ids = collections.Counter(r.doc_id for r in OPERATORS[name](ugly).where("piece = 0" if name == "op3" else "true").select("doc_id").collect())
    assert ids == collections.Counter(i for i, _ in ugly_rows())
    assert OPERATORS[name](ugly.limit(0)).count() == 0
    assert OPERATORS[name](spark.createDataFrame([(None, None)], "doc_id long, text string")).count() == 1


def test_slots_and_places_are_gapless_with_a_hot_id(ugly):
    for rows, group, at in ((sharding.shard_documents(ugly).collect(), "shard", "slot"),):
        by = collections.defaultdict(list)
        for r in rows:
            by[r[group]].append(r[at])
        assert all(sorted(v) == list(range(len(v))) for v in by.values())
    by = collections.defaultdict(list)
    for r in packing.pack(ugly).collect():
        by[r.sequence_id].append((r.offset, r.length))
    for own in by.values():
        assert [a for a, _ in sorted(own)] == [sum(n for _, n in sorted(own)[:k]) for k in range(len(own))] and sum(n for _, n in own) <= 1024


def test_one_row_of_equal_ones_keeps_its_passage(ugly):
    rows = [r for r in substring_dedup.substring_dedup(ugly).collect() if r.doc_id == 201]
    assert sorted(r.n_removed for r in rows) == [40, 40]  # the passage stands in earlier documents
    alone = ugly.where("doc_id = 201")
    assert sorted(r.n_removed for r in substring_dedup.substring_dedup(alone).collect()) == [0, 40]


def test_blocks_follow_bytes_and_spread_one_id(spark, ugly, monkeypatch):
    monkeypatch.setattr(exchange, "BLOCK_BYTES", 100_000)
    blocks, shards = exchange.counts(ugly.select("doc_id", "text"))
    assert blocks > 15 and shards >= 1
    seven = exchange.with_block(ugly.where("doc_id = 7"), blocks)
    assert seven.select("_block").distinct().count() > 8
    texts = {i: t for i, t in ugly_rows() if i is not None and i >= 100 and i != 201}
    own = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r.doc_id: r.kept_text for r in line_dedup.line_dedup(own).collect()} == brute_lines(texts)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_words) for r in substring_dedup.substring_dedup(own).collect()} == brute_windows(texts, 20)


def test_askers_in_chunks_lose_no_link(spark, monkeypatch):
    rng = random.Random(3)
    base = prose(rng, 120).split()
    texts = {}
    for i in range(120):  # a chain of groups that are near, but not all near each other
        words = list(base)
        for _ in range(rng.choice([2, 4, 6, 8])):
            words[rng.randrange(len(words))] = rng.choice(WORDS)
        texts[i] = " ".join(words)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    monkeypatch.setattr(minhash, "BLOCK_BYTES", 3_000)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(df, minhash.MinHash(list_rows=16)).collect()}
    assert got == brute_near(texts, 4, 80)


def test_pipeline_on_ugly_tables(spark, ugly, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    given = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    odd = given.withColumn("doc_id", F.when(F.col("doc_id") % 3 == 0, 7).when(F.col("doc_id") % 7 != 0, F.col("doc_id")))  # repeated, none
    docs = odd.unionByName(ugly.select(*given.columns))
    for table, name in ((docs, "ugly"), (docs.limit(0), "none")):
        table.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        out = pipeline.run(spark, f"{tmp_path}/{name}")
        assert (out.count() > 0) == (name == "ugly")
    now = docs
    for name, stage in pipeline.STAGES[:-1]:
        now = stage(spark, now, str(tmp_path))
        assert now.columns == docs.columns, name


# The classifier against a plain version of features, updates and scores.


def plain_mix(x):
    m = (1 << 64) - 1
    x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & m
    x = (x ^ x >> 27) * 0x94D049BB133111EB & m
    return x ^ x >> 31


def plain_features(text, bits):
    def token(t):
        shape = 5 if not t[0].isalnum() else 3 if t.isdigit() else 0 if t.islower() else 2 if t.isupper() and len(t) > 1 else 1 if t.istitle() else 4
        return (xxh3_64_intdigest(t.encode()) & ~7) | shape

    h, m = [token(t) for t in re.findall(r"\w+|[^\w\s]+", text)], (1 << 64) - 1
    every = [plain_mix(x) for x in h]
    every += [1 if a == b else plain_mix((a * 0x9E3779B97F4A7C15 + b) & m) for a, b in zip(h, h[1:])]
    every += [(x & 7) + 16 for x in h] + [plain_mix((a & 7) * 8 + (b & 7) + 64) for a, b in zip(h, h[1:])]
    n = collections.Counter(plain_mix(x) & ((1 << bits) - 1) for x in every)
    value = {k: math.log1p(c) for k, c in n.items()}
    size = math.sqrt(sum(v * v for v in value.values()))
    return {k: v / size for k, v in value.items()}


def test_scores_are_those_of_the_plain_method():
    s = quality_classifier.Settings(bits=12, epochs=3)
    rng = random.Random(6)
    rows = [(k % 2, (prose(rng, 20) if k % 2 else " ".join(rng.choice(["buy", "NOW", "!!!", "10"]) for _ in range(20)))) for k in range(40)]
    model = quality_classifier.ftrl([(y, *quality_classifier.features(t, s.bits)) for y, t in rows], s)
    z, n = collections.defaultdict(float), collections.defaultdict(float)

    def weight(i):
        return 0.0 if abs(z[i]) <= s.l1 else -(z[i] - math.copysign(s.l1, z[i])) / ((s.beta + math.sqrt(n[i])) / s.alpha + s.l2)

    def probability(x):
        return 1 / (1 + math.exp(-sum(weight(i) * v for i, v in x.items())))

    order = np.random.default_rng(7)
    for _ in range(s.epochs):
        for k in order.permutation(len(rows)):
            y, x = rows[k][0], plain_features(rows[k][1], s.bits) | {-1: 1.0}
            now = {i: weight(i) for i in x}
            error = probability(x) - y
            for i, v in x.items():
                g = error * v
                z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / s.alpha * now[i]
                n[i] += g * g
    for _, t in rows + [(0, "buy bdkae !!!"), (1, prose(rng, 7))]:
        assert abs(model.score(*quality_classifier.features(t, s.bits)) - probability(plain_features(t, s.bits) | {-1: 1.0})) < 1e-4


def test_training_is_bounded_and_in_one_order(spark):
    texts = [(i % 50, prose(random.Random(i), 12), i) for i in range(300)]  # every id six times
    docs = spark.createDataFrame([(i, t) for i, t, _ in texts], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(50)] * 2, "doc_id long, quality int")
    s = quality_classifier.Settings(bits=10, per_class=10, epochs=2)
    a, b = quality_classifier.train(docs, labels, s), quality_classifier.train(docs.repartition(7), labels.repartition(3), s)
    assert a.intercept == b.intercept and (a.weights == b.weights).all()
    assert quality_classifier.train(docs.limit(0), labels, s).weights.any() == False  # noqa: E712


def test_long_blank_runs_are_quick():
    codec = sentencepiece_codec.Codec()
    for t in (" " * 60_000, "x" + " " * 20_000 + "y", "a  b" * 500):
        assert codec.encode([t])[0].tolist() == codec.pieces.lib.encode(t)


def test_edited_texts_take_part_in_the_comparison(spark):
    rows = spark.createDataFrame([(1, 1, "p", 5, 5, "q"), (2, 2, "r", 1, 1, "s"), (3, 3, "t", 3, 3, "t")], "a long, b long, sha string, ea long, eb long, edited_sha string")
    assert [tuple(r) for r in fingerprints.impure_digests(rows).collect()] == [(1, 1)]
    assert fingerprints.impure_digests(rows.where(F.col("a") == 3)).count() == 0
