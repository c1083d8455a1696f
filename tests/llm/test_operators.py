"""Text operators against brute force, on awkward small tables and on the smallest given one."""

import base64
import collections
import hashlib
import itertools
import random
import re
import textwrap
import unicodedata
import zlib

import numpy as np
import pytest
import zstandard
from pyspark.sql import functions as F

from tests_support import WORD, brute_lines, brute_near, brute_windows

from truekeys.llm import fingerprints, licences, line_dedup, minhash, packing, quality_classifier, quality_rules, sentencepiece_codec, sharding, substring_dedup
from truekeys.llm.exchange import range_bucket, ranked
from truekeys.llm.text import windows

SMALL = "/root/testdata/sf0.001"


def prose(rng, n):
    return " ".join(rng.choice(VOCABULARY) for _ in range(n))


VOCABULARY = ["".join(p) for p in itertools.product("bdk", "aeiou", "lmn", "aei")]


def awkward():
    """Nulls, empty and very long texts, repeated rows, ties, odd blanks, and groups of near copies."""
    rng = random.Random(5)
    base = prose(rng, 120)
    rows = [(1, None), (2, ""), (3, "   \n\t"), (4, "one two"), (5, base), (6, base), (7, base.upper()), (8, "a b  c\n" + base), (9, prose(rng, 30_000)), (10, "x" * 5000)]
    for i in range(60):
        words = base.split()
        for _ in range(rng.choice([0, 1, 2, 5, 9])):
            words[rng.randrange(len(words))] = rng.choice(VOCABULARY)
        rows.append((20 + i, " ".join(words)))
    line = "This very line stands in a great many documents."
    for i in range(40):
        rows.append((200 + i, "\n".join([prose(rng, 25), "  " + line.upper() if i % 3 else line + "\t", prose(rng, 12), line if i % 5 == 0 else "short"])))
    passage = prose(rng, 60)
    rows += [(300 + i, f"{prose(rng, 20)} {passage} {prose(rng, 15)} {passage if i % 4 == 0 else ''}") for i in range(20)]
    rows += [(400, " ".join(["stutter"] * 80)), (401, "same words here " * 40), (402, "<|endoftext|> plain <|endoftext|>"), (403, "ﬁ ⅷ é é ß SS")]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame([(i, t, "key clash", -1, "z") for i, t in awkward()], "doc_id long, text string, _block string, length int, shard string")
    return df.repartition(5)


@pytest.fixture(scope="module")
def texts():
    return dict(awkward())


def sha(s):
    return hashlib.sha256(s.encode()).hexdigest()


def empty_of(df):
    return df.limit(0)


def test_windows_are_those_of_the_definition():
    h = np.arange(1, 40, dtype=np.uint64) * np.uint64(77777777777)
    m = 0x9E3779B97F4A7C15
    for width in (1, 2, 3, 5, 8, 20, 39, 40):
        want = [sum(int(h[i + j]) * pow(m, width - 1 - j, 1 << 64) for j in range(width)) % (1 << 64) for i in range(max(0, 40 - width))]
        assert windows(h, width).tolist() == want


def test_quality_rules(spark, docs, texts):
    got = {r.doc_id: r for r in quality_rules.quality_rules(docs).collect()}
    assert got.keys() == texts.keys()
    for i, t in texts.items():
        t, w = t or "", WORD.findall(t or "")
        runs = collections.Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
        repeated = {k + j for k in range(len(w) - 4) if runs[tuple(w[k : k + 5])] > 1 for j in range(5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)))
        assert (r.n_dup_lines, r.n_repeat_words) == (len(lines) - len(set(lines)), len(repeated))
        assert r.base_failed == (len(w) < 10 or 100 * len(repeated) > 20 * len(w))
        assert not (r.base_failed and r.kept)
    assert got[5].kept and not got[400].kept and not got[401].kept and not got[1].kept
    assert quality_rules.quality_rules(empty_of(docs)).count() == 0


def test_quality_bands_reject_noise_and_keep_prose(spark):
    rng = random.Random(9)

    def lines(n):
        s = base64.b64encode(rng.randbytes(n)).decode()
        return "\n".join(s[i : i + 76] for i in range(0, len(s), 76))[:n]

    def tokens(letters, n):
        return " ".join("".join(rng.choice(letters) for _ in range(rng.randint(3, 9))) for _ in range(n))[:n]

    bands, pack = quality_rules.Bands(), zstandard.ZstdCompressor(level=3)
    clean = spark.read.parquet("/root/testdata/sf0.1/labels.parquet").where("quality = 1").where(quality_classifier.remainder() == 0).select("doc_id")
    kept = [r for r in (quality_rules.profile(d.text, bands, pack) | {"text": d.text} for d in spark.read.parquet("/root/testdata/sf0.1/documents.parquet").join(clean, "doc_id").collect()) if not r["base_failed"]]
    assert sum(r["kept"] for r in kept) >= 0.98 * len(kept) > 400
    noise = [lines(n) for n in (1500, 5000, 100_000)] + [tokens("0123456789abcdef", n) for n in (5000, 100_000)] + [tokens("abcdefghijklmnopqrstuvwxyz", n) for n in (1500, 5000, 100_000)]
    assert not any(quality_rules.profile(t, bands, pack)["kept"] for t in noise)
    long = [r["text"] for r in kept if 6000 <= len(r["text"].encode()) <= 16_000][:40]
    assert len(long) == 40 and not any(quality_rules.profile(t[: len(t) // 2] + lines(len(t) // 2), bands, pack)["kept"] for t in long)
    tails = [r["text"] for r in kept if 2048 <= len(r["text"].encode()) < 2400][:20]
    assert tails and all(quality_rules.profile(t.encode()[:2048].decode("utf-8", "ignore") + lines(1500), bands, pack)["bad_chunks"] > 0.2 for t in tails)


def test_quality_bands_are_learnt_on_the_training_fold(spark):
    sf = "/root/testdata/sf0.1"
    got = quality_rules.learn(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    for n in (800, 1500, 5000):
        assert all(abs(a - b) < 0.05 for a, b in zip(got.limits(n), quality_rules.Bands().limits(n), strict=True))
    assert 0.45 < got.chunk[0] < 0.48 and 0.53 < got.chunk[1] < 0.57


def test_line_dedup(docs, texts):
    got = {r.doc_id: r for r in line_dedup.line_dedup(docs).collect()}
    want = brute_lines(texts)
    assert {i: r.kept_text for i, r in got.items()} == want
    assert sum(r.n_dropped for r in got.values()) > 40
    assert all(r.n_lines == (texts[i] or "").count("\n") + 1 for i, r in got.items())
    assert line_dedup.line_dedup(empty_of(docs)).count() == 0


def test_line_dedup_repeated_ids_and_nulls(spark):
    line = "a line of more than twenty characters"
    df = spark.createDataFrame([(None, line), (7, line), (7, line), (3, line)], "doc_id long, text string")
    assert sorted(((r.doc_id or 0), r.n_dropped) for r in line_dedup.line_dedup(df).collect()) == [(0, 1), (3, 1), (7, 0), (7, 0)]


def test_line_index_is_reversible(spark, docs, texts):
    show = lambda ix: sorted((r["_shard"], bytes(r["filter"]), bytes(r["refs"])) for r in ix.collect())
    plain = docs.select("doc_id", "text")
    some = plain.where("doc_id % 3 = 0")
    before = plain.where("doc_id % 3 <> 0")
    index = line_dedup.build_index(before, 8, 4)
    more = line_dedup.update_index(index, plain, some, 8, 4)
    assert show(more) == show(line_dedup.build_index(plain, 8, 4)) != show(index)
    assert show(line_dedup.update_index(more, before, some, 8, 4)) == show(index)
    assert show(line_dedup.update_index(index, plain.limit(0), before, 8, 4)) == []
    got = {r.doc_id: r.kept_text for r in line_dedup.dedup_with(more, plain, 8).collect()}
    assert got == brute_lines(texts)


def test_cuckoo_filter_never_forgets_and_deletes():
    rng = np.random.default_rng(1)
    h = rng.integers(0, 1 << 63, 20_000, dtype=np.uint64)
    f = line_dedup.CuckooFilter(len(h))
    assert f.insert(h[:15_000]) and f.insert(h[15_000:])
    assert f.contains(h).all()
    other = rng.integers(0, 1 << 63, 20_000, dtype=np.uint64)
    assert f.contains(other).mean() < 0.01
    f.delete(h[:10_000])
    assert f.contains(h[10_000:]).all() and f.contains(h[:10_000]).mean() < 0.01 and f.size == 10_000
    assert not line_dedup.CuckooFilter(8).fits(500) and not line_dedup.CuckooFilter(8).insert(h[:500])
    a, b = line_dedup.CuckooFilter(20_000), line_dedup.CuckooFilter(20_000)
    assert a.insert(h) and b.insert(h[::-1]) and (a.table == b.table).all()


def refs_of(rows):
    out = np.zeros(len(rows), line_dedup.REFERENCE)
    for i, (key, *rest) in enumerate(rows):
        out[i] = (key.to_bytes(16, "little"), *rest)
    return out


def test_line_shard_counts_by_block():
    shard = line_dedup.LineShard()
    shard.insert(refs_of([(5, 0, 2, 10), (9, 0, 1, 4)]))
    shard.insert(refs_of([(5, 1, 1, 30)]))
    assert shard.common(3)[2].tolist() == [30, 30] and len(shard.solo) == 1 and len(shard.table) == 2
    shard.delete(np.array([1]))
    assert len(shard.common(3)[1]) == 0 and shard.common(2)[2].tolist() == [10]


def test_line_shard_goes_through_its_filter():
    rng = random.Random(8)
    shard, held = line_dedup.LineShard(), collections.defaultdict(dict)
    for block in range(40):  # grows from the smallest filter
        rows = [(rng.getrandbits(120) if rng.random() < 0.8 else rng.randrange(50), block, rng.randint(1, 3), rng.randrange(10**6)) for _ in range(300)]
        rows = list({r[0]: r for r in rows}.values())
        shard.insert(refs_of(rows))
        for key, b, n, last in rows:
            held[key][b] = (n, last)
    assert shard.filter.contains(line_dedup._hash(shard.keys())).all() and shard.filter.size == len(held)
    assert shard.spared > 0.75 * (shard.spared + shard.looked_up)  # lines that occur once are never looked up
    before = shard.state()
    extra = [(k, 99, 1, 7) for k in [*list(held)[:500], *range(10**6, 10**6 + 500)]]
    shard.insert(refs_of(extra))
    assert shard.state() != before
    shard.delete(np.array([99]))
    assert shard.state() == before and line_dedup.LineShard.of(before).state() == before
    for gone in ([3, 7], list(range(10, 40))):
        shard.delete(np.array(gone))
        held = {k: kept for k, v in held.items() if (kept := {b: x for b, x in v.items() if b not in gone})}
        want = {(b, k.to_bytes(16, "little")): max(x[1] for x in v.values()) for k, v in held.items() if sum(x[0] for x in v.values()) >= 3 for b in v}
        blocks, keys, last = shard.common(3)
        raw = np.ascontiguousarray(keys).tobytes()
        assert {(int(b), raw[16 * i : 16 * i + 16]): int(x) for i, (b, x) in enumerate(zip(blocks, last))} == want
        assert shard.filter.size == len(held)


def test_substring_dedup(docs, texts):
    got = {r.doc_id: r for r in substring_dedup.substring_dedup(docs).collect()}
    assert {i: (r.n_words, r.n_removed, r.kept_words) for i, r in got.items()} == brute_windows(texts, 20)
    assert sum(r.n_removed > 0 for r in got.values()) > 40
    for r in got.values():
        assert WORD.findall(r.kept_text) == WORD.findall(r.kept_words)
    assert substring_dedup.substring_dedup(empty_of(docs)).count() == 0


def test_difference_cover_must_cover():
    with pytest.raises(ValueError):
        substring_dedup.Cover(cover=(0, 1, 3))
    with pytest.raises(ValueError):
        substring_dedup.Cover(anchor=9)


@pytest.mark.parametrize("settings", [minhash.MinHash(), minhash.MinHash(shingle=5, coords=64, matches=36, list_rows=8, fan_out=3)])
def test_near_duplicates(docs, texts, settings):
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(docs, settings).collect()}
    want = brute_near(texts, settings.shingle, 80)
    assert got == want
    assert 5 < sum(k for _, _, k in want.values()) < len(want)


def test_near_duplicates_of_nothing(spark, docs):
    assert minhash.near_duplicates(empty_of(docs)).count() == 0
    df = spark.createDataFrame([(1, None), (2, " ")], "doc_id long, text string")
    assert sorted(tuple(r) for r in minhash.near_duplicates(df).collect()) == [(1, 0, 1, True), (2, 0, 2, True)]


def test_near_duplicates_of_repeated_ids(spark):
    a, b = "one two three four five six", "seven eight nine ten eleven twelve"
    df = spark.createDataFrame([(5, a), (7, a), (7, b), (9, b), (None, "other words")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect()), key=str)
    assert got == [(5, 5, True), (7, 5, False), (7, 5, False), (9, 5, False), (None, None, True)]


def test_blocks_are_sparks(spark):
    ids = [0, 1, -5, 2**40, 7**20]
    df = spark.createDataFrame([(i,) for i in ids], "doc_id long").select("doc_id", F.pmod(F.xxhash64("doc_id"), F.lit(37)).alias("b"))
    assert {r.doc_id: r.b for r in df.collect()} == {i: minhash.block_of(i, 37) for i in ids}


def ids_of(texts):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.default_tokenizer())
    return {i: [*tok.encode(t or "", add_special_tokens=False).ids, 2] for i, t in texts.items()}


def test_packing(docs, texts):
    rows, ids = packing.pack(docs, with_ids=True).collect(), ids_of(texts)
    by_doc, by_sequence = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        own = ids[r.doc_id][r.start : r.start + r.length]
        assert list(r.ids) == own and zlib.crc32(np.array(own, "<u4").tobytes()) == r.ids_crc32
        by_doc[r.doc_id].append((r.piece, r.start, r.length))
        by_sequence[r.sequence_id].append((r.offset, r.length))
    for i, own in ids.items():
        got = sorted(by_doc[i])
        assert [p for p, _, _ in got] == list(range(len(got))) and sum(n for _, _, n in got) == len(own)
        assert all(n == 1024 for _, _, n in got[1:]) and (len(got) == 1) == (len(own) <= 1024)
    for own in by_sequence.values():
        at = 0
        for offset, n in sorted(own):
            assert offset == at
            at += n
        assert at <= 1024
    assert len(by_sequence) <= -(-sum(map(len, ids.values())) // 1024) + 4
    assert packing.pack(empty_of(docs)).count() == 0


def test_long_runs_get_the_same_ids():
    from tokenizers import Tokenizer

    tok, own = Tokenizer.from_file(packing.default_tokenizer()), packing.ByteTokenizer(packing.default_tokenizer())
    rng = random.Random(2)
    for text in ["a" * 6000, " " * 5000 + "x", "ab" * 4000, "<|endoftext|>" * 3, "".join(chr(rng.choice([32, 65, 97, 233, 0x4E2D, 0x1F600, 10, 9, 39, 115])) for _ in range(3000))]:
        assert own.encode(text) == tok.encode(text, add_special_tokens=False).ids


def test_plan_uses_the_histogram_exactly():
    rng = np.random.default_rng(3)
    histogram = {int(k): int(v) for k, v in zip(range(1, 1025), rng.integers(0, 60, 1024))}
    used, sequences, tokens = collections.Counter(), 0, sum(k * v for k, v in histogram.items())
    for pattern, n in packing.plan(histogram):
        assert sum(pattern) <= 1024 and n > 0
        sequences += n
        for length in pattern:
            used[length] += n
    assert used == collections.Counter({k: v for k, v in histogram.items() if v})
    large = sum(v for k, v in histogram.items() if k > 512)  # no two of these share a sequence
    assert sequences <= max(-(-tokens // 1024), large) * 1.005 + 1
    assert packing.plan({}) == [] and packing.plan({1024: 3}) == [((1024,), 3)] and packing.plan({600: 2}) == [((600,), 2)]


def test_sharding(docs, texts):
    rows = sharding.shard_documents(docs).collect()
    assert {r.doc_id for r in rows} == texts.keys()
    slots = collections.defaultdict(list)
    for r in rows:
        raw = (texts[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32, r.law) == (len(raw) + 1, zlib.crc32(raw), "key")
        assert r.grown_shard in (r.shard, 8)
        slots[r.shard].append(r.slot)
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert sharding.shard_documents(empty_of(docs)).count() == 0


def test_sharding_moves_only_where_weights_change(spark):
    ids = spark.range(20_000).select(F.col("id").alias("doc_id"))
    a, b = sharding.tree(8), sharding.tree(9)
    heavier = sharding.Node("root", (a.children[0], sharding.Node("region1", (a.children[1].children[0], sharding.Node("rack3", (*a.children[1].children[1].children, sharding.Node("shard99", shard=99)))))))
    row = ids.select(*(sharding.shard_of("doc_id", x).alias(n) for n, x in (("a", a), ("b", b), ("c", heavier)))).collect()
    counts = collections.Counter(r.a for r in row)
    assert set(counts) == set(range(8)) and all(abs(v - 2500) < 250 for v in counts.values())
    assert all(r.b in (r.a, 8) for r in row) and abs(sum(r.b == 8 for r in row) - 20_000 / 9) < 250
    assert all(r.c == r.a or r.c >= 4 for r in row)  # a heavier region only takes from the other


def canon(t):
    n = unicodedata.normalize
    return " ".join(n("NFKC", n("NFKC", t).casefold()).split())


def test_fingerprints(docs, texts):
    got = {r.doc_id: r for r in fingerprints.fingerprints(docs).collect()}
    order, seen = sorted(texts), {}
    for i, j in zip(order, order[1:] + order[:1]):
        t, u = texts[i] or "", texts[j] or ""
        k = len(t) // 4
        e = t[: len(t) - k] + u[:k]
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(t), sha(e))
        assert (r.near_edited, r.near_next) == (float(canon(t) == canon(e)), float(canon(t) == canon(u)))
        for f, c in ((r.fingerprint, canon(t)), (r.edited_fingerprint, canon(e))):
            assert seen.setdefault(f, c) == c
    assert len(set(seen.values())) == len(seen)
    assert got[5].fingerprint == got[6].fingerprint == got[7].fingerprint
    assert fingerprints.fingerprints(empty_of(docs)).count() == 0


def test_fingerprints_compare_bytes(spark):
    df = spark.createDataFrame([(1, "a b"), (2, "A  b"), (3, "c")], "doc_id long, text string")
    same = df.select(F.lit(1).cast("long").alias("a"), F.lit(2).cast("long").alias("b"))
    plain = fingerprints._hashes
    try:
        fingerprints._hashes = lambda d, c, a, b: d.withColumns({a: F.lit(1).cast("long"), b: F.lit(2).cast("long")})
        assert fingerprints.impure_buckets(df, same).count() == 1
        prints = {r.doc_id: r.fingerprint for r in fingerprints.fingerprints(df).collect()}
    finally:
        fingerprints._hashes = plain
    assert prints[1] == prints[2] != prints[3]


def test_licences(spark):
    notice = licences.SENTENCES
    mit = "\n\n".join(notice[i] for i in (22, 23, 24))
    wrapped = re.sub(r"((?:\S+ ){8})", r"\1\n", mit).replace(" \n", "\n")
    rows = [(1, "Some text.\nReleased under the MIT License.\nMore"), (2, mit), (3, wrapped), (4, None), (5, "no licence here"), (6, "Licensed under the Apache License, Version 2.0."), (7, "released  UNDER the mit licence."), (8, notice[41] + "\n" + notice[40])]
    got = {r.doc_id: r for r in licences.licence_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].licence for i in range(1, 9)] == ["MIT", "MIT", "MIT", None, None, "Apache-2.0", None, None]
    assert got[2].sentence_ids == got[3].sentence_ids == ",22,23,24," and got[8].sentence_ids == ",41,40,"


def test_licence_files_with_head_lines(spark):
    n, mark = licences.SENTENCES, "Copyright (c) 2020 Jane Doe"

    def file(*paragraphs):
        return "\n\n".join(textwrap.fill(p, 78) for p in paragraphs)

    mit = (n[22], n[23], n[24] + " IN NO EVENT SHALL THE AUTHORS BE LIABLE.")
    gpl = (f"{n[11]} {n[12]}", f"{n[13]} {n[14]} {n[15]}", n[16])
    bsd = (n[40], "1. " + n[41], "2. " + n[42])
    texts = {
        "MIT": [file("MIT License", mark, *mit), "MIT License\n" + mark + "\n" + file(*mit), "The MIT License (MIT)\n" + file(*mit), file("MIT License", mark, *mit).replace("\n", "\r\n"), re.sub("(?m)^", " * ", file("MIT License", mark, *mit))],
        "GPL-3.0-or-later": [mark + "\n" + file(*gpl), file("A program", mark, *gpl)],
        "BSD-2-Clause": [file("BSD 2-Clause License", mark, *bsd), "Copyright (c) 2020, Jane Doe\nAll rights reserved.\n\n" + file(*bsd)],
        "BSD-3-Clause": [file("BSD 3-Clause License", mark, *bsd, "3. " + n[43])],
        "ISC": [file("ISC License", mark, n[61])],
        "Apache-2.0": ["Copyright 2020 Jane Doe\n" + file(f"{n[2]} {n[3]} {n[4]}", "    http://www.apache.org/licenses/LICENSE-2.0", f"{n[5]} {n[6]}")],
        "GPL-2.0-or-later": [mark + "\n" + file(f"{n[11].replace(':', ';')} {n[91]} {n[92]}", f"{n[13]} {n[14]} {n[15]}")],
        "LGPL-2.1-or-later": [file(mark, f"{n[17]} {n[18]} {n[19]}")],
        "LGPL-3.0-or-later": [file(mark, f"{n[11]} {n[95]}"), file(mark, f"{n[17]} {n[18]} {n[93]}")],
        "AGPL-3.0-or-later": [file(mark, f"{n[11]} {n[94]}", f"{n[13]} {n[14]} {n[96]}")],
        "GPL-3.0-only": [f"                    {n[80]}\n                       {n[83]}\n\n Copyright (C) 2007\n {n[125]}\n", "# SPDX-License-Identifier: GPL-3.0-only\nimport this"],
        "Zlib": [file("zlib License", mark, f"{n[110]} {n[111]}", n[112])],
        "EPL-2.0": [file(n[100]) + "\nhttps://www.eclipse.org/legal/epl-2.0/"],
        "CC0-1.0": [file(n[64]), "/* SPDX-License-Identifier: CC0-1.0 */"],
        "BSL-1.0": [file(n[114], n[113])],
        "All-Rights-Reserved": ["Some text.\nAll rights reserved.", mark + "\nAll rights reserved."],
    }
    rows = [(f"{name} {i}", t) for name, ts in texts.items() for i, t in enumerate(ts)]
    got = {r.doc_id: r.licence for r in licences.licence_scan(spark.createDataFrame(rows, "doc_id string, text string")).collect()}
    assert got == {i: i.split(" ")[0] for i, _ in rows}


@pytest.mark.parametrize("algorithm", ["bpe", "unigram"])
def test_sentencepiece_ids_are_the_librarys(algorithm):
    proto = None
    if algorithm == "unigram":
        with open(sentencepiece_codec.default_model(), "rb") as f:
            proto = as_unigram(f.read())
    codec = sentencepiece_codec.Codec(algorithm=algorithm, proto=proto)
    lib = codec.pieces.lib
    rng = random.Random(4)
    letters = "abcdefghinorstuaaaeeettt  \n.,ABééü漢字😀  \t"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 120))) for _ in range(400)] + ["", " ", "   ", "a" * 300, "  x    y", "ﬁ ▁▁a"] + [prose(rng, 50)] * 2
    for t, ids in zip(texts, codec.encode(texts)):
        want = lib.encode(t)
        if algorithm == "bpe":
            assert ids.tolist() == want
            assert codec.decode(ids) == lib.decode(want)
        else:  # ties between equal sums may fall either way
            total = lambda x: sum(lib.get_score(i) for i in x if not lib.is_byte(i))
            assert abs(total(ids.tolist()) - total(want)) <= 1e-3 * max(1, abs(total(want)))


def as_unigram(raw):
    """The model with its type set to unigram and positive-free scores kept: field 3 of the trainer specification."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    model = pb.ModelProto()
    model.ParseFromString(raw)
    model.trainer_spec.model_type = 1
    del model.pieces[:]
    source = pb.ModelProto()
    source.ParseFromString(raw)
    for p in source.pieces:
        p.score = max(p.score, -40000.0)
        model.pieces.append(p)
    return model.SerializeToString()


def test_sentencepiece_round_trip(docs, texts):
    rows = {r.doc_id: r for r in sentencepiece_codec.round_trip(docs).collect()}
    coded = sentencepiece_codec.encode_documents(docs)
    back = {r.doc_id: r.text for r in sentencepiece_codec.decode_documents(coded).collect()}
    for i, t in texts.items():
        assert rows[i].round_trip == (back[i] == (t or "")) and rows[i].decoded_sha256 == sha(back[i])
    assert sum(r.round_trip for r in rows.values()) >= len(rows) - 2
    assert sentencepiece_codec.round_trip(empty_of(docs)).count() == 0


def test_quality_classifier(spark):
    docs, labels = spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet")
    model = quality_classifier.train(docs, labels)
    got = {r.doc_id: r for r in quality_classifier.classify(docs, model).collect()}
    assert len(got) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got.values())
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())
    known = [(got[r.doc_id].score, r.quality) for r in labels.collect()]
    good, bad = [s for s, q in known if q == 1], [s for s, q in known if q == 0]
    assert sum(g > b for g in good for b in bad) >= 0.97 * len(good) * len(bad)
    alone = quality_classifier.train(docs, labels.where("quality = 1"))
    assert quality_classifier.classify(spark.createDataFrame([(1, None)], "doc_id long, text string"), alone).first().score > 0.5


def test_held_out_labels_do_not_reach_the_model(spark):
    docs, labels = spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet")
    flipped = labels.withColumn("quality", F.when(quality_classifier.remainder() == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = quality_classifier.train(docs, labels), quality_classifier.train(docs, flipped)
    assert a.intercept == b.intercept and (a.weights == b.weights).all()


def test_range_buckets_and_ranks(spark):
    ids = [*range(0, 1000), *range(10**12, 10**12 + 50), -(2**62), 2**62]
    df = spark.createDataFrame([(i, i % 3) for i in ids] + [(None, 0)], "doc_id long, g int")
    rows = df.withColumn("b", range_bucket(df, "doc_id", 40)).collect()
    order = sorted((r.doc_id, r.b) for r in rows if r.doc_id is not None)
    assert all(x[1] <= y[1] for x, y in zip(order, order[1:])) and len({b for _, b in order}) > 10
    got = ranked(df, "g", ["doc_id"], "rank", rows=40).collect()
    for g in range(3):
        own = sorted((r.doc_id if r.doc_id is not None else -(2**63), r.rank) for r in got if r.g == g)
        assert [k for _, k in own] == list(range(len(own)))
