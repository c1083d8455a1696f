"""MinHash near-dedup by an inverted join on signature coordinates.

Each document's set of word shingles gives a signature of ``coords`` minima.  Documents with equal sets are one class
with one representative, so copies are never paired.  A representative is posted under its (coordinate, value) pairs,
and two of them are candidates if at least ``matches`` coordinates collide.

Prefix merging: with pairs ordered by ascending frequency, two signatures that collide in t of k coordinates share one
of the k - t + 1 rarest pairs of each, so only these are posted, and pairs that occur once need no posting at all.
Skip merging: the frequent lists left out are not merged; for the candidates that the short lists bring up, collisions
are counted on sketches (one byte of each of ``sketch`` coordinates, the posted ones among them, which never undercounts)
and ``alike`` of them are asked for.  Lists that remain long belong to groups of near copies and are split by salt.

Only connections matter, so a list proposes a tree over its similar members, not all pairs.  Proposals are confirmed on
the full shingle sets.  A second round then looks for links between different components: every pair in a list whose
members are in different components is counted, and those that collide enough are confirmed, so no link between
components is lost.  There a document that stands apart meets the members of a group block by block, one row for each
block with the numbers of those that collide enough, and one link to a component is enough.  What is written grows with
the pairs that collide often enough without being linked: texts nearly similar enough.  The longer sketch leaves few of
them (one pair in a thousand at a similarity of 0.59), but a large group of texts at 0.7 or more to each other and no
link among them still costs a row for each pair.

A link needs 100 * intersection >= percent * union; at exactly 0.8, a link is missed with a probability of about 1e-5.
Defined results: a text without words has an empty set and no links; fewer words than a shingle are one shingle; rows
that repeat a doc_id are one node with the links of all of them; a null doc_id sorts first, as the least 64-bit integer
does, and rows without one are one node; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_128_intdigest, xxh64_intdigest

from ..operators.components import connected_components
from .exchange import BLOCK_BYTES, POSTING, counts, empty, packed, scatter, staged, unpacked, with_block
from .text import mix, windows, word_hashes, words

NO_ID = -(1 << 63)
#: Ids (8 bytes each) that are broadcast at most, to pick the documents that candidates need; beyond, the join shuffles.
BROADCAST_IDS = 1_000_000


@dataclass(frozen=True)
class MinHash:
    shingle: int = 4
    percent: int = 80
    coords: int = 128
    matches: int = 81
    sketch: int = 256
    alike: int = 176
    list_rows: int = 2048
    fan_out: int = 32

    @property
    def prefix(self) -> int:
        return self.coords - self.matches + 1

    def parameters(self) -> tuple[np.ndarray, np.ndarray]:
        n = np.arange(2 * self.sketch, dtype=np.uint64)
        with np.errstate(over="ignore"):
            r = (mix((n + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)).astype(np.uint32)
        return r[: self.sketch] | np.uint32(1), r[self.sketch :]


def shingles(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's shingles."""
    tokens = [] if not text else text.encode("utf-8", "surrogatepass").lower().split()
    if not tokens:
        return np.empty(0, np.uint64)
    h = word_hashes(tokens)
    if len(tokens) < width:
        return mix(windows(h, len(h)) ^ np.uint64(len(h)))
    return np.unique(mix(windows(h, width)))


def signature(own: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The minima of as many permutations of the (upper 32 bits of the) hashes."""
    x, low = (own >> np.uint64(32)).astype(np.uint32), np.full(len(a), np.iinfo(np.uint32).max, np.uint32)
    with np.errstate(over="ignore"):
        for at in range(0, len(x), 512):
            part = x[at : at + 512, None] * a
            part += b
            np.minimum(low, part.min(0), out=low)
    return low


def _packed_signature(low: np.ndarray, p: MinHash) -> bytes:
    """The posted coordinates in full, and one byte of each other one."""
    return low[: p.coords].astype("<u4").tobytes() + (low[p.coords :] & 255).astype("u1").tobytes()


def _unpacked_signatures(column: pa.ChunkedArray, p: MinHash) -> tuple[np.ndarray, np.ndarray]:
    """(posted coordinates, sketches of one byte for every coordinate), a row for each signature."""
    raw = _matrix(column, "u1", 4 * p.coords + p.sketch - p.coords)
    sigs = np.ascontiguousarray(raw[:, : 4 * p.coords]).view("<u4")
    return sigs, np.concatenate([(sigs & 255).astype("u1"), raw[:, 4 * p.coords :]], axis=1)


def signatures(docs: DataFrame, p: MinHash) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_shingles, ha, hb (128 bits of the set), sig."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = p.parameters()
        for batch in batches:
            n, ha, hb, sig = [], [], [], []
            for text in batch.column(1):
                own = shingles(text.as_py(), p.shingle)
                wide = xxh3_128_intdigest(own.tobytes())
                n.append(len(own))
                ha.append((wide >> 64) - (1 << 63))
                hb.append((wide & (1 << 64) - 1) - (1 << 63))
                sig.append(_packed_signature(signature(own, a, b), p) if len(own) else None)
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0), "n_shingles": pa.array(n, pa.int64()), "ha": pa.array(ha, pa.int64()), "hb": pa.array(hb, pa.int64()), "sig": pa.array(sig, pa.binary())})

    return docs.mapInArrow(run, "doc_id long, n_shingles long, ha long, hb long, sig binary")


def _matrix(column: pa.ChunkedArray, kind: str, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), kind).reshape(-1, width)


def coordinate_keys(sigs: np.ndarray) -> np.ndarray:
    """One 64-bit key for each (coordinate, value) pair of each signature."""
    return mix(sigs.astype(np.uint64) | (np.arange(sigs.shape[1], dtype=np.uint64) << np.uint64(32)))


def prefix_postings(reps: DataFrame, p: MinHash) -> DataFrame:
    """reps(doc_id, n, sig) -> key, freq, doc, n, sketch: the rarest shared keys of every representative."""
    blocks, shards = counts(reps)
    dealt = with_block(reps.select("doc_id", "n", "sig"), blocks, ("doc_id", "sig"))
    by_block = dealt.groupBy("_block")

    def count_keys(table: pa.Table) -> pa.Table:
        keys, n = np.unique(coordinate_keys(_unpacked_signatures(table.column("sig"), p)[0]), return_counts=True)
        return scatter(table.column("_block")[0].as_py(), keys, [keys, n.astype("<u4")], shards)

    def total(table: pa.Table) -> pa.Table:
        owner, (keys, n) = unpacked(table, ["<u8", "<u4"], "_block")
        _, back = np.unique(keys, return_inverse=True)
        freq = np.bincount(back, n)[back].astype("<u4")
        at = np.flatnonzero(freq > 1)
        at = at[np.argsort(owner[at], kind="stable")]
        return packed(owner[at], [keys[at], freq[at]], "_block", {"_shard": table.column("_shard")[0].as_py()}) if len(at) else empty()

    def choose(table: pa.Table, verdict: pa.Table) -> pa.Table:
        if not table.num_rows:
            return _postings([], [], [], [], [])
        _, (known, f) = unpacked(verdict, ["<u8", "<u4"], "_block")
        order = np.argsort(known)
        known, f = known[order], f[order]
        sigs, own = _unpacked_signatures(table.column("sig"), p)
        keys = coordinate_keys(sigs)
        freq = np.ones(keys.shape, np.int64)
        if len(known):
            at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
            freq = np.where(known[at] == keys, f[at], 1).astype(np.int64)
        rank = np.lexsort((keys, freq), axis=1)[:, : p.prefix]  # ascending frequency, ties by key: one order for all
        row = np.repeat(np.arange(len(keys)), rank.shape[1])
        col = rank.ravel()
        shared = freq[row, col] > 1
        row, col = row[shared], col[shared]
        sketch = [x.tobytes() for x in own]
        docs, n = table.column("doc_id").to_numpy(), table.column("n").to_numpy()
        return _postings(keys[row, col].view(np.int64), freq[row, col], docs[row], n[row], [sketch[i] for i in row])

    verdict = by_block.applyInArrow(count_keys, POSTING).groupBy("_shard").applyInArrow(total, POSTING)
    return by_block.cogroup(verdict.groupBy("_block")).applyInArrow(choose, "key long, freq long, doc long, n long, sketch binary")


def _postings(key, freq, doc, n, sketch) -> pa.Table:  # noqa: ANN001
    return pa.table({"key": pa.array(key, pa.int64()), "freq": pa.array(freq, pa.int64()), "doc": pa.array(doc, pa.int64()), "n": pa.array(n, pa.int64()), "sketch": pa.array(sketch, pa.binary())})


def _lists(table: pa.Table) -> Iterator[np.ndarray]:
    """Row numbers of every list (key, salt) with two members or more, by ascending document."""
    key, salt, doc = (table.column(c).to_numpy() for c in ("key", "salt", "doc"))
    order = np.lexsort((doc, salt, key))
    new = np.flatnonzero((key[order][1:] != key[order][:-1]) | (salt[order][1:] != salt[order][:-1])) + 1
    for part in np.split(order, new):
        if len(part) > 1:
            yield part


class _Members:
    """The members that a shard received: documents, set sizes and sketches."""

    def __init__(self, table: pa.Table, p: MinHash) -> None:
        self.p = p
        self.sketch, self.docs, self.size = _matrix(table.column("sketch"), "u1", p.sketch), table.column("doc").to_numpy(), table.column("n").to_numpy()

    def collisions(self, rows: np.ndarray, other: np.ndarray) -> np.ndarray:
        """Collisions of each row with the other (one, or one each); 0 where the set sizes rule a link out."""
        n = (self.sketch[rows] == self.sketch[other]).sum(1)
        small, large = np.minimum(self.size[rows], self.size[other]), np.maximum(self.size[rows], self.size[other])
        return np.where(100 * small >= self.p.percent * large, n, 0)


def _pairs(rows: list[tuple[int, int, int]]) -> pa.Table:
    a, b, n = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "n": pa.array(n, pa.int32())})


def _sharded(postings: DataFrame, salts: F.Column, shards: int) -> DataFrame:
    return postings.withColumn("salt", salts).withColumn("_shard", F.pmod(F.xxhash64("key", "salt"), F.lit(shards)).cast("int"))


def trees(postings: DataFrame, p: MinHash, shards: int) -> DataFrame:
    """Candidate links a < b: in each list a tree of bounded fan-out over members that collide often enough."""

    def run(table: pa.Table) -> pa.Table:
        own_rows, found = _Members(table, p), {}
        docs = own_rows.docs
        for alive in _lists(table):
            while len(alive) > 1:
                n = own_rows.collisions(alive, alive[0])
                n[0] = p.sketch
                own, alive = alive[n >= p.alike], alive[n < p.alike]
                up = own[np.maximum(np.arange(len(own)) - 1, 0) // p.fan_out]
                up = np.where(own_rows.collisions(own, up) >= p.alike, up, own[0])
                n = own_rows.collisions(own, up)
                found.update(((x, y), k) for x, y, k in zip(docs[up[1:]].tolist(), docs[own[1:]].tolist(), n[1:].tolist(), strict=True) if x != y)
        return _pairs([(x, y, k) for (x, y), k in found.items()])

    salt = F.pmod(F.xxhash64("doc", "key"), F.ceil(F.col("freq") / p.list_rows)).cast("int")
    found = _sharded(postings, salt, shards).groupBy("_shard").applyInArrow(run, "a long, b long, n int")
    best = found.groupBy("b").agg(F.min_by("a", F.struct((-F.col("n")).alias("n"), F.col("a"))).alias("a"))  # one proposal a document
    return best.select("a", "b")


def block_of(doc: int, blocks: int) -> int:
    """The block that Spark's xxhash64 gives a document, for use inside a task."""
    h = xxh64_intdigest(doc.to_bytes(8, "little", signed=True), 42)
    return (h - (1 << 64) if h >= 1 << 63 else h) % blocks


def mixed_lists(postings: DataFrame, labels: DataFrame, p: MinHash) -> DataFrame:
    """Postings of the lists with members of different components: root (component), minor, home and part.

    A list of any length is split into parts by salt, in the join as well.  Members of its most frequent component stay
    in their home part; the others (minor) go to every part, where they meet the members that live there.
    """
    parts = F.ceil(F.col("freq") / p.list_rows).cast("int")
    marked = postings.join(labels.select(F.col("node").alias("doc"), "root"), "doc", "left").withColumn("root", F.coalesce("root", "doc"))
    per_root = marked.groupBy("key", "root").agg(F.count(F.lit(1)).alias("count"), F.max("freq").alias("freq"))
    mixed = per_root.groupBy("key").agg(F.max_by("root", F.struct("count", "root")).alias("major"), F.count(F.lit(1)).alias("n_roots"), F.max("freq").alias("freq")).where("n_roots > 1")
    salted = mixed.select("key", "major", F.explode(F.sequence(F.lit(0), parts - 1)).alias("home"))
    rows = marked.withColumn("home", F.pmod(F.xxhash64("doc", "key"), parts).cast("int")).join(salted, ["key", "home"])
    minor = F.col("root") != F.col("major")
    spread = F.explode(F.when(minor, F.sequence(F.lit(0), parts - 1)).otherwise(F.array("home")))
    return rows.select("key", "doc", "n", "sketch", "root", "home", minor.alias("minor"), spread.alias("part"))


def across(mixed: DataFrame, p: MinHash, shards: int, blocks: int) -> DataFrame:
    """x, block, ys: documents of other components that collide with x often enough, (document, root) by their block.

    Two members meet in one part only: with a major one where that lives, and two minor ones in the lower of their homes.
    """

    def run(table: pa.Table) -> pa.Table:
        rows, root, home, minor = _Members(table, p), *(table.column(c).to_numpy(zero_copy_only=False) for c in ("root", "home", "minor"))
        part = table.column("part").to_numpy()
        found: dict[tuple[int, int], set[tuple[int, int]]] = {}
        for own in _lists(table):
            major, others, here = own[~minor[own]], own[minor[own]], part[own[0]]
            for k, i in enumerate(others):
                later = others[k + 1 :]
                if home[i] == here:  # the other minor ones that live here or further on
                    met = np.concatenate([major, later[home[later] >= here], (before := others[:k])[home[before] > here]])
                else:
                    met = major
                hit = met[root[met] != root[i]]
                hit = hit[rows.collisions(hit, i) >= p.alike]
                for y, r in zip(rows.docs[hit].tolist(), root[hit].tolist(), strict=True):
                    found.setdefault((int(rows.docs[i]), block_of(y, blocks)), set()).add((y, r))
        x, block = zip(*found, strict=True) if found else ((), ())
        return pa.table({"x": pa.array(x, pa.int64()), "block": pa.array(block, pa.int32()), "ys": pa.array([np.array(sorted(v), np.int64).tobytes() for v in found.values()], pa.binary())})

    return _sharded(mixed, F.col("part"), shards).groupBy("_shard").applyInArrow(run, "x long, block int, ys binary")


def _similar(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sorted sets are similar enough."""
    small, large = (x, y) if len(x) <= len(y) else (y, x)
    if not len(small) or 100 * len(small) < percent * len(large):
        return False
    inter = int((large[np.minimum(np.searchsorted(large, small), len(large) - 1)] == small).sum())
    return 100 * inter >= percent * (len(x) + len(y) - inter)


def _needed(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents with these ids; the ids are broadcast only if they are few enough."""
    small = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if small else ids, "doc_id", "left_semi")


def confirmed_across(docs: DataFrame, postings: DataFrame, labels: DataFrame, p: MinHash, shards: int) -> DataFrame:
    """Links (a, b) between components, confirmed on the full sets: for each document one link to each component.

    A block of documents and the askers' texts are both bounded by bytes: a block that many ask is asked in chunks.
    """
    mixed = staged(mixed_lists(postings, labels, p))
    ids = staged(mixed.select(F.col("doc").alias("doc_id")).distinct())
    texts = _needed(docs, ids)
    blocks, _ = counts(texts)
    requests = staged(across(mixed, p, shards, blocks).groupBy("block", "x").agg(F.collect_list("ys").alias("ys")))  # as many as x has lists
    asked = requests.join(texts.select(F.col("doc_id").alias("x"), F.col("text").alias("own")), "x").select("block", "x", "own", "ys")
    sizes = texts.select(F.col("doc_id").alias("x"), F.octet_length("text").alias("size"))
    chunks = requests.join(sizes, "x").groupBy("block").agg(F.ceil(F.sum("size") / BLOCK_BYTES).cast("int").alias("chunks"))
    several = staged(chunks.where("chunks > 1"))  # the others are asked in one go
    asked = asked.join(several, "block", "left").withColumn("chunk", F.coalesce(F.pmod(F.xxhash64("x"), "chunks"), F.lit(0)).cast("int"))
    there = with_block(texts, blocks, ("doc_id",)).select(F.col("_block").alias("block"), F.col("doc_id").alias("doc"), F.col("text").alias("body"))
    there = there.join(several, "block", "left").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("chunks") - 1, F.lit(0)))))
    there, asked = there.select("block", "chunk", "doc", "body"), asked.select("block", "chunk", "x", "own", "ys")

    def run(there: pa.Table, asked: pa.Table) -> pa.Table:
        sets: dict[int, list[np.ndarray]] = {}
        by_id: dict[int, list[int]] = {}
        for i, d in enumerate(there.column("doc").to_pylist()):
            by_id.setdefault(d, []).append(i)
        text, out = there.column("body"), []
        for x, own, ys in zip(asked.column("x").to_pylist(), asked.column("own"), asked.column("ys").to_pylist(), strict=True):
            a, done = shingles(own.as_py(), p.shingle), set()
            for y, root in sorted({tuple(r) for v in ys for r in np.frombuffer(v, np.int64).reshape(-1, 2).tolist()}):
                if root in done:
                    continue
                if y not in sets:
                    sets[y] = [shingles(text[i].as_py(), p.shingle) for i in by_id.get(y, ())]
                if any(_similar(a, b, p.percent) for b in sets[y]):
                    done.add(root)
                    out.append((min(x, y), max(x, y)))
        a, b = zip(*out, strict=True) if out else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return there.groupBy("block", "chunk").cogroup(asked.groupBy("block", "chunk")).applyInArrow(run, "a long, b long").distinct()


def confirmed(docs: DataFrame, pairs: DataFrame, p: MinHash) -> DataFrame:
    """The pairs (a, b) whose full shingle sets are similar enough."""
    pairs = staged(pairs)
    texts = _needed(docs, pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    both = pairs.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b").join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, x = None, None
        for batch in batches:
            keep = []
            for ta, tb in zip(batch.column(2), batch.column(3), strict=True):
                text = ta.as_py()
                if text != last or x is None:
                    last, x = text, shingles(text, p.shingle)
                keep.append(_similar(x, shingles(tb.as_py(), p.shingle), p.percent))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_pydict({"a": batch.column(0).filter(mask), "b": batch.column(1).filter(mask)})

    return both.select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _repeated(sigs: DataFrame, classes: DataFrame) -> DataFrame:
    """Links (a, b) between a doc_id that several rows have and the representatives of those rows' sets."""
    twice = sigs.groupBy("doc_id").count().where("count > 1").select("doc_id")
    if twice.isEmpty():
        return sigs.limit(0).select(F.col("doc_id").alias("a"), F.col("doc_id").alias("b"))
    rows = sigs.join(twice, "doc_id").select("ha", "hb", F.col("doc_id").alias("b"))
    return rows.join(classes.select("ha", "hb", F.col("doc_id").alias("a")), ["ha", "hb"]).select("a", "b")


def near_duplicates(docs: DataFrame, p: MinHash = MinHash()) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_shingles, component_id, kept."""
    known = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), "text")
    sigs = staged(signatures(known, p))
    classes = staged(sigs.where("n_shingles > 0").groupBy("ha", "hb").agg(F.min(F.struct("doc_id", "n_shingles", "sig")).alias("r")).select("ha", "hb", "r.doc_id", F.col("r.n_shingles").alias("n"), "r.sig"))
    postings = staged(prefix_postings(classes, p))
    shards = max(1, math.ceil(postings.count() / 8192))
    first = staged(confirmed(known, trees(postings, p, shards), p))
    second = confirmed_across(known, postings, connected_components(first), p, shards)
    roots = connected_components(first.unionByName(second).unionByName(_repeated(sigs, classes)))
    rep = classes.select("ha", "hb", F.col("doc_id").alias("rep")).join(roots.select(F.col("node").alias("rep"), "root"), "rep", "left").select("ha", "hb", F.coalesce("root", "rep").alias("root"))
    out = sigs.select("doc_id", "n_shingles", "ha", "hb").join(rep, ["ha", "hb"], "left")
    component = F.coalesce("root", "doc_id")
    unknown = F.lit(NO_ID)
    return out.select(F.nullif("doc_id", unknown).alias("doc_id"), "n_shingles", F.nullif(component, unknown).alias("component_id"), (component == F.col("doc_id")).alias("kept"))
