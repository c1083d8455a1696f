"""Line dedup over sharded cuckoo filters with exact reference counts.

A line's key is the line stripped of ASCII blanks, A-Z lower-cased.  Keys of at least ``min_chars`` code points that are
found in at least ``min_docs`` documents lose all their lines, except in the largest doc_id that holds them.

Every key shard owns a cuckoo filter and an exact table.  A reference is (key, block of documents, number of documents,
largest of them).  A key that the filter has never seen is put aside without a look at anything; only one that it may
have seen is looked up, and the table holds those with two references or more.  Most lines occur once, so most never
reach the table, and the verdicts are read from the table (and from references that count enough alone).  Deletions go
the same way: references leave the table, and a key without any leaves the filter, so counts stay exact and taking out
what was put in gives back the same index, byte by byte.  References are folded inside a block, so a line that a third
of all documents hold costs a shard one of them a block.

Defined results: a null or empty text is one empty line; rows that repeat a doc_id count as documents of their own, and
the largest doc_id keeps the line in each of its rows; a null doc_id sorts below all others (as the least 64-bit integer
does); other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_128_digest

from .exchange import POSTING, carried, counts, empty, packed, scatter, unpacked, with_block
from .text import BLANKS, mix

#: Digests compare as 16 bytes; one that ends in zero bytes equals no shorter one, as all have 16.
KEY = np.dtype("S16")
REFERENCE = np.dtype([("key", KEY), ("block", "<i4"), ("docs", "<i4"), ("last", "<i8")])
#: References that a shard takes in at a time while it is built.
BATCH = 16_384
NO_ID = -(1 << 63)
_LOWER = str.maketrans({c: c + 32 for c in range(65, 91)})


def line_key(line: str) -> str:
    return line.strip(BLANKS).translate(_LOWER)


class CuckooFilter:
    """Approximate set of 64-bit hashes with deletion: 16-bit fingerprints, two buckets of four slots each.

    Bulk operations are vector steps: every round places one candidate for each bucket, and what finds both buckets
    full kicks a resident out.  insert() says whether all found a place; if not, the filter is to be built anew with
    more buckets by its owner, who knows the hashes.
    """

    SLOTS, KICKS, LOAD = 4, 200, 0.8

    def __init__(self, capacity: int, buckets: int | None = None) -> None:
        self.buckets = buckets or 1 << max(2, math.ceil(math.log2(max(1, capacity) / (self.SLOTS * self.LOAD))))
        self.table = np.zeros((self.buckets, self.SLOTS), np.uint16)
        self.size = 0

    def fits(self, more: int) -> bool:
        return self.size + more <= self.LOAD * self.SLOTS * self.buckets

    def _places(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        m = mix(h)
        f = ((m >> np.uint64(48)) % np.uint64(65535) + np.uint64(1)).astype(np.uint16)  # never 0, which marks a free slot
        i = (m & np.uint64(self.buckets - 1)).astype(np.int64)
        return f, i, self._other(f, i)

    def _other(self, f: np.ndarray, i: np.ndarray) -> np.ndarray:
        return i ^ (mix(f.astype(np.uint64)) & np.uint64(self.buckets - 1)).astype(np.int64)

    def contains(self, h: np.ndarray) -> np.ndarray:
        f, i, j = self._places(h)
        return (self.table[i] == f[:, None]).any(1) | (self.table[j] == f[:, None]).any(1)

    def insert(self, h: np.ndarray) -> bool:
        """Adds distinct hashes that are not in the set; their order does not matter to where they go."""
        f, i, j = self._places(h)
        at = np.minimum(i, j)
        order = np.lexsort((f, at))
        f, at = f[order], at[order]
        self.size += len(f)
        for turn in range(self.KICKS):
            if not len(f):
                return True
            first = np.unique(at, return_index=True)[1]  # one candidate a bucket in each round
            rows = self.table[at[first]]
            free = (rows == 0).any(1)
            put = first[free]
            self.table[at[put], (rows[free] == 0).argmax(1)] = f[put]
            keep = np.ones(len(f), bool)
            keep[put] = False
            if turn < 2:  # the others try their second bucket before anything is kicked out
                f, at = f[keep], at[keep]
                at = self._other(f, at) if turn == 0 else at
                continue
            kick = first[~free]
            slot = (turn + at[kick]) % self.SLOTS
            out, home = self.table[at[kick], slot].copy(), at[kick]
            self.table[home, slot] = f[kick]
            keep[kick] = False
            f, at = np.concatenate([f[keep], out]), np.concatenate([at[keep], self._other(out, home)])
        return not len(f)

    def delete(self, h: np.ndarray) -> None:
        """Takes out hashes that are in the set, one slot for each; vector steps over distinct slots."""
        f, i, j = self._places(h)
        for second in (False, True):
            while len(f):
                home = j if second else i
                hit = self.table[home] == f[:, None]
                there = np.flatnonzero(hit.any(1))
                slot = hit[there].argmax(1)
                first = np.unique(home[there] * self.SLOTS + slot, return_index=True)[1]  # two equal fingerprints take two slots
                if not len(first):
                    break
                done = there[first]
                self.table[home[done], slot[first]] = 0
                self.size -= len(done)
                keep = np.ones(len(f), bool)
                keep[done] = False
                f, i, j = f[keep], i[keep], j[keep]


class LineShard:
    """The filter and the exact references of one key shard.

    ``solo`` holds the only reference of a key, ``table`` those of keys that have several, both sorted by key and block.
    looked_up and spared count the keys for which the filter asked for a look, and those for which it did not.
    """

    def __init__(self, capacity: int = 64) -> None:
        self.filter = CuckooFilter(capacity)
        self.solo, self.table = _no_references(), _no_references()
        self.looked_up = self.spared = 0

    def insert(self, refs: np.ndarray) -> None:
        """Adds references; a (key, block) must not be there already."""
        refs = _ordered(refs)
        at, size = _runs(refs["key"])
        keys = refs["key"][at]
        known = self.filter.contains(_hash(keys))
        self.looked_up, self.spared = self.looked_up + int(known.sum()), self.spared + int((~known).sum())
        lone = np.zeros(len(keys), bool)  # may be known: the exact side decides
        lone[known] = _member(keys[known], self.solo["key"])
        known[known] = lone[known] | _member(keys[known], self.table["key"])
        self._remember(keys[~known])
        several = np.repeat(known | (size > 1), size)
        moved = _member(self.solo["key"], keys[lone])
        self.table = _ordered(np.concatenate([self.table, self.solo[moved], refs[several]]))
        self.solo = _ordered(np.concatenate([self.solo[~moved], refs[~several]]))

    def _remember(self, keys: np.ndarray) -> None:
        """Keys into the filter; a full one grows, and is filled anew from the exact side."""
        if self.filter.fits(len(keys)) and self.filter.insert(_hash(keys)):
            return
        self._rebuilt(np.concatenate([self.keys(), keys]))

    def _rebuilt(self, keys: np.ndarray) -> None:
        """The filter laid out anew: it depends on the set of keys alone."""
        buckets = CuckooFilter(len(keys)).buckets
        while True:
            self.filter = CuckooFilter(0, buckets)
            if self.filter.insert(_hash(keys)):
                return
            buckets *= 2

    def keys(self) -> np.ndarray:
        """Every key once."""
        return np.concatenate([self.solo["key"], self.table["key"][_runs(self.table["key"])[0]]])

    def delete(self, blocks: np.ndarray) -> None:
        """Takes out all references of these blocks; keys without any left leave the filter."""
        before = self.keys()
        every = np.concatenate([self.solo, self.table])
        every = _ordered(every[~np.isin(every["block"], blocks)])
        at, size = _runs(every["key"])
        several = np.repeat(size > 1, size)
        self.solo, self.table = every[~several], every[several]
        self.filter.delete(_hash(before[~_member(before, every["key"][at])]))

    def common(self, min_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(blocks, keys, largest doc_id) of every reference to a key found in at least min_docs documents."""
        t = np.concatenate([self.table, self.solo[self.solo["docs"] >= min_docs]])
        at, size = _runs(t["key"])
        if not len(at):
            return t["block"], t["key"], t["last"]
        total, last = np.add.reduceat(t["docs"].astype(np.int64), at), np.maximum.reduceat(t["last"], at)
        pick = np.repeat(total >= min_docs, size)
        return t["block"][pick], t["key"][pick], np.repeat(last, size)[pick]

    def state(self) -> tuple[bytes, bytes]:
        """(filter, references): the same bytes for the same references, whatever came and went before."""
        self._rebuilt(self.keys())
        return self.filter.table.tobytes(), _ordered(np.concatenate([self.solo, self.table])).tobytes()

    @staticmethod
    def of(state: tuple[bytes, bytes]) -> LineShard:
        out, refs = LineShard(), np.frombuffer(state[1], REFERENCE)
        out.filter = CuckooFilter(0, len(state[0]) // (2 * CuckooFilter.SLOTS))
        out.filter.table = np.frombuffer(state[0], np.uint16).reshape(-1, CuckooFilter.SLOTS).copy()
        out.filter.size = int((out.filter.table > 0).sum())
        several = np.repeat((size := _runs(refs["key"])[1]) > 1, size)
        out.solo, out.table = refs[~several], refs[several]
        return out


def _no_references() -> np.ndarray:
    return np.empty(0, REFERENCE)


def _ordered(refs: np.ndarray) -> np.ndarray:
    half = np.ascontiguousarray(refs["key"]).view("<u8").reshape(-1, 2)
    return refs[np.lexsort((refs["block"], half[:, 1].byteswap(), half[:, 0].byteswap()))]  # as bytes compare


def _runs(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first index, length) of the runs of equal keys."""
    if not len(keys):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    at = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    return at, np.diff(np.append(at, len(keys)))


def _member(keys: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Mask of the keys that are in the sorted array ``of``."""
    if not len(of) or not len(keys):
        return np.zeros(len(keys), bool)
    return of[np.minimum(np.searchsorted(of, keys), len(of) - 1)] == keys


def _hash(keys: np.ndarray) -> np.ndarray:
    half = np.ascontiguousarray(keys).view("<u8").reshape(-1, 2)
    return half[:, 0] ^ mix(half[:, 1])


def _long_keys(text: str | None, min_chars: int) -> tuple[list[str], list[bytes | None]]:
    """The lines of a text, and for each the digest of its key, or None below min_chars."""
    lines = (text or "").split("\n")
    out: list[bytes | None] = []
    for line in lines:
        key = line_key(line) if len(line) >= min_chars else ""
        out.append(xxh3_128_digest(key.encode("utf-8", "surrogatepass")) if len(key) >= min_chars else None)
    return lines, out


def postings(docs: DataFrame, shards: int, min_chars: int = 20) -> DataFrame:
    """docs(doc_id, text, _block) -> packed references of each block for each shard."""

    def run(table: pa.Table) -> pa.Table:
        held: dict[bytes, list[int]] = {}
        for doc, text in zip(table.column("doc_id").to_pylist(), table.column("text"), strict=True):
            doc = NO_ID if doc is None else doc
            for key in {k for k in _long_keys(text.as_py(), min_chars)[1] if k}:
                ref = held.setdefault(key, [0, doc])
                ref[0] += 1
                ref[1] = max(ref[1], doc)
        if not held:
            return empty()
        keys = np.frombuffer(b"".join(held), KEY)
        refs = np.array(list(held.values()), np.int64)
        return scatter(table.column("_block")[0].as_py(), keys.view("<u8")[::2], [keys, refs[:, 0].astype("<i4"), refs[:, 1]], shards)

    return docs.groupBy("_block").applyInArrow(run, POSTING)


def _references(table: pa.Table) -> np.ndarray:
    blocks, (keys, n, last) = unpacked(table, [KEY, "<i4", "<i8"], "_block")
    refs = np.empty(len(keys), REFERENCE)
    refs["key"], refs["block"], refs["docs"], refs["last"] = keys, blocks, n, last
    return refs


def _filled(shard: LineShard, refs: np.ndarray) -> LineShard:
    """The shard with more references, taken in by batches, block after block."""
    refs = refs[np.argsort(refs["block"], kind="stable")]
    step = max(BATCH, len(refs) // 8)
    for at in range(0, len(refs), step):
        shard.insert(refs[at : at + step])
    return shard


def verdicts(references: DataFrame, min_docs: int) -> DataFrame:
    """Packed references -> for each block the common keys that it holds, with the largest doc_id of each."""

    def run(table: pa.Table) -> pa.Table:
        return _verdict(_filled(LineShard(), _references(table)), table.column("_shard")[0].as_py(), min_docs)

    return references.groupBy("_shard").applyInArrow(run, POSTING)


def _verdict(shard: LineShard, number: int, min_docs: int) -> pa.Table:
    blocks, keys, last = shard.common(min_docs)
    if not len(keys):
        return empty()
    order = np.argsort(blocks, kind="stable")
    return packed(blocks[order], [keys[order], last[order]], "_block", {"_shard": number})


def line_dedup(docs: DataFrame, min_chars: int = 20, min_docs: int = 3, keep: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_lines (before), n_dropped, kept_text, and with ``keep`` the other columns."""
    blocks, shards = counts(docs)
    rows, others, schema = carried(docs, keep)
    dealt = with_block(rows, blocks)
    return _without(dealt, verdicts(postings(dealt, shards, min_chars), min_docs), min_chars, others, schema)


def _without(dealt: DataFrame, verdict: DataFrame, min_chars: int, others: list[str], schema: str) -> DataFrame:
    """The dealt documents without the lines that the verdicts take from them."""

    def run(docs: pa.Table, verdict: pa.Table) -> pa.Table:
        _, (keys, last) = unpacked(verdict, [KEY, "<i8"], "_block")
        raw = keys.tobytes()
        common = {raw[16 * i : 16 * i + 16]: d for i, d in enumerate(last.tolist())}
        n_lines, n_dropped, kept = [], [], []
        for doc, text in zip(docs.column("doc_id").to_pylist(), docs.column("text"), strict=True):
            doc = NO_ID if doc is None else doc
            lines, own = _long_keys(text.as_py(), min_chars)
            stay = [x for x, k in zip(lines, own, strict=True) if k is None or common.get(k, doc) == doc]
            n_lines.append(len(lines))
            n_dropped.append(len(lines) - len(stay))
            kept.append("\n".join(stay))
        return pa.table({"doc_id": docs.column("doc_id"), "n_lines": pa.array(n_lines, pa.int64()), "n_dropped": pa.array(n_dropped, pa.int64()), "kept_text": pa.array(kept, pa.string())} | {c: docs.column(c) for c in others})

    kind = dealt.schema["doc_id"].dataType.simpleString()
    return dealt.groupBy("_block").cogroup(verdict.groupBy("_block")).applyInArrow(run, f"doc_id {kind}, n_lines long, n_dropped long, kept_text string{schema}")


# The index as a table, one row for each shard: what incremental runs keep between batches of documents.

INDEX = "_shard int, filter binary, refs binary"


def _index_row(number: int, shard: LineShard) -> pa.Table:
    own = shard.state()
    return pa.table({"_shard": pa.array([number], pa.int32()), "filter": pa.array([own[0]], pa.binary()), "refs": pa.array([own[1]], pa.binary())})


def build_index(docs: DataFrame, blocks: int, shards: int, min_chars: int = 20) -> DataFrame:
    """The filter and the references of every shard that has any; write it to keep it."""

    def run(table: pa.Table) -> pa.Table:
        return _index_row(table.column("_shard")[0].as_py(), _filled(LineShard(), _references(table)))

    return postings(with_block(docs.select("doc_id", "text"), blocks), shards, min_chars).groupBy("_shard").applyInArrow(run, INDEX)


def update_index(index: DataFrame, docs: DataFrame, changed: DataFrame, blocks: int, shards: int, min_chars: int = 20) -> DataFrame:
    """The index after documents were added to or deleted from ``docs`` (the corpus as it now is).

    changed(doc_id, text): the rows that came or went.  Only their blocks are read anew: every shard takes the old
    references of these blocks out of its table and filter and puts the new ones in.  All other references stay, so
    deleting what was inserted gives back the index as it was.
    """
    touched = with_block(changed.select("doc_id", "text"), blocks).select("_block").distinct()
    fresh = postings(with_block(docs.select("doc_id", "text"), blocks).join(touched, "_block", "left_semi").select("doc_id", "text", "_block"), shards, min_chars)
    gone = touched.agg(F.collect_list("_block").alias("_gone"))  # one row, with as many numbers as blocks are touched
    kept = index.crossJoin(F.broadcast(gone)).mapInArrow(_trimmed, INDEX)

    def run(old: pa.Table, fresh: pa.Table) -> pa.Table:
        if not fresh.num_rows:
            return old
        shard = _loaded(old) if old.num_rows else LineShard()
        return _index_row(fresh.column("_shard")[0].as_py(), _filled(shard, _references(fresh)))

    return kept.groupBy("_shard").cogroup(fresh.groupBy("_shard")).applyInArrow(run, INDEX)


def _loaded(row: pa.Table | pa.RecordBatch) -> LineShard:
    return LineShard.of((row.column("filter")[0].as_py(), row.column("refs")[0].as_py()))


def _trimmed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Index rows without the references of the blocks in ``_gone``; shards without any reference go."""
    for b in batches:
        for i in range(b.num_rows):
            row = b.slice(i, 1)
            shard = _loaded(row)
            shard.delete(np.array(row.column("_gone")[0].as_py(), np.int64))
            if len(shard.solo) + len(shard.table):
                yield from _index_row(row.column("_shard")[0].as_py(), shard).to_batches()


def dedup_with(index: DataFrame, docs: DataFrame, blocks: int, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """docs without their common lines, by an index of them: doc_id, n_lines, n_dropped, kept_text."""

    def run(table: pa.Table) -> pa.Table:
        return _verdict(_loaded(table), table.column("_shard")[0].as_py(), min_docs)

    return _without(with_block(docs.select("doc_id", "text"), blocks), index.groupBy("_shard").applyInArrow(run, POSTING), min_chars, [], "")
