"""Substring dedup by difference-cover anchors.

A window is ``window`` consecutive words of one document; a word goes if some window over it has the same words as a
window that starts earlier (smaller doc_id, or earlier in the same document).

Positions are taken modulo ``period``, and only short anchors that begin at a position of the difference cover are
hashed for the whole corpus.  For any two offsets the cover holds a common shift, so two equal windows share an anchor
that is aligned alike in both, wherever they begin.  Anchors that occur once rule out all windows over them; only around
the others are full windows hashed (96 bits) and their first occurrences looked up.  Both lookups are folded inside
blocks of documents, so a passage that a third of all documents share costs one posting a block.

Defined results: a null or blank text has no words and loses nothing; rows that repeat a doc_id are documents of their
own, in one fixed order among them (by block, then by text); a null doc_id sorts before all others, as the least 64-bit
integer does; other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .exchange import POSTING, carried, counts, empty, packed, scatter, unpacked, with_block
from .text import among, covered, grouped, mix, windows, word_hashes, words

NO_ID = -(1 << 63)
_LOW = np.uint64((1 << 24) - 1)


@dataclass(frozen=True)
class Cover:
    """anchor + period - 1 must not exceed window, and every difference modulo period must occur in cover."""

    window: int = 20
    anchor: int = 8
    period: int = 13
    cover: tuple[int, ...] = (0, 1, 3, 9)

    def __post_init__(self) -> None:
        if self.anchor + self.period - 1 > self.window or {(a - b) % self.period for a in self.cover for b in self.cover} != set(range(self.period)):
            raise ValueError("not a difference cover for this window")


class _Block:
    """The words of a block's documents end to end, in the order (doc_id, text), with their hashes."""

    def __init__(self, table: pa.Table, cover: Cover) -> None:
        ids = [NO_ID if x is None else x for x in table.column("doc_id").to_pylist()]
        texts = [x.as_py() or "" for x in table.column("text")]
        self.order = sorted(range(len(ids)), key=lambda i: (ids[i], texts[i]))
        self.texts = [texts[i] for i in self.order]
        self.cover, hashes = cover, []
        for text in self.texts:
            hashes.append(word_hashes(words(text)))
        self.sizes = np.array([len(h) for h in hashes], np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.sizes)[:-1]]).astype(np.int64)
        self.hashes = np.concatenate(hashes) if hashes else np.empty(0, np.uint64)
        self.docs = np.array([ids[i] for i in self.order], np.int64)

    def _begins(self, width: int) -> tuple[np.ndarray, np.ndarray]:
        """Begins of all runs of ``width`` words inside one document, and the documents' numbers."""
        n = np.maximum(self.sizes - width + 1, 0)
        doc = np.repeat(np.arange(len(n)), n)
        skipped = np.concatenate([[0], np.cumsum(n)[:-1]])
        return np.arange(n.sum()) - skipped[doc] + self.starts[doc], doc

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """(begin, hash) of every anchor at a cover position, in documents long enough for a window."""
        at, doc = self._begins(self.cover.anchor)
        phase = (at - self.starts[doc]) % self.cover.period
        at = at[np.isin(phase, self.cover.cover) & (self.sizes[doc] >= self.cover.window)]
        return at, mix(windows(self.hashes, self.cover.anchor)[at]) if len(at) else np.empty(0, np.uint64)

    def candidates(self, shared: np.ndarray) -> np.ndarray:
        """Begins of the windows over at least one of the anchors that begin at ``shared``."""
        if not len(shared):
            return shared
        begins, _ = self._begins(self.cover.window)
        # an anchor at p is aligned in the windows that begin at p - period + 1 .. p
        near = np.zeros(len(self.hashes) + 1, np.int64)
        np.add.at(near, np.maximum(shared - self.cover.period + 1, 0), 1)
        np.subtract.at(near, shared + 1, 1)
        return begins[np.cumsum(near)[begins] > 0]

    def window_keys(self, begins: np.ndarray) -> np.ndarray:
        """96 bits of two independent hashes of the windows at begins."""
        out = np.empty(len(begins), KEY)
        if len(begins):
            out["a"] = mix(windows(self.hashes, self.cover.window)[begins])
            out["b"] = mix(windows(mix(self.hashes), self.cover.window, 0xD6E8FEB86659FD93)[begins]) >> np.uint64(32)
        return out


    def removed(self, elsewhere: np.ndarray) -> np.ndarray:
        """Mask of the words covered by a window found earlier in the block, or before the block (``elsewhere``)."""
        begins, _ = self._begins(self.cover.window)
        if not len(begins):
            return np.zeros(len(self.hashes), bool)
        a = mix(windows(self.hashes, self.cover.window)[begins])
        begins = begins[_found_twice(a) | _member(a, np.sort(elsewhere["a"]))]
        keys = self.window_keys(begins)
        again = np.ones(len(keys), bool)
        again[grouped(keys)[0]] = False
        return covered(begins[again | among(keys, elsewhere)], self.cover.window, len(self.hashes))


KEY = np.dtype([("a", "<u8"), ("b", "<u4")])


def _short(h: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """An anchor's shard and the 40 bits of its hash that travel: a false match only costs a needless window."""
    return (h & _LOW) % np.uint64(shards), (h >> np.uint64(32)).astype("<u4"), ((h >> np.uint64(24)) & np.uint64(255)).astype("u1")


def _joined(shard: np.ndarray, high: np.ndarray, low: np.ndarray) -> np.ndarray:
    return (high.astype(np.uint64) << np.uint64(32)) | (low.astype(np.uint64) << np.uint64(24)) | shard.astype(np.uint64)


def _member(values: np.ndarray, of: np.ndarray) -> np.ndarray:
    """values in the sorted array ``of``."""
    if not len(of):
        return np.zeros(len(values), bool)
    return of[np.minimum(np.searchsorted(of, values), len(of) - 1)] == values


def _shared_anchors(block: _Block, verdict: pa.Table, shards: int) -> np.ndarray:
    """Begins of the anchors found twice in the block, or in another block as well."""
    at, h = block.anchors()
    own = _joined(*_short(h, shards))
    _, back, n = np.unique(own, return_inverse=True, return_counts=True)
    shard, (high, low) = unpacked(verdict, ["<u4", "u1"], "_shard")
    return at[(n[back] > 1) | _member(own, np.sort(_joined(shard, high, low)))]


def _found_twice(keys: np.ndarray) -> np.ndarray:
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    same = np.zeros(len(k), bool)
    same[1:] = k[1:] == k[:-1]
    same[:-1] |= same[1:]
    out = np.empty(len(k), bool)
    out[order] = same
    return out


def substring_dedup(docs: DataFrame, cover: Cover = Cover(), keep: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_words, n_removed, kept_words (kept words joined by one blank), kept_text.

    kept_text is the text as it was if nothing was removed; else each kept word with the blanks before it.
    keep: the other columns as well.
    """
    blocks, shards = counts(docs)
    rows, others, schema = carried(docs, keep)
    dealt = with_block(rows, blocks)
    by_block = dealt.groupBy("_block")

    def post_anchors(table: pa.Table) -> pa.Table:
        _, h = _Block(table, cover).anchors()
        shard, high, low = _short(h, shards)
        _, first = np.unique(_joined(shard, high, low), return_index=True)
        return scatter(table.column("_block")[0].as_py(), shard[first], [high[first], low[first]], shards) if len(first) else empty()

    def match_anchors(table: pa.Table) -> pa.Table:
        owner, (high, low) = unpacked(table, ["<u4", "u1"], "_block")
        twice = _found_twice(_joined(np.zeros(len(high)), high, low))  # a block posts an anchor once
        owner, high, low = owner[twice], high[twice], low[twice]
        order = np.argsort(owner, kind="stable")
        return packed(owner[order], [high[order], low[order]], "_block", {"_shard": table.column("_shard")[0].as_py()}) if len(order) else empty()

    def post_windows(table: pa.Table, verdict: pa.Table) -> pa.Table:
        if not table.num_rows:
            return empty()
        block = _Block(table, cover)
        begins = block.candidates(_shared_anchors(block, verdict, shards))
        keys = block.window_keys(begins)
        first, _ = grouped(keys)  # the first in the block's order
        if not len(first):
            return empty()
        doc = block.docs[np.searchsorted(block.starts, begins[first], side="right") - 1]
        return scatter(table.column("_block")[0].as_py(), keys["a"][first], [keys[first], doc.astype("<i8")], shards)

    def match_windows(table: pa.Table) -> pa.Table:
        owner, (keys, doc) = unpacked(table, [KEY, "<i8"], "_block")
        order = np.lexsort((owner, doc, keys["b"], keys["a"]))
        keys, owner = keys[order], owner[order]
        later = np.zeros(len(keys), bool)
        later[1:] = keys[1:] == keys[:-1]  # a block has one posting of a window, and the first is the smallest doc_id
        keys, owner = keys[later], owner[later]
        order = np.argsort(owner, kind="stable")
        return packed(owner[order], [keys[order]], "_block", {"_shard": table.column("_shard")[0].as_py()}) if len(order) else empty()

    def remove(table: pa.Table, later: pa.Table) -> pa.Table:
        block = _Block(table, cover)
        gone = block.removed(unpacked(later, [KEY], "_block")[1][0])
        n_removed, kept_words, kept_text = [], [], []
        for text, at, n in zip(block.texts, block.starts, block.sizes, strict=True):
            out = gone[at : at + n]
            n_removed.append(int(out.sum()))
            tokens = words(text)
            kept_words.append(b" ".join([w for w, x in zip(tokens, out.tolist(), strict=True) if not x] if n_removed[-1] else tokens).decode("utf-8", "surrogatepass"))
            kept_text.append(_without(text, out) if n_removed[-1] else text)
        order = pa.array(block.order, pa.int64())
        return pa.table({"doc_id": table.column("doc_id").take(order), "n_words": pa.array(block.sizes), "n_removed": pa.array(n_removed, pa.int64()), "kept_words": pa.array(kept_words, pa.string()), "kept_text": pa.array(kept_text, pa.string())} | {c: table.column(c).take(order) for c in others})

    shared = by_block.applyInArrow(post_anchors, POSTING).groupBy("_shard").applyInArrow(match_anchors, POSTING)
    later = by_block.cogroup(shared.groupBy("_block")).applyInArrow(post_windows, POSTING).groupBy("_shard").applyInArrow(match_windows, POSTING)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return by_block.cogroup(later.groupBy("_block")).applyInArrow(remove, f"doc_id {kind}, n_words long, n_removed long, kept_words string, kept_text string{schema}")


_WORD = re.compile(rb"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+")


def _without(text: str, gone: np.ndarray) -> str:
    """The text without the words in ``gone`` and the blanks before each of them."""
    raw = text.encode("utf-8", "surrogatepass")
    return b"".join(m for m, x in zip(_WORD.findall(raw), gone.tolist(), strict=True) if not x).decode("utf-8", "surrogatepass")
