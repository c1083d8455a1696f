"""Best-fit packing by patterns: non-negative least squares on the histogram of piece lengths.

Documents are tokenized and, where longer than a sequence, cut.  Only the histogram of lengths (at most one entry for
each length up to the capacity) reaches the driver.  There, patterns of a few lengths that fill a sequence exactly are
enumerated, repeat counts are fitted to the histogram by non-negative least squares, rounded, and what they leave is
packed best-fit decreasing, also by counts.  The plan says, for each length, which runs of ranks go to which sequences
and offsets; every piece then finds its place from its rank among the pieces of its length.

Defined results: a null text is an empty one (one piece with the end token); rows that repeat a doc_id are packed each;
other columns are ignored; an empty table packs into no sequence.
"""

from __future__ import annotations

import json
import re
import zlib
from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .exchange import ranked, staged

#: How the byte-level vocabulary splits text before merging.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
CAPACITY, END = 1024, 2
#: Runs this long without (or of) blanks go to the library that merges with a heap; the other is quadratic in a run.
_LONG_RUN = re.compile(r"\S{2048}|\s{2048}")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class ByteTokenizer:
    """Ids as the tokenizers library gives them for a byte-level BPE file, by the faster merge loop where it is safe."""

    def __init__(self, path: str) -> None:
        import tiktoken

        self.path, self.slow = path, None
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves
        byte_of = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(plain))}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(byte_of[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
        self.fast = tiktoken.Encoding("file", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens=special)

    def encode(self, text: str) -> list[int]:
        if not _LONG_RUN.search(text):
            return self.fast.encode(text, allowed_special="all")
        if self.slow is None:
            from tokenizers import Tokenizer

            self.slow = Tokenizer.from_file(self.path)
        return self.slow.encode(text, add_special_tokens=False).ids


def cuts(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: whole sequences, after a shorter first piece if any."""
    head = n if n <= capacity else n % capacity or capacity
    return [(0, head), *((at, capacity) for at in range(head, n, capacity))]


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END, with_ids: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32 (and ids on request)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = ByteTokenizer(tokenizer)
        for b in batches:
            doc, piece, start, length, crc, ids = [], [], [], [], [], []
            for i, text in enumerate(b.column(1)):
                own = np.array([*tok.encode(text.as_py() or ""), end], "<u4")
                for k, (at, n) in enumerate(cuts(len(own), capacity)):
                    doc.append(i)
                    piece.append(k)
                    start.append(at)
                    length.append(n)
                    crc.append(zlib.crc32(own[at : at + n].tobytes()))
                    if with_ids:
                        ids.append(own[at : at + n].astype(np.int32))
            out = {"doc_id": b.column(0).take(pa.array(doc, pa.int64())), "piece": pa.array(piece, pa.int32()), "start": pa.array(start, pa.int64()), "length": pa.array(length, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())}
            yield pa.RecordBatch.from_pydict(out | ({"ids": pa.array(ids, pa.list_(pa.int32()))} if with_ids else {}))

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids)


def fills(lengths: list[int], capacity: int) -> np.ndarray:
    """All patterns of two or three of the lengths that fill the capacity exactly, as rows (0 for no third)."""
    there = np.zeros(capacity + 1, bool)
    there[lengths] = True
    own = np.array(sorted(lengths))
    out = []
    for a in own:
        b = own[own >= a]
        rest = capacity - a - b
        ok = (rest >= b) & there[np.maximum(rest, 0)] & (rest > 0)
        out += [np.stack([np.full(ok.sum(), a), b[ok], rest[ok]], 1)]
        if 2 * a <= capacity and there[capacity - a]:
            out += [np.array([[a, capacity - a, 0]])]
    return np.concatenate(out) if out else np.empty((0, 3), np.int64)


def nnls(patterns: np.ndarray, target: np.ndarray, rounds: int = 300) -> np.ndarray:
    """Repeat counts x >= 0 that bring the lengths used by the patterns near the target, by accelerated projection."""
    width = len(target)

    def used(x: np.ndarray) -> np.ndarray:
        out = sum(np.bincount(patterns[:, k], x, width) for k in range(3))
        out[0] = 0
        return out

    def back(r: np.ndarray) -> np.ndarray:
        r = r.copy()
        r[0] = 0
        return r[patterns].sum(1)

    step = 1 / max(back(used(np.ones(len(patterns)))).max(), 1)  # the row sums of the normal matrix bound its norm
    x = y = np.zeros(len(patterns))
    t = 1.0
    for _ in range(rounds):
        new = np.maximum(y + step * back(target - used(y)), 0)
        t, old = (1 + np.sqrt(1 + 4 * t * t)) / 2, t
        x, y = new, new + (old - 1) / t * (new - x)
    return x


def best_fit(left: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit decreasing on counts: (pattern, repeats) with equal sequences handled as one."""
    rooms: dict[int, dict[tuple[int, ...], int]] = defaultdict(dict)
    sizes: list[int] = []  # rooms that have sequences, ascending

    def put(room: int, pattern: tuple[int, ...], n: int) -> None:
        if not rooms[room]:
            sizes.insert(bisect_left(sizes, room), room)
        rooms[room][pattern] = rooms[room].get(pattern, 0) + n

    for length in sorted(left, reverse=True):
        n = left[length]
        while n and (at := bisect_left(sizes, length)) < len(sizes):
            room = sizes[at]
            pattern, there = rooms[room].popitem()
            if not rooms[room]:
                sizes.pop(at)
            k = min(n, there)
            if there > k:
                put(room, pattern, there - k)
            put(room - length, (*pattern, length), k)
            n -= k
        if n:
            each = capacity // length
            if n // each:
                put(capacity - each * length, (length,) * each, n // each)
            if n % each:
                put(capacity - n % each * length, (length,) * (n % each), 1)
    return [(p, n) for by in rooms.values() for p, n in by.items()]


def fitted(histogram: dict[int, int], capacity: int, most: int) -> list[tuple[tuple[int, ...], int]]:
    """A plan whose exact patterns have at most ``most`` pieces: pairs are fitted first, triples to what they leave."""
    left, out = dict(histogram), []
    found = fills(list(left), capacity) if left else np.empty((0, 3), np.int64)
    pairs = found[:, 2] == 0
    for patterns in [found[pairs], found[~pairs]][: most - 1]:
        if not len(patterns):
            continue
        target = np.zeros(capacity + 1)
        target[list(left)] = list(left.values())
        x = nnls(patterns, target)
        for i in np.lexsort((-x, -patterns.max(1))):
            pattern = tuple(int(v) for v in patterns[i] if v)
            need = {v: pattern.count(v) for v in pattern}
            k = min(int(x[i] + 0.5), *(left[v] // c for v, c in need.items()))
            if k > 0:
                out.append((pattern, k))
                for v, c in need.items():
                    left[v] -= k * c
    return out + best_fit({k: v for k, v in left.items() if v}, capacity)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """(pattern, repeats) that use up the histogram {length: pieces} exactly.

    Exact triples save sequences where pieces are short, and cost some where they take the pieces that large ones need;
    both fits are made and the one with fewer sequences is taken.
    """
    short = {k: v for k, v in histogram.items() if v and k < capacity}
    best = min((fitted(short, capacity, most) for most in (2, 3)), key=lambda x: sum(n for _, n in x))
    return ([((capacity,), histogram[capacity])] if histogram.get(capacity) else []) + best


def places(planned: list[tuple[tuple[int, ...], int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, sequence, offset) of every run of ranks, sorted by key = length * 2**40 + first rank."""
    taken: dict[int, int] = defaultdict(int)
    rows, sequence = [], 0
    for pattern, n in planned:
        offset = 0
        for length in pattern:
            rows.append(((length << 40) + taken[length], sequence, offset))
            taken[length] += n
            offset += length
        sequence += n
    rows.sort()
    out = np.array(rows, np.int64).reshape(-1, 3)
    return out[:, 0], out[:, 1], out[:, 2]


def pack(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, end: int = END, with_ids: bool = False) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids on request)."""
    cut = staged(pieces(docs, tokenizer or default_tokenizer(), capacity, end, with_ids))
    histogram = {r["length"]: r["count"] for r in cut.groupBy("length").count().collect()}  # at most ``capacity`` rows
    key, sequence, offset = places(plan(histogram, capacity))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            own = (b.column("length").to_numpy() << 40) + b.column("_rank").to_numpy()
            at = np.searchsorted(key, own, side="right") - 1
            cols = {n: b.column(n) for n in names}
            yield pa.RecordBatch.from_pydict(cols | {"sequence_id": pa.array(sequence[at] + own - key[at]), "offset": pa.array(offset[at])})

    names = cut.columns
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in cut.schema) + ", sequence_id long, offset long"
    return ranked(cut, "length", ["doc_id", "piece"], "_rank").mapInArrow(run, schema)
