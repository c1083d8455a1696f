"""SentencePiece encoding and decoding by suffix-array matching.

The distinct segments of a batch (runs of the blank mark and the characters after them, which no piece crosses) are
concatenated, and the suffixes are sorted by as many symbols as the longest piece has.  Every piece is binary-searched
for the range of suffixes that begin with it; the ranges give all (begin, end, piece) edges, which are sorted by end
and relaxed in that order for all segments at once:

* unigram models: the best sum of scores at each position;
* BPE models: the merge order leaves exactly one last piece for each prefix.  An edge is taken if its piece stays apart
  from the last piece before it under the merge order, which is decided from the pieces' own merge histories.

Pieces of blanks share one score, which leaves no merge order among them: a segment that begins with two blanks or more
is merged by a heap instead, in n log n steps.  Characters that no piece covers become byte pieces.  Decoding joins
pieces and bytes back.  Ids equal those of the sentencepiece library.  Defined results: a null text is an empty one and
has no ids; rows are encoded one by one, so repeated ids or rows get one result each; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLANK = "▁"
_SEGMENT = re.compile(f"{BLANK}*[^{BLANK}]+|{BLANK}+")
_SEPARATOR = "\ud800"  # never in a text
ROWS, CACHE, MEMO_BITS = 1024, 250_000, 21
START, NONE = -1, -2


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def merges(symbols: list[str], score: dict[str, float]) -> list[str]:
    """Plain BPE: the pair with the best score first, the leftmost of equals; n log n steps by a heap and links."""
    symbols = list(symbols)
    n = len(symbols)
    after, before = [*range(1, n), -1], [-1, *range(n - 1)]  # of the symbols that are left

    def entry(i: int) -> list[tuple[float, int, str, str]]:
        j = after[i]
        best = score.get(symbols[i] + symbols[j]) if j >= 0 else None
        return [] if best is None else [(-best, i, symbols[i], symbols[j])]

    heap = [e for i in range(n - 1) for e in entry(i)]
    heapify(heap)
    while heap:
        _, i, a, b = heappop(heap)
        j = after[i]
        if j < 0 or symbols[i] != a or symbols[j] != b:
            continue  # one of the two has been merged since
        symbols[i], symbols[j] = a + b, ""
        after[i] = after[j]
        if after[j] >= 0:
            before[after[j]] = i
        for e in entry(i) + (entry(before[i]) if before[i] >= 0 else []):
            heappush(heap, e)
    return [x for x in symbols if x]


class Pieces:
    """A model's pieces: their ids, scores and, for BPE, merge histories."""

    def __init__(self, path: str, algorithm: str = "bpe", proto: bytes | None = None) -> None:
        import sentencepiece

        self.lib = sentencepiece.SentencePieceProcessor(model_proto=proto) if proto else sentencepiece.SentencePieceProcessor(model_file=path)
        self.algorithm, sp = algorithm, self.lib
        every = range(sp.get_piece_size())
        plain = [i for i in every if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.bytes = {int(sp.id_to_piece(i)[3:-1], 16): i for i in every if sp.is_byte(i)}
        self.ids = {sp.id_to_piece(i): i for i in plain}
        self.score = {p: sp.get_score(i) for p, i in self.ids.items()}
        self.table = [bytes([int(sp.id_to_piece(i)[3:-1], 16)]) if sp.is_byte(i) else b"" if sp.is_control(i) else sp.id_to_piece(i).replace(BLANK, " ").encode() for i in every]
        self.longest = max(map(len, self.ids))
        # ranks: single characters first, then merged pieces in the order in which they merge
        by_rank = sorted(self.ids, key=lambda p: (len(p) > 1, -self.score[p]))
        self.names, self.rank = by_rank, {p: r for r, p in enumerate(by_rank)}
        self.id_of = np.array([self.ids[p] for p in by_rank], np.int32)
        self.scores = np.array([self.score[p] for p in by_rank])
        self.size = np.array([len(p) for p in by_rank], np.int64)
        self.codes = np.zeros((len(by_rank), self.longest), np.uint32)
        for r, p in enumerate(by_rank):
            self.codes[r, : len(p)] = [ord(c) for c in p]
        self.usable = np.ones(len(by_rank), bool)
        if algorithm == "bpe":
            self._histories()
        self.memo_key, self.memo = np.full(1 << MEMO_BITS, -1, np.int64), np.zeros(1 << MEMO_BITS, bool)

    def _histories(self) -> None:
        """left, right: the last merge of each piece (itself for one character); pairs: what two pieces merge into."""
        n = len(self.names)
        self.left, self.right = np.arange(n), np.arange(n)
        keys, made = [], []
        for r, p in enumerate(self.names):
            if len(p) == 1:
                continue
            for k in range(1, len(p)):
                a, b = self.rank.get(p[:k]), self.rank.get(p[k:])
                if a is not None and b is not None:
                    keys.append(a * n + b)
                    made.append(r)
            halves = merges(list(p), {q: s for q, s in ((p[i:j], self.score.get(p[i:j])) for i in range(len(p)) for j in range(i + 2, len(p) + 1)) if s is not None and q != p})
            if len(halves) == 2:
                self.left[r], self.right[r] = self.rank[halves[0]], self.rank[halves[1]]
            else:
                self.usable[r] = False  # merging its characters never ends in this piece
        order = np.argsort(keys)
        self.pair_key, self.pair_rank = np.array(keys, np.int64)[order], np.array(made, np.int64)[order]

    def _merged(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        key = x * len(self.names) + y
        at = np.minimum(np.searchsorted(self.pair_key, key), len(self.pair_key) - 1)
        return np.where(self.pair_key[at] == key, self.pair_rank[at], np.iinfo(np.int64).max)

    def _apart(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether two adjacent pieces stay apart: undo merges, latest first, and see if an earlier one crosses the seam."""
        out = np.zeros(len(x), bool)
        live, limit = np.arange(len(x)), np.full(len(x), np.iinfo(np.int64).max)
        x, y = x.copy(), y.copy()
        while len(live):
            stays = self._merged(x, y) >= limit
            live, x, y, limit = live[stays], x[stays], y[stays], limit[stays]
            first = x > y  # which of the two was merged last, and can it be undone
            down_x, down_y = self.right[x], self.left[y]
            take_x = np.where(first, down_x != x, down_y == y)
            over = np.where(take_x, down_x == x, down_y == y)
            limit = np.where(take_x, x, y + 1)
            x, y = np.where(take_x, down_x, x), np.where(take_x, y, down_y)
            out[live[over]] = True
            live, x, y, limit = live[~over], x[~over], y[~over], limit[~over]
        return out

    def apart(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The same, by a direct-mapped memo: few pairs make up most of any text."""
        key = x * len(self.names) + y
        slot = ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - MEMO_BITS)).astype(np.int64)
        new = self.memo_key[slot] != key
        out = self.memo[slot]
        if new.any():
            fresh, at = np.unique(key[new], return_inverse=True)
            value = self._apart(fresh // len(self.names), fresh % len(self.names))
            out[new] = value[at]
            self.memo_key[slot[new]], self.memo[slot[new]] = key[new], value[at]
        return out


class Codec:
    """Encodes and decodes with one model; keeps the ids of recent segments."""

    def __init__(self, path: str | None = None, algorithm: str = "bpe", proto: bytes | None = None) -> None:
        self.pieces = Pieces(path or default_model(), algorithm, proto)
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        split = [_SEGMENT.findall(self.pieces.lib.normalize(t)) if t else [] for t in texts]
        if len(self.known) > CACHE:  # what is still in use moves over from the older half
            self.known, self.older = {}, self.known
        new = {s for own in split for s in own if s not in self.known}
        again = new & self.older.keys()
        self.known.update((s, self.older[s]) for s in again)
        if len(new) > len(again):
            self.known.update(self._segments(list(new - again)))
        get = self.known.__getitem__
        return [np.frombuffer(b"".join(map(get, own)), np.int32) for own in split]

    def decode(self, ids: np.ndarray) -> str:
        text = b"".join(map(self.pieces.table.__getitem__, ids.tolist())).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text

    def _segments(self, segments: list[str]) -> dict[str, bytes]:
        out, p = {}, self.pieces
        if p.algorithm == "bpe":  # pieces of blanks share one score, which leaves no merge order: the rule by position decides
            for s in [s for s in segments if BLANK * 2 in s]:
                out[s] = np.concatenate([self._of(x) for x in merges(list(s), p.score)]).astype(np.int32).tobytes()
            segments = [s for s in segments if s not in out]
        if not segments:
            return out
        text = np.frombuffer((_SEPARATOR.join(segments) + _SEPARATOR * (p.longest + 1)).encode("utf-32-le", "surrogatepass"), np.uint32)
        starts = np.concatenate([[0], np.cumsum([len(s) + 1 for s in segments])[:-1]]).astype(np.int64)
        ends = starts + np.array([len(s) for s in segments])
        begin, end, piece = self._edges(text, int(ends[-1]))
        last, cut = self._relax(begin, end, piece, starts, ends)
        return out | self._walk(segments, starts, ends, last, cut)

    def _of(self, piece: str) -> np.ndarray:
        i = self.pieces.ids.get(piece)
        if i is not None:
            return np.array([i], np.int32)
        if not self.pieces.bytes:
            return np.array([self.pieces.lib.unk_id()], np.int32)
        return np.array([self.pieces.bytes[b] for b in piece.encode("utf-8", "surrogatepass")], np.int32)

    def _edges(self, text: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All occurrences of pieces, and one edge (piece NONE) for each character that is no piece."""
        p = self.pieces
        symbols, sym = np.unique(text, return_inverse=True)
        sym = np.where(text == ord(_SEPARATOR), 0, sym + 1).astype(np.uint64)
        bits = int(len(symbols) + 1).bit_length()
        per = 64 // bits
        levels = -(-p.longest // per)

        def pack(of: np.ndarray, level: int, size: int) -> np.ndarray:
            key = np.zeros(size, np.uint64)
            for k in range(level * per, (level + 1) * per):
                key = (key << np.uint64(bits)) | (of[k : k + size] if k < p.longest else np.uint64(0))
            return key

        keys = [pack(np.concatenate([sym, np.zeros(per * levels, np.uint64)]), level, n) for level in range(levels)]
        suffixes = np.lexsort(keys[::-1])
        keys = [k[suffixes] for k in keys]
        at = np.minimum(np.searchsorted(symbols, p.codes), len(symbols) - 1)
        rows = np.where(symbols[at] == p.codes, at + 1, 0).astype(np.uint64)  # 0: no symbol of the batch
        cand = np.flatnonzero(p.usable & ((rows > 0).sum(1) == p.size))
        rows, size = rows[cand], p.size[cand]
        lo, hi = np.zeros(len(cand), np.int64), np.full(len(cand), n, np.int64)
        for level in range(levels):
            low, high = np.zeros(len(cand), np.uint64), np.zeros(len(cand), np.uint64)
            for k in range(level * per, (level + 1) * per):
                there = rows[:, k] if k < p.longest else np.zeros(len(cand), np.uint64)
                open_ = (size <= k) if k < p.longest else np.zeros(len(cand), bool)
                low = (low << np.uint64(bits)) | there
                high = (high << np.uint64(bits)) | np.where(open_, np.uint64((1 << bits) - 1), there)
            if level == 0:
                lo, hi = np.searchsorted(keys[0], low), np.searchsorted(keys[0], high, side="right")
            else:
                more = (size > level * per) & (lo < hi)
                lo[more], hi[more] = _bisect(keys[level], low[more], lo[more], hi[more], False), _bisect(keys[level], high[more], lo[more], hi[more], True)
        count = np.maximum(hi - lo, 0)
        piece = np.repeat(cand, count)
        at = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(lo, count)
        begin = suffixes[at]
        end = begin + np.repeat(size, count)
        single = np.zeros(n, bool)
        single[begin[end == begin + 1]] = True
        odd = np.flatnonzero(~single & (text[:n] != ord(_SEPARATOR)))
        return np.concatenate([begin, odd]), np.concatenate([end, odd + 1]), np.concatenate([piece, np.full(len(odd), NONE)])

    def _relax(self, begin: np.ndarray, end: np.ndarray, piece: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """last[i], cut[i]: the last piece of the best way to position i, and where it begins."""
        p, n = self.pieces, int(ends[-1]) + 2
        last, cut = np.full(n, NONE - 1, np.int64), np.zeros(n, np.int64)
        best = np.full(n, -np.inf)
        last[starts], best[starts] = START, 0.0
        reach = end - np.repeat(starts, np.diff(np.append(starts, n)))[begin]
        order = np.argsort(reach.astype(np.uint16) if reach.max(initial=0) < 1 << 16 else reach, kind="stable")  # by end inside the segment: all segments advance together
        begin, end, piece, reach = begin[order], end[order], piece[order], reach[order]
        bounds = np.flatnonzero(np.append(True, reach[1:] != reach[:-1]))
        unknown = p.scores.min() - 10
        for s, e in zip(bounds, np.append(bounds[1:], len(reach)), strict=True):
            b, t, own = begin[s:e], end[s:e], piece[s:e]
            prev = last[b]
            if p.algorithm == "bpe":
                ok = prev > NONE - 1
                both = (prev >= 0) & (own >= 0)
                ok[both] = p.apart(prev[both], own[both])
                b, t, own = b[ok], t[ok], own[ok]
                last[t], cut[t] = own, b
            else:
                value = best[b] + np.where(own >= 0, p.scores[np.maximum(own, 0)], unknown)
                by = np.lexsort((-b, value, t))  # of equal values the longest edge comes last
                keep = by[np.append(t[by][1:] != t[by][:-1], True)]
                last[t[keep]], cut[t[keep]], best[t[keep]] = own[keep], b[keep], value[keep]
        return last, cut

    def _walk(self, segments: list[str], starts: np.ndarray, ends: np.ndarray, last: np.ndarray, cut: np.ndarray) -> dict[str, bytes]:
        """Ids of every segment, walked back from its end, all segments at a time."""
        at, live, used = ends.copy(), np.arange(len(segments)), np.full(len(last), NONE - 1, np.int64)
        while len(live):
            here = at[live]
            used[cut[here]] = last[here]
            at[live] = cut[here]
            live = live[at[live] > starts[live]]
        pos = np.flatnonzero(used > NONE - 1)
        piece = used[pos]
        ids = np.where(piece >= 0, self.pieces.id_of[np.maximum(piece, 0)], -1).astype(np.int32)
        edge = np.append(np.searchsorted(pos, starts), len(pos)).tolist()
        raw, out = ids.tobytes(), {}
        odd = set((np.searchsorted(starts, pos[ids < 0], side="right") - 1).tolist())
        for i, s in enumerate(segments):
            if i in odd:
                parts = [self._of(s[pos[k] - starts[i]]) if ids[k] < 0 else ids[k : k + 1] for k in range(edge[i], edge[i + 1])]
                out[s] = np.concatenate(parts).astype(np.int32).tobytes()
            else:
                out[s] = raw[4 * edge[i] : 4 * edge[i + 1]]
        return out


def _bisect(keys: np.ndarray, value: np.ndarray, lo: np.ndarray, hi: np.ndarray, right: bool) -> np.ndarray:
    """searchsorted of each value inside its own range of keys."""
    lo, hi = lo.copy(), hi.copy()
    while (open_ := lo < hi).any():
        mid = (lo + hi) // 2
        k = keys[np.minimum(mid, len(keys) - 1)]
        up = open_ & ((k <= value) if right else (k < value))
        lo, hi = np.where(up, mid + 1, lo), np.where(open_ & ~up, mid, hi)
    return lo


@lru_cache(maxsize=2)
def codec(path: str | None = None, algorithm: str = "bpe") -> Codec:
    return Codec(path, algorithm)


def encode_documents(docs: DataFrame, model: str | None = None, algorithm: str = "bpe", with_ids: bool = True) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_tokens, ids_crc32 and, on request, ids."""
    return _coded(docs, model, algorithm, with_ids, False)


def round_trip(docs: DataFrame, model: str | None = None, algorithm: str = "bpe") -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_tokens, ids_crc32, decoded_sha256, round_trip (the decoded text is the text)."""
    out = _coded(docs, model, algorithm, False, True)
    return out.select("doc_id", "n_tokens", "ids_crc32", F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"), "round_trip")


def _coded(docs: DataFrame, model: str | None, algorithm: str, with_ids: bool, decoded: bool) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model, algorithm)
        for whole in batches:
            for at in range(0, whole.num_rows, ROWS):
                b = whole.slice(at, ROWS)
                texts = [t or "" for t in b.column(1).to_pylist()]
                ids = own.encode(texts)
                cols = {"doc_id": b.column(0), "n_tokens": pa.array([len(x) for x in ids], pa.int64()), "ids_crc32": pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in ids], pa.int64())}
                if with_ids:
                    cols["ids"] = pa.array(ids, pa.list_(pa.int32()))
                if decoded:
                    back = [own.decode(x) for x in ids]
                    cols |= {"decoded": pa.array(back, pa.string()), "round_trip": pa.array([x == t for x, t in zip(back, texts, strict=True)], pa.bool_())}
                yield pa.RecordBatch.from_pydict(cols)

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids + ", decoded string, round_trip boolean" * decoded)


def decode_documents(coded: DataFrame, model: str | None = None) -> DataFrame:
    """coded(doc_id, ids) -> doc_id, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        for b in batches:
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "text": pa.array([own.decode(np.array(x or [], np.int64)) for x in b.column(1).to_pylist()], pa.string())})

    kind = coded.schema["doc_id"].dataType.simpleString()
    return coded.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, text string")
