"""Quality rules by compression bands.

A text that repeats itself compresses far better than prose, and noise hardly compresses at all.  The ratio of
zstandard-compressed to raw bytes is taken of the whole document and of fixed chunks of it (the last one may be
shorter), and each ratio must lie in a band that depends on the length, since short texts compress worse.  A document is
kept if its base rules hold, its whole ratio lies in the band, and at most a given share of its bytes lies in chunks
outside theirs.  The bands are the spread of clean prose, learnt by ``learn`` on the training fold.

Defined results: a null text counts as no text; a text without words fails the base rules; rows are judged one by one,
so repeated ids or rows get one result each; other columns of the input are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .text import BLANKS, covered, mix, windows, word_hashes, words


#: Raw lengths at which a class of whole ratios begins, and the room given below and above the learnt spread.
CLASSES = (64, 128, 181, 256, 362, 512, 724, 1024, 1448, 2048, 2896, 4096, 5793, 8192, 11585, 16384, 32768)
ROOM = (0.004, 0.01)
WHOLE = ((0, 0.7, 9.9), (64, 0.779, 1.148), (128, 0.688, 0.959), (181, 0.632, 0.826), (256, 0.587, 0.807), (362, 0.575, 0.736), (512, 0.42, 0.697), (724, 0.496, 0.661), (1024, 0.482, 0.604), (1448, 0.47, 0.568), (2048, 0.453, 0.553), (2896, 0.444, 0.526), (4096, 0.434, 0.518), (5793, 0.422, 0.485), (8192, 0.414, 0.471), (11585, 0.411, 0.462), (16384, 0.398, 0.45), (32768, 0.389, 0.437), (65536, 0.36, 0.437))
CHUNK = (0.466, 0.55)


@dataclass(frozen=True)
class Bands:
    """Limits of compressed / raw bytes, by the raw length from which they hold (ascending)."""

    #: learn() on the training fold of check_s, but for two: 512 keeps its wider lower limit, as texts of a small vocabulary
    #: count as prose there; below 64 bytes, where noise shows no longer, only repetition goes; 65536 on, where there is no clean text to learn from, is the class before with room below.
    whole: tuple[tuple[int, float, float], ...] = WHOLE
    chunk_bytes: int = 2048
    chunk: tuple[float, float] = CHUNK
    bad_chunks: float = 0.2
    level: int = 3
    min_words: int = 10
    max_repeat_percent: int = 20
    window: int = 5

    def limits(self, n: int) -> tuple[float, float]:
        """Least and greatest ratio of n bytes."""
        return [b[1:] for b in self.whole if b[0] <= n][-1]


def n_repeated(tokens: list[bytes], width: int) -> int:
    """Words inside a window of ``width`` words that occurs twice or more in the text, the first one included."""
    if len(tokens) <= width:
        return 0
    h = mix(windows(word_hashes(tokens), width))
    _, back, count = np.unique(h, return_inverse=True, return_counts=True)
    starts = np.flatnonzero(count[back] > 1)
    return int(covered(starts, width, len(tokens)).sum()) if len(starts) else 0


def profile(text: str | None, bands: Bands, compressor) -> dict:
    """All counts and ratios of one text, and the verdict."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    tokens = words(text)
    full = [x for x in text.split("\n") if x.strip(BLANKS)]
    row = {
        "n_words": len(tokens),
        "word_chars": len(text) - sum(map(text.count, BLANKS)),
        "n_symbols": sum(map(text.count, "#*$%&|<>")),
        "n_dup_lines": len(full) - len(set(full)),
        "n_repeat_words": n_repeated(tokens, bands.window),
    }
    row["base_failed"] = row["n_words"] < bands.min_words or 100 * row["n_repeat_words"] > bands.max_repeat_percent * row["n_words"]
    row["ratio"] = len(compressor.compress(raw)) / len(raw) if raw else 1.0
    low, high = bands.limits(len(raw))
    bad = 0
    if len(raw) > bands.chunk_bytes:
        for at in range(0, len(raw), bands.chunk_bytes):
            part = raw[at : at + bands.chunk_bytes]
            least, most = bands.chunk if len(part) == bands.chunk_bytes else bands.limits(len(part))
            bad += len(part) * (not least <= len(compressor.compress(part)) / len(part) <= most)
    row["bad_chunks"] = bad / len(raw) if raw else 0.0
    row["kept"] = not row["base_failed"] and low <= row["ratio"] <= high and row["bad_chunks"] <= bands.bad_chunks
    return row


LONGS, FLAGS, REALS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"), ("base_failed", "kept"), ("ratio", "bad_chunks")


def quality_rules(docs: DataFrame, bands: Bands = Bands()) -> DataFrame:
    """docs(doc_id, text) -> doc_id, the counts, base_failed, kept, ratio, bad_chunks; one pass, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        compressor = zstandard.ZstdCompressor(level=bands.level)
        for b in batches:
            rows = [profile(t.as_py(), bands, compressor) for t in b.column(1)]
            cols = {"doc_id": b.column(0)}
            cols |= {k: pa.array([r[k] for r in rows], pa.int64()) for k in LONGS}
            cols |= {k: pa.array([r[k] for r in rows], pa.bool_()) for k in FLAGS}
            cols |= {k: pa.array([r[k] for r in rows], pa.float64()) for k in REALS}
            yield pa.RecordBatch.from_pydict(cols)

    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, " + ", ".join([*(f"{k} long" for k in LONGS), *(f"{k} boolean" for k in FLAGS), *(f"{k} double" for k in REALS)])
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def kept_documents(docs: DataFrame, bands: Bands = Bands()) -> DataFrame:
    """The rows of docs that the rules keep, with all their columns; one pass, no shuffle."""
    place = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        compressor = zstandard.ZstdCompressor(level=bands.level)
        for b in batches:
            yield b.filter(pa.array([profile(t.as_py(), bands, compressor)["kept"] for t in b.column(place)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def learn(docs: DataFrame, labels: DataFrame, classes: tuple[int, ...] = CLASSES, least: int = 30) -> Bands:
    """Bands from the clean texts (label 1, base rules hold) of the training fold.

    The limits of a length class are the outer thousandths of its ratios, with some room; a class of fewer than
    ``least`` texts has those of the class before it.  Driver memory is bounded by the number of classes.
    """
    from .quality_classifier import remainder

    clean = labels.where((F.col("quality") == 1) & (remainder() != 0)).select("doc_id").distinct()
    wide = Bands(whole=((0, 0.0, 9.9),), chunk=(0.0, 9.9))
    ratios = docs.join(clean, "doc_id").select("doc_id", "text").mapInArrow(lambda it: _ratios(it, wide), "size long, ratio double, chunk boolean")
    start = F.greatest(*(F.when(F.col("size") >= c, F.lit(c)) for c in classes), F.lit(0))
    spread = ratios.groupBy("chunk", start.alias("start")).agg(F.count(F.lit(1)).alias("n"), F.percentile("ratio", F.lit(0.001)).alias("low"), F.percentile("ratio", F.lit(0.999)).alias("high"))
    found = {(r["chunk"], r["start"]): (round(r["low"] - ROOM[0], 3), round(r["high"] + ROOM[1], 3)) for r in spread.where(F.col("n") >= least).collect()}
    whole, now = [], (0.0, 9.9)
    for c in (0, *classes):
        now = found.get((False, c), now) if c else now
        whole.append((c, *now))
    chunk = next((v for (part, _), v in found.items() if part), wide.chunk)
    return Bands(whole=tuple(whole), chunk=chunk)


def _ratios(batches: Iterator[pa.RecordBatch], bands: Bands) -> Iterator[pa.RecordBatch]:
    """Raw size and ratio of each text whose base rules hold, and of its full chunks."""
    import zstandard

    compressor = zstandard.ZstdCompressor(level=bands.level)
    for b in batches:
        rows = []
        for t in b.column(1):
            raw = (t.as_py() or "").encode("utf-8", "surrogatepass")
            if not profile(t.as_py(), bands, compressor)["base_failed"]:
                parts = [raw[at : at + bands.chunk_bytes] for at in range(0, len(raw) - bands.chunk_bytes + 1, bands.chunk_bytes)]
                rows += [(len(x), len(compressor.compress(x)) / len(x), i > 0) for i, x in enumerate([raw, *parts])]
        yield pa.RecordBatch.from_pydict({"size": pa.array([r[0] for r in rows], pa.int64()), "ratio": pa.array([r[1] for r in rows], pa.float64()), "chunk": pa.array([r[2] for r in rows], pa.bool_())})
