"""Words, word hashes and window hashes of document texts (numpy side of the Arrow operators).

A word is a maximal run of bytes other than space, tab, line feed, vertical tab, form feed and carriage return:
exactly what ``bytes.split()`` yields, and the same as the pattern ``[^\\x20\\x09-\\x0D]+`` over code points.
"""

from __future__ import annotations

import numpy as np
from xxhash import xxh3_64_intdigest

#: The six ASCII blanks that separate words.
BLANKS = " \t\n\x0b\x0c\r"

_MULT = np.uint64(0x9E3779B97F4A7C15)


class _WordHashes(dict):
    """word -> 64-bit hash; a bounded per-worker cache, since a few words make up most of any text."""

    LIMIT = 1 << 18

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        value = self[word] = xxh3_64_intdigest(word)
        return value


_HASHES = _WordHashes()


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split() if text else []


def word_hashes(tokens: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_HASHES.__getitem__, tokens), np.uint64, len(tokens))


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the 64 output bits (a bijection)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def windows(hashes: np.ndarray, width: int, multiplier: int = int(_MULT)) -> np.ndarray:
    """Polynomial hash of every run of ``width`` values, by doubling: O(n log width) vector steps, not mixed."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    base = np.uint64(multiplier)
    power, span, done, out = hashes, 1, 0, None
    factor = base  # base ** span
    with np.errstate(over="ignore"):
        while True:
            if width & span:
                if out is None:
                    out, done = power, span
                else:  # out covers ``done`` values, append the next ``span``
                    m = len(hashes) - done - span + 1
                    out = out[:m] * factor + power[done : done + m]
                    done += span
            if done == width:
                return out[:n]
            power = power[: len(power) - span] * factor + power[span:]
            factor = factor * factor
            span *= 2


def covered(starts: np.ndarray, width: int, n: int) -> np.ndarray:
    """Mask of the positions below ``n`` inside a window of ``width`` that begins at one of ``starts``."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.subtract.at(edge, np.minimum(starts + width, n), 1)
    return np.cumsum(edge[:-1]) > 0


def grouped(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first, number): the first index of each distinct key, in key order, and each element's place in that list.

    keys: structured with the fields a and b; numpy sorts such arrays far slower than two plain columns.
    """
    if not len(keys):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    a, b = keys["a"], keys["b"]
    order = np.lexsort((b, a))
    new = np.ones(len(order), bool)
    new[1:] = (a[order[1:]] != a[order[:-1]]) | (b[order[1:]] != b[order[:-1]])
    number = np.empty(len(order), np.int64)
    number[order] = np.cumsum(new) - 1
    return order[new], number


def among(keys: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Mask of the keys that are in ``of``."""
    if not len(of) or not len(keys):
        return np.zeros(len(keys), bool)
    first, number = grouped(np.concatenate([of, keys]))
    return (first < len(of))[number[len(of) :]]
