"""Brute-force versions of what the operators compute."""

import collections
import itertools
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(s):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)


def brute_lines(texts):
    key = lambda line: lower(line.strip(" \t\n\x0b\x0c\r"))
    held = collections.defaultdict(list)
    for i, t in texts.items():
        for k in {key(x) for x in (t or "").split("\n")}:
            held[k].append(i)
    stay = lambda i, k: len(k) < 20 or len(held[k]) < 3 or max(held[k]) == i
    return {i: "\n".join(x for x in (t or "").split("\n") if stay(i, key(x))) for i, t in texts.items()}


def brute_windows(texts, width):
    seen, out = set(), {}
    for i in sorted(texts):
        w = WORD.findall(texts[i] or "")
        gone = [False] * len(w)
        for p in range(len(w) - width + 1):
            k = tuple(w[p : p + width])
            if k in seen:
                gone[p : p + width] = [True] * width
            seen.add(k)
        out[i] = (len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g))
    return out


def brute_near(texts, width, percent):
    sets = {}
    for i, t in texts.items():
        w = WORD.findall(lower(t or ""))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} - {()}
    up = {i: i for i in texts}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(texts), 2):
        n = len(sets[a] & sets[b])
        if n and 100 * n >= percent * len(sets[a] | sets[b]):
            x, y = sorted((root(a), root(b)))
            up[y] = x
    return {i: (len(sets[i]), root(i), root(i) == i) for i in texts}
