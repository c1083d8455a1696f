"""What the method is held against: key, dependency and inclusion discovery, plain and local deduplication."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable
from functools import reduce
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.canon import comparable, fingerprint
from ..plans.model import Database
from .equivalence import sk_map
from .propagate import apply_map

#: Distinct counts in one job: each multiplies the rows of its aggregate.
BATCH = 8
#: Rows that may refute a key on the driver.
SAMPLE = 10_000
#: Rows of a slice that may refute keys before the whole table is grouped; tables below two slices have none.
SLICE = 500_000


def distinct_counts(df: DataFrame, sets: list[tuple[str, ...]]) -> list[int]:
    """Distinct rows over each set of columns (null is a value)."""
    out: list[int] = []
    for at in range(0, len(sets), BATCH):
        part = sets[at : at + BATCH]
        row = df.agg(*(F.countDistinct(F.struct(*(comparable(df, c) for c in s))).alias(f"d{i}") for i, s in enumerate(part))).first()
        out += list(row)
    return out


def few_codes(df: DataFrame, columns: list[str], rows: int = SAMPLE) -> dict[str, np.ndarray]:
    """The values of a few rows, at most ``rows`` of them on the driver, as numbers: equal values have equal ones."""
    few = df.select(*(fingerprint(df, [c]).alias(f"c{i}") for i, c in enumerate(columns))).limit(rows).toPandas()
    return {c: pd.factorize(few[f"c{i}"].map(str))[0].astype("int64") for i, c in enumerate(columns)}


def repeats_in(df: DataFrame, columns: list[str], rows: int = SAMPLE, codes: dict[str, np.ndarray] | None = None) -> Callable[[tuple[str, ...]], bool]:
    """Whether a set of columns repeats within a few rows.

    A repeat there is one in the table, so it refutes uniqueness for certain; no repeat says nothing.
    """
    codes = codes or few_codes(df, columns, rows)

    def repeats(names: tuple[str, ...]) -> bool:
        key = codes[names[0]]
        for c in names[1:]:
            key = pd.factorize(key * len(key) + codes[c])[0].astype("int64")
        return len(np.unique(key)) < len(key)

    return repeats


def repeated_groups(df: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """The values (_r0, _r1 ...) of a set of columns that several rows have; null is a value."""
    return df.groupBy(*(comparable(df, c).alias(f"_r{j}") for j, c in enumerate(names))).agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def repeated(df: DataFrame, sets: list[tuple[str, ...]]) -> dict[tuple[str, ...], int]:
    """How many values of each set of columns several rows have: one grouping a set, some of them in a job."""
    out: dict[tuple[str, ...], int] = {}
    for at in range(0, len(sets), BATCH):
        part = sets[at : at + BATCH]
        counts = [repeated_groups(df, s).agg(F.count(F.lit(1)).alias("k")).select(F.lit(i).alias("i"), "k") for i, s in enumerate(part)]
        out |= {part[r["i"]]: r["k"] for r in reduce(DataFrame.unionByName, counts).collect()}
    return out


class LargeTable:
    """Looks for repeats of sets of columns in a table that is costly to group; every answer holds for the whole table.

    A set is looked at in a slice first: all rows whose value of the set's most varied column has one remainder of a
    hash.  Rows that agree on the set are all in the slice or all outside, so a repeat there refutes it for certain.
    What is left is grouped over the whole table, but where several sets share a subset with few repeats only the rows
    that agree on that subset are looked at: no others can agree on the sets.
    """

    def __init__(self, df: DataFrame, n: int, rows: int, varied: dict[str, int]) -> None:
        self.df, self.rows, self.varied, self.parts = df, rows, varied, n // rows
        self.slices: dict[str, DataFrame] = {}
        self.agreeing: dict[tuple[str, ...], DataFrame] = {}
        self.known: dict[tuple[str, ...], int] = {}  # about how many values repeat
        self.held: list[DataFrame] = []

    def _hold(self, df: DataFrame) -> DataFrame:
        self.held.append(df.persist())
        return df

    def _dealt(self, names: tuple[str, ...], columns: list[str]) -> DataFrame:
        return self.df.select(columns).repartition(2 * self.parts, *(comparable(self.df, c) for c in names))

    def _refuted(self, sets: list[tuple[str, ...]]) -> None:
        by: dict[str, list[tuple[str, ...]]] = {}
        for s in sets:
            by.setdefault(max(s, key=self.varied.get), []).append(s)
        for c, own in by.items():
            if c not in self.slices:
                slice_ = self.df.where(F.pmod(F.xxhash64(comparable(self.df, c)), F.lit(self.parts)) == 0)
                self.slices[c] = self._hold(slice_.repartition(self.df.sparkSession.sparkContext.defaultParallelism, comparable(self.df, c)))
            self.known |= {s: k * self.parts for s, k in repeated(self.slices[c], own).items() if k}

    def _rows_that_agree(self, names: tuple[str, ...]) -> DataFrame:
        if names not in self.agreeing:
            groups = self._hold(repeated_groups(self._dealt(names, list(names)), names).drop("n"))
            small = groups.count() <= self.rows
            same = reduce(lambda x, y: x & y, [comparable(self.df, c).eqNullSafe(F.col(f"_r{j}")) for j, c in enumerate(names)])
            self.agreeing[names] = self._hold(self.df.join(F.broadcast(groups) if small else groups, same, "left_semi"))
        return self.agreeing[names]

    def repeating(self, sets: list[tuple[str, ...]]) -> set[tuple[str, ...]]:
        self._refuted(sets)
        left = [s for s in sets if s not in self.known]
        while left:
            subsets = Counter(b for s in left for b in combinations(s, len(s) - 1) if self.known.get(b, self.rows) < self.rows)
            base = max(subsets, key=lambda b: (b in self.agreeing, subsets[b], -self.known[b]), default=None)
            if base is None or (subsets[base] < 2 and base not in self.agreeing):
                break
            own = [s for s in left if set(base) < set(s)]
            self.known |= {s: k for s, k in repeated(self._rows_that_agree(base), own).items() if k}
            left = [s for s in left if s not in own]
        for s in left:
            self.known |= {s: k for s, k in repeated(self._dealt(s, list(s)), [s]).items() if k}
        return {s for s in sets if s in self.known}

    def close(self) -> None:
        for df in self.held:
            df.unpersist()


def uccs(df: DataFrame, columns: list[str] | None = None, max_width: int | None = None, rows: int = SLICE) -> list[tuple[str, ...]]:
    """Minimal unique column combinations, level by level up to ``max_width`` (none: until nothing is left to try).

    Supersets of a unique one are never counted, nor are sets that a few rows already refute.  Tables of at least twice
    ``rows`` rows are searched as a LargeTable.
    """
    columns, n, found = columns or df.columns, df.count(), []
    codes = few_codes(df, columns)
    repeats = repeats_in(df, columns, codes=codes)
    large = LargeTable(df.select(columns), n, rows, {c: len(np.unique(v)) for c, v in codes.items()}) if n >= 2 * rows else None
    try:
        for width in range(1, (max_width or len(columns)) + 1):
            level = [c for c in combinations(columns, width) if not any(set(u) <= set(c) for u in found)]
            if not level:
                break
            open_sets = [c for c in level if not repeats(c)]
            gone = large.repeating(open_sets) if large else {s for s, k in repeated(df, open_sets).items() if k}
            found += [c for c in open_sets if c not in gone]
    finally:
        if large:
            large.close()
    return found


def key_accuracy(found: list[tuple[str, ...]], truth: tuple[str, ...]) -> dict[str, float]:
    """Precision and recall of discovered keys against the expert's one."""
    hit = sum(set(f) == set(truth) for f in found)
    return {"found": len(found), "precision": round(hit / len(found), 6) if found else 0.0, "recall": float(hit > 0)}


def fds(df: DataFrame, columns: list[str] | None = None, max_left: int = 2, eps: float = 0.0) -> list[tuple[tuple[str, ...], str, float]]:
    """Minimal dependencies with at most ``max_left`` columns on the left, exact by partition counts or g3 <= eps."""
    from .stability import g3

    columns, found = columns or df.columns, []
    singles: dict[tuple[str, ...], int] = {}
    for width in range(1, max_left + 1):
        lefts = list(combinations(columns, width))
        tests = [(x, a) for x in lefts for a in columns if a not in x and not any(set(y) <= set(x) and b == a for y, b, _ in found)]
        need = [s for s in dict.fromkeys([*(x for x, _ in tests), *(tuple(sorted({*x, a})) for x, a in tests)]) if s not in singles]
        singles.update(zip(need, distinct_counts(df, need), strict=True))
        for x, a in tests:
            if singles[x] == singles[tuple(sorted({*x, a}))]:
                found.append((x, a, 0.0))
            elif eps and (e := g3(df, list(x), a).first()["g3"]) <= eps:
                found.append((x, a, e))
    return found


def unary_inds(db: Database, columns: dict[str, list[str]]) -> DataFrame:
    """dependent, referenced: every pair of the columns where all values of the first occur in the second.

    One pass: values are grouped with the set of columns that hold them, and a column's referenced ones are those that
    never miss from its sets.  Sets are of columns, so their size is bounded by the schema.
    """
    parts = [db.tables[n].select(F.col(c).cast("string").alias("v"), F.lit(f"{n}.{c}").alias("c")).where("v is not null").distinct() for n, cs in columns.items() for c in cs]
    held = reduce(DataFrame.unionByName, parts).groupBy("v").agg(F.collect_set("c").alias("cs"))
    size = held.select(F.explode("cs").alias("dependent")).groupBy("dependent").agg(F.count(F.lit(1)).alias("n"))
    both = held.select(F.explode("cs").alias("dependent"), "cs").select("dependent", F.explode("cs").alias("referenced")).where("dependent <> referenced")
    return both.groupBy("dependent", "referenced").agg(F.count(F.lit(1)).alias("m")).join(size, "dependent").where("m = n").select("dependent", "referenced")


def distinct_only(db: Database) -> DataFrame:
    """relation, n_rows, n_distinct: plain duplicate elimination, which surrogate keys defeat."""
    parts = [t.agg(F.count(F.lit(1)).alias("n_rows")).crossJoin(t.distinct().agg(F.count(F.lit(1)).alias("n_distinct"))).select(F.lit(n).alias("relation"), "*") for n, t in db.tables.items()]
    return reduce(DataFrame.unionByName, parts)


def local_dedup(db: Database) -> Database:
    """Each relation by its own natural key, references left as they are."""
    out = {}
    for n, t in db.tables.items():
        r = db.spec.relations[n]
        kept = apply_map(t, r.sks[0], sk_map(t, r.sks[0], r.potential_key())).withColumn("_k", fingerprint(t, r.potential_key()))
        out[n] = kept.dropDuplicates(["_k"]).drop("_k")
    return Database(db.spec, out)


def attribute_match(df: DataFrame, sk: str, columns: list[str]) -> DataFrame:
    """n, classes by descriptive attributes alone: merges what merely looks alike."""
    from .metrics import au

    return au(df, sk, columns)
