"""What is known of a database: relations with their keys, foreign keys, and the expert's decisions.

All of it is metadata; Spark enforces none.  Plans are built from it on the driver before any data is read.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class ForeignKey:
    """columns of ``source`` refer to ``target_columns`` of ``target``."""

    source: str
    columns: tuple[str, ...]
    target: str
    target_columns: tuple[str, ...]


@dataclass(frozen=True)
class Relation:
    """sks: surrogate keys; nk: natural key the expert found; declared_nk: one the schema declares."""

    name: str
    sks: tuple[str, ...] = ()
    nk: tuple[str, ...] | None = None
    declared_nk: tuple[str, ...] | None = None
    columns: tuple[str, ...] = ()

    def potential_key(self) -> tuple[str, ...]:
        """The natural key if there is one, else every column but the surrogate keys."""
        return self.nk or self.declared_nk or tuple(c for c in self.columns if c not in self.sks)

    def remaining(self) -> tuple[str, ...]:
        """Columns that are neither surrogate keys nor in the potential key."""
        key = set(self.potential_key()) | set(self.sks)
        return tuple(c for c in self.columns if c not in key)


@dataclass(frozen=True)
class DatabaseSpec:
    relations: dict[str, Relation]
    fks: tuple[ForeignKey, ...] = ()

    def is_sfk(self, fk: ForeignKey) -> bool:
        """A foreign key is surrogate if it is one column that points to a surrogate key."""
        return len(fk.columns) == 1 and fk.target_columns[0] in self.relations[fk.target].sks

    def sfks(self) -> list[ForeignKey]:
        return [fk for fk in self.fks if self.is_sfk(fk)]

    def unary(self) -> list[tuple[str, str, str, str]]:
        """The one-column inclusion dependencies that the foreign keys imply."""
        return [(fk.source, a, fk.target, b) for fk in self.fks for a, b in zip(fk.columns, fk.target_columns, strict=True)]

    def with_columns(self, tables: dict[str, DataFrame]) -> DatabaseSpec:
        return replace(self, relations={n: replace(r, columns=tuple(tables[n].columns)) if n in tables else r for n, r in self.relations.items()})

    def restrict(self, names: list[str]) -> DatabaseSpec:
        """Only the relations of interest, and the foreign keys between them."""
        keep = set(names)
        return DatabaseSpec({n: r for n, r in self.relations.items() if n in keep}, tuple(f for f in self.fks if {f.source, f.target} <= keep))

    def to_json(self) -> str:
        return json.dumps(asdict(self), indent=1)

    @staticmethod
    def from_json(text: str) -> DatabaseSpec:
        raw = json.loads(text)
        tup = lambda x: tuple(x) if isinstance(x, list) else x
        return DatabaseSpec({n: Relation(**{k: tup(v) for k, v in r.items()}) for n, r in raw["relations"].items()}, tuple(ForeignKey(**{k: tup(v) for k, v in f.items()}) for f in raw["fks"]))


@dataclass
class Database:
    spec: DatabaseSpec
    tables: dict[str, DataFrame]

    def __post_init__(self) -> None:
        self.spec = self.spec.with_columns(self.tables)

    def restrict(self, names: list[str]) -> Database:
        return Database(self.spec.restrict(names), {n: t for n, t in self.tables.items() if n in set(names)})


@dataclass
class ExpertDecisions:
    """Everything a person decided, as data: a run can be replayed from the file."""

    sks: dict[str, list[str]] = field(default_factory=dict)
    nks: dict[str, list[str]] = field(default_factory=dict)
    stable: dict[str, list[str]] = field(default_factory=dict)
    unstable: dict[str, list[str]] = field(default_factory=dict)
    completing: dict[str, list[str]] = field(default_factory=dict)  # candidates for O, in order
    rules: dict[str, dict[str, str | dict]] = field(default_factory=dict)  # relation -> attribute -> rule, see chase.decided
    interest: list[str] = field(default_factory=list)

    def apply(self, spec: DatabaseSpec) -> DatabaseSpec:
        """Tags go on; a round with new tags follows until none is new."""
        out = {}
        for n, r in spec.relations.items():
            sks = tuple(dict.fromkeys((*r.sks, *self.sks.get(n, ()))))
            out[n] = replace(r, sks=sks, nk=tuple(self.nks[n]) if n in self.nks else r.nk)
        spec = replace(spec, relations=out)
        return spec.restrict(self.interest) if self.interest else spec

    def rounds(self, spec: DatabaseSpec, more: list[ExpertDecisions]) -> DatabaseSpec:
        for step in [self, *more]:
            new = step.apply(spec)
            if new == spec:
                break
            spec = new
        return spec

    def to_json(self) -> str:
        return json.dumps(asdict(self), indent=1)

    @staticmethod
    def from_json(text: str) -> ExpertDecisions:
        return ExpertDecisions(**json.loads(text))
