"""Conjunctive queries over DataFrames: atoms, selections, self-joins, rule text."""

from __future__ import annotations

import re
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Atom:
    """A relation whose columns are named by query variables."""

    name: str
    frame: DataFrame = field(compare=False, hash=False)
    variables: tuple[str, ...] = ()

    def with_frame(self, frame: DataFrame) -> Atom:
        return replace(self, frame=frame)


@dataclass(frozen=True)
class FD:
    """Functional dependency on query variables: lhs determines rhs in the atom of that name."""

    atom: str
    lhs: tuple[str, ...]
    rhs: str


@dataclass(frozen=True)
class ConjunctiveQuery:
    atoms: tuple[Atom, ...]
    head: tuple[str, ...]
    relations: tuple[str, ...] = ()

    @property
    def variables(self) -> tuple[str, ...]:
        """All variables in the order in which atoms name them."""
        return tuple(dict.fromkeys(v for a in self.atoms for v in a.variables))

    @property
    def is_full(self) -> bool:
        return set(self.head) == set(self.variables)

    @property
    def edges(self) -> list[frozenset[str]]:
        return [frozenset(a.variables) for a in self.atoms]

    def atom(self, name: str) -> Atom:
        return next(a for a in self.atoms if a.name == name)

    def is_self_join_free(self) -> bool:
        """Whether no relation stands in two atoms (the scope of lower bounds)."""
        return len(set(self.relations)) == len(self.relations)


def atom(name: str, frame: DataFrame, columns: Mapping[str, object] | Sequence[object], keep_nulls: bool = False) -> Atom:
    """An atom from a frame: ``columns`` maps columns to variables, or gives one term a column in order.

    Terms: a variable name, ``None`` or ``"_"`` for a column to ignore, or a constant in a one-item tuple. Constants and
    repeated variables become filters that reach the scan. Rows with a null variable go, as a null joins with nothing,
    unless ``keep_nulls``.
    """
    terms = dict(columns) if isinstance(columns, Mapping) else dict(zip(frame.columns, columns, strict=True))
    unknown = set(terms) - set(frame.columns)
    if unknown:
        raise ValueError(f"{name} has no columns {sorted(unknown)}")
    first: dict[str, str] = {}
    for column, term in terms.items():
        if isinstance(term, tuple):
            frame = frame.where(F.col(column) == F.lit(term[0]))
        elif term in (None, "_"):
            continue
        elif term in first:
            frame = frame.where(F.col(column) == F.col(first[term]))
        else:
            first[str(term)] = column
    out = frame.select(*[F.col(c).alias(v) for v, c in first.items()])
    for v, dtype in out.dtypes:
        if dtype in ("double", "float"):
            out = out.withColumn(v, F.when(F.col(v) == 0, F.lit(0.0).cast(dtype)).otherwise(F.col(v)))  # -0.0 and 0.0 join
    return Atom(name, out if keep_nulls else out.dropna(), tuple(first))


def split_self_joins(q: ConjunctiveQuery) -> ConjunctiveQuery:
    """The same query with a relation name of its own for every use: ``e`` in two atoms becomes ``e#1`` and ``e#2``."""
    seen: dict[str, int] = {}
    names = []
    for name in q.relations:
        seen[name] = seen.get(name, 0) + 1
        names.append(f"{name}#{seen[name]}" if q.relations.count(name) > 1 else name)
    return ConjunctiveQuery(q.atoms, q.head, tuple(names))


def cq(atoms: Sequence[Atom], head: Sequence[str] | None = None, relations: Sequence[str] = ()) -> ConjunctiveQuery:
    """A query; without a head all variables are free. Atom names are made distinct (self-joins by renamed copies)."""
    seen: dict[str, int] = {}
    named = []
    for a in atoms:
        seen[a.name] = seen.get(a.name, 0) + 1
        named.append(a if seen[a.name] == 1 else replace(a, name=f"{a.name}_{seen[a.name]}"))
    q = ConjunctiveQuery(tuple(named), (), tuple(relations) or tuple(a.name for a in atoms))
    free = tuple(head) if head is not None else q.variables
    missing = set(free) - set(q.variables)
    if missing:
        raise ValueError(f"the head's {sorted(missing)} stand in no atom")
    return replace(q, head=free)


_TERM = re.compile(r"\s*(?:(\w+)\s*=\s*)?('(?:[^']|'')*'|-?\d+(?:\.\d+)?|\w+)\s*(?:,|$)")


def parse_rule(text: str, tables: Mapping[str, DataFrame]) -> ConjunctiveQuery:
    """``q(a, c) :- r(a, b), s(b, c, 3)``: terms by position, or by column as ``r(col=a)``; quoted text or numbers are constants."""
    head, _, body = text.partition(":-")
    inside = re.fullmatch(r"\s*\w+\s*\(([^)]*)\)\s*", head)
    if not inside or not body.strip():
        raise ValueError(f"not a rule: {text}")
    atoms, names = [], []
    for name, args in re.findall(r"(\w+)\s*\(([^)]*)\)", body):
        terms: dict[str, object] = {}
        for i, (column, term) in enumerate(_TERM.findall(args)):
            key = column or tables[name].columns[i]
            quoted = term.startswith("'")
            number = re.fullmatch(r"-?\d+(\.\d+)?", term)
            terms[key] = (term[1:-1].replace("''", "'"),) if quoted else ((float(term) if "." in term else int(term)),) if number else term
        atoms.append(atom(name, tables[name], terms))
        names.append(name)
    free = [v.strip() for v in inside[1].split(",") if v.strip()]
    return cq(atoms, free, names)


def as_set(q: ConjunctiveQuery) -> ConjunctiveQuery:
    """Set semantics: each relation without repeated rows."""
    return replace(q, atoms=tuple(a.with_frame(a.frame.distinct()) for a in q.atoms))
