"""Functional dependencies: extend atoms and head by implied variables through lookup joins."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordjoin.plans.hypergraph import fd_closure
from ordjoin.plans.model import FD, ConjunctiveQuery


def violations(q: ConjunctiveQuery, fd: FD) -> DataFrame:
    """Left sides with more than one right side; empty if the dependency holds."""
    rows = q.atom(fd.atom).frame
    return rows.groupBy(*fd.lhs).agg(F.min(fd.rhs).alias("a"), F.max(fd.rhs).alias("b")).where("a <> b").select(*fd.lhs)


def fd_rewrite(q: ConjunctiveQuery, fds: Sequence[FD], check: bool = False) -> tuple[ConjunctiveQuery, tuple[str, ...]]:
    """The extended query and the head to show. Each atom that holds a left side gains the right side by a lookup join
    with the dependency's distinct pairs; the head gains what it implies. ``check`` verifies the dependencies first."""
    if check:
        for fd in fds:
            if not violations(q, fd).isEmpty():
                raise ValueError(f"{fd} doesn't hold")
    atoms = list(q.atoms)
    changed = True
    while changed:
        changed = False
        for fd in fds:
            source = q.atom(fd.atom).frame.select(*fd.lhs, fd.rhs).distinct()
            for n, a in enumerate(atoms):
                if set(fd.lhs) <= set(a.variables) and fd.rhs not in a.variables:
                    atoms[n] = replace(a, frame=a.frame.join(source, list(fd.lhs)), variables=(*a.variables, fd.rhs))
                    changed = True
    closed = fd_closure(q.head, fds)
    head = (*q.head, *sorted(closed - set(q.head)))
    return replace(q, atoms=tuple(atoms), head=head), q.head
