"""The plan of a repair: bound and free attributes, the order of FDs, which of them close cycles, and how reach is computed."""

from __future__ import annotations

import random
from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql.types import StructType

from . import fd as fds_
from .fd import FD


@dataclass(frozen=True)
class RepairPlan:
    """fds are in processing order; groups has those that may run side by side together."""

    fds: tuple[FD, ...]
    groups: tuple[tuple[FD, ...], ...]
    bound: tuple[str, ...]
    free: tuple[str, ...]
    closing: frozenset[FD]
    component: dict[str, int]
    reach: str
    back_edges: str = "target"
    on_conflict: str = "keep_first"
    nulls: str = "missing"
    lhs_source: str = "chased"

    @property
    def attributes(self) -> tuple[str, ...]:
        return (*self.bound, *self.free)

    @property
    def forward(self) -> tuple[FD, ...]:
        return tuple(f for f in self.fds if f not in self.closing)

    def after(self, attribute: str) -> tuple[FD, ...]:
        """Forward FDs that an attribute's value leads to."""
        return tuple(g for g in self.forward if attribute in g.lhs)

    def shared_rhs(self) -> tuple[str, ...]:
        """Attributes that several FDs determine."""
        return tuple(a for a in self.free if sum(f.rhs == a for f in self.fds) > 1)

    def assigned_before(self, f: FD) -> bool:
        """Whether f's right side already has a value when it is f's turn."""
        before = self.fds[: self.fds.index(f)]
        return f.rhs in self.bound or any(g.rhs == f.rhs for g in before)


def bound_free(fds: Sequence[FD], prefer: Iterable[str] = (), seed: int | None = None, distinct: dict[str, int] | None = None) -> tuple[tuple[str, ...], tuple[str, ...]]:
    """Bound attributes (on no right side, and one for each cycle that nothing outside determines) and the others.

    The one of a cycle: a preferred one, else the one with most distinct values if counts are given, else one
    drawn by the seed, else the first in the order of the FDs.
    """
    rhs = {f.rhs for f in fds}
    seen = list(dict.fromkeys(a for f in fds for a in (*f.lhs, f.rhs)))
    bound = [a for a in seen if a not in rhs]
    layered = [part for _, part in fds_.layers(fds_.dependency_graph(fds))]
    while missing := set(seen) - fds_.closure(bound, fds):  # a cycle through composite left sides may need several
        part = next(part for part in layered if missing & set(part))
        members = [a for a in seen if a in part and a in missing]
        wanted = [a for a in prefer if a in members]
        if wanted:
            chosen = wanted[0]
        elif distinct:
            chosen = max(members, key=lambda a: (distinct.get(a, 0), -members.index(a)))
        else:
            chosen = random.Random(seed).choice(members) if seed is not None else members[0]
        bound.append(chosen)
    return tuple(a for a in seen if a in bound), tuple(a for a in seen if a not in bound)


def order(fds: Sequence[FD], bound: Sequence[str]) -> tuple[list[list[FD]], frozenset[FD]]:
    """Groups of FDs from the leftmost attributes to the rightmost, and the FDs that close a cycle.

    Components of attributes come by layer. Inside a component FDs follow one after the other, breadth-first from what is
    known, so that every left side has a value at its turn; then the FDs that leave it form one group. An FD
    with a composite left side leaves the last component that one of its attributes is in.
    """
    layered = fds_.layers(fds_.dependency_graph(fds))
    place = {a: k for k, (_, part) in enumerate(layered) for a in part}
    known, groups, closing = set(bound), [], set()
    for k, (_, part) in enumerate(layered):
        inner = [f for f in fds if place[f.rhs] == k and max(place[a] for a in f.lhs) == k]
        while inner:
            ready = [f for f in inner if known.issuperset(f.lhs)]
            if not ready:
                raise ValueError("no attribute of this cycle has a value: " + ", ".join(part))
            f = next((g for g in ready if g.rhs not in known), ready[0])
            inner.remove(f)
            if f.rhs in known:
                closing.add(f)
            known.add(f.rhs)
            groups.append([f])
        leaving = [f for f in fds if place[f.rhs] != k and max(place[a] for a in f.lhs) == k]
        if leaving:
            groups.append(leaving)
            known.update(f.rhs for f in leaving)
    return groups, frozenset(closing)


def path_equals_distinct(fds: Sequence[FD], closing: frozenset[FD]) -> bool:
    """Whether no pattern can be reached in two ways: no way on from a right side is longer than two FDs, so that only its last value could be met twice."""
    forward = [f for f in fds if f not in closing]

    def longest(a: str) -> int:
        return max((1 + longest(g.rhs) for g in forward if a in g.lhs), default=0)

    return all(longest(f.rhs) <= 2 and len(f.lhs) == 1 for f in fds)


def build_plan(
    fds: str | Iterable,
    schema: StructType | None = None,
    *,
    prefer_bound: Iterable[str] = (),
    seed: int | None = None,
    distinct: dict[str, int] | None = None,
    reach: str = "auto",
    back_edges: str = "target",
    on_conflict: str = "keep_first",
    nulls: str = "missing",
    lhs_source: str = "chased",
    minimal: str = "keep",
    ordered: bool = True,
) -> RepairPlan:
    """minimal: keep the FDs as given, reduce them, or be strict. ordered=False keeps the declared order (for comparison)."""
    for value, allowed in ((reach, ("auto", "distinct", "path")), (back_edges, ("target", "outside")), (on_conflict, ("keep_first", "overwrite", "component", "deferred")), (nulls, ("missing", "value")), (lhs_source, ("chased", "input")), (minimal, ("keep", "reduce", "strict"))):
        if value not in allowed:
            raise ValueError(f"{value!r} is none of {', '.join(allowed)}")
    listed = fds_.parse(fds, schema)
    if minimal == "reduce":
        listed = fds_.minimal_cover(listed)
    elif minimal == "strict":
        fds_.assert_minimal(listed)
    bound, free = bound_free(listed, prefer_bound, seed, distinct)
    groups, closing = order(listed, bound)
    flat = [f for g in groups for f in g] if ordered else listed
    if reach == "auto":
        reach = "path" if path_equals_distinct(listed, closing) else "distinct"
    component = {a: k for k, (_, part) in enumerate(fds_.layers(fds_.dependency_graph(listed))) for a in part}
    return RepairPlan(tuple(flat), tuple(map(tuple, groups)), bound, free, closing, component, reach, back_edges, on_conflict, nulls, lhs_source)
