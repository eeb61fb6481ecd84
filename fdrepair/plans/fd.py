"""Functional dependencies: parsing, implication, minimal cover, graphs, components and layers."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass

from pyspark.sql.types import ArrayType, MapType, StructType, VariantType


@dataclass(frozen=True, order=True)
class FD:
    """lhs determines rhs; one attribute on the right, several allowed on the left."""

    lhs: tuple[str, ...]
    rhs: str

    @property
    def name(self) -> str:
        return ",".join(self.lhs) + "->" + self.rhs

    @property
    def attributes(self) -> frozenset[str]:
        return frozenset((*self.lhs, self.rhs))


def parse(given: str | Iterable, schema: StructType | None = None) -> list[FD]:
    """FDs from "a,b -> c,d; c -> e", or from a list of such texts or FDs, without repeats, one attribute on each right side.

    A trivial FD (right side among the left) is an error, as is an attribute that the schema lacks or
    whose type can't be compared (map, variant) or is a list or record of floats used as a key (array).
    """
    pieces = [p for p in given.replace("\n", ";").split(";") if p.strip()] if isinstance(given, str) else list(given)
    out: list[FD] = []
    for piece in pieces:
        if isinstance(piece, FD):
            found = [piece]
        else:
            left, arrow, right = piece.partition("->")
            lhs = tuple(dict.fromkeys(a.strip() for a in left.split(",") if a.strip()))
            rhs = [a.strip() for a in right.split(",") if a.strip()]
            if not arrow or not lhs or not rhs:
                raise ValueError(f"no dependency: {piece!r}")
            found = [FD(lhs, r) for r in rhs]
        for f in found:
            if f.rhs in f.lhs:
                raise ValueError(f"trivial dependency: {f.name}")
            if f not in out:
                out.append(f)
    if schema is not None:
        for a in dict.fromkeys(a for f in out for a in (*f.lhs, f.rhs)):
            if a not in schema.fieldNames():
                raise ValueError(f"no such attribute: {a}")
            if isinstance(schema[a].dataType, (MapType, VariantType, ArrayType)):
                raise ValueError(f"{a}: values of type {schema[a].dataType.simpleString()} can't be a side of a dependency")
    return out


def closure(attributes: Iterable[str], fds: Sequence[FD]) -> frozenset[str]:
    """All attributes that the given ones determine."""
    known, grown = set(attributes), True
    while grown:
        grown = False
        for f in fds:
            if f.rhs not in known and known.issuperset(f.lhs):
                known.add(f.rhs)
                grown = True
    return frozenset(known)


def implies(fds: Sequence[FD], f: FD) -> bool:
    return f.rhs in closure(f.lhs, fds)


def minimal_cover(fds: Sequence[FD]) -> list[FD]:
    """An equivalent set without attributes or FDs that the rest implies."""
    kept = list(dict.fromkeys(fds))
    for k, f in enumerate(kept):
        for a in f.lhs:
            fewer = tuple(x for x in kept[k].lhs if x != a)
            if fewer and f.rhs in closure(fewer, kept):
                kept[k] = FD(fewer, f.rhs)
    kept = list(dict.fromkeys(kept))
    for f in list(kept):
        rest = [g for g in kept if g != f]
        if implies(rest, f):
            kept = rest
    return kept


def assert_minimal(fds: Sequence[FD]) -> None:
    cover = minimal_cover(fds)
    if set(cover) != set(fds):
        raise ValueError("not minimal; a minimal cover is " + "; ".join(f.name for f in cover))


def fd_graph(fds: Sequence[FD]) -> dict[frozenset[str], set[frozenset[str]]]:
    """Vertices are the attribute sets on either side; an edge for each FD."""
    graph: dict[frozenset[str], set[frozenset[str]]] = {}
    for f in fds:
        graph.setdefault(frozenset((f.rhs,)), set())
        graph.setdefault(frozenset(f.lhs), set()).add(frozenset((f.rhs,)))
    return graph


def dependency_graph(fds: Sequence[FD]) -> dict[str, set[str]]:
    """Attributes, with an edge from each one of a left side to the right side; so composite left sides are linked too."""
    graph: dict[str, set[str]] = {a: set() for f in fds for a in (*f.lhs, f.rhs)}
    for f in fds:
        for a in f.lhs:
            graph[a].add(f.rhs)
    return graph


def sccs(graph: dict) -> list[list]:
    """Strongly connected components in linear time, without recursion; components later in the list reach earlier ones only."""
    number: dict = {}
    low: dict = {}
    stack: list = []
    on_stack: set = set()
    out: list[list] = []
    for root in graph:
        if root in number:
            continue
        work = [(root, iter(sorted(graph[root], key=str)))]
        number[root] = low[root] = len(number)
        stack.append(root)
        on_stack.add(root)
        while work:
            v, rest = work[-1]
            step = next(rest, None)
            if step is None:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[v])
                if low[v] == number[v]:
                    part = []
                    while not part or part[-1] != v:
                        part.append(stack.pop())
                        on_stack.discard(part[-1])
                    out.append(sorted(part, key=str))
            elif step not in number:
                number[step] = low[step] = len(number)
                stack.append(step)
                on_stack.add(step)
                work.append((step, iter(sorted(graph[step], key=str))))
            elif step in on_stack:
                low[v] = min(low[v], number[step])
    return out


def layers(graph: dict) -> list[tuple[int, list]]:
    """(layer, component): 0 without predecessors, else one more than the greatest layer before it; by layer."""
    parts = sccs(graph)
    home = {v: k for k, part in enumerate(parts) for v in part}
    layer = [0] * len(parts)
    for k in range(len(parts) - 1, -1, -1):  # predecessors come later in the list
        for v in parts[k]:
            for w in graph[v]:
                if home[w] != k:
                    layer[home[w]] = max(layer[home[w]], layer[k] + 1)
    return sorted(zip(layer, parts), key=lambda x: (x[0], str(x[1])))


def interaction(f: FD, g: FD) -> str:
    """same_lhs, same_rhs, chain, cycle or none: how patterns of two FDs meet."""
    if f == g:
        return "none"
    forth, back = f.rhs in g.lhs, g.rhs in f.lhs
    if forth and back:
        return "cycle"
    if forth or back:
        return "chain"
    if f.rhs == g.rhs:
        return "same_rhs"
    if set(f.lhs) & set(g.lhs):
        return "same_lhs"
    return "none"


def dependent(f: FD, g: FD) -> bool:
    """Whether the choice for one can bear on the choice for the other."""
    return interaction(f, g) in ("same_rhs", "chain", "cycle")


def parts(fds: Sequence[FD]) -> list[list[FD]]:
    """FDs in groups that depend on each other; patterns of different groups are independent."""
    rest, out = list(fds), []
    while rest:
        group, todo = [], [rest.pop(0)]
        while todo:
            f = todo.pop(0)
            group.append(f)
            near = [g for g in rest if dependent(f, g)]
            rest = [g for g in rest if g not in near]
            todo += near
        out.append([f for f in fds if f in group])
    return out
