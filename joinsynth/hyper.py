"""Join hypergraphs: specifications, boundaries, acyclicity, attribute trees, edge covers.

Everything here is driver-side and depends on the (constant-size) query only, never on data.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np


@dataclass(frozen=True)
class AttrDomain:
    """A public, finite domain: a list of values, or the keys that a SQL text over public tables gives."""

    values: tuple = ()
    sql: str | None = None

    @property
    def is_key(self) -> bool:
        return self.sql is not None


@dataclass(frozen=True)
class RelationSpec:
    """One relation of a join: its attributes, and the SQL text (``{table}`` placeholders) that derives them."""

    name: str
    attrs: tuple[str, ...]
    source: str

    def sql(self) -> str:
        """The text for an engine that knows the tables by name."""
        return self.source.replace("{", "").replace("}", "").replace("element_at(", "list_extract(")


@dataclass(frozen=True)
class JoinSpec:
    """A natural join with public domains.

    ``group_factor``: relations derived from one private table.  ``public``: SQL texts over public tables that give the domain
    of several attributes together, where it is smaller than the product of theirs.
    """

    name: str
    relations: tuple[RelationSpec, ...]
    domains: dict[str, AttrDomain] = field(default_factory=dict, hash=False)
    group_factor: int = 1
    public: tuple[tuple[tuple[str, ...], str], ...] = ()

    @property
    def m(self) -> int:
        return len(self.relations)

    @property
    def attrs(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(a for r in self.relations for a in r.attrs))

    def atom(self, attr: str) -> frozenset[int]:
        """Relations (numbered from 0) that hold the attribute."""
        return frozenset(i for i, r in enumerate(self.relations) if attr in r.attrs)


def meet(spec: JoinSpec, rels: Iterable[int]) -> tuple[str, ...]:
    """Attributes held by every relation of the set."""
    rels = list(rels)
    return tuple(a for a in spec.attrs if all(a in spec.relations[i].attrs for i in rels)) if rels else ()


def union(spec: JoinSpec, rels: Iterable[int]) -> tuple[str, ...]:
    rels = set(rels)
    return tuple(a for a in spec.attrs if spec.atom(a) & rels)


def boundary(spec: JoinSpec, rels: Iterable[int]) -> tuple[str, ...]:
    """Attributes both inside and outside the set of relations."""
    rels = frozenset(rels)
    return tuple(a for a in spec.attrs if spec.atom(a) & rels and spec.atom(a) - rels)


def components(spec: JoinSpec, rels: Iterable[int], without: Iterable[str] = ()) -> list[tuple[int, ...]]:
    """Connected parts of a set of relations once some attributes are removed."""
    without, left, out = set(without), set(rels), []
    while left:
        part, edge = set(), {min(left)}
        while edge:
            part |= edge
            held = {a for i in edge for a in spec.relations[i].attrs} - without
            edge = {i for i in left - part if held & set(spec.relations[i].attrs)}
        out.append(tuple(sorted(part)))
        left -= part
    return sorted(out)


def is_acyclic(spec: JoinSpec) -> bool:
    """Ear removal: drop private attributes and contained edges until nothing or a core is left."""
    edges = [set(r.attrs) for r in spec.relations]
    while True:
        before = sum(map(len, edges)), len(edges)
        for e in edges:
            e -= {a for a in e if sum(a in f for f in edges) == 1}
        edges = [e for i, e in enumerate(edges) if e and not any(e < f or (e == f and i < j) for j, f in enumerate(edges) if j != i)]
        if len(edges) <= 1:
            return True
        if (sum(map(len, edges)), len(edges)) == before:
            return False


def is_hierarchical(spec: JoinSpec) -> bool:
    """Any two attributes' relation sets are nested or disjoint."""
    return all(a <= b or b <= a or not a & b for a, b in combinations([spec.atom(x) for x in spec.attrs], 2))


@dataclass(frozen=True)
class Node:
    """A tree node: one attribute, or several with the same relations."""

    attrs: tuple[str, ...]
    atom: frozenset[int]

    @property
    def name(self) -> str:
        return "".join(self.attrs)


class AttrTree:
    """Attribute tree of a hierarchical join; a forest where the join is not connected."""

    def __init__(self, spec: JoinSpec) -> None:
        if not is_hierarchical(spec):
            raise ValueError(f"{spec.name} is not hierarchical")
        self.spec = spec
        sets = dict.fromkeys(spec.atom(a) for a in spec.attrs)
        self.nodes = [Node(tuple(a for a in spec.attrs if spec.atom(a) == s), s) for s in sets]

    def ancestors(self, node: Node) -> tuple[str, ...]:
        """Attributes above the node, in the order of the specification."""
        return tuple(a for a in self.spec.attrs if self.spec.atom(a) > node.atom)

    def children(self, node: Node) -> list[Node]:
        below = [n for n in self.nodes if n.atom < node.atom]
        return [n for n in below if not any(n.atom < o.atom for o in below)]

    def roots(self) -> list[Node]:
        return [n for n in self.nodes if not any(n.atom < o.atom for o in self.nodes)]

    def below(self, node: Node) -> list[Node]:
        return [x for c in self.children(node) for x in (*self.below(c), c)]

    def post_order(self) -> Iterator[Node]:
        for root in self.roots():
            yield from self.below(root)
            yield root


def product_factors(spec: JoinSpec, rels: Iterable[int], given: tuple[str, ...] | None = None) -> list[tuple[tuple[int, ...], tuple[str, ...]]]:
    """Maximum degrees (relations, attributes) whose product bounds the aggregate over ``rels`` grouped by ``given``.

    A connected set whose common attributes are not all given contributes the maximum degree of those
    common attributes, after which they are given too; a single relation contributes its own degree.
    """
    rels = tuple(sorted(rels))
    given = boundary(spec, rels) if given is None else given
    parts = components(spec, rels, given)
    if len(parts) > 1:
        return [f for p in parts for f in product_factors(spec, p, tuple(a for a in given if a in union(spec, p)))]
    if len(rels) == 1:
        return [(rels, given)]
    wider = tuple(dict.fromkeys((*given, *meet(spec, rels))))
    if set(wider) == set(given):
        raise ValueError("the join is not hierarchical")
    return [(rels, given), *product_factors(spec, rels, tuple(a for a in spec.attrs if a in wider))]


def fractional_edge_cover(spec: JoinSpec, rels: Iterable[int] | None = None, without: Iterable[str] = ()) -> float:
    """Least total weight of relations that covers every attribute (vertex enumeration; constant size)."""
    rels = list(range(spec.m)) if rels is None else list(rels)
    attrs = [a for a in union(spec, rels) if a not in set(without)]
    if not attrs:
        return 0.0
    a = np.array([[float(x in spec.relations[i].attrs) for i in rels] for x in attrs])
    rows, rhs = np.vstack([a, np.eye(len(rels))]), np.concatenate([np.ones(len(attrs)), np.zeros(len(rels))])
    best = float(len(rels))
    for pick in combinations(range(len(rows)), len(rels)):
        sub = rows[list(pick)]
        if abs(np.linalg.det(sub)) > 1e-9:
            x = np.linalg.solve(sub, rhs[list(pick)])
            if (rows @ x >= rhs - 1e-9).all():
                best = min(best, float(x.sum()))
    return best


def worst_case_error(spec: JoinSpec, n: float, bags: bool = False) -> float:
    """Worst-case error over instances of size ``n``: for bags n**(m - 1/2), for sets by fractional covers."""
    if bags:
        return n ** (spec.m - 0.5)
    every = range(spec.m)
    residual = max(fractional_edge_cover(spec, e, boundary(spec, e)) for k in range(spec.m) for e in combinations(every, k)) if spec.m > 1 else 0.0
    return float(np.sqrt(n ** fractional_edge_cover(spec) * n**residual))
