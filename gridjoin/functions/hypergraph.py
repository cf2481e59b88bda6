"""Query hypergraphs: one vertex for each variable, one edge for each relation's variables. Driver-side and small."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field
from functools import cached_property
from itertools import combinations

Edge = frozenset[str]


def _sorted(edges: Iterable[Edge]) -> tuple[Edge, ...]:
    return tuple(sorted({frozenset(e) for e in edges if e}, key=lambda e: (len(e), sorted(e))))


@dataclass(frozen=True)
class Hypergraph:
    edges: tuple[Edge, ...] = field(default=())

    @classmethod
    def of(cls, schemas: Iterable[Iterable[str]]) -> Hypergraph:
        return cls(_sorted(frozenset(s) for s in schemas))

    @cached_property
    def vertices(self) -> tuple[str, ...]:
        return tuple(sorted(set().union(*self.edges))) if self.edges else ()

    @property
    def arity(self) -> int:
        return max(map(len, self.edges), default=0)

    def induced(self, keep: Iterable[str]) -> Hypergraph:
        """Every edge cut down to ``keep``; empty ones drop out, equal ones merge."""
        kept = frozenset(keep)
        return Hypergraph(_sorted(e & kept for e in self.edges))

    def reduced(self) -> Hypergraph:
        """Without edges that lie inside another edge."""
        return Hypergraph(tuple(e for e in self.edges if not any(e < f for f in self.edges)))

    def is_reduced(self) -> bool:
        return len(self.reduced().edges) == len(self.edges)

    def components(self) -> list[Hypergraph]:
        groups: list[tuple[set[str], list[Edge]]] = []
        for e in self.edges:
            touching = [g for g in groups if g[0] & e]
            merged = (set(e).union(*(g[0] for g in touching)), [x for g in touching for x in g[1]] + [e])
            groups = [g for g in groups if g not in touching] + [merged]
        return sorted((Hypergraph(_sorted(g[1])) for g in groups), key=lambda h: h.vertices)

    def join_tree(self) -> list[tuple[Edge, Edge | None]] | None:
        """Edges in ear-removal order with the edge that each hangs on; None if the hypergraph has a cycle."""
        left, order = list(self.edges), []
        while left:
            for e in left:
                others = [f for f in left if f != e]
                shared = e & frozenset().union(*others) if others else frozenset()
                witness = next((f for f in others if shared <= f), None)
                if not others or witness is not None:
                    order.append((e, witness if shared or not others else None))
                    left.remove(e)
                    break
            else:
                return None
        return order

    def is_acyclic(self) -> bool:
        return self.join_tree() is not None

    def subsets(self) -> Iterable[frozenset[str]]:
        for k in range(1, len(self.vertices) + 1):
            for s in combinations(self.vertices, k):
                yield frozenset(s)

    def __str__(self) -> str:
        return " ".join("".join(sorted(e)) if all(len(x) == 1 for x in e) else "(" + ",".join(sorted(e)) + ")" for e in self.edges)
