"""Families of hypergraphs that the measures are tabulated on."""

from __future__ import annotations

from itertools import combinations

from .hypergraph import Hypergraph


def path(edges: int = 2) -> Hypergraph:
    return Hypergraph.of({f"x{i}", f"x{i + 1}"} for i in range(edges))


def star(leaves: int) -> Hypergraph:
    return Hypergraph.of({"hub", f"x{i}"} for i in range(leaves))


def cycle(k: int) -> Hypergraph:
    return Hypergraph.of({f"x{i}", f"x{(i + 1) % k}"} for i in range(k))


def clique(k: int) -> Hypergraph:
    return Hypergraph.of(combinations([f"x{i}" for i in range(k)], 2))


def triangle() -> Hypergraph:
    return Hypergraph.of(["xy", "yz", "xz"])


def loomis_whitney(k: int) -> Hypergraph:
    return Hypergraph.of(combinations([f"x{i}" for i in range(k)], k - 1))


def boat(k: int) -> Hypergraph:
    """Two disjoint edges of k vertices and k edges that pair them; k of 2 or more."""
    if k < 2:
        raise ValueError("a boat has k >= 2")
    return Hypergraph.of([[f"x{i}" for i in range(k)], [f"y{i}" for i in range(k)], *([f"x{i}", f"y{i}"] for i in range(k))])


def boat_plus_z(k: int) -> Hypergraph:
    """A boat with one further vertex in every edge."""
    return Hypergraph.of([*e, "z"] for e in boat(k).edges)


def bowtie() -> Hypergraph:
    """Two triangles that share z."""
    return Hypergraph.of(["xy", "yz", "xz", "zv", "zw", "vw"])


def nine_var() -> Hypergraph:
    """Nine variables in edges of several sizes. The edges."""
    return Hypergraph.of(["ab", "bcde", "bef", "efg", "gh", "gi", "hi"])


def not_reduced() -> Hypergraph:
    return Hypergraph.of(["x", "xy", "y"])


def named() -> dict[str, Hypergraph]:
    """The tabulated members."""
    return {
        "path_2": path(2),
        "triangle": triangle(),
        **{f"clique_{k}": clique(k) for k in (4, 5)},
        **{f"cycle_{k}": cycle(k) for k in (4, 5, 6)},
        **{f"star_{k}": star(k) for k in (3, 4)},
        "bowtie": bowtie(),
        **{f"loomis_whitney_{k}": loomis_whitney(k) for k in (4, 5)},
        **{f"boat_{k}": boat(k) for k in (2, 3, 4)},
        **{f"boat_z_{k}": boat_plus_z(k) for k in (2, 3, 4)},
        "nine_var": nine_var(),
        "not_reduced": not_reduced(),
    }
