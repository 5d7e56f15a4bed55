"""Patterns: small connected graphs with vertices 0..n-1, held by the driver."""

from __future__ import annotations

import random
from collections.abc import Sequence
from dataclasses import dataclass
from functools import cached_property

from graphstitch.plans.backtrack import Adjacency, adjacency, embeddings


@dataclass(frozen=True)
class Pattern:
    n: int
    edges: frozenset[tuple[int, int]]

    def __post_init__(self):
        edges = frozenset((min(e), max(e)) for e in self.edges)
        object.__setattr__(self, "edges", edges)
        if self.n < 1:
            raise ValueError("a pattern needs a vertex")
        if any(u == v or not 0 <= u < self.n or not 0 <= v < self.n for u, v in edges):
            raise ValueError("edges join two different vertices of 0..n-1")
        seen, todo = {0}, [0]
        while todo:
            for w in self.adj[todo.pop()] - seen:
                seen.add(w)
                todo.append(w)
        if len(seen) < self.n:
            raise ValueError("a pattern must be connected")

    @classmethod
    def of(cls, *edges: tuple[int, int]) -> Pattern:
        return cls(max(map(max, edges)) + 1, frozenset(edges))

    @classmethod
    def from_text(cls, text: str) -> Pattern:
        """From "0-1,1-2"; a lone number is a pattern of one vertex."""
        parts = [tuple(map(int, e.split("-"))) for e in text.split(",")]
        return cls(max(map(max, parts)) + 1, frozenset(e for e in parts if len(e) == 2))

    def text(self) -> str:
        return ",".join(f"{u}-{v}" for u, v in sorted(self.edges)) or "0"

    @cached_property
    def adj(self) -> Adjacency:
        return adjacency(self.edges, range(self.n))

    def automorphisms(self) -> list[tuple[int, ...]]:
        return sorted(tuple(m[i] for i in range(self.n)) for m in embeddings(self.adj, self.adj, induced=True))

    def symmetry_conditions(self) -> list[tuple[int, int]]:
        """Pairs (i, j), image of i below image of j, that leave one of every mapping's automorphic images: vertex by vertex,
        the image of v is the least in its orbit under the automorphisms that fix the vertices before it."""
        group, out = self.automorphisms(), []
        for v in range(self.n):
            out += [(v, w) for w in sorted({a[v] for a in group}) if w != v]
            group = [a for a in group if a[v] == v]
        return out


def path(k: int) -> Pattern:
    return Pattern(k, frozenset((i, i + 1) for i in range(k - 1)))


def ring(k: int) -> Pattern:
    return Pattern(k, frozenset((i, (i + 1) % k) for i in range(k)))


def star(k: int) -> Pattern:
    """A centre 0 with k leaves."""
    return Pattern(k + 1, frozenset((0, i) for i in range(1, k + 1)))


def induced_on(data: Adjacency, chosen: Sequence[int]) -> Pattern:
    """The pattern that the chosen vertices of a graph induce, numbered as they are listed."""
    at = {v: i for i, v in enumerate(chosen)}
    return Pattern(len(chosen), frozenset((at[u], at[w]) for u in chosen for w in data[u] if w in at and at[u] < at[w]))


def routed_star(data: Adjacency, way: Sequence[int], n: int) -> Pattern:
    """A star circuit routed on a device: the hub moves along a way, about three quarters of the vertices, and meets the others
    beside it. All are vertices of the device, so the pattern has a placement there."""
    for long in range(n - n // 4, n + 1):
        spine = list(way[:long])
        beside = [w for v in spine for w in sorted(data[v]) if w not in spine]
        chosen = spine + list(dict.fromkeys(beside))[: n - long]
        if len(chosen) == n:
            return induced_on(data, chosen)
    raise ValueError("the way is too short")


def sample_pattern(data: Adjacency, n: int, seed: int, compact: float = 0.0) -> Pattern:
    """A random connected vertex-induced subgraph: grown from a random vertex by random frontier vertices; with compact > 0,
    vertices with more chosen neighbours are preferred."""
    rng = random.Random(seed)
    chosen = [rng.choice(sorted(data))]
    inside = set(chosen)
    while len(chosen) < n:
        frontier = sorted({w for v in chosen for w in data[v]} - inside)
        if not frontier:
            raise ValueError("the component has too few vertices")
        weights = [1 + compact * len(data[w] & inside) for w in frontier]
        chosen.append(rng.choices(frontier, weights)[0])
        inside.add(chosen[-1])
    return induced_on(data, chosen)
