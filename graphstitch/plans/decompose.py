"""Tiling: a pattern's edges are covered by motif occurrences that share no edge, one after another."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

from graphstitch.plans.backtrack import adjacency, find_one
from graphstitch.plans.motifs import Motif, motif_set
from graphstitch.plans.pattern import Pattern


@dataclass(frozen=True)
class Tile:
    """Motif position j lies on pattern vertex verts[j]. seam: vertices bound before; fresh: the others; boundary: vertices
    with edges left after this tile."""

    motif: str
    verts: tuple[int, ...]
    edges: tuple[tuple[int, int], ...]
    seam: tuple[int, ...]
    fresh: tuple[int, ...]
    boundary: tuple[int, ...]


@dataclass(frozen=True)
class StitchPlan:
    pattern: Pattern
    tiles: tuple[Tile, ...]

    def rows(self) -> list[tuple]:
        text = lambda vs: " ".join(map(str, vs))
        return [(i, t.motif, text(t.verts), text(t.seam), text(t.fresh)) for i, t in enumerate(self.tiles)]


ORDERS: dict[str, Callable[[Motif], tuple]] = {
    "size_desc": lambda m: (-m.n, -len(m.pattern.edges), m.name),
    "size_asc": lambda m: (m.n, len(m.pattern.edges), m.name),
    "edges_desc": lambda m: (-len(m.pattern.edges), -m.n, m.name),
}


def decompose(pattern: Pattern, motifs: Iterable[Motif | str] = ("edge",), order: str = "size_desc", rotate: int = 0, choose=None) -> StitchPlan:
    """Greedy: motifs in the given order ("user": as listed), the first occurrence wins, smaller motifs fill what is left.
    After the first tile, each must touch a vertex that is covered already. `rotate` moves the place where search begins;
    `choose`, if given, picks among the first occurrences of all motifs that fit."""
    motifs = list(motifs)
    ranked = motif_set(motifs)
    if order == "user":
        place = {(m if isinstance(m, str) else m.name): i for i, m in enumerate(motifs)}
        ranked.sort(key=lambda m: place.get(m.name, len(place)))
    else:
        ranked.sort(key=ORDERS[order])
    rank = (lambda v: (v - rotate) % pattern.n) if rotate else None
    left, covered, tiles = set(pattern.edges), set(), []
    while left:
        residual = adjacency(left)
        hits = ((m, hit) for m in ranked if len(m.pattern.edges) <= len(left) and (hit := find_one(m.pattern.adj, residual, covered & residual.keys(), rank)) is not None)
        m, hit = choose(list(hits), covered) if choose else next(hits)
        verts = tuple(hit[j] for j in range(m.n))
        edges = tuple(sorted((min(hit[a], hit[b]), max(hit[a], hit[b])) for a, b in m.pattern.edges))
        left -= set(edges)
        still = {v for e in left for v in e}
        tiles.append(Tile(m.name, verts, edges, tuple(v for v in verts if v in covered), tuple(v for v in verts if v not in covered), tuple(v for v in verts if v in still)))
        covered |= set(verts)
    return StitchPlan(pattern, tuple(tiles))
