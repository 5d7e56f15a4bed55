"""Motifs: small connected templates of which all placements in the data graph are tabulated."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from graphstitch.plans.pattern import Pattern, path, ring, star


@dataclass(frozen=True)
class Motif:
    name: str
    pattern: Pattern

    @classmethod
    def from_edges(cls, name: str, edges: Iterable[tuple[int, int]]) -> Motif:
        return cls(name, Pattern.of(*edges))

    @property
    def n(self) -> int:
        return self.pattern.n

    @property
    def size(self) -> tuple[int, int]:
        return self.n, len(self.pattern.edges)


def _library() -> dict[str, Motif]:
    """Shapes by rule: paths, rings, stars; a ladder of two squares; a 12-ring with a leaf at every other vertex."""
    shapes = {"edge": path(2), "triangle": ring(3), "claw4": star(3)}
    shapes |= {f"path{k}": path(k) for k in range(3, 9)} | {f"ring{k}": ring(k) for k in range(4, 13)} | {f"star{k}": star(k) for k in range(2, 7)}
    shapes["ladder6"] = Pattern(6, ring(6).edges | {(0, 3)})
    shapes["sunhex18"] = Pattern(18, ring(12).edges | {(2 * i, 12 + i) for i in range(6)})
    return {name: Motif(name, shape) for name, shape in shapes.items()}


LIBRARY = _library()
HEAVY_HEX_DEFAULT, GRID_DEFAULT = ("edge", "path4"), ("edge", "ring4", "ring6")
HEAVY_HEX_CLAW, GRID_SMALL = ("edge", "claw4"), ("edge", "ring4")


def motif(m: Motif | str) -> Motif:
    return m if isinstance(m, Motif) else LIBRARY[m]


def motif_set(motifs: Iterable[Motif | str]) -> list[Motif]:
    """Resolved, with `edge` always among them, smallest first."""
    got = {m.name: m for m in map(motif, motifs)}
    return sorted(({"edge": LIBRARY["edge"]} | got).values(), key=lambda m: (*m.size, m.name))
