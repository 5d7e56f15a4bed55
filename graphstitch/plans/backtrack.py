"""Sequential backtracking over small graphs: used by the tiler, as a baseline, and as the oracle of the tests."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import permutations

Adjacency = dict[int, set[int]]


def adjacency(edges: Iterable[tuple[int, int]], vertices: Iterable[int] = ()) -> Adjacency:
    out: Adjacency = {v: set() for v in vertices}
    for u, v in edges:
        out.setdefault(u, set()).add(v)
        out.setdefault(v, set()).add(u)
    return out


def visit_order(adj: Adjacency, start: int) -> list[int]:
    """From `start` on, always a vertex with most visited neighbours, then highest degree, then least number."""
    order, rest = [start], set(adj) - {start}
    while rest:
        seen = set(order)
        order.append(min(rest, key=lambda v: (-len(adj[v] & seen), -len(adj[v]), v)))
        rest.remove(order[-1])
    return order


def embeddings(pattern: Adjacency, data: Adjacency, induced: bool = False, start: int | None = None, roots: Iterable[int] | None = None) -> Iterator[dict[int, int]]:
    """All injective maps that keep edges (and non-edges if induced). `start` is placed first, on the given roots."""
    if not pattern:
        return
    start = max(pattern, key=lambda v: (len(pattern[v]), -v)) if start is None else start
    order = visit_order(pattern, start)
    back = [[w for w in order[:i] if w in pattern[v]] for i, v in enumerate(order)]
    apart = [[w for w in order[:i] if w not in pattern[v]] if induced else [] for i, v in enumerate(order)]
    image: dict[int, int] = {}
    used: set[int] = set()

    def choices(i: int):
        if not back[i]:
            pool = (sorted(data) if roots is None else roots) if i == 0 else sorted(data)
        else:
            pool = sorted(set.intersection(*(data[image[w]] for w in back[i])))
        need = len(pattern[order[i]])
        for c in pool:
            if c not in used and len(data.get(c, ())) >= need and all(c not in data[image[w]] for w in apart[i]):
                yield c

    stack = [choices(0)]
    while stack:
        i = len(stack) - 1
        v = order[i]
        if v in image:
            used.discard(image.pop(v))
        c = next(stack[-1], None)
        if c is None:
            stack.pop()
            continue
        image[v] = c
        used.add(c)
        if i + 1 == len(order):
            yield dict(image)
        else:
            stack.append(choices(i + 1))


def find_one(motif: Adjacency, residual: Adjacency, touch: Iterable[int] = (), rank=None) -> dict[int, int] | None:
    """The first occurrence of a motif among the residual edges; with `touch`, one that uses such a vertex. Stops at one hit."""
    touch = sorted(touch, key=rank) if rank else sorted(touch)
    if not touch:
        return next(embeddings(motif, residual, roots=sorted(residual, key=rank) if rank else None), None)
    for root in touch:
        if not residual.get(root):
            continue
        for position in sorted(motif):
            if (hit := next(embeddings(motif, residual, start=position, roots=[root]), None)) is not None:
                return hit
    return None


def brute(pattern_n: int, pattern_edges: Iterable[tuple[int, int]], data: Adjacency, induced: bool) -> set[tuple[int, ...]]:
    """By trying all injective assignments; for tiny graphs only."""
    edges = {frozenset(e) for e in pattern_edges}
    pairs = [(i, j) for i in range(pattern_n) for j in range(i)]
    out = set()
    for image in permutations(sorted(data), pattern_n):
        if all(image[j] in data[image[i]] if frozenset((i, j)) in edges else not (induced and image[j] in data[image[i]]) for i, j in pairs):
            out.add(image)
    return out
