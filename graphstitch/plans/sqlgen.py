"""SQL text of a pattern or a stitch plan; it runs on Spark SQL and on DuckDB alike, given a relation edges(u, v)."""

from __future__ import annotations

from graphstitch.plans.backtrack import visit_order
from graphstitch.plans.decompose import StitchPlan
from graphstitch.plans.pattern import Pattern


def select_list(n: int) -> str:
    return ", ".join(f"v{i}" for i in range(n))


def flat(pattern: Pattern, induced: bool, symmetry: bool = False) -> str:
    """One n-way self-join; for small patterns. A table per edge of a spanning order, the rest are conditions."""
    order = visit_order(pattern.adj, 0)
    at, tables, where = {}, [], []
    for v in order:
        back = [w for w in order[: order.index(v)] if w in pattern.adj[v]]
        if not back:
            if pattern.n == 1:
                return "SELECT id AS v0 FROM ids"
            first = min(pattern.adj[v], key=order.index)
            tables.append("edges e0")
            at[v], at[first] = "e0.u", "e0.v"
            done = {v, first}
            continue
        if v not in at:
            k = f"e{len(tables)}"
            tables.append(f"edges {k}")
            where.append(f"{k}.u = {at[back[0]]}")
            at[v] = f"{k}.v"
        for w in back if v not in done else back[1:]:
            if w != back[0] or v in done and {v, w} != done:
                where.append(f"EXISTS (SELECT 1 FROM edges x WHERE x.u = {at[w]} AND x.v = {at[v]})")
    for i in range(pattern.n):
        for j in range(i):
            if j not in pattern.adj[i]:
                where.append(f"{at[i]} <> {at[j]}")
                if induced:
                    where.append(f"NOT EXISTS (SELECT 1 FROM edges x WHERE x.u = {at[j]} AND x.v = {at[i]})")
    if symmetry:
        where += [f"{at[i]} < {at[j]}" for i, j in pattern.symmetry_conditions()]
    return f"SELECT {', '.join(f'{at[i]} AS v{i}' for i in range(pattern.n))} FROM {', '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "")


def steps(pattern: Pattern, induced: bool, prefix: str = "s", materialized: bool = True) -> tuple[str, str]:
    """CTEs, one for each added vertex, and the name of the last: for larger patterns."""
    keep = " AS MATERIALIZED" if materialized else " AS"
    order = visit_order(pattern.adj, 0)
    out = [f"{prefix}0{keep} (SELECT id AS v{order[0]} FROM ids)"]
    for k, v in enumerate(order[1:], 1):
        seen = order[:k]
        back = [w for w in seen if w in pattern.adj[v]]
        joins = [f"JOIN edges e0 ON e0.u = b.v{back[0]}"] + [f"JOIN edges e{i} ON e{i}.u = b.v{w} AND e{i}.v = e0.v" for i, w in enumerate(back[1:], 1)]
        where = [f"e0.v NOT IN ({', '.join(f'b.v{w}' for w in seen)})"]
        if induced:
            apart = [w for w in seen if w not in back]
            where += [f"NOT EXISTS (SELECT 1 FROM edges x WHERE x.u = b.v{w} AND x.v = e0.v)" for w in apart]
        out.append(f"{prefix}{k}{keep} (SELECT b.*, e0.v AS v{v} FROM {prefix}{k - 1} b {' '.join(joins)} WHERE {' AND '.join(where)})")
    return ", ".join(out), f"{prefix}{len(order) - 1}"


def to_sql(pattern: Pattern, ctes: str, induced: bool = True, style: str = "steps", what: str | None = None) -> str:
    """A whole statement; ctes must define ids(id) and edges(u, v). what: the outer select over relation m."""
    if style == "flat":
        return f"WITH {ctes}, m AS ({flat(pattern, induced)}) SELECT {what or select_list(pattern.n)} FROM m"
    body, last = steps(pattern, induced)
    return f"WITH {ctes}, {body}, m AS (SELECT * FROM {last}) SELECT {what or select_list(pattern.n)} FROM m"


def plan_sql(plan: StitchPlan, motif_ctes: dict[str, str], ctes: str, materialized: bool = False) -> str:
    """A stitch plan as one CTE per tile over CTEs of its motif tables (monomorphisms)."""
    keep = " AS MATERIALIZED" if materialized else " AS"
    out = [ctes, *[f"motif_{name}{keep} ({sql})" for name, sql in motif_ctes.items()]]
    bound: list[int] = []
    for k, t in enumerate(plan.tiles):
        if not k:
            cols = ", ".join(f"c{j} AS v{v}" for j, v in enumerate(t.verts))
            out.append(f"t0{keep} (SELECT {cols} FROM motif_{t.motif})")
        else:
            at = {v: j for j, v in enumerate(t.verts)}
            on = [f"b.v{v} = m.c{at[v]}" for v in t.seam]
            on += [f"m.c{at[v]} NOT IN ({', '.join(f'b.v{w}' for w in bound)})" for v in t.fresh]
            cols = ", ".join([f"b.v{v}" for v in bound] + [f"m.c{at[v]} AS v{v}" for v in t.fresh])
            out.append(f"t{k}{keep} (SELECT {cols} FROM t{k - 1} b JOIN motif_{t.motif} m ON {' AND '.join(on)})")
        bound += [v for v in t.fresh]
    return f"WITH {', '.join(out)} SELECT {select_list(plan.pattern.n)} FROM t{len(plan.tiles) - 1}"


def motif_sql(pattern: Pattern) -> str:
    """The table of a motif, columns c0..: all its placements, non-induced."""
    return f"SELECT {', '.join(f'v{i} AS c{i}' for i in range(pattern.n))} FROM ({flat(pattern, False)}) q"
