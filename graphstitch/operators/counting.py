"""Rows of motif tables without making them: counts are pushed below the stitches.

A table of placements grows with the third or fourth power of a hub's degree; its number of rows needs far less. Stars and
paths come from degrees; triangles from wedges at their least vertex; a ring of four is two wedges over the same ends, counted
once for each pair of ends, at centres that lie below one of them. The order of vertices is by degree for the heavy ones, which
are few and broadcast, and by id for the others, whose degree is bounded; so wedges stay near the edges times that bound.
"""

from __future__ import annotations

import math
from decimal import Decimal
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.plans.pattern import Pattern
from graphstitch.session import cut, forget

#: Degree beyond which a vertex is heavy; it is raised until no more than HEAVY_ROWS are.
LIGHT, HEAVY_ROWS = 64, 200_000
#: Undirected edges for a class of ends, and pairs of ends that a task holds unsorted.
CLASS_EDGES, PAIRS = 8_000_000, 8_000_000
#: Edges that are dealt at once.
DEAL = 200_000
_MIX = np.uint64(0x9E3779B97F4A7C15)
_SCHEMA = pa.schema([("t", pa.int32()), ("same", pa.bool_()), ("x", pa.binary()), ("xn", pa.binary()), ("y", pa.binary()), ("yn", pa.binary())])
NAMES = _SCHEMA.names


class Counts:
    """Placements of small patterns in a graph whose edges are held in both directions."""

    def __init__(self, edges: DataFrame, light: int = LIGHT, class_edges: int = CLASS_EDGES):
        self.edges, self.least, self.class_edges = edges, light, class_edges

    def of(self, pattern: Pattern) -> int | None:
        """Ordered injective placements; None for a shape that has to be enumerated."""
        degrees = sorted(len(pattern.adj[v]) for v in range(pattern.n))
        n = pattern.n
        if n > 1 and len(pattern.edges) == n - 1 and degrees[-1] == n - 1:
            return self.stars(n - 1)
        return {(3, (2, 2, 2)): self.triangles, (4, (1, 1, 2, 2)): self.paths4, (4, (2, 2, 2, 2)): self.rings4}.get((n, tuple(degrees)), lambda: None)()

    @cached_property
    def _degrees(self) -> tuple[dict[int, int], DataFrame]:
        """How many vertices have a degree, and the heavy ones with theirs."""
        spark = self.edges.sparkSession
        held = cut(self.edges.groupBy("u").agg(F.count("*").alias("h")))
        many = {r["h"]: r["n"] for r in held.groupBy("h").agg(F.count("*").alias("n")).collect()}
        light = self.least
        while sum(n for d, n in many.items() if d > light) > HEAVY_ROWS:
            light *= 2
        heavy = held.where(F.col("h") > light).toArrow()
        forget(held)
        return many, spark.createDataFrame(heavy) if heavy.num_rows else spark.createDataFrame([], "u long, h long")

    def _heavy(self, v: str, h: str) -> DataFrame:
        return F.broadcast(self._degrees[1].select(F.col("u").alias(v), F.col("h").alias(h)))

    @cached_property
    def _ordered(self) -> DataFrame:
        """u, v, hu, hv (degrees of heavy ends, else 0), and whether v lies above u."""
        e = self.edges.select("u", "v").join(self._heavy("u", "hu"), "u", "left").join(self._heavy("v", "hv"), "v", "left").fillna(0, ["hu", "hv"])
        return e.select("u", "v", "hu", "hv", (F.struct("hv", "v") > F.struct(F.col("hu").alias("hv"), F.col("u").alias("v"))).alias("above"))

    @cached_property
    def _climbers(self) -> DataFrame:
        """Heavy vertices with a neighbour above them."""
        rows = self._ordered.where("hu > 0 and hv > 0 and above").select("u").distinct().toArrow()
        spark = self.edges.sparkSession
        return spark.createDataFrame(rows) if rows.num_rows else spark.createDataFrame([], "u long")

    def stars(self, leaves: int) -> int:
        return sum(n * math.perm(d, leaves) for d, n in self._degrees[0].items())

    def paths4(self) -> int:
        """Over the middle edges, (d(u) - 1)(d(v) - 1) pairs of ends; ends that coincide close a triangle. A heavy end's degree
        is broadcast, a light end's is counted beside its heavy neighbours; only edges of two light ends are joined."""
        e = self._ordered
        wide = lambda a, b: F.sum(((a - 1) * (b - 1)).cast("decimal(38,0)")).alias("n")
        total = e.where("hu > 0 and hv > 0").agg(wide(F.col("hu"), F.col("hv"))).first()["n"] or 0
        beside = e.where("hu = 0").groupBy("u").agg(F.count("*").alias("d"), F.sum(F.when(F.col("hv") > 0, F.col("hv") - 1).otherwise(0)).alias("s"))
        total += 2 * (beside.agg(F.sum(((F.col("d") - 1) * F.col("s")).cast("decimal(38,0)")).alias("n")).first()["n"] or 0)
        both = e.where("hu = 0 and hv = 0").select("u", "v")
        if not both.isEmpty():
            d = e.where("hu = 0").groupBy("u").agg(F.count("*").alias("d"))
            sums = both.join(d.select(F.col("u").alias("v"), F.col("d").alias("dv")), "v").groupBy("u").agg(F.sum(F.col("dv") - 1).alias("s"))
            total += sums.join(d, "u").agg(F.sum(((F.col("d") - 1) * F.col("s")).cast("decimal(38,0)")).alias("n")).first()["n"] or 0
        return int(total) - self.triangles()

    @cached_property
    def _triangles(self) -> int:
        up = self._ordered.where("above")
        # the middle vertex has a neighbour above it
        legs = up.join(F.broadcast(self._climbers.select(F.col("u").alias("v"), F.lit(True).alias("climbs"))), "v", "left").where("hv = 0 or climbs").select("u", F.col("v").alias("b"))
        if legs.isEmpty():
            return 0
        wedges = legs.join(up.select("u", F.col("v").alias("a")), "u").where("a <> b").select("a", "b")
        return wedges.join(up.select(F.col("u").alias("b"), F.col("v").alias("a")), ["a", "b"], "left_semi").count()

    def triangles(self) -> int:
        return 6 * self._triangles

    def rings4(self) -> int:
        """Each centre deals its ends to tasks by two classes of vertices; a pair of ends with n centres closes n (n - 1) / 2
        rings, of eight placements each. A centre counts for a pair only if it lies below one of the two: both centres of a
        ring do for the ends that hold its greatest vertex, and not both for the other ends, so a ring comes once."""
        edges = sum(d * n for d, n in self._degrees[0].items()) // 2
        classes = max(4, edges // self.class_edges)
        centres = self._ordered.join(F.broadcast(self._climbers.withColumn("climbs", F.lit(True))), "u", "left").where("hu = 0 or climbs")
        dealt = centres.select("u", "v", "above").repartition("u").sortWithinPartitions("u").mapInArrow(_deal(classes), "t int, same boolean, x binary, xn binary, y binary, yn binary")
        tasks = dealt.groupBy("t").applyInArrow(_rings, "n decimal(38,0)")
        return 8 * int(tasks.agg(F.sum("n").alias("n")).first()["n"] or 0)


def _packed(values: np.ndarray) -> bytes:
    """The least value, then the distances from it in four bytes each where they fit."""
    least = values.min()
    short = int(values.max()) - int(least) < 2**32
    return bytes([short]) + least.tobytes() + ((values - least).astype(np.uint32) if short else values).tobytes()


def _unpacked(raw: bytes) -> np.ndarray:
    least, rest = np.frombuffer(raw, np.int64, 1, 1)[0], raw[9:]
    return np.frombuffer(rest, np.uint32).astype(np.int64) + least if raw[0] else np.frombuffer(rest, np.int64)


def _deal(classes: int):
    """Rows sorted by centre to products of ends, many centres in a row. x and y are the ends of a centre in two classes, or in
    one (same: pairs inside x); xn and yn say how many each centre has. Of a pair one end at least is above the centre."""

    def products(u: np.ndarray, v: np.ndarray, above: np.ndarray):
        owner = np.cumsum(np.concatenate([[False], u[1:] != u[:-1]]))
        many = int(owner[-1]) + 1
        with np.errstate(over="ignore"):
            kind = ((v.astype(np.uint64) * _MIX) >> np.uint64(33)) % np.uint64(classes)
        high, low = [(kind == i) & above for i in range(classes)], [(kind == i) & ~above for i in range(classes)]
        for i in range(classes):
            for j in range(i, classes):
                for x, y in [(high[i], None), (high[i], low[i])] if i == j else [(high[i], high[j] | low[j]), (low[i], high[j])]:
                    xn = np.bincount(owner[x], minlength=many)
                    yn = xn if y is None else np.bincount(owner[y], minlength=many)
                    ok = xn > 1 if y is None else (xn > 0) & (yn > 0)
                    if ok.any():
                        x = x & ok[owner]
                        other = (b"", b"") if y is None else (_packed(v[y & ok[owner]]), yn[ok].astype(np.int32).tobytes())
                        yield pa.RecordBatch.from_pylist([dict(zip(NAMES, (i * classes + j, y is None, _packed(v[x]), xn[ok].astype(np.int32).tobytes(), *other)))], _SCHEMA)

    def run(batches):
        held: list[tuple] = []
        rows = 0

        def whole(last: bool):
            """All centres, but the last one while rows may follow."""
            u, v, above = (np.concatenate(x) for x in zip(*held))
            at = len(u) if last else int(np.searchsorted(u, u[-1]))
            held[:] = [(u[at:], v[at:], above[at:])]
            if at:
                yield from products(u[:at], v[:at], above[:at])

        for batch in batches:
            if len(batch):
                held.append(tuple(batch.column(c).to_numpy(zero_copy_only=False) for c in ("u", "v", "above")))
                rows += len(batch)
                if rows >= DEAL:
                    yield from whole(False)
                    rows = 0
        if held:
            yield from whole(True)

    return run


def _merged(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, n = keys[order], n[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, int)
    return keys[first], np.add.reduceat(n, first) if len(first) else n


def _rings(table: pa.Table) -> pa.Table:
    """Pairs of centres that share a pair of ends, over all pairs of ends of the task."""
    rows = table.to_pylist()
    products = [(r["same"], _unpacked(r["x"]), np.frombuffer(r["xn"], np.int32), _unpacked(r["x" if r["same"] else "y"]), np.frombuffer(r["xn" if r["same"] else "yn"], np.int32)) for r in rows]
    # ends are numbered in the task, so that a pair is one number
    ids = np.unique(np.concatenate([np.unique(p[k]) for p in products for k in (1, 3)]))
    total = (np.zeros(0, np.int64), np.zeros(0, np.int64))
    fresh: list[np.ndarray] = []

    def settle():
        nonlocal total
        keys = np.sort(np.concatenate(fresh)) if fresh else np.zeros(0, np.int64)
        fresh.clear()
        first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, int)
        total = _merged(np.concatenate([total[0], keys[first]]), np.concatenate([total[1], np.diff(np.append(first, len(keys)))]))

    waiting = 0
    for same, x, xn, y, yn in products:
        x, y = np.searchsorted(ids, x), np.searchsorted(ids, y)
        start = np.cumsum(yn, dtype=np.int64) - yn
        many, begin = np.repeat(yn.astype(np.int64), xn), np.repeat(start, xn)
        ends, at = np.cumsum(many), 0
        while at < len(x):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + PAIRS, "right")))
            n = many[at:to]
            a = np.repeat(x[at:to], n)
            b = y[np.repeat(begin[at:to] - (np.cumsum(n) - n), n) + np.arange(len(a))]
            # inside one list every pair comes twice, and each end with itself
            fresh.append((np.minimum(a, b) * len(ids) + np.maximum(a, b))[a < b] if same else np.minimum(a, b) * len(ids) + np.maximum(a, b))
            waiting += len(fresh[-1])
            if waiting > max(PAIRS, len(total[0])):
                settle()
                waiting = 0
            at = to
    settle()
    # pairs of centres: exact in Python where the sum may pass 64 bits
    often, times = np.unique(total[1], return_counts=True)
    return pa.table({"n": pa.array([Decimal(sum(int(n) * (int(n) - 1) // 2 * int(m) for n, m in zip(often, times)))], pa.decimal128(38, 0))})
