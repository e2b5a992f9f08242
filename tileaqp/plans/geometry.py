"""Where objects and tiles lie: one definition of all bounds, path codes by bit interleaving, containment."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

from .model import LEVELS, Viewport

CELL_BITS = 2 * LEVELS


@dataclass(frozen=True)
class Domain:
    """The root grid over a closed rectangle; every bound of every tile is ``bound`` of an integer."""

    box: Viewport
    gx: int
    gy: int

    def steps(self, axis: str) -> int:
        return (self.gx if axis == "x" else self.gy) << LEVELS

    def bound(self, axis: str, j: int) -> float:
        lo, hi = (self.box.x1, self.box.x2) if axis == "x" else (self.box.y1, self.box.y2)
        return lo + (hi - lo) * (j / self.steps(axis))

    def scale(self, axis: str) -> tuple[float, float, int]:
        lo, hi = (self.box.x1, self.box.x2) if axis == "x" else (self.box.y1, self.box.y2)
        return lo, hi - lo, self.steps(axis)

    def covers(self, x: Column, y: Column) -> Column:
        """Inside, with neither axis null or NaN."""
        return F.coalesce(self.box.condition(x, y) & ~F.isnan(x) & ~F.isnan(y), F.lit(False))


def spread_int(v: int) -> int:
    return sum((v >> i & 1) << 2 * i for i in range(LEVELS))


def gather_int(z: int) -> int:
    return sum((z >> 2 * i & 1) << i for i in range(LEVELS))


def with_codes(df: DataFrame, domain: Domain, x: str = "ax", y: str = "ay") -> DataFrame:
    """Adds root (the cell) and zcode (the path inside it).

    The integer coordinate of a value is set right by comparing with the bounds on
    either side, so that codes and bounds never disagree. Each step is a projection of
    its own: written as one expression, its repeated parts would be copied into it.
    """
    jx, jy = "_jx", "_jy"
    axes = [(v, j, *domain.scale(a)) for a, v, j in (("x", x, jx), ("y", y, jy))]
    rough = {j: F.least(F.lit(n - 1), F.greatest(F.lit(0), F.floor((F.col(v) - lo) / F.lit(w) * F.lit(float(n))))) if w else F.lit(0).cast("long") for v, j, lo, w, n in axes}
    out = df.withColumns(rough)
    edge = lambda lo, w, n, k: F.lit(lo) + F.lit(w) * (k / F.lit(float(n)))
    right = {}
    for v, j, lo, w, n in axes:
        c = F.col(j)
        right[j] = F.when((F.col(v) < edge(lo, w, n, c)) & (c > 0), c - 1).when((F.col(v) >= edge(lo, w, n, c + 1)) & (c < n - 1), c + 1).otherwise(c)
    out = out.withColumns(right)
    low = F.lit((1 << LEVELS) - 1)
    out = out.withColumns({"root": (F.shiftright(jy, LEVELS) * domain.gx + F.shiftright(jx, LEVELS)).cast("int"), jx: F.col(jx).bitwiseAND(low), jy: F.col(jy).bitwiseAND(low)})
    for shift, mask in ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555)):
        out = out.withColumns({j: F.col(j).bitwiseOR(F.shiftleft(j, shift)).bitwiseAND(F.lit(mask)) for j in (jx, jy)})
    return out.withColumn("zcode", F.col(jx).bitwiseOR(F.shiftleft(jy, 1))).drop(jx, jy)


@dataclass
class Tile:
    """A rectangle of the hierarchy: a contiguous range of path codes of one root cell."""

    tile_id: int
    parent_id: int | None
    depth: int
    root: int
    zlo: int
    zhi: int
    n_objects: int
    is_leaf: bool = True
    children: tuple[int, ...] = ()

    @property
    def start(self) -> int:
        """First code over all cells."""
        return self.root << CELL_BITS | self.zlo

    @property
    def end(self) -> int:
        return (self.root << CELL_BITS) + self.zhi

    def corner(self, domain: Domain) -> tuple[int, int, int]:
        """Integer coordinates of the lower corner, and the side."""
        jx = (self.root % domain.gx << LEVELS) + gather_int(self.zlo)
        jy = (self.root // domain.gx << LEVELS) + gather_int(self.zlo >> 1)
        return jx, jy, 1 << LEVELS - self.depth

    def bounds(self, domain: Domain) -> Viewport:
        jx, jy, side = self.corner(domain)
        return Viewport(domain.bound("x", jx), domain.bound("x", jx + side), domain.bound("y", jy), domain.bound("y", jy + side))

    def parts(self, n: int = 4) -> list[tuple[int, int]]:
        """Code ranges of equal parts, a power of four of them."""
        step = (self.zhi - self.zlo) // n
        return [(self.zlo + i * step, self.zlo + (i + 1) * step) for i in range(n)]


def classify(t: Viewport, q: Viewport) -> str:
    """full, partial or disjoint. Tiles are half open, windows closed; a tile is full if the window holds all its extent."""
    if q.x1 <= t.x1 and t.x2 <= q.x2 and q.y1 <= t.y1 and t.y2 <= q.y2:
        return "full"
    return "partial" if t.x1 <= q.x2 and q.x1 <= t.x2 and t.y1 <= q.y2 and q.y1 <= t.y2 else "disjoint"


def classify_columns(q: Viewport, x1="x_lo", x2="x_hi", y1="y_lo", y2="y_hi") -> Column:
    x1, x2, y1, y2 = (F.col(c) for c in (x1, x2, y1, y2))
    full = (x1 >= q.x1) & (x2 <= q.x2) & (y1 >= q.y1) & (y2 <= q.y2)
    meets = (x1 <= q.x2) & (x2 >= q.x1) & (y1 <= q.y2) & (y2 >= q.y1)
    return F.when(full, "full").when(meets, "partial").otherwise("disjoint")

