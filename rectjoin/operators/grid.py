"""Partitioning: uniform stripes and grids, with one copy of a rectangle for every cell it touches.

Cells are half open and clamped, so a coordinate has exactly one cell and the cell of the later of two starts
is the later of their cells. That makes the duplicate test an exact comparison of integers.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rect import Bounds


@dataclass(frozen=True)
class GridSpec:
    """kind: none, stripe_x, stripe_y, grid. bins: parts of a stripe along the sweep axis (stripes only)."""

    kind: str
    bounds: Bounds
    kx: int = 1
    ky: int = 1

    def __post_init__(self):
        if self.kind not in ("none", "stripe_x", "stripe_y", "grid"):
            raise ValueError(self.kind)
        for axis, keep in (("x", self.kind in ("stripe_x", "grid")), ("y", self.kind in ("stripe_y", "grid"))):
            if not keep or self.bounds.width(axis) <= 0:  # a space without width has one cell
                object.__setattr__(self, f"k{axis}", 1)

    @property
    def tiles(self) -> int:
        return self.kx * self.ky

    def k(self, axis: str) -> int:
        return self.kx if axis == "x" else self.ky

    def binned(self, bins: int) -> GridSpec:
        """Stripes cut into bins along the sweep axis; what makes a stripe fit many tasks."""
        if bins <= 1 or self.kind not in ("stripe_x", "stripe_y"):
            return self
        return replace(self, kind="grid", **{"ky" if self.kind == "stripe_x" else "kx": bins})


def stripes(axis: str, k: int, b: Bounds) -> GridSpec:
    return GridSpec(f"stripe_{axis}", b, **{f"k{axis}": k})


def cell(v: Column, lo: float, hi: float, k: int) -> Column:
    if k <= 1:
        return F.lit(0)
    return F.least(F.greatest(F.floor((v - F.lit(lo)) / F.lit(hi - lo) * F.lit(k)), F.lit(0)), F.lit(k - 1)).cast("int")


def cells(df: DataFrame, spec: GridSpec) -> DataFrame:
    """With the first and last cell on each axis: cx, cx_hi, cy, cy_hi."""
    new = {}
    for a in "xy":
        b, k = spec.bounds.of(a), spec.k(a)
        new |= {f"c{a}": cell(F.col(f"{a}l"), *b, k), f"c{a}_hi": cell(F.col(f"{a}u"), *b, k)}
    return df.withColumns(new)


def assign(df: DataFrame, spec: GridSpec) -> DataFrame:
    """A copy for every cell: adds tile, tx, ty, cx, cy (the cell of the start)."""
    df = cells(df, spec)
    keep = [c for c in df.columns if c not in ("cx_hi", "cy_hi")]
    cut = [a for a in "xy" if spec.k(a) > 1]
    if not cut:
        return df.select(*keep, F.lit(0).alias("tx"), F.lit(0).alias("ty"), F.lit(0).cast("long").alias("tile"))
    if len(cut) == 1:
        a = cut[0]
        df = df.select(*keep, F.explode(F.sequence(F.col(f"c{a}"), F.col(f"c{a}_hi"))).alias(f"t{a}")).withColumn("ty" if a == "x" else "tx", F.lit(0))
    else:
        pairs = F.flatten(F.transform(F.sequence("cy", "cy_hi"), lambda y: F.transform(F.sequence("cx", "cx_hi"), lambda x: F.struct(x.alias("tx"), y.alias("ty")))))
        df = df.select(*keep, F.inline(pairs))
    return df.withColumn("tile", F.col("ty").cast("long") * spec.kx + F.col("tx"))


def copies() -> Column:
    """Copies of a rectangle of :func:`cells`."""
    return (F.col("cx_hi") - F.col("cx") + 1).cast("long") * (F.col("cy_hi") - F.col("cy") + 1)


def quantile_cuts(df: DataFrame, axis: str, k: int, accuracy: int = 10_000) -> list[float]:
    """Data-driven borders, for skewed starts: k - 1 of them."""
    return [float(v) for v in df.agg(F.percentile_approx(f"{axis}l", [i / k for i in range(1, k)], accuracy)).first()[0] or []] if k > 1 else []


def assign_quantiles(df: DataFrame, axis: str, cuts: list[float]) -> DataFrame:
    """Stripes between given borders."""
    borders = F.array(*(F.lit(c) for c in cuts)) if cuts else F.array().cast("array<double>")
    at = lambda v: F.size(F.filter(borders, lambda c: c <= v))
    return df.withColumn(f"c{axis}", at(F.col(f"{axis}l"))).withColumn(f"t{axis}", F.explode(F.sequence(F.col(f"c{axis}"), at(F.col(f"{axis}u"))))).withColumn("tile", F.col(f"t{axis}").cast("long"))
