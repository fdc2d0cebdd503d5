"""Statistics of the inputs: one aggregate each."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rect import Bounds


@dataclass(frozen=True)
class Stats:
    n: int
    bounds: Bounds
    ext: tuple[float, float]
    most: tuple[float, float]

    def relative(self, b: Bounds, axis: str) -> float:
        w, i = b.width(axis), "xy".index(axis)
        return self.ext[i] / w if w > 0 else 0.0


def fused_stats(df: DataFrame) -> Stats:
    """Cardinality, bounds, mean and greatest extents in one pass."""
    row = df.agg(F.count(F.lit(1)), F.min("xl"), F.min("yl"), F.max("xu"), F.max("yu"), *(f(F.col(f"{a}u") - F.col(f"{a}l")) for f in (F.avg, F.max) for a in "xy")).first()
    if not row[0]:
        return Stats(0, Bounds(0.0, 0.0, 1.0, 1.0), (0.0, 0.0), (0.0, 0.0))
    return Stats(row[0], Bounds(*map(float, row[1:5])), tuple(row[5:7]), tuple(row[7:9]))


def joint(*stats: Stats) -> Bounds:
    own = [s.bounds for s in stats if s.n] or [Bounds(0.0, 0.0, 1.0, 1.0)]
    return Bounds(min(b.xlo for b in own), min(b.ylo for b in own), max(b.xhi for b in own), max(b.yhi for b in own))


def describe(df: DataFrame, b: Bounds) -> DataFrame:
    """One row: cardinality and mean extents relative to the space."""
    rel = {a: (F.avg(F.col(f"{a}u") - F.col(f"{a}l")) / F.lit(b.width(a) or 1.0)).alias(f"mean_{a}_extent") for a in "xy"}
    return df.agg(F.count(F.lit(1)).alias("n"), rel["x"], rel["y"])


def density(df: DataFrame, b: Bounds, kx: int, ky: int) -> DataFrame:
    """(tx, ty, n): rectangles by the cell of their start."""
    from .grid import GridSpec, cells

    return cells(df, GridSpec("grid", b, kx, ky)).groupBy(F.col("cx").alias("tx"), F.col("cy").alias("ty")).agg(F.count(F.lit(1)).alias("n"))
