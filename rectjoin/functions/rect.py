"""The rectangle contract and its expressions.

A rectangle row is (rid, xl, yl, xu, yu, payload...): any comparable id and closed double intervals on two
axes. Touching counts as intersecting. Sides of a join carry the prefixes ``r_`` and ``s_``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

COORDS = ("xl", "yl", "xu", "yu")


@dataclass(frozen=True)
class Bounds:
    xlo: float
    ylo: float
    xhi: float
    yhi: float

    def of(self, axis: str) -> tuple[float, float]:
        return (self.xlo, self.xhi) if axis == "x" else (self.ylo, self.yhi)

    def width(self, axis: str) -> float:
        lo, hi = self.of(axis)
        return hi - lo


UNIT = Bounds(0.0, 0.0, 1.0, 1.0)


def bounds(*frames: DataFrame) -> Bounds:
    """Joint bounds of rectangle frames: one aggregate of min and max for each."""
    aggs = (F.min("xl"), F.min("yl"), F.max("xu"), F.max("yu"))
    rows = [r for f in frames if (r := f.agg(*aggs).first()) and r[0] is not None]
    if not rows:
        return UNIT
    return Bounds(*(float(f(r[i] for r in rows)) for i, f in enumerate((min, min, max, max))))


def overlaps(axis: str, r: str = "r_", s: str = "s_") -> Column:
    """Closed intervals meet on one axis."""
    return (F.col(f"{r}{axis}l") <= F.col(f"{s}{axis}u")) & (F.col(f"{s}{axis}l") <= F.col(f"{r}{axis}u"))


def intersects(r: str = "r_", s: str = "s_") -> Column:
    return overlaps("x", r, s) & overlaps("y", r, s)


def prefixed(df: DataFrame, p: str, *more: str) -> DataFrame:
    """(rid, coordinates, more) as (p_id, p_xl, ...)."""
    return df.select(F.col("rid").alias(f"{p}id"), *(F.col(c).alias(p + c) for c in (*COORDS, *more)))


def eps_square(df: DataFrame, eps: float) -> DataFrame:
    """Points (degenerate rectangles) to squares of side ``eps``: two meet iff their maximum distance is at most eps."""
    h = F.lit(eps / 2)
    return df.withColumns({"px": F.col("xl"), "py": F.col("yl"), "xl": F.col("xl") - h, "yl": F.col("yl") - h, "xu": F.col("xu") + h, "yu": F.col("yu") + h})


def mbr(df: DataFrame, key: str | list[str], x: str, y: str) -> DataFrame:
    """Bounding rectangles of the parts of each object."""
    keys = [key] if isinstance(key, str) else key
    rid = F.col(keys[0]) if len(keys) == 1 else F.struct(*keys)
    mins = {"xl": F.min(x), "yl": F.min(y), "xu": F.max(x), "yu": F.max(y)}
    return df.groupBy(*keys).agg(*(v.cast("double").alias(k) for k, v in mins.items())).select(rid.alias("rid"), *COORDS)


def normalize(df: DataFrame, b: Bounds) -> DataFrame:
    """Coordinates relative to the space. A space without width on an axis maps to 0."""
    def one(c: str) -> Column:
        lo, hi = b.of(c[0])
        return (F.col(c) - F.lit(lo)) / F.lit(hi - lo) if hi > lo else F.lit(0.0)

    return df.withColumns({c: one(c) for c in COORDS})


def validate_rects(df: DataFrame, on_bad: str = "drop") -> DataFrame:
    """Rows with null or NaN coordinates or a null id are bad, and ones whose ends are the wrong way round.

    ``drop`` leaves them out, ``swap`` turns the ends of the latter, ``error`` fails the job on any.
    """
    if on_bad == "swap":
        df = df.withColumns({f"{a}{e}": F.when(F.col(f"{a}l") > F.col(f"{a}u"), F.col(f"{a}{o}")).otherwise(F.col(f"{a}{e}")) for a in "xy" for e, o in ("lu", "ul")})
    ok = F.col("rid").isNotNull() & (F.col("xl") <= F.col("xu")) & (F.col("yl") <= F.col("yu"))
    for c in COORDS:
        ok = ok & F.col(c).isNotNull() & ~F.isnan(c)
    ok = F.coalesce(ok, F.lit(False))
    if on_bad == "error":
        return df.where(F.when(ok, F.lit(True)).otherwise(F.raise_error(F.lit("bad rectangle")).cast("boolean")))
    return df.where(ok)


def area(p: str = "") -> Column:
    return (F.col(f"{p}xu") - F.col(f"{p}xl")) * (F.col(f"{p}yu") - F.col(f"{p}yl"))


def shared_area(r: str = "r_", s: str = "s_") -> Column:
    def side(a: str) -> Column:
        return F.greatest(F.lit(0.0), F.least(f"{r}{a}u", f"{s}{a}u") - F.greatest(f"{r}{a}l", f"{s}{a}l"))

    return side("x") * side("y")


def iou(r: str = "r_", s: str = "s_") -> Column:
    both = shared_area(r, s)
    total = area(r) + area(s) - both
    return F.when(total > 0, both / total).otherwise(0.0)


def z_order(cx: Column, cy: Column, bits: int = 16) -> Column:
    """Interleaved bits of two cell numbers, for clustering files."""
    code = F.lit(0).cast("long")
    for i in range(bits):
        for c, at in ((cx, 2 * i), (cy, 2 * i + 1)):
            code = code.bitwiseOR(F.shiftleft(F.shiftright(c.cast("long"), i).bitwiseAND(F.lit(1).cast("long")), at))
    return code
