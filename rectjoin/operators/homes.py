"""Homes: large cells that rectangles are dealt to tasks by, to be cut into the small cells of a join only there.

Small cells keep comparisons few but copy rectangles; large ones hardly do. So what is shuffled is a row for each home, and the copies
for the cells inside a home never leave its task. A home's pairs are few ids over and over, which files of columns hold in few bytes.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS, prefixed
from .coincide import expected_pairs
from .grid import GridSpec, cell, cells
from .stats import Stats, joint
from .tune import expected_replication

#: Fewer rows than this are shuffled by their cells.
ROWS = 1_000_000
#: Rows that a home is to have at most for evenly spread rectangles; how many homes are made at most; copies a rectangle at most.
ABOUT, MANY, COPIES = 60_000, 4096, 1.5
#: Pairs of a home at most, for evenly spread rectangles, where a task holds its pairs; copies a rectangle at most for that.
PAIRS, COPIES_HELD = 400_000, 4.0
#: Rows of one home from which cells are dealt one by one instead, as adaptive execution can split what is large.
HOT = 2_000_000


@dataclass(frozen=True)
class Homes:
    """Homes of px by py cells of a spec."""

    spec: GridSpec
    px: int
    py: int

    @property
    def nx(self) -> int:
        return -(-self.spec.kx // self.px)

    @property
    def n(self) -> int:
        return self.nx * -(-self.spec.ky // self.py)

    def per(self, axis: str) -> int:
        return self.px if axis == "x" else self.py

    def of(self, axis: str, home: str = "home") -> Column:
        """A home's number on an axis."""
        return F.pmod(F.col(home), F.lit(self.nx)).cast("int") if axis == "x" else F.floor(F.col(home) / F.lit(self.nx)).cast("int")

    def at(self, axis: str, v: Column) -> Column:
        """The number on an axis of the home that a coordinate is in."""
        return F.floor(cell(v, *self.spec.bounds.of(axis), self.spec.k(axis)) / F.lit(self.per(axis))).cast("int")


def homes(r: DataFrame, s: DataFrame, known: tuple[Stats, Stats], spec: GridSpec, pairs: float = 0.0) -> Homes | None:
    """Homes of the cells of ``spec``, by rows; None for few rows, and where much lies in one place. pairs: how many the tasks
    have to hold, if they do."""
    rows = sum(st.n for st in known)
    if rows < ROWS or spec.tiles <= 1:
        return None
    large = replace(spec, kind="grid", kx=1, ky=1)
    want, most = max(rows / ABOUT, pairs / PAIRS), COPIES_HELD if pairs else COPIES
    while large.tiles < min(MANY, want):
        finer = [replace(large, **{f"k{a}": min(2 * large.k(a), spec.k(a))}) for a in "xy" if large.k(a) < spec.k(a)]
        finer = [g for g in finer if max(expected_replication(st, g) for st in known) <= most]
        if not finer:
            break
        large = min(finer, key=lambda g: sum(expected_replication(st, g) * st.n for st in known) / g.tiles)
    out = Homes(spec, -(-spec.kx // large.kx), -(-spec.ky // large.ky))
    starts = r.select("xl", "yl").unionByName(s.select("xl", "yl")).groupBy(out.at("x", F.col("xl")), out.at("y", F.col("yl"))).count()
    return out if (starts.agg(F.max("count")).first()[0] or 0) <= HOT else None


def _both(df: DataFrame, ends: dict[str, tuple[Column, Column]]) -> DataFrame:
    """A row for each pair of numbers between two ends on either axis, as hx, hy."""
    for a in "xy":
        df = df.withColumn(f"h{a}", F.explode(F.sequence(*ends[a])))
    return df


def sent(df: DataFrame, h: Homes, ends: dict[str, tuple[Column, Column]] | None = None) -> DataFrame:
    """Dealt to tasks: a row for each home that a rectangle touches, or that is between ``ends``, with its number."""
    ends = ends or {a: (h.at(a, F.col(f"{a}l")), h.at(a, F.col(f"{a}u"))) for a in "xy"}
    out = _both(df, ends).withColumn("home", F.col("hy") * F.lit(h.nx) + F.col("hx"))
    return out.drop("hx", "hy").repartitionById(h.n, F.col("home"))


def cut(df: DataFrame, spec: GridSpec, h: Homes | None = None) -> DataFrame:
    """What a task has, in the cells of ``spec``: adds tx, ty and tile. h: only the cells inside the row's home."""
    df = cells(df, spec)
    ends = {}
    for a in "xy":
        lo, hi = F.least(f"c{a}", f"c{a}_hi"), F.greatest(f"c{a}", f"c{a}_hi")
        first = h.of(a) * F.lit(h.per(a)) if h else None
        ends[a] = (F.greatest(lo, first), F.least(hi, first + F.lit(h.per(a) - 1))) if h else (lo, hi)
    out = _both(df, ends).withColumnsRenamed({"hx": "tx", "hy": "ty"}).drop("cx_hi", "cy_hi")
    return out.withColumn("tile", F.col("ty").cast("long") * spec.kx + F.col("tx"))


def side(df: DataFrame, p: str, h: Homes, *more: str) -> DataFrame:
    """One input of a join in the cells of the homes' spec, with prefixes: (id, coordinates, home, tile, more)."""
    own = [c for c in more if c not in ("tx", "ty")]
    return prefixed(cut(sent(df.select("rid", *COORDS, *own), h), h.spec, h), p, "home", "tile", *more)


def by_start(r: DataFrame, s: DataFrame, known: tuple[Stats, Stats]) -> tuple[DataFrame, DataFrame] | None:
    """Both inputs dealt to tasks so that a rectangle of ``r`` is in the home of its start only, and one of ``s`` in all
    homes that a partner may start in; None where :func:`homes` has none."""
    b = joint(*known)
    room = [known[0].most["xy".index(a)] * (1 + 1e-9) + 1e-9 * b.width(a) for a in "xy"]  # differences are rounded
    wide = replace(known[1], ext=tuple(e + m for e, m in zip(known[1].ext, room)))
    h = homes(r, s, (replace(known[0], ext=(0.0, 0.0)), wide), GridSpec("grid", b, MANY, MANY), expected_pairs(*known))
    if not h:
        return None
    starts = {a: (h.at(a, F.col(f"{a}l")),) * 2 for a in "xy"}
    reach = {a: (h.at(a, F.col(f"{a}l") - F.lit(m)), h.at(a, F.col(f"{a}u"))) for a, m in zip("xy", room)}
    return sent(r.select("rid", *COORDS), h, starts), sent(s.select("rid", *COORDS), h, reach)
