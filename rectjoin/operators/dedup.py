"""Ways to report a pair once though it is found in many tiles."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS, intersects, prefixed
from .grid import GridSpec, assign, cell, cells

#: Pairs of start classes that can hold a pair not owned by an earlier tile. Bit 1: starts before the tile in x, bit 2: in y.
A, C, B, D = 0, 1, 2, 3
KEPT_2D = [(r, s) for r in range(4) for s in range(4) if not r & s]
KEPT_1D = [(r, s) for r in range(2) for s in range(2) if not r & s]


def ref_cell(spec: GridSpec) -> Column:
    """The pair belongs to the cell of its later start on each axis: integers only."""
    cond = [F.col(f"t{a}") == F.greatest(f"r_c{a}", f"s_c{a}") for a in "xy" if spec.k(a) > 1]
    return reduce(Column.__and__, cond, F.lit(True))


def ref_tile(spec: GridSpec) -> Column:
    """The same from coordinates and the tile: a cell never falls as its coordinate grows, so the later start's is the later cell."""
    at = {a: cell(F.greatest(f"r_{a}l", f"s_{a}l"), *spec.bounds.of(a), spec.k(a)) for a in "xy"}
    return F.col("r_tile") == at["y"].cast("long") * spec.kx + at["x"] if spec.tiles > 1 else F.lit(True)


def ref_point(spec: GridSpec) -> Column:
    """The same by coordinates: the later start isn't before the tile's, on the cut axes. Like the cells, the first tile
    reaches below the bounds and the last one beyond them."""
    def one(a: str) -> Column:
        lo, hi = spec.bounds.of(a)
        return (F.col(f"t{a}") == 0) | ((F.greatest(f"r_{a}l", f"s_{a}l") - F.lit(lo)) / F.lit(hi - lo) * F.lit(spec.k(a)) >= F.col(f"t{a}"))

    return reduce(Column.__and__, [one(a) for a in "xy" if spec.k(a) > 1], F.lit(True))


def classify(assigned: DataFrame) -> DataFrame:
    """Adds cls: where the copy's rectangle starts relative to its tile."""
    return assigned.withColumn("cls", (F.col("tx") > F.col("cx")).cast("int") + 2 * (F.col("ty") > F.col("cy")).cast("int"))


def class_predicate(cr: int | Column, cs: int | Column) -> Column:
    """Intersection in a tile when one side's class is known: an axis on which a side starts before the tile, and the
    other doesn't, needs one comparison."""
    cr, cs = (F.lit(c) if isinstance(c, int) else c for c in (cr, cs))

    def axis(a: str, bit: int) -> Column:
        r_before, s_before = cr.bitwiseAND(F.lit(bit)) != 0, cs.bitwiseAND(F.lit(bit)) != 0
        r_reaches, s_reaches = F.col(f"r_{a}u") >= F.col(f"s_{a}l"), F.col(f"s_{a}u") >= F.col(f"r_{a}l")
        return F.when(r_before, r_reaches).when(s_before, s_reaches).otherwise(r_reaches & s_reaches)

    return axis("x", 1) & axis("y", 2)


def class_split(r: DataFrame, s: DataFrame, spec: GridSpec, mode: str = "expand", bins: int = 1) -> DataFrame:
    """Pairs without any test on found pairs: only joins of compatible start classes are made.

    ``expand``: each copy of ``r`` meets the classes it can go with, as part of the join key. ``residual``: the
    key is the tile, classes are compared. ``union``: one join for each of the kept class pairs. ``bins``: parts of a
    stripe along the other axis, so that fewer rows have a key; pairs found in many of them belong to their reference bin.
    """
    kept = KEPT_2D if spec.kx > 1 and spec.ky > 1 else KEPT_1D if spec.kx > 1 else [(2 * a, 2 * b) for a, b in KEPT_1D]
    cut, fine = (1 if spec.kx > 1 else 2), spec.binned(bins)
    own = lambda df: df if fine is spec else df.withColumn("cls", F.col("cls").bitwiseAND(F.lit(cut)))
    ra, sa = (prefixed(own(classify(assign(df, fine))), p, "tile", "cls") for df, p in ((r, "r_"), (s, "s_")))
    if fine is not spec:
        if mode != "expand":
            raise ValueError("bins are for expand")
        kept = [(cut * a, cut * b) for a, b in KEPT_1D]
    if mode == "union":
        parts = [ra.where(F.col("r_cls") == a).join(sa.where(F.col("s_cls") == b), (F.col("r_tile") == F.col("s_tile")) & class_predicate(a, b)) for a, b in kept]
        return reduce(DataFrame.unionByName, parts).select("r_id", "s_id")
    if mode == "residual":
        return ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & (F.col("r_cls").bitwiseAND(F.col("s_cls")) == 0) & class_predicate(F.col("r_cls"), F.col("s_cls"))).select("r_id", "s_id")
    classes = sorted({b for _, b in kept})
    goes_with = reduce(lambda acc, c: acc.when(F.col("r_cls") == c, F.array(*(F.lit(b) for a, b in kept if a == c))), classes, F.when(F.lit(False), F.array(F.lit(0))))
    ra = ra.withColumn("with", F.explode(goes_with))
    cond = (F.col("r_tile") == F.col("s_tile")) & (F.col("with") == F.col("s_cls")) & class_predicate(F.col("r_cls"), F.col("s_cls"))
    if fine is not spec:
        a = "y" if cut == 1 else "x"
        tile = F.floor(F.col("r_tile") / F.lit(fine.kx)) if a == "y" else F.pmod(F.col("r_tile"), F.lit(fine.kx))
        cond = cond & (tile == cell(F.greatest(f"r_{a}l", f"s_{a}l"), *spec.bounds.of(a), bins))
    return ra.join(sa, cond).select("r_id", "s_id")


def found(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """Every (pair, tile) that is found, with what the tests need."""
    ra, sa = (prefixed(assign(df, spec), p, "cx", "cy", "tile", *(("tx", "ty") if p == "r_" else ())) for df, p in ((r, "r_"), (s, "s_")))
    return ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & intersects()).withColumnsRenamed({"r_tx": "tx", "r_ty": "ty"})


#: Cells that a pair's first cell may be away from a found one, over both axes, up to which found pairs stay in their task.
NEAR = 16


def distinct(r: DataFrame, s: DataFrame, spec: GridSpec, fine: GridSpec | None = None) -> DataFrame:
    """Distinct pairs of all that are found. Few need to be sorted out: one that shares a single cell is found once; those are
    joined by ``fine``, in parts of cells, so that fewer rows have a key, and belong to their reference part.

    The others lie across a border, as both their rectangles do. Those are joined apart, by the first cell of ``r``, which ``s``
    is copied to where it may share several cells; so the finds of a pair meet in one task and are not shuffled. Rectangles
    of ``r`` that reach over very many cells have their finds shuffled. Ids are taken to be unique.
    """
    lo, hi = (lambda p, a: F.least(f"{p}c{a}", f"{p}c{a}_hi")), (lambda p, a: F.greatest(f"{p}c{a}", f"{p}c{a}_hi"))
    if spec.tiles <= 1:
        return prefixed(r, "r_").join(prefixed(s, "s_"), intersects()).select("r_id", "s_id")
    span = [f"{e}{a}" for a in "xy" for e in ("lo", "hi")]  # carried: computed for each pair, they make code that the JVM doesn't compile
    fine, alone = fine or spec, (F.col("lox") == F.col("hix")) & (F.col("loy") == F.col("hiy"))
    rs, ss = (cells(df.select("rid", *COORDS), spec).withColumns({f"{e}{a}": f("", a) for a in "xy" for e, f in (("lo", lo), ("hi", hi))}).select("rid", *COORDS, *span) for df in (r, s))
    once = reduce(Column.__and__, [F.greatest(f"r_lo{a}", f"s_lo{a}") == F.least(f"r_hi{a}", f"s_hi{a}") for a in "xy" if spec.k(a) > 1])
    ra, sa = (prefixed(assign(df, fine), p, "tile", *span) for df, p in ((rs, "r_"), (ss, "s_")))
    out = ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & intersects() & ref_tile(fine) & once).select("r_id", "s_id")
    wide, near = rs.where(~alone), ss.where(~alone)
    far = wide.agg(*(F.max(F.col(f"hi{a}") - F.col(f"lo{a}")) for a in "xy")).first()
    if (far[0] or 0) + 1 > NEAR or ((far[0] or 0) + 1) * ((far[1] or 0) + 1) > NEAR:
        ra, sa = (prefixed(assign(df, spec), p, "tile", *span) for df, p in ((wide, "r_"), (near, "s_")))
        rest = ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & intersects() & ~once)
        return out.unionByName(rest.select("r_id", "s_id").dropDuplicates(["r_id", "s_id"]))
    found = prefixed(assign(wide, spec).withColumn("home", F.col("loy").cast("long") * spec.kx + F.col("lox")), "r_", "home", "tx", "ty", *span)
    for a, d in zip("xy", far):
        near = near.withColumn(f"h{a}", F.explode(F.sequence(F.greatest(F.col(f"lo{a}") - F.lit(d or 0), F.lit(0)), F.col(f"hi{a}"))))
        near = near.withColumn(f"n{a}", F.least(F.col(f"hi{a}"), F.col(f"h{a}") + F.lit(d or 0)) - F.greatest(f"lo{a}", f"h{a}") + 1)
    near = prefixed(near.where("nx * ny > 1").withColumn("home", F.col("hy").cast("long") * spec.kx + F.col("hx")), "s_", "home", *span)
    there = reduce(Column.__and__, [F.col(f"r_t{a}").between(F.col(f"s_lo{a}"), F.col(f"s_hi{a}")) for a in "xy"])
    rest = found.join(near, (F.col("r_home") == F.col("s_home")) & intersects() & there & ~once)
    return out.unionByName(rest.dropDuplicates(["r_home", "r_id", "s_id"]).select("r_id", "s_id"))
