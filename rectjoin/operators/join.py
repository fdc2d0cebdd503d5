"""The join of two rectangle frames, and its relatives.

Engines: ``catalyst`` is an equi-join on the tile with the overlap and the duplicate test as residuals, all in
generated JVM code; adaptive execution splits skewed tiles. ``sweep`` is the Arrow kernel, a true forward scan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS, eps_square, intersects, overlaps, prefixed
from . import coincide
from . import dedup as dd
from .axis import choose_axis, stripe_rule
from .grid import GridSpec, assign, cells, copies, stripes
from .homes import by_start, cut, homes, side
from .stats import Stats, fused_stats, joint
from .sweep import sweep_kernel, sweep_sql
from .tune import by_rows


def spatial_join(r: DataFrame, s: DataFrame, spec: GridSpec | str = "auto", sweep: str = "auto", dedup: str = "ref_cell", engine: str = "catalyst", hint: str | None = None, on: list[str] | None = None, keep: tuple[list[str], list[str]] = ((), ()), dense: float | None = None, known: tuple[Stats, Stats] | None = None, within: str | None = None, starts: DataFrame | None = None) -> DataFrame:
    """(r_id, s_id) of all pairs with a common point, each once.

    spec: a grid, or ``auto`` for stripes by the statistics. sweep: x, y, adaptive, or auto. dedup: ref_cell,
    ref_point, distinct, class_split, none. hint: a join hint (broadcast, broadcast_left, merge, shuffle_hash). on: columns that
    must be equal too. keep: more columns of either side, with its prefix. Except with ``distinct`` beside hint, on or keep, the
    catalyst engine cuts the cells of a given spec further by the inputs' rows. dense: expected pairs a row from which equal
    rectangles are joined as lists (``coincide.DENSE``), if nothing but the reference tests and ids are asked for. known: the
    statistics of both inputs, where a caller has them. within: a column that both inputs are dealt to tasks by, for the reference
    tests: pairs are found inside its values, without a shuffle, and keep it. starts: rectangles that start where those of ``r`` do, where they are cheaper to count.
    """
    if engine in ("catalyst", "sweep") and dedup in ("ref_cell", "ref_point") and not (on or keep[0] or keep[1]) and dense != float("inf"):
        known = known or (fused_stats(r), fused_stats(s))
        (ra, sa), are = coincide.listed(r, s, known=known, dense=dense)
        if any(are):
            pairs = spatial_join(ra, sa, spec, sweep, dedup, engine, hint, dense=float("inf"))
            return coincide.members(pairs, ["r_id", "s_id"], [r, s], are)
    if spec == "auto":
        from ..plans.planner import auto_plan

        plan = auto_plan(r, s, engine=engine, known=known)
        spec, hint = plan.spec, hint or plan.hint
    elif engine == "catalyst" and dedup != "distinct" and not (dedup == "class_split" and spec.kind == "grid"):
        inner = by_rows(*(known or (fused_stats(r), fused_stats(s))), spec)
        if dedup == "class_split":
            return dd.class_split(r, s, spec, bins=inner.tiles // spec.tiles)
        spec = inner  # the engine compares all rows of a key
    if dedup == "class_split":
        return dd.class_split(r, s, spec)
    if dedup == "distinct" and engine == "catalyst" and not (hint or on or keep[0] or keep[1]):
        return dd.distinct(r, s, spec, by_rows(*(known or (fused_stats(r), fused_stats(s))), spec))
    if engine == "sweep":
        if dedup != "ref_cell":
            raise ValueError("the kernel uses the reference cell")
        axis = (stripe_rule(spec) or "adaptive") if sweep == "auto" else sweep
        if axis == "adaptive":
            return sweep_kernel(r, s, spec, axes=choose_axis(r, s, spec))
        return sweep_kernel(r, s, spec, axis)
    if engine == "sweep_sql":
        return sweep_sql(r, s, spec, "x" if sweep not in ("x", "y") else sweep)
    on = on or []
    one_axis = [a for a in "xy" if spec.k(a) > 1]
    place = ("tx", "ty") if dedup == "ref_point" else ()  # what can be computed from the rest isn't shuffled
    more = ((*place, *on, *(c for c in keep[0] if c not in COORDS)), (*on, *(c for c in keep[1] if c not in COORDS)))
    at = None
    if dedup in ("ref_cell", "ref_point") and hint in (None, "merge", "shuffle_hash") and not within:
        at = homes(r if starts is None else starts, s, known or (fused_stats(r), fused_stats(s)), spec)
    if within:
        ra, sa = prefixed(cut(r, spec), "r_", within, "tile", *more[0]), prefixed(cut(s, spec), "s_", within, "tile", *more[1])
    elif at:
        ra, sa = side(r, "r_", at, *more[0]), side(s, "s_", at, *more[1])
    else:
        ra, sa = prefixed(assign(r, spec), "r_", "tile", *more[0]), prefixed(assign(s, spec), "s_", "tile", *more[1])
    ra = ra.withColumnsRenamed({"r_tx": "tx", "r_ty": "ty"})
    shared = within or (at and "home")
    cond = (F.col(f"r_{shared}") == F.col(f"s_{shared}")) & intersects() if shared else intersects()
    if one_axis or spec.kind != "none":
        cond = (F.col("r_tile") == F.col("s_tile")) & cond
    for c in on:
        cond = cond & (F.col(f"r_{c}") == F.col(f"s_{c}"))
    if dedup in ("ref_cell", "ref_point"):
        cond = cond & (dd.ref_tile(spec) if dedup == "ref_cell" else dd.ref_point(spec))
    if hint == "broadcast_left":
        ra, hint = ra.hint("broadcast"), None
    out = ra.join(sa.hint(hint) if hint else sa, cond).select(*([F.col(f"r_{within}").alias(within)] if within else []), "r_id", "s_id", *(f"r_{c}" for c in keep[0]), *(f"s_{c}" for c in keep[1]))
    return out.dropDuplicates(["r_id", "s_id"]) if dedup == "distinct" else out


def self_join(r: DataFrame, **options) -> DataFrame:
    """Unordered pairs of one frame: r_id < s_id."""
    return spatial_join(r, r, **options).where(F.col("r_id") < F.col("s_id"))


def distance_join(p: DataFrame, q: DataFrame, eps: float, metric: str = "l2", **options) -> DataFrame:
    """Pairs of points at most ``eps`` apart (l2, l1 or linf), by squares of that side."""
    pairs = spatial_join(eps_square(p, eps), eps_square(q, eps), keep=(["px", "py"], ["px", "py"]), **options)
    dx, dy = F.abs(F.col("r_px") - F.col("s_px")), F.abs(F.col("r_py") - F.col("s_py"))
    near = {"l2": dx * dx + dy * dy <= F.lit(eps) * F.lit(eps), "l1": dx + dy <= F.lit(eps), "linf": F.greatest(dx, dy) <= F.lit(eps)}[metric]
    return pairs.where(near)


def interval_join(r: DataFrame, s: DataFrame, axis: str = "x", k: int | None = None, dense: float | None = None) -> DataFrame:
    """Pairs that meet on one axis. Rectangles that are equal on it are joined as lists where :func:`spatial_join` does that."""
    from .tune import k_rule

    ids = [r, s]
    r, s = (df.select("rid", *(c if c[0] == axis else F.lit(0.0).alias(c) for c in COORDS)) for df in ids)
    st = tuple(fused_stats(df) for df in (r, s))
    b = joint(*st)
    spec = stripes(axis, k or k_rule(st, b, axis), b)
    (r, s), are = coincide.listed(r, s, known=st, dense=dense)
    ra = prefixed(assign(r, spec), "r_", f"c{axis}", f"t{axis}").withColumnRenamed(f"r_t{axis}", f"t{axis}")
    sa = prefixed(assign(s, spec), "s_", f"c{axis}", f"t{axis}")
    pairs = ra.join(sa, (F.col(f"t{axis}") == F.col(f"s_t{axis}")) & overlaps(axis) & dd.ref_cell(spec)).select("r_id", "s_id")
    return coincide.members(pairs, ["r_id", "s_id"], ids, are)


def spatial_semi(r: DataFrame, s: DataFrame, **options) -> DataFrame:
    """Rectangles of ``r`` with a partner."""
    pairs = spatial_join(r, s, **options)
    return r.join(pairs.select(F.col("r_id").alias("rid")), "rid", "left_semi")


def spatial_anti(r: DataFrame, s: DataFrame, **options) -> DataFrame:
    """Rectangles of ``r`` without one, in any tile."""
    pairs = spatial_join(r, s, **options)
    return r.join(pairs.select(F.col("r_id").alias("rid")), "rid", "left_anti")


def spatial_left(r: DataFrame, s: DataFrame, **options) -> DataFrame:
    """(r_id, s_id), with a null partner where there is none."""
    return r.select(F.col("rid").alias("r_id")).join(spatial_join(r, s, **options), "r_id", "left")


def multiway(r: DataFrame, s: DataFrame, t: DataFrame, dense: float | None = None, **options) -> DataFrame:
    """(r_id, s_id, t_id): r meets s and s meets t. Where :func:`spatial_join` has lists, these are joined and shuffled, and
    taken apart as triples."""
    (ra, sa, ta), are = coincide.listed(r, s, t, dense=dense)
    first = spatial_join(ra, sa, dense=float("inf"), **options)
    second = spatial_join(sa, ta, dense=float("inf"), **options).select(F.col("r_id").alias("s_id"), F.col("s_id").alias("t_id"))
    return coincide.members(first.join(second, "s_id"), ["r_id", "s_id", "t_id"], [r, s, t], are)


def same_pairs(r: DataFrame, s: DataFrame, a: GridSpec, b: GridSpec, dense: float | None = None) -> DataFrame:
    """One row: how many pairs only the join by ``a`` finds, as often as it does, only the one by ``b``, and both.

    Where :func:`spatial_join` has lists, pairs of lists are found and compared, each by its first id and its length, and count
    for all pairs of their members. Ids are taken to be unique. Many rectangles are dealt by where those of ``r`` start, so that a pair has
    one place whichever join finds it, and pairs are found and compared in one task without being shuffled.
    """
    known = fused_stats(r), fused_stats(s)
    frames, are = coincide.listed(r, s, known=known, dense=dense)
    r, s = (df.withColumn("rid", F.struct(F.col("rid")[0].alias("first"), F.size("rid").cast("long").alias("n"))) if yes else df for df, yes in zip(frames, are))
    dealt = None if any(are) else by_start(r, s, known)
    if dealt:
        one, two = (spatial_join(*dealt, spec, dense=float("inf"), hint="shuffle_hash", known=known, within="home") for spec in (a, b))
        times = lambda df, c: df.groupBy("home", F.struct("r_id", "s_id").alias("pair")).agg(F.count(F.lit(1)).alias(c))
        all_pairs = times(one, "in_a").join(times(two, "in_b").hint("shuffle_hash"), ["home", "pair"], "full")
        more = lambda x, y: F.greatest(F.coalesce(x, F.lit(0)) - F.coalesce(y, F.lit(0)), F.lit(0))
        counts = {"only_a": more("in_a", "in_b"), "only_b": more("in_b", "in_a"), "both": (F.col("in_a").isNotNull() & F.col("in_b").isNotNull()).cast("int")}
        return all_pairs.agg(*(F.coalesce(F.sum(v), F.lit(0)).cast("long").alias(c) for c, v in counts.items()))
    one, two = (spatial_join(r, s, spec, dense=float("inf")) for spec in (a, b))
    pairs = F.lit(1).cast("long")
    for name, yes in zip(("r_id", "s_id"), are):
        pairs = pairs * F.col(name)["n"] if yes else pairs
    n = lambda df, c: df.agg(F.coalesce(F.sum(pairs), F.lit(0).cast("long")).alias(c))
    return n(one.exceptAll(two), "only_a").crossJoin(n(two.exceptAll(one), "only_b")).crossJoin(n(one.intersect(two), "both"))  # a row each


def salt_parts(r: DataFrame, s: DataFrame, spec: GridSpec, budget: int) -> DataFrame:
    """(tile, parts) of hot tiles: a part for each ``budget`` of comparisons, or for each quarter of a task's average if that is more."""
    from .parallel import tile_counts

    tasks = int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    counts = tile_counts(r, s, spec).select("tile", (F.col("nr") * F.col("ns")).alias("cost"))
    share = (counts.agg(F.sum("cost")).first()[0] or 0) // (4 * tasks)
    return counts.select("tile", F.ceil(F.col("cost") / F.lit(max(budget, share))).cast("int").alias("parts")).where("parts > 1")


def salted_join(r: DataFrame, s: DataFrame, spec: GridSpec, budget: int = 50_000_000) -> DataFrame:
    """The join with hot tiles cut into parts: copies of ``r`` are dealt over a tile's parts, those of ``s`` go to all.

    Tiles that aren't hot beside the others gain nothing from parts, each of which copies ``s`` (:func:`salt_parts`). Only hot
    tiles are looked up; their table is broadcast after its size is checked, else joined.
    """
    hot = salt_parts(r, s, spec, budget)
    hot = F.broadcast(hot) if hot.limit(100_001).count() <= 100_000 else hot
    ra = prefixed(assign(r, spec), "r_", "cx", "cy", "tx", "ty", "tile").withColumnsRenamed({"r_tx": "tx", "r_ty": "ty", "r_tile": "tile"}).join(hot, "tile", "left")
    sa = prefixed(assign(s, spec), "s_", "cx", "cy", "tile").withColumnRenamed("s_tile", "tile").join(hot, "tile", "left")
    ra = ra.withColumn("part", F.pmod(F.xxhash64("r_id"), F.coalesce("parts", F.lit(1))).cast("int")).drop("parts")
    sa = sa.withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    return ra.join(sa.withColumnsRenamed({"tile": "s_tile", "part": "s_part"}), (F.col("tile") == F.col("s_tile")) & (F.col("part") == F.col("s_part")) & intersects() & dd.ref_cell(spec)).select("r_id", "s_id")


def two_level_join(r: DataFrame, s: DataFrame, spec: GridSpec, most: int = 16, coarser: int = 16) -> DataFrame:
    """For inputs with some very large rectangles: those of more than ``most`` copies are joined on a coarser grid."""
    rough = GridSpec(spec.kind, spec.bounds, max(1, spec.kx // coarser), max(1, spec.ky // coarser))

    def parts(df: DataFrame) -> tuple[DataFrame, DataFrame]:
        marked = cells(df, spec).withColumn("_copies", copies())
        return tuple(marked.where(c).select(*df.columns) for c in (F.col("_copies") <= most, F.col("_copies") > most))

    (r_thin, r_fat), (s_thin, s_fat) = parts(r), parts(s)
    out = spatial_join(r_thin, s_thin, spec)
    for a, b in ((r_fat, s_thin), (r_thin, s_fat), (r_fat, s_fat)):
        out = out.unionByName(spatial_join(a, b, rough))
    return out


