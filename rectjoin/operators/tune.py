"""How many partitions, and everything else a plan needs, from statistics."""

from __future__ import annotations

import time
import warnings
from collections.abc import Iterable
from dataclasses import replace

from pyspark.sql import DataFrame

from ..functions.rect import Bounds
from .grid import GridSpec, stripes
from .stats import Stats, fused_stats, joint

RATIO = 10.0


def k_rule(stats: Iterable[Stats], b: Bounds, axis: str, ratio: float = RATIO, pick: str = "max") -> int:
    """Partitions about ``ratio`` times as wide as the mean rectangle. pick: whose mean, of several inputs."""
    stats = [s for s in stats if s.n]
    ext = [s.ext["xy".index(axis)] for s in stats] or [0.0]
    mean = {"max": max(ext), "min": min(ext), "pooled": sum(s.n * e for s, e in zip(stats, ext)) / max(1, sum(s.n for s in stats))}[pick]
    return 1 if mean <= 0 or b.width(axis) <= 0 else max(1, int(b.width(axis) / (ratio * mean)))


def expected_replication(s: Stats, spec: GridSpec) -> float:
    out = 1.0
    for a in "xy":
        out *= 1 + (spec.k(a) - 1) * s.relative(spec.bounds, a)
    return out


def clamp(spec: GridSpec, stats: Iterable[Stats], most: float = 2.0, force: bool = False) -> GridSpec:
    """Refuse a grid whose expected copies a rectangle exceed ``most``; warn outside the range that is known to do well."""
    worst = max((expected_replication(s, spec) for s in stats), default=1.0)
    if worst > most and not force:
        raise ValueError(f"{worst:.2f} copies a rectangle are expected; pass force=True")
    if spec.kind == "grid" and max(spec.kx, spec.ky) > 2000 or spec.kind.startswith("stripe") and spec.tiles > 10_000:
        warnings.warn("more partitions than are known to pay", stacklevel=2)
    return spec


def stripes_for_memory(r: Stats, s: Stats, b: Bounds, axis: str, budget_rows: int) -> int:
    """Stripes so that the rectangles of both inputs that are active at once in a sweep fit the budget."""
    other = "y" if axis == "x" else "x"
    active = sum(st.n * max(st.relative(b, other), 1e-12) for st in (r, s))
    return max(1, -(-int(active) // max(1, budget_rows)))


def within(spec: GridSpec, stats: Iterable[Stats], most: float = 2.0) -> GridSpec:
    """The grid, with fewer cuts where the copies a rectangle would exceed ``most``."""
    stats = list(stats)
    while max((expected_replication(s, spec) for s in stats), default=1.0) > most:
        # The axis whose cuts make more copies loses half of them.
        axis = max((a for a in "xy" if spec.k(a) > 1), key=lambda a: max((spec.k(a) - 1) * s.relative(spec.bounds, a) for s in stats))
        spec = replace(spec, **{f"k{axis}": spec.k(axis) // 2})
    return spec


def comparisons(r: Stats, s: Stats, spec: GridSpec) -> float:
    """Pairs of copies that share a cell, for evenly spread rectangles: what the equi-join compares."""
    return expected_replication(r, spec) * r.n * expected_replication(s, spec) * s.n / spec.tiles


def refined(r: Stats, s: Stats, spec: GridSpec, per_row: float = 24.0, most: float = 2.0) -> GridSpec:
    """Cells by rows: either axis is cut further while that saves more comparisons than its copies cost.

    The rule on extents alone leaves ever more rows in a cell as inputs grow, and the equi-join compares all rows of a
    cell; ``per_row`` comparisons cost as much as a copy. At most ``most`` copies a rectangle are made, as far as
    the cuts of ``spec`` allow.
    """
    cost = lambda g: comparisons(r, s, g) + per_row * sum(expected_replication(x, g) * x.n for x in (r, s))
    while r.n and s.n:
        finer = [replace(spec, kind="grid", **{f"k{a}": 2 * spec.k(a)}) for a in "xy" if spec.bounds.width(a) > 0 and spec.k(a) < 1 << 29]
        finer = [g for g in finer if max(expected_replication(x, g) for x in (r, s)) <= most and cost(g) < cost(spec)]
        if not finer:
            return spec
        spec = min(finer, key=cost)
    return spec


def by_rows(r: Stats, s: Stats, spec: GridSpec) -> GridSpec:
    """What the equi-join is to be keyed by: the spec with its cells cut into smaller ones where rows make that pay. Stripes
    stay as they are and get bins."""
    if spec.kind.startswith("stripe"):
        return spec.binned(bins_for(r, s, spec))
    return refined(r, s, spec) if spec.kind == "grid" else spec


def bins_for_tasks(r: Stats, s: Stats, spec: GridSpec, rows: int = 4_000_000) -> int:
    """Sweep bins for the kernel, so that a tile has about ``rows`` copies: a tile is one task's."""
    copies = sum(expected_replication(x, spec) * x.n for x in (r, s))
    return max(1, -(-int(copies) // max(1, spec.tiles * rows)))


def bins_for(r: Stats, s: Stats, spec: GridSpec, per_row: float = 24.0, most: int = 4096) -> int:
    """Sweep bins for the equi-join engine: it compares all of a key's rows, so keys must be small, yet bins make copies.

    Doubles the bins while that saves more comparisons (``per_row`` of them cost as much as a copy).
    """
    axis = "y" if spec.kind == "stripe_x" else "x"
    if not r.n or not s.n or not spec.kind.startswith("stripe"):
        return 1

    def cost(bins: int) -> float:
        rho = [expected_replication(st, spec.binned(bins)) for st in (r, s)]
        return rho[0] * r.n * rho[1] * s.n / (spec.tiles * bins) + per_row * (rho[0] * r.n + rho[1] * s.n)

    bins = 1
    while bins < most and spec.bounds.width(axis) > 0 and cost(2 * bins) < cost(bins):
        bins *= 2
    return bins


def binned_sweep(r: Stats, s: Stats, spec: GridSpec, axis: str, per_row: float = 100.0, most: float = 2.0) -> GridSpec:
    """Stripes swept along the axis that they are cut on, with bins along the other one: the sweep alone meets all that overlaps
    on one axis, which is quadratic in the rows. Doubles the bins while that saves more candidates (``per_row`` of them cost
    as much as a copy), up to ``most`` copies a rectangle."""
    if spec.kind != f"stripe_{axis}" or not r.n or not s.n or spec.bounds.width("y" if axis == "x" else "x") <= 0:
        return spec
    meet = min(1.0, (r.relative(spec.bounds, axis) + s.relative(spec.bounds, axis)) * spec.k(axis))

    def cost(bins: int) -> float:
        g = spec.binned(bins)
        return comparisons(r, s, g) * meet + per_row * sum(expected_replication(x, g) * x.n for x in (r, s))

    bins = 1
    while bins < 1 << 29 and cost(2 * bins) < cost(bins) and max(expected_replication(x, spec.binned(2 * bins)) for x in (r, s)) <= most:
        bins *= 2
    return spec.binned(bins)


def best_cut(r: Stats, s: Stats, b: Bounds) -> str:
    """The axis on which the mean rectangle is smaller relative to the space: more stripes at the same copies."""
    return min("xy", key=lambda a: max(r.relative(b, a), s.relative(b, a)))


def k_sweep(r: DataFrame, s: DataFrame, kinds: Iterable[str], ks: Iterable[int], run=None) -> list[dict]:
    """Time, copies and candidates over a grid of settings. Sample large inputs first."""
    from .join import spatial_join
    from .measure import timed

    st = [fused_stats(df) for df in (r, s)]
    b, ks, out = joint(*st), list(ks), []
    for kind in kinds:
        for k in ks:
            spec = GridSpec(kind, b, k, k) if kind == "grid" else stripes(kind[-1], k, b)
            began = time.perf_counter()
            (run or timed)(spatial_join(r, s, spec))
            out.append({"kind": kind, "k": k, "seconds": time.perf_counter() - began, "replication": [expected_replication(x, spec) for x in st]})
    return out
