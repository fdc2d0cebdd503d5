"""Choice of the sweep axis by histograms of where the two inputs lie on each axis."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .grid import GridSpec, assign
from .stats import Stats, fused_stats

#: Sampled rows that the model wants for each input; fewer make it use every row.
MIN_SAMPLE = 1000


def bucket_count(tile_extent: float, mean_extent: float, cap: int = 1000) -> int:
    return cap if mean_extent <= 0 else int(min(cap, max(1, tile_extent // mean_extent)))


def stripe_rule(spec: GridSpec) -> str | None:
    """Stripes are swept along the axis that they aren't cut on; no model is needed."""
    return {"stripe_x": "y", "stripe_y": "x"}.get(spec.kind)


def sample(df: DataFrame, phi: int, how: str = "hash", side: str = "r", key: str = "rid") -> DataFrame:
    """One of every ``phi`` rows. hash: by a hash of id and side (so a self-join doesn't sample the same objects);
    modulo: ids divisible by phi; rank: by place in each tile."""
    if phi <= 1:
        return df
    if how == "hash":
        return df.where(F.pmod(F.xxhash64(F.col(key), F.lit(side)), F.lit(phi)) == 0)
    if how == "modulo":
        return df.where(F.pmod(F.col(key), F.lit(phi)) == 0)
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy("tile").orderBy(key))
    return df.withColumn("_place", place).where(F.pmod(F.col("_place"), F.lit(phi)) == 0).drop("_place")


def _bucket(v: Column, axis: str, spec: GridSpec, k: int) -> Column:
    """Bucket of a coordinate inside a tile, clamped to the tile."""
    lo, hi = spec.bounds.of(axis)
    width = (hi - lo) / spec.k(axis) or 1.0
    start = F.lit(lo) + F.col(f"t{axis}") * F.lit(width)
    return F.least(F.greatest(F.floor((v - start) / F.lit(width) * F.lit(k)), F.lit(0)), F.lit(k - 1)).cast("int")


def histograms(assigned: DataFrame, spec: GridSpec, kx: int, ky: int) -> DataFrame:
    """(tile, axis, bucket, cnt, starts): copies that touch a bucket, and those that start there."""
    parts = []
    for a, k in (("x", kx), ("y", ky)):
        first, last = _bucket(F.col(f"{a}l"), a, spec, k), _bucket(F.col(f"{a}u"), a, spec, k)
        rows = assigned.select("tile", F.lit(a).alias("axis"), first.alias("first"), F.explode(F.sequence(first, last)).alias("bucket"))
        parts.append(rows.groupBy("tile", "axis", "bucket").agg(F.count(F.lit(1)).alias("cnt"), F.sum((F.col("bucket") == F.col("first")).cast("long")).alias("starts")))
    return parts[0].unionByName(parts[1])


def choose_axis(r: DataFrame, s: DataFrame, spec: GridSpec, k: int | str = "auto", phi: int = 100, how: str = "hash", estimator: str = "product", least: int = MIN_SAMPLE, known: tuple[Stats, Stats] | None = None) -> DataFrame:
    """(tile, ix, iy, axis): estimated candidates of a sweep along x and along y in every tile, and the cheaper axis.

    product: sum of products of the two histograms. debiased: a pair counts only in the bucket of its later start.
    ``known``: statistics of the two sides, if a caller has them.
    """
    if k == "auto" or (phi > 1 and least):
        known = known or (fused_stats(r), fused_stats(s))  # one pass of each side for cardinality and extents
    if phi > 1 and least:
        phi = max(1, min(phi, *(x.n // least for x in known)))
    if k == "auto":
        kx, ky = (bucket_count(spec.bounds.width(a) / spec.k(a), max(x.ext[i] for x in known)) for i, a in enumerate("xy"))
    else:
        kx = ky = int(k)
    hr, hs = (histograms(sample(assign(df, spec), phi, how, side), spec, kx, ky) for df, side in ((r, "r"), (s, "s")))
    key = ["tile", "axis", "bucket"]
    both = hr.withColumnsRenamed({"cnt": "hr", "starts": "br"}).join(hs.withColumnsRenamed({"cnt": "hs", "starts": "bs"}), key)
    each = F.col("hr") * F.col("hs") if estimator == "product" else F.col("br") * F.col("hs") + F.col("hr") * F.col("bs") - F.col("br") * F.col("bs")
    one = lambda a: F.sum(F.when(F.col("axis") == a, each).otherwise(0)).alias(f"i{a}")
    return both.groupBy("tile").agg(one("x"), one("y")).withColumn("axis", F.when(F.col("ix") <= F.col("iy"), "x").otherwise("y"))
