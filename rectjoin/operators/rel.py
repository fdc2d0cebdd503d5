"""Relational surroundings: windows of space, ranks, running sets, as-of and nearest neighbours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rect import Bounds, shared_area
from .count import partners
from .join import distance_join, spatial_join


def range_query(df: DataFrame, box: Bounds) -> DataFrame:
    """Rectangles that meet a window. On stored rectangles the four comparisons reach the scan."""
    return df.where((F.col("xl") <= box.xhi) & (F.col("xu") >= box.xlo) & (F.col("yl") <= box.yhi) & (F.col("yu") >= box.ylo))


def within(df: DataFrame, box: Bounds) -> DataFrame:
    return df.where((F.col("xl") >= box.xlo) & (F.col("xu") <= box.xhi) & (F.col("yl") >= box.ylo) & (F.col("yu") <= box.yhi))


def point_query(df: DataFrame, x: float, y: float) -> DataFrame:
    return range_query(df, Bounds(x, y, x, y))


def top_k_area(r: DataFrame, s: DataFrame, k: int, **options) -> DataFrame:
    """The k pairs with the largest common area; ties by ids."""
    pairs = spatial_join(r, s, keep=(["xl", "yl", "xu", "yu"],) * 2, **options)
    return pairs.select("r_id", "s_id", shared_area().alias("area")).orderBy(F.desc("area"), "r_id", "s_id").limit(k)


def ranked_partners(r: DataFrame, s: DataFrame, k: int, **options) -> DataFrame:
    """For every r its k partners with the largest common area: row_number, rank and dense_rank."""
    pairs = spatial_join(r, s, keep=(["xl", "yl", "xu", "yu"],) * 2, **options).withColumn("area", shared_area())
    by_area = Window.partitionBy("r_id").orderBy(F.desc("area"))
    return pairs.select("r_id", "s_id", F.row_number().over(by_area.orderBy(F.desc("area"), "s_id")).alias("place"), F.rank().over(by_area).alias("rank"), F.dense_rank().over(by_area).alias("dense_rank")).where(F.col("place") <= k)


def partner_counts(r: DataFrame, s: DataFrame) -> DataFrame:
    """(r_id, partners): exact, and no pair is made."""
    return partners(r, s).withColumnRenamed("n", "partners")


def active_set(df: DataFrame, axis: str, by: Column) -> DataFrame:
    """(lane, place, active): how many rectangles a sweep holds after each place, separately for each value of ``by``."""
    up = df.select(by.alias("lane"), F.col(f"{axis}l").alias("place"), F.lit(1).alias("step"))
    down = df.select(by.alias("lane"), F.col(f"{axis}u").alias("place"), F.lit(-1).alias("step"))
    steps = up.unionByName(down).groupBy("lane", "place").agg(F.sum("step").alias("step"))
    return steps.select("lane", "place", F.sum("step").over(Window.partitionBy("lane").orderBy("place")).alias("active"))


def asof(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Each left row with the latest right value at or before it, for the same key: one sort, no range join."""
    a = left.select(F.col(key), F.col(at), F.col("id"), F.lit(None).cast(dict(right.dtypes)[value]).alias("v"), F.lit(1).alias("side"))
    b = right.select(F.col(key), F.col(at), F.lit(None).cast(dict(left.dtypes)["id"]).alias("id"), F.col(value).alias("v"), F.lit(0).alias("side"))
    w = Window.partitionBy(key).orderBy(at, "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn("v", F.last("v", ignorenulls=True).over(w)).where("side = 1").select("id", F.col("v").alias(value))


def knn(p: DataFrame, q: DataFrame, k: int, eps: float, most: int = 30) -> DataFrame:
    """(r_id, s_id, place): the k nearest points of ``q`` for each of ``p``, in rings that double until all have k."""
    from ..runtime import written

    left, out, enough = p, None, min(k, q.limit(k).count())
    for _ in range(most):
        near = distance_join(left, q, eps)
        d = (F.col("r_px") - F.col("s_px")) ** 2 + (F.col("r_py") - F.col("s_py")) ** 2
        place = F.row_number().over(Window.partitionBy("r_id").orderBy("d", "s_id"))
        full = near.withColumn("d", d).withColumn("place", place).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("r_id"))).where((F.col("n") >= enough) & (F.col("place") <= enough))
        full = written(full.select("r_id", "s_id", "place"), "knn")
        out = full if out is None else out.unionByName(full)
        left = written(left.join(full.select(F.col("r_id").alias("rid")), "rid", "left_anti"), "knn-left")
        if not left.limit(1).count():
            return out
        eps *= 2
    raise RuntimeError("eps is too small for the space")
