"""The phases of parallel evaluation, made visible: counts, offsets, and tiles packed onto tasks.

The engine itself needs none of it: input splits, the shuffle and its block index do the work. The tables
here are for audit, and for placing tiles by their cost.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .grid import GridSpec, assign


#: A table of tiles (20 bytes each) is broadcast up to so many.
BROADCAST_TILES = 1_000_000


def tile_counts(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """(tile, nr, ns)."""
    one = lambda df, x: assign(df, spec).select("tile", F.lit(1 if x == "r" else 0).alias("nr"), F.lit(0 if x == "r" else 1).alias("ns"))
    return one(r, "r").unionByName(one(s, "s")).groupBy("tile").agg(F.sum("nr").cast("long").alias("nr"), F.sum("ns").cast("long").alias("ns"))


def part_counts(df: DataFrame, spec: GridSpec, part=None) -> DataFrame:
    """(part, tile, n): what each input part contributes to each tile. part: a column, or the input partition."""
    return assign(df, spec).groupBy((F.spark_partition_id() if part is None else part).alias("part"), "tile").agg(F.count(F.lit(1)).alias("n"))


def write_offsets(counts: DataFrame) -> DataFrame:
    """Where in a tile's space each part starts to write."""
    before = Window.partitionBy("tile").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("start", F.coalesce(F.sum("n").over(before), F.lit(0)).cast("long"))


def pack_tiles(counts: DataFrame, tasks: int, most: int = 1_000_000) -> DataFrame:
    """(tile, cost, task): tiles to tasks by cost nr * ns, greedily; by ranges of the cumulative share beyond ``most`` tiles."""
    costs = counts.select("tile", (F.col("nr") * F.col("ns")).alias("cost"))
    if counts.limit(most + 1).count() > most:
        total = costs.agg(F.sum("cost")).first()[0] or 1
        coarse = costs.groupBy((F.pmod(F.xxhash64("tile"), F.lit(most))).alias("slot")).agg(F.sum("cost").alias("share"))
        at = coarse.withColumn("task", F.least(F.floor(F.sum("share").over(Window.orderBy("slot")) * F.lit(tasks) / F.lit(total)), F.lit(tasks - 1)).cast("int"))
        return costs.withColumn("slot", F.pmod(F.xxhash64("tile"), F.lit(most))).join(at.drop("share"), "slot").select("tile", "cost", "task")
    rows = sorted(costs.collect(), key=lambda x: (-x.cost, x.tile))
    heap = [(0, t) for t in range(tasks)]
    out = []
    for tile, cost in rows:
        load, t = heapq.heappop(heap)
        out.append((tile, cost, t))
        heapq.heappush(heap, (load + cost, t))
    return counts.sparkSession.createDataFrame(out, "tile long, cost long, task int")


def packed_join(r: DataFrame, s: DataFrame, spec: GridSpec, tasks: int, axis: str = "y") -> DataFrame:
    """The sweep with every tile on the task that packing gives it."""
    from .sweep import _pair, _stream, _swept

    places = pack_tiles(tile_counts(r, s, spec), tasks).select("tile", "task")
    places = F.broadcast(places) if places.limit(BROADCAST_TILES + 1).count() <= BROADCAST_TILES else places
    rows = _stream(r, s, spec, axis, None, deal=False).join(places, "tile").repartitionById(tasks, F.col("task"))
    return _swept(rows.drop("task"), spec, _pair(r, s))
