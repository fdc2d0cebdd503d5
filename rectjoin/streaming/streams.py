"""Rectangles that arrive as a stream.

The duplicate test needs nothing but the pair and its cells, so a stream keeps no state for it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rect import COORDS, intersects, prefixed
from ..operators.dedup import ref_cell
from ..operators.grid import GridSpec, assign
from ..runtime import scratch


def file_stream(spark: SparkSession, folder: str, glob: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("pathGlobFilter", glob).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def stream_static(stream: DataFrame, static: DataFrame, spec: GridSpec) -> DataFrame:
    """Pairs (r_id, s_id) of arriving rectangles with fixed ones. ``spec`` is fixed, so every batch uses the same cells."""
    ra = prefixed(assign(stream, spec), "r_", "cx", "cy", "tx", "ty", "tile").withColumnsRenamed({"r_tx": "tx", "r_ty": "ty"})
    sa = prefixed(assign(static, spec), "s_", "cx", "cy", "tile")
    return ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & intersects() & ref_cell(spec)).select("r_id", "s_id")


def stream_stream(r: DataFrame, s: DataFrame, spec: GridSpec, longest: float, late: str = "10 minutes") -> DataFrame:
    """Pairs of two streams with an event time ``ts`` that is the start on x in seconds. ``longest`` bounds how long a
    rectangle lasts (longer ones are left out), hence how far apart two starts can be and when state may go.
    Tiles are stripes on y."""
    sides = []
    for df, p in ((r, "r_"), (s, "s_")):
        df = df.where(F.col("xu") - F.col("xl") <= longest).withWatermark("ts", late)
        sides.append(assign(df, spec).select(F.col("rid").alias(f"{p}id"), F.col("ts").alias(f"{p}ts"), *(F.col(c).alias(p + c) for c in (*COORDS, "cy", "ty"))))
    a, b = sides
    span = F.expr(f"INTERVAL {int(longest) + 1} SECONDS")
    cond = (F.col("r_ty") == F.col("s_ty")) & (F.col("r_ts") <= F.col("s_ts") + span) & (F.col("s_ts") <= F.col("r_ts") + span) & intersects() & (F.col("r_ty") == F.greatest("r_cy", "s_cy"))
    return a.join(b, cond).select("r_id", "s_id")


def density(stream: DataFrame, spec: GridSpec, width: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Copies by tile and time window (tumbling, or sliding with ``slide``)."""
    rows = assign(stream.withWatermark("ts", late), spec)
    return rows.groupBy(F.window("ts", width, slide), "tile").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "tile", "n")


def sessions(stream: DataFrame, spec: GridSpec, gap: str, late: str = "10 minutes") -> DataFrame:
    """Copies by tile and session: a tile's session ends when nothing starts in it for ``gap``."""
    rows = assign(stream.withWatermark("ts", late), spec)
    return rows.groupBy(F.session_window("ts", gap).alias("session"), "tile").agg(F.count(F.lit(1)).alias("n")).select(F.col("session.start").alias("start"), "tile", "n")


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All that is there now, through a file sink that commits whole batches; read back as a table."""
    spark, out = stream.sparkSession, scratch(stream.sparkSession, name)
    stream.writeStream.format("parquet").outputMode(mode).option("path", out).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def each_batch(stream: DataFrame, action: Callable[[DataFrame, int], None], state: str) -> None:
    """Run an action on every micro-batch, e.g. plan anew by its statistics."""
    stream.writeStream.foreachBatch(action).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
