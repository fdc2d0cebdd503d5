"""Rectangle files: text forms in, and layouts that later joins and window queries profit from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.grid import GridSpec, assign, cell

SCHEMA = "rid long, xl double, yl double, xu double, yu double"


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).option("mode", "DROPMALFORMED").csv(path)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).json(path)


def read_text(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """Lines "rid,xl,yl,xu,yu"; what isn't a number becomes null (see validate_rects)."""
    parts = F.split("value", sep)
    kinds = ("long", *["double"] * 4)
    return spark.read.text(path).select(*(F.try_element_at(parts, F.lit(i + 1)).try_cast(k).alias(c) for i, (c, k) in enumerate(zip(("rid", "xl", "yl", "xu", "yu"), kinds))))


def write_stripes(df: DataFrame, spec: GridSpec, path: str) -> None:
    """Copies by the stripe of their cut axis, a folder each, sorted by the sweep axis' start."""
    axis = "y" if spec.kind == "stripe_x" else "x"
    assign(df, spec).withColumnRenamed("tile", "stripe").repartition("stripe").sortWithinPartitions("stripe", f"{axis}l").write.partitionBy("stripe").parquet(path)


def write_bucketed(df: DataFrame, spec: GridSpec, table: str, buckets: int) -> None:
    """A table of copies bucketed by tile: joins of two such tables need no exchange."""
    axis = "y" if spec.kind == "stripe_x" else "x"
    assign(df, spec).write.bucketBy(buckets, "tile").sortBy(f"{axis}l").mode("overwrite").saveAsTable(table)


def read_window(spark: SparkSession, path: str, spec: GridSpec, lo: float, hi: float) -> DataFrame:
    """Stored stripes that a window on the cut axis touches (partition pruning), each rectangle once."""
    axis = "x" if spec.kind == "stripe_x" else "y"
    b, k = spec.bounds.of(axis), spec.kx if axis == "x" else spec.ky
    first, last = spark.range(1).select(cell(F.lit(lo), *b, k), cell(F.lit(hi), *b, k)).first()
    rows = spark.read.parquet(path).where(F.col("stripe").between(first, last) & (F.col(f"{axis}l") <= hi) & (F.col(f"{axis}u") >= lo))
    return rows.where(F.col("stripe") == F.greatest(F.col(f"c{axis}"), F.lit(first)))
