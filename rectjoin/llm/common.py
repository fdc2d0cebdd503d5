"""Shared pieces of the corpus operators: scratch tables, bounded id filters, tokenizers."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import release, scratch, shared_dir, written  # noqa: F401
from .tokens import forget

#: Buckets of the id filter that is broadcast; with 8 bytes each the relation has a proven bound of a few MB.
ID_BUCKETS = 1 << 18


def id_bucket(col: Column) -> Column:
    return F.pmod(F.xxhash64(col), F.lit(ID_BUCKETS)).cast("int")


def _buckets(ids: DataFrame, key: str, name: str) -> DataFrame:
    return F.broadcast(ids.select(id_bucket(F.col(key)).alias(name)).distinct())


def _bucket_name(df: DataFrame) -> str:
    """A column name that the table hasn't."""
    return "__rj_bucket" + "_" * max((len(c) for c in df.columns if c.lower().startswith("__rj_bucket")), default=0)


def rows_with(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """Rows of ``df`` whose key may be in ``ids``: a superset, found without a shuffle of ``df``.

    What is broadcast is a set of at most ``ID_BUCKETS`` integers, whatever the size of ``ids``.
    """
    name = _bucket_name(df)
    return df.withColumn(name, id_bucket(F.col(key))).join(_buckets(ids, key, name), name, "left_semi").drop(name)


def rows_without(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """Exactly the rows of ``df`` whose key isn't in ``ids``; only rows in a bucket of ``ids`` are shuffled."""
    name = _bucket_name(df)
    marked = df.withColumn(name, id_bucket(F.col(key)))
    clear = marked.join(_buckets(ids, key, name), name, "left_anti").drop(name)
    doubtful = rows_with(df, ids, key).join(ids.select(key).distinct(), key, "left_anti")
    return clear.unionByName(doubtful.select(*df.columns))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def kept_texts(df: DataFrame, column: str, keep: Callable[[list[str | None]], list[bool]], rows: int = 1000) -> DataFrame:
    """The rows whose text ``keep`` wants, as they are. Only that column goes through Python, in slices."""

    @F.arrow_udf("boolean")
    def wanted(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        tidied()
        for texts in arrays:
            yield pa.array([k for at in range(0, len(texts), rows) for k in keep(texts.slice(at, rows).to_pylist())], pa.bool_())

    return df.where(wanted(F.col(f"`{column}`")))


def tidied(keep_encoder: bool = False) -> None:
    """Give back what a worker holds but doesn't use: memory of Arrow and of the C library, and the pieces of a tokenizer.

    Workers live on from task to task, so else each keeps the most that any of its tasks has needed.
    """
    if not keep_encoder:
        forget()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def sliced(batches, rows: int = 1000, keep_encoder: bool = False):
    """Arrow batches in slices of so many rows, so that Python copies of their values stay small."""
    tidied(keep_encoder)
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
    batch = None
    tidied(keep_encoder)
