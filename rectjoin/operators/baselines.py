"""What the tuned join is compared with."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS, intersects, overlaps, prefixed
from .grid import GridSpec, assign, cell, cells, stripes
from .join import spatial_join
from .stats import fused_stats, joint
from .sweep import sweep_kernel
from .tune import bins_for, k_rule, within

#: Rows and pairs that the nested loop compares at once: masks that stay in a core's cache.
ROWS, PAIRS = 16, 1 << 16


def _joint(r: DataFrame, s: DataFrame):
    st = [fused_stats(df) for df in (r, s)]
    return st, joint(*st)


def global_sweep(r: DataFrame, s: DataFrame, axis: str) -> DataFrame:
    """One sweep over the whole space in one task: small inputs only."""
    return sweep_kernel(r, s, GridSpec("none", _joint(r, s)[1]), axis)


def naive_grid(r: DataFrame, s: DataFrame, k: int = 50, axis: str = "x") -> DataFrame:
    """An untuned grid with a fixed axis and the reference test by coordinates."""
    return spatial_join(r, s, GridSpec("grid", _joint(r, s)[1], k, k), dedup="ref_point")


def same_axis(r: DataFrame, s: DataFrame, k: int, axis: str = "x") -> DataFrame:
    """Stripes swept along the axis that they are cut on."""
    return sweep_kernel(r, s, stripes(axis, k, _joint(r, s)[1]), axis)


def tuned_grid(r: DataFrame, s: DataFrame) -> DataFrame:
    """A grid by the rule on both axes, swept along each tile's own axis."""
    st, b = _joint(r, s)
    return spatial_join(r, s, GridSpec("grid", b, k_rule(st, b, "x"), k_rule(st, b, "y")), engine="sweep", sweep="adaptive")


def single_assign(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """``r`` once, in the stripe of its start; ``s`` in all stripes where a partner may start. No duplicates arise."""
    axis = "x" if spec.kind == "stripe_x" else "y"
    b, k = spec.bounds.of(axis), spec.k(axis)
    most = F.lit(fused_stats(r).most["xy".index(axis)])
    ra = prefixed(cells(r, spec), "r_", f"c{axis}")
    probes = cells(s, spec).withColumn("t", F.explode(F.sequence(cell(F.col(f"{axis}l") - most, *b, k), F.col(f"c{axis}_hi"))))
    return ra.join(prefixed(probes, "s_", "t"), (F.col(f"r_c{axis}") == F.col("s_t")) & intersects()).select("r_id", "s_id")


def _smaller_in_blocks(r: DataFrame, s: DataFrame, most_rows: int, join: Callable[[DataFrame, DataFrame, bool], DataFrame]) -> DataFrame:
    """join(r, s, whether r is the smaller) with the smaller side in blocks of about ``most_rows``, the other dealt over all
    cores: small tables come as few splits."""
    n = [df.count() for df in (r, s)]
    left = n[0] < n[1]
    small, large = (r, s) if left else (s, r)
    large = large.repartition(4 * r.sparkSession.sparkContext.defaultParallelism)
    k = -(-min(n) // most_rows)
    block = F.pmod(F.xxhash64("rid", *COORDS), F.lit(k))
    parts = [join(*((x, large) if left else (large, x)), left) for x in ([small] if k <= 1 else [small.where(block == i) for i in range(k)])]
    return reduce(DataFrame.unionByName, parts)


def _last(v: np.ndarray) -> np.ndarray:
    """NaN comes after all numbers, as in Spark's comparisons."""
    return np.where(np.isnan(v), np.inf, v)


def _every_pair(held: Broadcast[bytes], left: bool):
    """A function for batches of the larger side: each row against each of the held ones, ``PAIRS`` at a time."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        small = pa.ipc.open_stream(held.value).read_all().combine_chunks()
        ids = pa.concat_arrays(small.column("rid").chunks) if len(small) else pa.nulls(0)
        rest = np.full(-len(ids) % 8, np.nan)  # meets nothing
        b = {c: np.concatenate((_last(small.column(c).to_numpy()), rest)) for c in COORDS}
        for batch in batches:
            a = {c: _last(batch.column(c).to_numpy(zero_copy_only=False)) for c in COORDS}
            for i0 in range(0, batch.num_rows, ROWS):
                at = slice(i0, i0 + ROWS)
                for j0 in range(0, len(ids), PAIRS // ROWS):
                    to = slice(j0, j0 + PAIRS // ROWS)
                    meet = a["xl"][at, None] <= b["xu"][to]
                    for x, y in ((b["xl"][to], a["xu"][at, None]), (a["yl"][at, None], b["yu"][to]), (b["yl"][to], a["yu"][at, None])):
                        meet &= x <= y
                    words = np.flatnonzero(meet.reshape(-1).view(np.uint64) != 0)  # most of eight pairs have none that meet
                    if len(words):
                        w, k = np.nonzero(meet.reshape(-1, 8)[words])
                        i, j = np.divmod(words[w] * 8 + k, meet.shape[1])
                        own, other = batch.column("rid").take(pa.array(i + i0)), ids.take(pa.array(j + j0))
                        yield pa.RecordBatch.from_arrays([other, own] if left else [own, other], ["r_id", "s_id"])

    return run


def nested_loop(r: DataFrame, s: DataFrame, most_rows: int = 200_000) -> DataFrame:
    """Every pair compared: the ground truth for small inputs. The smaller side is broadcast, in blocks."""
    schema = ", ".join(f"{x}_id {df.schema['rid'].dataType.simpleString()}" for x, df in (("r", r), ("s", s)))

    def join(r: DataFrame, s: DataFrame, left: bool) -> DataFrame:
        known = reduce(Column.__and__, (F.col(c).isNotNull() for c in COORDS))  # NaN stays
        small, large = (df.select("rid", *COORDS).where(known) for df in ((r, s) if left else (s, r)))
        table, out = small.toArrow(), pa.BufferOutputStream()
        with pa.ipc.new_stream(out, table.schema) as to:
            to.write_table(table)
        held = small.sparkSession.sparkContext.broadcast(out.getvalue().to_pybytes())
        return large.mapInArrow(_every_pair(held, left), schema)

    return _smaller_in_blocks(r, s, most_rows, join)


def broadcast_join(r: DataFrame, s: DataFrame, most_rows: int = 200_000) -> DataFrame:
    """The smaller side sent to all tasks, in blocks of a checked number of rows. Stripes have bins, as all of a key is compared."""
    st, b = _joint(r, s)
    spec = stripes("x", k_rule(st, b, "x"), b)
    spec = within(spec.binned(bins_for(*st, spec)), st)
    return _smaller_in_blocks(r, s, most_rows, lambda r, s, left: spatial_join(r, s, spec, hint="broadcast_left" if left else "broadcast"))


def one_axis_bins(r: DataFrame, s: DataFrame, k: int, axis: str = "x") -> DataFrame:
    """A plain range join: bins on one axis, the rest as residual, distinct pairs."""
    spec = stripes(axis, k, _joint(r, s)[1])
    ra, sa = prefixed(assign(r, spec), "r_", "tile"), prefixed(assign(s, spec), "s_", "tile")
    return ra.join(sa, (F.col("r_tile") == F.col("s_tile")) & overlaps("x") & overlaps("y")).select("r_id", "s_id").distinct()
