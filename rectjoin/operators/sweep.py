"""Forward-scan plane sweep inside a partition: as an Arrow kernel, and as declarative joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS, overlaps, prefixed
from ..runtime import written
from .grid import GridSpec, assign, cells

#: Candidate pairs that the kernel holds at once.
CHUNK = 1 << 20
#: Pairs in a batch where ids are lists.
LISTS = 1 << 12


def _ranges(lo: np.ndarray, hi: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All (i, j) with lo[i] <= j < hi[i], about ``CHUNK`` at a time."""
    n = np.maximum(hi - lo, 0)
    ends, at = np.cumsum(n), 0
    while at < len(n):
        upto = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + CHUNK, "right")))
        part = n[at:upto]
        i = np.repeat(np.arange(at, upto), part)
        j = np.repeat(lo[at:upto] - (np.cumsum(part) - part), part) + np.arange(int(part.sum()))
        if len(i):
            yield i, j
        at = upto


def _spans(rl: np.ndarray, ru: np.ndarray, sl: np.ndarray, su: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, bool]]:
    """What each start of one side meets of the other, as ranges; of both sides, the second ones swapped."""
    for a_l, a_u, b_l, side, swap in ((rl, ru, sl, "left", False), (sl, su, rl, "right", True)):
        yield np.searchsorted(b_l, a_l, side), np.searchsorted(b_l, a_u, "right"), swap


def scan(rl: np.ndarray, ru: np.ndarray, sl: np.ndarray, su: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs whose intervals meet. Both sides are sorted by start; each start scans the other side forward
    over the starts inside its own interval, ties going to the first side, so the two scans share no pair."""
    for lo, hi, swap in _spans(rl, ru, sl, su):
        for i, j in _ranges(lo, hi):
            yield (j, i) if swap else (i, j)


class Side:
    """Rectangles of one input in a tile: ids, and columns of numbers, sorted by their start."""

    def __init__(self, ids: pa.Array, columns: dict[str, np.ndarray]):
        self.ids, self.columns = ids, columns

    def __len__(self) -> int:
        return len(self.ids)

    def pick(self, at: np.ndarray) -> Side:
        return Side(self.ids.take(pa.array(at)), {c: v[at] for c, v in self.columns.items()})

    def with_more(self, other: Side) -> Side:
        return Side(pa.concat_arrays([self.ids, other.ids]), {c: np.concatenate((v, other.columns[c])) for c, v in self.columns.items()}) if len(self) and len(other) else self if len(self) else other


def _meetings(old: tuple[Side, Side], new: tuple[Side, Side], axis: str) -> Iterator[tuple[Side, Side, np.ndarray, np.ndarray]]:
    """Candidates of a sweep that goes on: among the new ones, and of those still active with new ones, which start later."""
    low, up = f"{axis}l", f"{axis}u"
    (r0, s0), (r1, s1) = old, new
    for i, j in scan(r1.columns[low], r1.columns[up], s1.columns[low], s1.columns[up]):
        yield r1, s1, i, j
    for i, j in _ranges(np.zeros(len(r0), np.int64), np.searchsorted(s1.columns[low], r0.columns[up], "right")):
        yield r0, s1, i, j
    for j, i in _ranges(np.zeros(len(s0), np.int64), np.searchsorted(r1.columns[low], s0.columns[up], "right")):
        yield r1, s0, i, j


def _number(old: tuple[Side, Side], new: tuple[Side, Side], axis: str) -> int:
    """How many candidates :func:`_meetings` has: the ranges' lengths, without the pairs."""
    low, up = f"{axis}l", f"{axis}u"
    (r0, s0), (r1, s1) = old, new
    n = sum(int(np.maximum(hi - lo, 0).sum()) for lo, hi, _ in _spans(r1.columns[low], r1.columns[up], s1.columns[low], s1.columns[up]))
    return n + sum(int(np.searchsorted(b.columns[low], a.columns[up], "right").sum()) for a, b in ((r0, s1), (s0, r1)))


def kernel(cut: str, count_only: bool = False):
    """A function for Arrow batches that are sorted by tile and start. cut: the axes that tiles are cut on.

    Tiles pass by as a stream: what is held is a batch and the rectangles that are still active, as a plane sweep
    holds them, and ``CHUNK`` candidates. No tile needs to fit the worker.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tile, old, candidates = None, None, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in (*COORDS, "cx", "cy", "tx", "ty", "tile", "side", "along")}
            borders = np.flatnonzero(np.diff(held["tile"])) + 1
            for start, end in zip([0, *borders.tolist()], [*borders.tolist(), batch.num_rows]):
                now = int(held["tile"][start])
                chosen = "y" if held["along"][start] else "x"
                other = "x" if chosen == "y" else "y"
                sides = []
                for k, name in enumerate(("r_id", "s_id")):
                    at = start + np.flatnonzero(held["side"][start:end] == k)
                    sides.append(Side(batch.column(name).take(pa.array(at)), {c: held[c][at] for c in (*COORDS, "cx", "cy")}))
                new = (sides[0], sides[1])
                if now != tile:
                    if count_only and tile is not None:
                        yield _counted(tile, candidates)
                    tile, candidates, old = now, 0, tuple(x.pick(np.empty(0, np.int64)) for x in new)
                if count_only:
                    candidates += _number(old, new, chosen)
                for r, s, i, j in () if count_only else _meetings(old, new, chosen):
                    ok = (r.columns[f"{other}l"][i] <= s.columns[f"{other}u"][j]) & (s.columns[f"{other}l"][j] <= r.columns[f"{other}u"][i])
                    for a in cut:
                        ok &= np.maximum(r.columns[f"c{a}"][i], s.columns[f"c{a}"][j]) == held[f"t{a}"][start]
                    found = np.flatnonzero(ok)
                    step = LISTS if any(pa.types.is_list(x.ids.type) for x in (r, s)) else CHUNK
                    for at in (found[k : k + step] for k in range(0, len(found), step)):
                        yield pa.RecordBatch.from_arrays([r.ids.take(pa.array(i[at])), s.ids.take(pa.array(j[at]))], ["r_id", "s_id"])
                if end == batch.num_rows:  # the tile may go on: who is active where the batch ends stays
                    last = held[f"{chosen}l"][end - 1]
                    old = tuple((both := x.with_more(y)).pick(np.flatnonzero(both.columns[f"{chosen}u"] >= last)) for x, y in zip(old, new))
        if count_only and tile is not None:
            yield _counted(tile, candidates)

    return run


def _counted(tile: int, candidates: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([tile], pa.int64()), pa.array([candidates], pa.int64())], ["tile", "candidates"])


def _sides(r: DataFrame, s: DataFrame, spec: GridSpec) -> tuple[DataFrame, DataFrame]:
    ra = prefixed(assign(r, spec), "r_", "cx", "cy", "tx", "ty", "tile").withColumnsRenamed({"r_tx": "tx", "r_ty": "ty", "r_tile": "tile"})
    sa = prefixed(assign(s, spec), "s_", "cx", "cy", "tile").withColumnRenamed("s_tile", "tile")
    return ra, sa


def _stream(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str, axes: DataFrame | None, deal: bool = True) -> DataFrame:
    """Copies of both inputs in one table, dealt to tasks by tile unless the caller does that, with the axis that their tile is swept along, and where they start on it.

    A tile that the model says nothing of is swept along the axis that is cheaper over all tiles.
    """
    kind = {x: df.schema["rid"].dataType for x, df in (("r", r), ("s", s))}
    none = {x: F.lit(None).cast(k) for x, k in kind.items()}
    one = lambda df, x: assign(df, spec).select(*COORDS, "tile", F.lit("rs".index(x)).cast("byte").alias("side"), *((F.col("rid") if y == x else none[y]).alias(f"{y}_id") for y in "rs"))
    both = one(r, "r").unionByName(one(s, "s"))
    if axes is not None:
        axes = written(axes.select("tile", "ix", "iy", "axis"), "axes")
        total = axes.agg(F.sum("ix"), F.sum("iy")).first()
        rest = "y" if (total[1] or 0) < (total[0] or 0) else "x"
        both = both.join(axes.select("tile", "axis"), "tile", "left").withColumn("along", (F.coalesce("axis", F.lit(rest)) == "y").cast("byte")).drop("axis")
    both = both.repartition("tile") if deal else both
    both = cells(both, spec).drop("cx_hi", "cy_hi")  # what follows from the rest isn't shuffled
    both = both.withColumn("tx", F.pmod("tile", F.lit(spec.kx)).cast("int")).withColumn("ty", F.floor(F.col("tile") / F.lit(spec.kx)).cast("int"))
    if axes is None:
        both = both.withColumn("along", F.lit("xy".index(axis)).cast("byte"))
    return both.withColumn("start", F.when(F.col("along") == 1, F.col("yl")).otherwise(F.col("xl")))


def _swept(rows: DataFrame, spec: GridSpec, schema: str, count_only: bool = False) -> DataFrame:
    """The kernel over rows that are dealt by tile already."""
    cut = "".join(a for a in "xy" if spec.k(a) > 1)
    return rows.sortWithinPartitions("tile", "start").drop("start").mapInArrow(kernel(cut, count_only), schema)


def _pair(r: DataFrame, s: DataFrame) -> str:
    return ", ".join(f"{x}_id {df.schema['rid'].dataType.simpleString()}" for x, df in (("r", r), ("s", s)))


def sweep_kernel(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str = "x", axes: DataFrame | None = None) -> DataFrame:
    """Pairs by a true sweep of every tile. Spark sorts, and spills; a worker holds the active rectangles of a tile."""
    return _swept(_stream(r, s, spec, axis, axes), spec, _pair(r, s))


def sweep_counts(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str = "x", axes: DataFrame | None = None) -> DataFrame:
    """(tile, candidates) that the sweep meets, without testing them."""
    return _swept(_stream(r, s, spec, axis, axes), spec, "tile long, candidates long", True)


def sweep_sql(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str = "x") -> DataFrame:
    """The two forward scans as two range joins that share no pair."""
    from .dedup import ref_cell

    ra, sa = _sides(r, s, spec)
    other = overlaps("y" if axis == "x" else "x") & ref_cell(spec)
    sa = sa.withColumnRenamed("tile", "s_tile")
    same = F.col("tile") == F.col("s_tile")
    first = ra.join(sa, same & F.col(f"s_{axis}l").between(F.col(f"r_{axis}l"), F.col(f"r_{axis}u")) & other)
    second = ra.join(sa, same & (F.col(f"r_{axis}l") > F.col(f"s_{axis}l")) & (F.col(f"r_{axis}l") <= F.col(f"s_{axis}u")) & other)
    return first.unionByName(second).select("r_id", "s_id")
