"""Partners counted without their pairs: what is quadratic in a join is a few sums here.

Where no rectangle has its ends the wrong way round, the ``s`` that meet an ``r`` are those that start at or before its
end less those that end before its start, on both axes at once. That leaves four counts of points that lie low on both
axes. Each axis is cut into stripes by values; a query needs the points of its own x stripe, those of its own y stripe
in lower x stripes, and the number of points that are lower in both numbers, which is a small table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ..functions.rect import COORDS, intersects, prefixed
from ..runtime import written
from .grid import quantile_cuts

#: Points that the kernel holds at once, rows that a stripe is to have, and the most stripes of an axis.
CHUNK, STRIPE_ROWS, STRIPES = 1 << 18, 100_000, 256


def below(x: np.ndarray, y: np.ndarray, at: np.ndarray, y_at: np.ndarray, x_side: str, y_side: str) -> np.ndarray:
    """For each query (at, y_at) the points (x, y) that are lower on both axes; side ``right`` counts equal ones, too."""
    n = len(x)
    ranks, first = np.empty(n, np.int64), np.argsort(x, kind="stable")
    order = np.argsort(y, kind="stable")
    ranks[order] = np.arange(n)
    rows, upto = ranks[first], np.searchsorted(x[first], at, x_side)
    least = np.searchsorted(y[order], y_at, y_side)
    full = least == n  # all of the prefix
    lo, hi, out = np.zeros(len(at), np.int64), upto.astype(np.int64), np.zeros(len(at), np.int64)
    for bit in range(max(1, int(n).bit_length()) - 1, -1, -1):  # the ranks' bits from the highest: zeros go first
        zero = (rows >> bit & 1) == 0
        zeros = np.concatenate(([0], np.cumsum(zero)))
        one, low, high = (least >> bit & 1).astype(bool), zeros[lo], zeros[hi]
        out += np.where(one, high - low, 0)
        lo, hi = np.where(one, zeros[-1] + lo - low, low), np.where(one, zeros[-1] + hi - high, high)
        rows = np.concatenate((rows[zero], rows[~zero]))
    return np.where(full, upto, out)


def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(r_id, n) for rows sorted by part and side: a part's queries come first and are held, its points pass by."""
    part, ids, queries, points, held, total = None, [], [], [], 0, None

    def take() -> None:
        nonlocal points, held, total, queries
        if not queries or not points:
            points, held = [], 0
            return
        if len(queries) > 1:
            queries = [tuple(map(np.concatenate, zip(*queries)))]
        (v, lo, hi), (pv, plo, phi) = queries[0], map(np.concatenate, zip(*points))
        across, later = part & 1, part >> 1 & 1  # dealt by y; the second kind of point, which is strictly below and taken off
        sides = "left" if later else "right"
        n = below(pv, plo, v, hi, sides, "left" if across else "right") - below(pv, phi, v, lo, sides, "left")
        total = (0 if total is None else total) + (-n if later else n)
        points, held = [], 0

    def done() -> Iterator[pa.RecordBatch]:
        take()
        if ids and total is not None:
            yield pa.RecordBatch.from_arrays([pa.concat_arrays(ids), pa.array(total, pa.int64())], ["r_id", "n"])

    for batch in batches:
        if not batch.num_rows:
            continue
        parts, side = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("part", "side"))
        columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("v", "lo", "hi")]
        borders = np.flatnonzero((np.diff(parts) != 0) | (np.diff(side) != 0)) + 1
        for start, end in zip([0, *borders.tolist()], [*borders.tolist(), batch.num_rows]):
            if int(parts[start]) != part:
                if part is not None:
                    yield from done()
                part, ids, queries, points, held, total = int(parts[start]), [], [], [], 0, None
            own = tuple(c[start:end] for c in columns)
            if side[start] == 0:
                ids.append(batch.column("r_id").slice(start, end - start))
                queries.append(own)
            else:
                points.append(own)
                held += end - start
                if held >= CHUNK:
                    take()
    if part is not None:
        yield from done()


def _ends(batch: pa.RecordBatch, cuts: dict[str, np.ndarray]) -> tuple[dict[str, np.ndarray], dict[str, np.ndarray]]:
    """Coordinates, and the stripes they lie in: borders at or below them, which never fall as they grow."""
    held = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in COORDS}
    return held, {c: np.searchsorted(cuts[c[0]], v, "right") for c, v in held.items()}


def _dealt(side: int, cuts: dict[str, np.ndarray], kind: pa.DataType):
    """Four rows (part, side, v, lo, hi, r_id) for each rectangle: by either axis and either end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held, at = _ends(batch, cuts)
            ids = pa.nulls(batch.num_rows, kind) if side else batch.column("rid")
            for a, o in (("x", "y"), ("y", "x")):
                lo, hi = ((held if a == "x" else at)[f"{o}{e}"].astype(np.float64) for e in "lu")
                for later in (0, 1):
                    v = f"{a}{'lu'[later] if side else 'ul'[later]}"
                    part = at[v] * 4 + (a == "y") + 2 * later
                    yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array(np.full(len(part), side, np.int8)), pa.array(held[v]), pa.array(lo), pa.array(hi), ids], ["part", "side", "v", "lo", "hi", "r_id"])

    return run


def _cells(cuts: dict[str, np.ndarray]):
    """(which, x, y, n): points by their stripes on both axes, for each pair of ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, width = _ends(batch, cuts)[1], len(cuts["y"]) + 1
            for i, x in enumerate(("xl", "xu")):
                for j, y in enumerate(("yl", "yu")):
                    found, n = np.unique(at[x] * width + at[y], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), 2 * i + j)), pa.array(found // width), pa.array(found % width), pa.array(n)], ["which", "x", "y", "n"])

    return run


def _lower(table: np.ndarray, cuts: dict[str, np.ndarray]):
    """(r_id, n) from the table of points in lower stripes of both axes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = _ends(batch, cuts)[1]
            n = sum((-1) ** (i + j) * table[2 * i + j, at["xl" if i else "xu"], at["yl" if j else "yu"]] for i in (0, 1) for j in (0, 1))
            yield pa.RecordBatch.from_arrays([batch.column("rid"), pa.array(n, pa.int64())], ["r_id", "n"])

    return run


def partners(r: DataFrame, s: DataFrame) -> DataFrame:
    """(r_id, n): how many rectangles of ``s`` each of ``r`` meets, at least one; in proportion to the rows, whatever their overlap."""
    r, s = (df.select("rid", *COORDS).dropna(subset=COORDS) for df in (r, s))
    r = written(r, "count")  # read four times; it may be grouped
    proper = (F.col("xl") <= F.col("xu")) & (F.col("yl") <= F.col("yu"))
    n, odd = s.agg(F.count(F.lit(1)), F.count_if(~proper)).first()
    odd += r.agg(F.count_if(~proper)).first()[0]
    kind = r.schema["rid"].dataType
    schema = f"r_id {kind.simpleString()}, n long"
    k = max(1, min(STRIPES, n // STRIPE_ROWS))
    cuts = {a: np.unique(np.array(quantile_cuts(s, a, k), np.float64)) for a in "xy"}
    good_r, good_s = (df.where(proper) for df in (r, s))
    table = np.zeros((4, len(cuts["x"]) + 2, len(cuts["y"]) + 2), np.int64)  # shifted by one: lower ones only
    for which, x, y, m in good_s.select(*COORDS).mapInArrow(_cells(cuts), "which long, x long, y long, n long").groupBy("which", "x", "y").agg(F.sum("n")).collect():
        table[which, x + 1, y + 1] = m
    table = table.cumsum(1).cumsum(2)
    row = f"part long, side byte, v double, lo double, hi double, r_id {kind.simpleString()}"
    rows = good_r.mapInArrow(_dealt(0, cuts, to_arrow_type(kind)), row).unionByName(good_s.select(*COORDS).mapInArrow(_dealt(1, cuts, to_arrow_type(kind)), row))
    out = rows.repartition("part").sortWithinPartitions("part", "side").mapInArrow(kernel, schema)
    out = out.unionByName(good_r.mapInArrow(_lower(table, cuts), schema))
    if odd:  # ends the wrong way round: the sums don't hold, each such row is compared
        for a, b in ((r, s.where(~proper)), (r.where(~proper), s.where(proper))):
            out = out.unionByName(prefixed(a, "r_").join(prefixed(b, "s_"), intersects()).select("r_id", F.lit(1).cast("long").alias("n")))
    return out.groupBy("r_id").agg(F.sum("n").alias("n")).where("n > 0")
