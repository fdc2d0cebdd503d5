"""Rectangles that coincide: joined once, as lists of ids, and taken apart again where the pairs leave.

A join whose results far outnumber its rows is paid by the pair. Where many rectangles are the same one, a pair of lists stands for
all pairs of its members, so these are neither compared nor shuffled; they are made as the last step.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rect import COORDS
from ..runtime import written
from .stats import Stats, fused_stats, joint

#: Expected pairs for each row of the inputs from which lists are looked for.
DENSE = 16.0
#: Members of a list on average at most; more rectangles of a kind make several lists, which go to different tasks.
MOST = 256


def expected_pairs(*stats: Stats) -> float:
    """Pairs of two inputs, for evenly spread rectangles."""
    b, out = joint(*stats), 1.0
    for st in stats:
        out *= st.n
    for a in "xy":
        out *= min(1.0, sum(st.relative(b, a) for st in stats)) if b.width(a) > 0 else 1.0
    return out


def lists(df: DataFrame, n: int, most: int = MOST) -> DataFrame | None:
    """(rid, coordinates) with rid the list of all ids of equal rectangles, if there are two to a list or more; else None."""
    about = df.agg(F.approx_count_distinct(F.xxhash64(*COORDS), 0.02)).first()[0]  # exact counts shuffle every kind
    if not n or 2 * about > 1.2 * n:
        return None
    kinds, largest = df.groupBy(*COORDS).agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)), F.max("n")).first()
    if not n or 2 * kinds > n:
        return None
    rid = F.col("rid") if not df.schema["rid"].nullable else F.struct("rid")  # a list would leave out an id that is null
    part = F.pmod(F.xxhash64("rid"), F.lit(-(-largest // most))).alias("part")
    out = df.groupBy(*COORDS, part).agg(F.collect_list(rid).alias("rid"))
    return written(out.select("rid", *COORDS), "lists")


def listed(*frames: DataFrame, known: tuple[Stats, ...] | None = None, dense: float | None = None) -> tuple[list[DataFrame], list[bool]]:
    """The frames, those with many rectangles of a kind as lists, and which ones are; as they are unless joins of neighbours have many pairs."""
    known = known or tuple(map(fused_stats, frames))
    pairs = sum(expected_pairs(a, b) for a, b in zip(known, known[1:]))
    if pairs <= (DENSE if dense is None else dense) * sum(st.n for st in known):
        return list(frames), [False] * len(frames)
    found = [lists(df, st.n) for df, st in zip(frames, known)]
    return [df if new is None else new for df, new in zip(frames, found)], [new is not None for new in found]


def members(pairs: DataFrame, names: list[str], of: list[DataFrame], are: list[bool]) -> DataFrame:
    """A row for each combination of members. names: the columns of lists; of: the frames that the ids are from. The first
    column changes slowest, so its ids leave in runs."""
    for name, df, yes in zip(names, of, are):
        if yes:
            one = F.col("_one") if not df.schema["rid"].nullable else F.col("_one.rid")
            pairs = pairs.select(*(c for c in pairs.columns if c != name), F.explode(name).alias("_one")).withColumn(name, one).drop("_one")
    return pairs.select(*names)
