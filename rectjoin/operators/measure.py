"""Cost and accuracy measures. Counters come from the data and are exact; times are of this machine."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .axis import choose_axis
from .count import partners
from .dedup import classify, found, ref_cell
from .grid import GridSpec, assign, cells, copies
from .parallel import tile_counts
from .sweep import sweep_counts


def timed(df: DataFrame) -> float:
    """Seconds to compute ``df`` in full, without keeping it."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def breakdown(r: DataFrame, s: DataFrame, spec: GridSpec, **options) -> dict[str, float]:
    """Seconds to assign both inputs, and for the rest of the join."""
    from .join import spatial_join

    cut = sum(timed(assign(df, spec).repartition("tile")) for df in (r, s))
    total = timed(spatial_join(r, s, spec, **options))
    return {"partition": cut, "join": max(0.0, total - cut), "total": total}


def candidates(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str) -> DataFrame:
    """One row: pairs that a sweep along the axis meets in all tiles."""
    return sweep_counts(r, s, spec, axis).agg(F.coalesce(F.sum("candidates"), F.lit(0)).cast("long").alias("candidates"))


def replication(df: DataFrame, spec: GridSpec) -> DataFrame:
    """One row: objects and their copies, without making any."""
    return cells(df, spec).agg(F.count(F.lit(1)).alias("objects"), F.coalesce(F.sum(copies()), F.lit(0)).alias("copies"))


def duplicates(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """One row: pairs found in tiles, pairs reported."""
    return found(r, s, spec).agg(F.count(F.lit(1)).alias("found"), F.count_if(ref_cell(spec)).alias("reported"))


def class_mix(df: DataFrame, spec: GridSpec) -> DataFrame:
    """(cls, n): copies by start class. 0: starts inside; 1: before in x; 2: before in y; 3: both."""
    return classify(assign(df, spec)).groupBy("cls").agg(F.count(F.lit(1)).alias("n"))


def selectivity(pairs: DataFrame, n: int, m: int) -> float:
    return pairs.count() / (n * m) if n and m else 0.0


def pass_ratio(r: DataFrame, s: DataFrame, spec: GridSpec, axis: str) -> DataFrame:
    """One row: candidates and results. Neither is made, both are counted."""
    results = partners(r, s).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("results"))
    return candidates(r, s, spec, axis).crossJoin(results)  # a row each


def balance(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """One row: tiles with work, the costliest, and the sum of costs (nr * ns)."""
    cost = tile_counts(r, s, spec).select((F.col("nr") * F.col("ns")).alias("c")).where("c > 0")
    return cost.agg(F.count(F.lit(1)).alias("tiles"), F.coalesce(F.max("c"), F.lit(0)).alias("costliest"), F.coalesce(F.sum("c"), F.lit(0)).alias("total"))


def tile_stats(r: DataFrame, s: DataFrame, spec: GridSpec) -> DataFrame:
    """One row: tiles of the grid, and those that hold something."""
    return tile_counts(r, s, spec).agg(F.lit(spec.tiles).cast("long").alias("tiles"), F.count(F.lit(1)).alias("filled"))


def axis_accuracy(queries: list[tuple[DataFrame, DataFrame, GridSpec]], **options) -> dict:
    """Share of queries whose model picks the axis with fewer candidates; ties count as right."""
    rows = []
    for r, s, spec in queries:
        est = choose_axis(r, s, spec, **options).agg(F.sum("ix"), F.sum("iy")).first()
        exact = {a: candidates(r, s, spec, a).first()[0] for a in "xy"}
        chosen = "x" if (est[0] or 0) <= (est[1] or 0) else "y"
        rows.append({"estimate": tuple(est), "exact": exact, "chosen": chosen, "right": exact[chosen] == min(exact.values())})
    return {"accuracy": sum(x["right"] for x in rows) / max(1, len(rows)), "queries": rows}


def speedup(base: float, other: float) -> float:
    return base / other if other else float("inf")


def scaleup(run, sessions: dict[int, object]) -> dict[int, dict[str, float]]:
    """run(session) -> seconds, for sessions of different numbers of cores: seconds, speedup and efficiency."""
    times = {m: run(s) for m, s in sessions.items()}
    least = min(times)
    return {m: {"seconds": t, "speedup": times[least] / t, "efficiency": times[least] / t * least / m} for m, t in times.items()}


def tests_per_pair(spec: GridSpec, dedup: str) -> int:
    """Comparisons for a found pair that only serve against duplicates."""
    return {"ref_cell": sum(spec.k(a) > 1 for a in "xy"), "ref_point": sum(spec.k(a) > 1 for a in "xy")}.get(dedup, 0)


def same_pairs(a: DataFrame, b: DataFrame) -> bool:
    """Two results are the same bag of pairs."""
    return not a.exceptAll(b).limit(1).count() and not b.exceptAll(a).limit(1).count()
