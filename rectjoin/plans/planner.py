"""A plan from one pass of statistics over each input."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..operators.grid import GridSpec, stripes
from ..operators.stats import Stats, fused_stats, joint
from ..operators.tune import best_cut, bins_for_tasks, clamp, expected_replication, k_rule, refined, within

#: A side of at most so many rows is sent to all tasks, before it is assigned.
BROADCAST_ROWS = 20_000
#: Up to so many rows of the smaller side a tile partition is hashed; beyond, sort-merge, which spills.
HASH_ROWS = 50_000_000


@dataclass(frozen=True)
class JoinPlan:
    spec: GridSpec
    sweep: str
    dedup: str
    engine: str
    hint: str | None
    stats: tuple[Stats, Stats]

    def explain(self) -> str:
        rho = ", ".join(f"{expected_replication(s, self.spec):.3f}" for s in self.stats)
        return f"{self.spec.kind} {self.spec.kx} x {self.spec.ky}, sweep {self.sweep}, {self.dedup}, {self.engine}{', ' + self.hint if self.hint else ''}; copies {rho}"


def auto_plan(r: DataFrame, s: DataFrame, engine: str = "catalyst", ratio: float = 10.0, known: tuple[Stats, Stats] | None = None) -> JoinPlan:
    """Stripes on the axis with the smaller extents, as wide as the rule says and with no more copies than the guard
    allows. The engine that compares all of a key gets cells by rows, the kernel bins by rows."""
    st = known or (fused_stats(r), fused_stats(s))
    b = joint(*st)
    cut = best_cut(*st, b)
    spec = clamp(within(stripes(cut, k_rule(st, b, cut, ratio), b), st), st)
    spec = refined(*st, spec) if engine == "catalyst" else spec.binned(bins_for_tasks(*st, spec))
    small = min(x.n for x in st)
    if engine != "catalyst":
        hint = None
    elif 0 < small <= BROADCAST_ROWS:
        hint = "broadcast" if st[1].n == small else "broadcast_left"
    else:
        hint = "shuffle_hash" if st[1].n <= HASH_ROWS else "merge"
    return JoinPlan(spec, "y" if cut == "x" else "x", "ref_cell", engine, hint, st)
