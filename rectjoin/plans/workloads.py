"""The experiment workloads on the given tables, and the experiments themselves."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..operators import baselines, measure
from ..operators.axis import choose_axis
from ..operators.grid import GridSpec, stripes
from ..operators.join import spatial_join
from ..operators.stats import Stats, fused_stats, joint
from ..operators.sweep import sweep_kernel
from ..operators.tune import k_rule
from ..sources.views import rect_view


@dataclass(frozen=True)
class Workload:
    r: str
    s: str
    r_where: str = ""
    s_where: str = ""

    def load(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
        return rect_view(spark, sf_dir, self.r, self.r_where), rect_view(spark, sf_dir, self.s, self.s_where)


WORKLOADS = {
    "w1": Workload("sale", "ship", "o_orderstatus = 'F'", "l_returnflag = 'N' AND l_linestatus = 'O'"),
    "w2": Workload("visit", "visit", "event_type = 'click'", "event_type <> 'click'"),
    "w3": Workload("sale", "sale", "o_orderstatus = 'F'", "o_orderstatus = 'O'"),
    "w4": Workload("ship", "ship", "l_returnflag = 'A' AND l_linestatus = 'F'", "NOT (l_returnflag = 'A' AND l_linestatus = 'F')"),
    "w5": Workload("ship", "sale"),
    "w6": Workload("ship", "ship", "l_returnflag = 'A'", "l_returnflag <> 'A'"),
    "w7": Workload("vendor", "account"),
    "w8": Workload("docbox", "docbox"),
    "w9": Workload("prod", "prod"),
    "w10": Workload("ordbox", "sale", "l_orderkey % 20 = 0"),
}


def specs(r: DataFrame, s: DataFrame, ratio: float = 10.0, known: tuple[Stats, Stats] | None = None) -> dict[str, GridSpec]:
    """Stripes on either axis and the grid, by the rule."""
    st = known or [fused_stats(df) for df in (r, s)]
    b = joint(*st)
    kx, ky = (k_rule(st, b, a, ratio) for a in "xy")
    return {"stripe_x": stripes("x", kx, b), "stripe_y": stripes("y", ky, b), "grid": GridSpec("grid", b, kx, ky), "none": GridSpec("none", b)}


def axis_effect(spark: SparkSession, sf_dir: str, names=("w1", "w2", "w3", "w4", "w5", "w6", "w7", "w9")) -> list[dict]:
    """One tile: exact candidates of both axes, the model's estimate, its choice, and whether it was right."""
    out = []
    for name in names:
        r, s = WORKLOADS[name].load(spark, sf_dir)
        out.append({"workload": name} | measure.axis_accuracy([(r, s, specs(r, s)["none"])], phi=1)["queries"][0])
    return out


def stripe_combinations(spark: SparkSession, sf_dir: str, name: str, ks=(1, 10, 30, 100, 300)) -> list[dict]:
    """Cut and sweep on x or y, for numbers of stripes: exact candidates, copies and seconds."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    b = specs(r, s)["none"].bounds
    out = []
    for cut in "xy":
        for sweep in "xy":
            for k in ks:
                spec = stripes(cut, k, b)
                out.append({"combination": cut + sweep, "k": k, "candidates": measure.candidates(r, s, spec, sweep).first()[0], "copies": [measure.replication(df, spec).first()[1] for df in (r, s)], "seconds": measure.timed(sweep_kernel(r, s, spec, sweep))})
    return out


def grid_axes(spark: SparkSession, sf_dir: str, name: str, ks=(1, 5, 20, 50)) -> list[dict]:
    """K by K tiles swept along x, y, or each along its own axis."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    b = specs(r, s)["none"].bounds
    out = []
    for k in ks:
        spec = GridSpec("grid", b, k, k)
        axes = choose_axis(r, s, spec, phi=1)
        for sweep in ("x", "y", "adaptive"):
            chosen = {"axes": axes} if sweep == "adaptive" else {"axis": sweep}
            from ..operators.sweep import sweep_counts

            n = sweep_counts(r, s, spec, **chosen).agg({"candidates": "sum"}).first()[0]
            out.append({"k": k, "sweep": sweep, "candidates": n or 0, "seconds": measure.timed(sweep_kernel(r, s, spec, **chosen))})
    return out


def best_of_both(spark: SparkSession, sf_dir: str, name: str) -> dict:
    """Stripes and grid by the rule against the better single-tile sweep."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    own = specs(r, s)
    base = min(measure.timed(baselines.global_sweep(r, s, a)) for a in "xy")
    one, two = measure.timed(sweep_kernel(r, s, own["stripe_x"], "y")), measure.timed(sweep_kernel(r, s, own["grid"], axes=choose_axis(r, s, own["grid"])))
    return {"single": base, "1d": one, "2d": two, "speedup_1d": measure.speedup(base, one), "speedup_2d": measure.speedup(base, two)}


def duplicate_handling(spark: SparkSession, sf_dir: str, name: str) -> list[dict]:
    """Reference test, class split and distinct, on stripes and on the grid."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    return [{"spec": kind, "dedup": d, "seconds": measure.timed(spatial_join(r, s, specs(r, s)[kind], dedup=d))} for kind in ("stripe_x", "grid") for d in ("ref_cell", "class_split", "distinct")]


def breakdowns(spark: SparkSession, sf_dir: str, name: str, factors=(0.3, 1.0, 3.0)) -> list[dict]:
    """Seconds to partition and to join, copies, for numbers of stripes and of grid cells around the rule's."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    own, out = specs(r, s), []
    for factor in factors:
        for kind in ("stripe_x", "grid"):
            k = {a: max(1, int(own[kind].k(a) * factor)) for a in "xy"}
            spec = GridSpec(kind, own["none"].bounds, k["x"], k["y"])
            out.append({"spec": kind, "k": (spec.kx, spec.ky), "copies": [measure.replication(df, spec).first()[1] for df in (r, s)]} | measure.breakdown(r, s, spec, engine="sweep"))
    return out


def threads(sf_dir: str, name: str, cores=(1, 2, 4), dedups=("ref_cell", "class_split")) -> list[dict]:
    """Seconds, speedup and efficiency of the stripe join by cores and duplicate handling. Each number of cores is a
    session of its own, so none may run."""
    out = []
    for dedup in dedups:
        times = {}
        for m in cores:
            spark = SparkSession.builder.master(f"local[{m}]").config("spark.sql.shuffle.partitions", str(2 * m)).config("spark.ui.enabled", "false").getOrCreate()
            r, s = WORKLOADS[name].load(spark, sf_dir)
            spec = specs(r, s)["stripe_x"].binned(16)
            measure.timed(spatial_join(r, s, spec, dedup=dedup))  # starts the JVM's compiler
            times[m] = measure.timed(spatial_join(r, s, spec, dedup=dedup))
            spark.stop()
        out += [{"dedup": dedup, "cores": m} | x for m, x in measure.scaleup(lambda t: t, times).items()]
    return out


def model_sensitivity(spark: SparkSession, sf_dir: str, name: str, phis=(1, 10, 100), ks=(10, 100, 1000, "auto")) -> list[dict]:
    """The model's estimates and choice for sampling rates and numbers of buckets."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    spec, out = specs(r, s)["none"], []
    for phi in phis:
        for k in ks:
            row = choose_axis(r, s, spec, k=k, phi=phi, least=0).first()
            out.append({"phi": phi, "k": k, "estimate": (row.ix, row.iy) if row else None, "axis": row.axis if row else None})
    return out


def ratio_ablation(spark: SparkSession, sf_dir: str, name: str, ratios=(1, 3, 10, 30, 100)) -> list[dict]:
    """Partition width over mean extent: copies, candidates and seconds."""
    r, s = WORKLOADS[name].load(spark, sf_dir)
    out = []
    for ratio in ratios:
        spec = specs(r, s, ratio)["stripe_x"]
        out.append({"ratio": ratio, "k": spec.kx, "copies": [measure.replication(df, spec).first()[1] for df in (r, s)], "candidates": measure.candidates(r, s, spec, "y").first()[0], "seconds": measure.timed(sweep_kernel(r, s, spec, "y"))})
    return out
