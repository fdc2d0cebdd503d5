"""The micro-fixture's hand values, random inputs against brute force, borders, plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rectjoin.functions.rect import Bounds, eps_square, normalize, validate_rects
from rectjoin.operators import axis, coincide, dedup, join, measure, parallel, tune
from rectjoin.operators.grid import GridSpec, assign, cells, stripes
from rectjoin.operators.stats import fused_stats
from rectjoin.operators.sweep import scan, sweep_kernel

SCHEMA = "rid string, xl double, yl double, xu double, yu double"
R = [("r1", 0.2, 0.2, 1.3, 0.5), ("r2", 1.5, 0.6, 1.8, 1.4), ("r3", 2.2, 0.3, 2.6, 0.7), ("r4", 0.3, 1.2, 0.6, 1.6), ("r5", 1.0, 2.0, 1.5, 2.3), ("r6", 0.7, 1.5, 2.4, 2.2), ("r7", 2.5, 2.5, 3.0, 3.0)]
S = [("s1", 0.8, 0.3, 1.4, 0.8), ("s2", 1.7, 0.9, 2.3, 1.2), ("s3", 0.1, 2.4, 0.4, 2.8), ("s4", 1.5, 2.3, 1.9, 2.7), ("s5", 1.6, 1.7, 2.1, 2.6), ("s6", 2.6, 0.7, 2.9, 2.5)]
PAIRS = {("r1", "s1"), ("r2", "s2"), ("r3", "s6"), ("r5", "s4"), ("r6", "s5"), ("r7", "s6")}
B3 = Bounds(0.0, 0.0, 3.0, 3.0)
GRID, COLS, NONE = GridSpec("grid", B3, 3, 3), stripes("x", 3, B3), GridSpec("none", B3)


@pytest.fixture(scope="module")
def small(spark):
    return spark.createDataFrame(R, SCHEMA), spark.createDataFrame(S, SCHEMA)


def bag(df):
    return sorted((r.r_id, r.s_id) for r in df.collect())


def brute(a, b):
    return sorted((x[0], y[0]) for x in a for y in b if x[1] <= y[3] and y[1] <= x[3] and x[2] <= y[4] and y[2] <= x[4])


def test_micro_counts(small):
    r, s = small
    assert measure.duplicates(r, s, GRID).first() == (11, 6) and measure.duplicates(r, s, COLS).first() == (8, 6)
    assert [measure.replication(x, g).first()[1] for g in (GRID, COLS) for x in (r, s)] == [14, 15, 10, 9]
    assert [measure.candidates(r, s, NONE, a).first()[0] for a in "xy"] == [15, 17]
    assert {(x.rid, x.tx) for x in assign(r, COLS).collect() if x.rid in ("r5", "r6")} == {("r5", 1), ("r6", 0), ("r6", 1), ("r6", 2)}
    mix = {x.rid: x.cls for x in dedup.classify(assign(r, COLS)).where("tx = 1").collect()}
    assert mix["r6"] == 1 and mix["r5"] == 0


@pytest.mark.parametrize("spec", [GRID, COLS, stripes("y", 3, B3), NONE, COLS.binned(4)])
@pytest.mark.parametrize("how", ["ref_cell", "ref_point", "distinct", "expand", "residual", "union", "sweep_x", "sweep_y", "sql"])
def test_micro_methods(small, spec, how):
    r, s = small
    if how in ("expand", "residual", "union"):
        out = dedup.class_split(r, s, spec, how)
    elif how.startswith("sweep"):
        out = sweep_kernel(r, s, spec, how[-1])
    elif how == "sql":
        out = join.spatial_join(r, s, spec, engine="sweep_sql", sweep="x")
    else:
        out = join.spatial_join(r, s, spec, dedup=how)
    assert bag(out) == sorted(PAIRS)


def rects(kind, n, seed):
    g = np.random.default_rng(seed)
    c, e = g.random((n, 2)), g.random((n, 2)) * 0.08
    if kind == "lattice":
        c, e = g.integers(0, 8, (n, 2)) / 8, g.integers(0, 3, (n, 2)) / 8
    if kind == "points":
        c, e = np.round(c, 1), e * 0
    if kind == "clustered":
        c = 0.5 + (c - 0.5) ** 5
    if kind == "outside":
        c = c * 3 - 1
    if kind == "negative":
        c = c - 5
    rows = [(f"{kind}{i}", *map(float, (*a, *(a + b)))) for i, (a, b) in enumerate(zip(c, e))]
    return rows + [(f"{kind}fat", float(c.min()), float(c.min()), float(c.max()) + 1, float(c.max()) + 1)] if kind == "fat" else rows


@pytest.mark.parametrize("kind", ["uniform", "lattice", "points", "clustered", "fat", "negative", "one", "empty", "outside"])
def test_random(spark, kind):
    """Every method gives the pairs of brute force, also where rectangles lie outside the grid's bounds."""
    a, b = (rects(kind, 0 if kind == "empty" else 1 if kind == "one" else 70, s) for s in (1, 2))
    r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
    st = [fused_stats(x) for x in (r, s)]
    bounds = join.joint(*st)
    bounds = Bounds(0.0, 0.0, 1.0, 1.0) if kind == "outside" else bounds
    want, grid = brute(a, b), GridSpec("grid", bounds, 8, 5)
    for how in ("ref_point", "distinct"):
        assert bag(join.spatial_join(r, s, grid, dedup=how)) == want
    assert bag(join.spatial_join(r, s)) == want
    assert bag(join.spatial_join(r, s, grid, hint="merge")) == want
    assert bag(dedup.class_split(r, s, grid)) == want
    assert bag(join.two_level_join(r, s, grid, 3, 4)) == want
    assert bag(join.salted_join(r, s, grid, 5)) == want
    assert bag(sweep_kernel(r, s, grid, axes=axis.choose_axis(r, s, grid))) == want
    assert sorted((y, x) for x, y in bag(join.spatial_join(s, r, grid))) == want


def test_scan_is_disjoint_and_complete():
    g = np.random.default_rng(0)
    rl, sl = np.sort(g.integers(0, 20, 60)).astype(float), np.sort(g.integers(0, 20, 50)).astype(float)
    ru, su = rl + g.integers(0, 4, 60), sl + g.integers(0, 4, 50)
    got = [(i, j) for a, b in scan(rl, ru, sl, su) for i, j in zip(a.tolist(), b.tolist())]
    assert len(got) == len(set(got)) and set(got) == {(i, j) for i in range(60) for j in range(50) if rl[i] <= su[j] and sl[j] <= ru[i]}


def test_same_axis_sweep_gains_nothing_and_other_does(spark):
    a, b = rects("uniform", 300, 3), rects("uniform", 300, 4)
    r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
    n = {(k, ax): measure.candidates(r, s, stripes("x", k, Bounds(0.0, 0.0, 1.1, 1.1)), ax).first()[0] for k in (1, 20) for ax in "xy"}
    assert n[20, "x"] >= n[1, "x"] and n[20, "y"] < n[1, "y"] / 4


def test_bad_rows_and_rules(spark):
    rows = [("a", 0.0, 0.0, 1.0, 1.0), ("b", None, 0.0, 1.0, 1.0), ("c", float("nan"), 0.0, 1.0, 1.0), ("d", 2.0, 0.0, 1.0, 1.0), (None, 0.0, 0.0, 1.0, 1.0)]
    df = spark.createDataFrame(rows, SCHEMA)
    assert validate_rects(df).count() == 1 and validate_rects(df, "swap").count() == 2
    with pytest.raises(Exception, match="bad rectangle"):
        validate_rects(df, "error").collect()
    assert GridSpec("grid", Bounds(1.0, 0.0, 1.0, 2.0), 9, 9).kx == 1
    st = fused_stats(df.where("rid = 'a'"))
    assert tune.k_rule([st], Bounds(0.0, 0.0, 100.0, 100.0), "x") == 10
    with pytest.raises(ValueError):
        tune.clamp(GridSpec("grid", Bounds(0.0, 0.0, 100.0, 100.0), 1000, 1000), [st])
    assert axis.bucket_count(10, 2) == 5 and axis.bucket_count(1e9, 1) == 1000 and axis.bucket_count(1, 2) == 1
    assert normalize(df.where("rid = 'a'"), Bounds(0.0, 0.0, 2.0, 4.0)).first()[1:] == (0.0, 0.0, 0.5, 0.25)
    assert eps_square(df.where("rid = 'a'"), 1.0).first().xl == -0.5


def test_offsets_tile_the_space(small):
    counts = parallel.write_offsets(parallel.part_counts(small[0], GRID, F.lit(0))).collect()
    assert all(c.start == 0 for c in counts) and sum(c.n for c in counts) == 14
    packed = parallel.pack_tiles(parallel.tile_counts(*small, GRID), 3).collect()
    assert {p.task for p in packed} <= {0, 1, 2} and len(packed) == 9


def test_plan_is_an_equi_join(small):
    r, s = small
    plan = join.spatial_join(r, s, COLS, hint="merge")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Cartesian" not in plan and "NestedLoop" not in plan and plan.count("Exchange hashpartitioning") == 2
    assert cells(r, GRID).count() == 7


def test_choice_agrees_with_exact_counts(spark):
    from rectjoin.plans.workloads import WORKLOADS, specs

    queries = []
    for name in ("w1", "w3", "w7", "w9"):
        r, s = WORKLOADS[name].load(spark, "/root/testdata/sf0.01")
        queries.append((r, s, specs(r, s)["none"]))
    assert measure.axis_accuracy(queries, phi=1)["accuracy"] == 1.0


def test_fat_joins_take_every_order(spark, tmp_path):
    import datetime

    from rectjoin.plans.queries import QUERIES

    g, day = np.random.default_rng(3), datetime.date(1995, 1, 1)
    items = [(k, day + datetime.timedelta(int(d)), float(p)) for k in range(1, 41) for d, p in zip(g.integers(0, 30, 3), g.integers(0, 1000, 3))]
    orders = [(k, day + datetime.timedelta(int(g.integers(0, 30))), 5.0 * float(g.integers(0, 1000)), k) for k in range(1, 81)]
    spark.createDataFrame(items, "l_orderkey long, l_shipdate date, l_extendedprice double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_orderdate date, o_totalprice double, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    at = lambda d: float((d - datetime.date(1970, 1, 1)).days)
    s = [(k, at(d), 0.2 * v, at(d) + 1 + c % 3, 0.21 * v) for k, d, v, c in orders]
    own = {k: [(at(d), p) for n, d, p in items if n == k] for k in range(1, 41)}
    r = [(k, min(x for x, _ in v), min(y for _, y in v), max(x for x, _ in v), max(y for _, y in v)) for k, v in own.items()]
    pairs = brute(r, s)
    counts = {x.r_l_orderkey: x.partners for x in QUERIES["fat_count_all"](spark, str(tmp_path)).collect()}
    assert counts == {k: n for k in own if (n := sum(a == k for a, _ in pairs))} and len(counts) > 2
    met = sorted((k, b[0]) for k, v in own.items() for b in s if any(b[1] <= x <= b[3] and b[2] <= y <= b[4] for x, y in v))
    assert met and sorted(tuple(x) for x in QUERIES["refine_ordpath_all"](spark, str(tmp_path)).collect()) == met


def test_partners_are_counted_without_pairs(spark, monkeypatch):
    """Fat and odd rectangles against brute force, in few and in many stripes, and no join in the plan."""
    from collections import Counter

    from rectjoin.operators import count, rel

    monkeypatch.setattr(count, "STRIPE_ROWS", 9)
    monkeypatch.setattr(count, "CHUNK", 16)
    for kind in ("uniform", "lattice", "points", "fat", "negative", "one", "empty"):
        a, b = (rects(kind, 0 if kind == "empty" else 1 if kind == "one" else 70, s) for s in (1, 2))
        a = [(i, x, y, x + 9 * (u - x), y + 9 * (v - y)) for i, x, y, u, v in a]
        r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
        out = rel.partner_counts(r, s)
        assert {x.r_id: x.partners for x in out.collect()} == Counter(i for i, _ in brute(a, b))
        assert "Join" not in out._jdf.queryExecution().executedPlan().toString()
    a += [("inverted", 0.6, 0.1, 0.4, 0.9), ("null", None, 0.0, 1.0, 1.0), ("all", -9.0, -9.0, 9.0, 9.0)]
    b = [*S, ("inverted", 0.5, 0.5, 0.5, 0.2), ("null", 0.0, 0.0, 1.0, None)]
    known = [[x for x in side if None not in x] for side in (a, b)]
    r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
    assert {x.r_id: x.partners for x in rel.partner_counts(r, s).collect()} == Counter(i for i, _ in brute(*known))


def test_pass_ratio_makes_no_pairs(spark, monkeypatch):
    from rectjoin.operators import sweep

    a, b = rects("uniform", 300, 5), rects("uniform", 200, 6)
    r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
    spec = GridSpec("none", Bounds(0.0, 0.0, 1.1, 1.1))
    out = measure.pass_ratio(r, s, spec, "x")
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == plan.count("Join Cross") == 1  # of the two rows
    assert out.first() == (sum(x[1] <= y[3] and y[1] <= x[3] for x in a for y in b), len(brute(a, b)))
    rows = [np.array(sorted((x[1], x[3]) for x in side)) for side in (a, b)]
    sides = tuple(sweep.Side(np.arange(len(x)), {"xl": x[:, 0], "xu": x[:, 1]}) for x in rows)
    none = tuple(sweep.Side(np.arange(0), {"xl": x[:0, 0], "xu": x[:0, 1]}) for x in rows)
    monkeypatch.setattr(sweep, "_ranges", None)  # pairs would be made by it
    assert sweep._number(none, sides, "x") == out.first()[0]


def test_paths_take_a_pair_at_their_first_vertex(spark):
    """Many vertices of a path in a box, on its border and with nulls, against brute force; no bounding rectangle is joined."""
    from rectjoin.operators import refine

    g = np.random.default_rng(8)
    v = [(f"p{k % 12}", float(x), float(y)) for k, (x, y) in enumerate(g.integers(0, 12, (90, 2)))] + [("p0", None, 1.0), ("p99", 3.0, None)]
    boxes = [(f"b{k}", float(x), float(y), float(x + e), float(y + f)) for k, (x, y, e, f) in enumerate(zip(*g.integers(0, 12, (2, 60)), *g.integers(0, 4, (2, 60))))]
    out = refine.paths_in_boxes(spark.createDataFrame(v, "rid string, x double, y double"), spark.createDataFrame(boxes, SCHEMA))
    want = {(i, b[0]) for i, x, y in v if None not in (x, y) for b in boxes if b[1] <= x <= b[3] and b[2] <= y <= b[4]}
    assert bag(out) == sorted(want)
    assert "Deduplicate" not in (plan := out._jdf.queryExecution().optimizedPlan().toString()) and plan.count("Join") == 1


def test_broadcasts_take_blocks_of_the_smaller_side(spark):
    from rectjoin.operators import baselines

    a, b = rects("uniform", 90, 1), rects("uniform", 60, 2)
    r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
    for how in (baselines.broadcast_join, baselines.nested_loop):
        assert bag(how(r, s, most_rows=25)) == bag(how(r, s)) == brute(a, b)  # both sides have more rows than a block
        assert sorted((y, x) for x, y in bag(how(s, r, most_rows=25))) == brute(a, b)
        assert bag(how(r.where("false"), s)) == []


def test_nested_loop_compares_in_masks(spark):
    """Pairs are compared by arrays, not row by row; ids of any type, nulls and odd ends come out as in the plain join."""
    from rectjoin.functions.rect import intersects, prefixed
    from rectjoin.operators import baselines

    nan, inf = float("nan"), float("inf")
    odd = [("n", None, 0.0, 1.0, 1.0), ("nan", 0.0, 0.0, nan, 1.0), ("turned", 0.9, 0.9, 0.1, 0.1), ("all", -inf, -inf, inf, inf)]
    r, s = (spark.createDataFrame(rects("lattice", n, n) + odd, SCHEMA).selectExpr("struct(rid, 1 AS k) AS rid", "xl", "yl", "xu", "yu") for n in (37, 60))
    out = baselines.nested_loop(r, s)
    assert "MapInArrow" in out._jdf.queryExecution().toString() and "NestedLoop" not in out._jdf.queryExecution().toString()
    want = prefixed(r, "r_").join(prefixed(s, "s_"), intersects()).select("r_id", "s_id")
    assert bag(out) == bag(want)


def test_sweep_along_the_cut_axis_gets_bins(spark):
    """Where a stripe's rows are many, a sweep along the cut axis meets a stripe's rows by bins of the other axis."""
    from rectjoin.operators.stats import Stats

    unit = Bounds(0.0, 0.0, 1.0, 1.0)
    big = Stats(3_000_000, unit, (0.001, 0.02), (0.001, 0.02))
    fine = tune.binned_sweep(big, big, stripes("y", 5, unit), "y")
    assert fine.ky == 5 and fine.kx >= 256 and max(tune.expected_replication(x, fine) for x in (big, big)) <= 2
    assert tune.binned_sweep(big, big, stripes("y", 5, unit), "x") == stripes("y", 5, unit)
    few = Stats(5, unit, (0.001, 0.02), (0.001, 0.02))
    assert tune.binned_sweep(few, few, stripes("y", 5, unit), "y") == stripes("y", 5, unit)
    for kind in ("lattice", "points", "fat", "outside"):
        a, b = (rects(kind, 70, s) for s in (1, 2))
        r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
        assert bag(sweep_kernel(r, s, stripes("y", 3, unit).binned(7), "y")) == brute(a, b)


def test_distinct_shuffles_no_found_pairs(spark):
    """Pairs found in several cells are sorted out where they are found; rectangles over very many cells are, too, by a shuffle."""
    import re

    unit = Bounds(0.0, 0.0, 1.0, 1.0)
    for kind in ("uniform", "lattice", "fat", "outside", "points"):
        a, b = (rects(kind, 70, s) for s in (5, 6))
        r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
        for spec in (GridSpec("grid", unit, 9, 7), GridSpec("grid", unit, 40, 3), stripes("x", 6, unit), stripes("y", 6, unit)):
            out = join.spatial_join(r, s, spec, dedup="distinct")
            assert bag(out) == brute(a, b)
            if spec.kx == 9:
                assert bag(dedup.distinct(r, s, spec, GridSpec("grid", unit, 18, 28))) == brute(a, b)
            plan = out._jdf.queryExecution().executedPlan().toString()
            if kind == "uniform" and spec.kx < 40:
                assert bool(re.search(r"Exchange hashpartitioning\([^)]*\br_id#", plan)) is False and plan.count("Aggregate") > 0


def test_keys_get_smaller_as_rows_grow(spark):
    """At many rows the equi-join isn't keyed by whole stripes or cells; bins report each pair once."""
    from rectjoin.operators.stats import Stats

    big = Stats(10_000_000, Bounds(0.0, 0.0, 1.0, 1.0), (0.001, 0.005), (0.001, 0.005))
    unit = Bounds(0.0, 0.0, 1.0, 1.0)
    for spec in (stripes("x", 100, unit), stripes("y", 20, unit), GridSpec("grid", unit, 100, 20)):
        fine = tune.by_rows(big, big, spec)
        assert tune.comparisons(big, big, fine) < tune.comparisons(big, big, spec) / 5
        assert all(fine.k(a) % spec.k(a) == 0 for a in "xy") and tune.by_rows(big, Stats(0, unit, (0.0, 0.0), (0.0, 0.0)), spec) == spec
    for kind in ("lattice", "points", "fat", "outside"):
        a, b = (rects(kind, 70, s) for s in (1, 2))
        r, s = spark.createDataFrame(a, SCHEMA), spark.createDataFrame(b, SCHEMA)
        for spec in (stripes("x", 4, unit), stripes("y", 3, unit), GridSpec("none", unit)):
            assert bag(dedup.class_split(r, s, spec, bins=5)) == brute(a, b)
            for how in ("ref_cell", "ref_point", "none"):
                if how != "none" or spec.kind == "none":
                    assert bag(join.spatial_join(r, s, spec.binned(3), dedup=how)) == brute(a, b)


def test_salting_copies_only_for_tiles_that_are_hot_beside_the_others(spark):
    """Even tiles of any cost get one part; a tile with most of the work is dealt over parts, by its share of a task's work."""
    spec = GridSpec("grid", Bounds(0.0, 0.0, 1.0, 1.0), 8, 8)
    even = [(f"e{x}{y}{k}", x / 8 + 0.01, y / 8 + 0.01, x / 8 + 0.02, y / 8 + 0.02) for x in range(8) for y in range(8) for k in range(4)]
    hot = [(f"h{k}", 0.01, 0.01, 0.02, 0.02) for k in range(60)]
    for rows, most in ((even, 1), (even + hot, 16)):
        df = spark.createDataFrame(rows, SCHEMA)
        parts = {x.tile: x.parts for x in join.salt_parts(df, df, spec, 5).collect()}
        assert len(parts) == (most > 1) and all(1 < n <= most for n in parts.values())
        assert bag(join.salted_join(df, df, spec, 5)) == brute(rows, rows)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def copies_of(n, times, seed, p):
    """Random rectangles of the unit square, each under several ids, and a few with one."""
    rng = np.random.default_rng(seed)
    lows, ext = rng.random((n, 2)), rng.random((n, 2)) * 0.2
    rows = [(f"{p}{i}-{k}", *map(float, (*lows[i], *(lows[i] + ext[i])))) for i in range(n) for k in range(1 if i % 9 == 0 else times)]
    return [(None, *rows[1][1:]), *rows] if p == "r" else rows


def text_bag(df):
    return sorted((str(x.r_id), str(x.s_id)) for x in df.collect())


def test_coinciding_rectangles_are_joined_once(spark, monkeypatch):
    """Lists of ids, several of a kind, one side only, and an id that is null, against brute force; the join holds no single id."""
    from rectjoin.operators import coincide

    monkeypatch.setattr(coincide, "MOST", 4)
    a, b, c = copies_of(30, 11, 1, "r"), copies_of(25, 7, 2, "s"), copies_of(60, 1, 3, "t")
    r, s, t = (spark.createDataFrame(x, SCHEMA) for x in (a, b, c))
    parts = coincide.lists(r, len(a), 4)
    assert sorted(str(x.rid) for row in parts.collect() for x in row.rid) == sorted(str(x[0]) for x in a) and parts.count() < len(a) / 2
    assert coincide.lists(t, len(c)) is None and coincide.listed(r, s, dense=1e9)[1] == [False, False]
    for x, y, rows in ((r, s, (a, b)), (r, t, (a, c)), (t, s, (c, b))):
        want = brute(*([(str(i), *at) for i, *at in side] for side in rows))
        assert text_bag(join.spatial_join(x, y, dense=0.0)) == text_bag(join.spatial_join(x, y, dense=float("inf"))) == want
    assert "Generate explode" in join.spatial_join(r, s, dense=0.0)._jdf.queryExecution().executedPlan().toString()


def test_sweep_hands_lists_over_in_small_batches(spark, monkeypatch):
    """The kernel with ids that are lists: right pairs, in batches of few rows, as a pair of lists may be large."""
    import pyarrow as pa

    from rectjoin.operators import sweep

    a, b = copies_of(40, 6, 4, "r")[1:], copies_of(40, 6, 5, "s")
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    assert bag(join.spatial_join(r, s, stripes("x", 3, Bounds(0.0, 0.0, 1.0, 1.0)), engine="sweep", dense=0.0)) == brute(a, b)
    monkeypatch.setattr(sweep, "LISTS", 8, raising=False)
    n, zeros = 30, np.zeros(30, np.int32)
    ids = pa.array([[str(i)] for i in range(n)])
    same = {"xl": np.zeros(n), "yl": np.zeros(n), "xu": np.ones(n), "yu": np.ones(n), **{c: zeros for c in ("cx", "cy", "tx", "ty", "tile")}}
    rows = pa.RecordBatch.from_pydict({**{c: pa.array(v) for c, v in same.items()}, "side": pa.array((np.arange(n) % 2).astype(np.int8)), "along": pa.array(np.zeros(n, np.int8)), "r_id": ids, "s_id": ids})
    sizes = [x.num_rows for x in sweep.kernel("x")(iter([rows]))]
    assert sum(sizes) == 15 * 15 and max(sizes) <= 8


def test_methods_are_compared_by_lists(spark, monkeypatch):
    """Counts of pairs that one join has and the other hasn't, from lists and from ids; also where the joins do differ."""
    a, b = copies_of(30, 6, 11, "r")[1:], copies_of(30, 5, 12, "s")
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    unit = Bounds(0.0, 0.0, 1.0, 1.0)
    for dense in (0.0, float("inf")):
        assert join.same_pairs(r, s, stripes("x", 4, unit), GridSpec("grid", unit, 3, 5), dense=dense).first() == (0, 0, len(brute(a, b)))
    whole = join.spatial_join
    monkeypatch.setattr(join, "spatial_join", lambda r, s, spec, **more: whole(r.where("xl < 0.5") if spec.kind == "grid" else r, s, spec, **more))
    both = len(brute([x for x in a if x[1] < 0.5], b))
    for dense in (0.0, float("inf")):
        assert join.same_pairs(r, s, stripes("x", 4, unit), GridSpec("grid", unit, 3, 5), dense=dense).first() == (len(brute(a, b)) - both, 0, both)


def test_reference_point_works_on_lists(spark):
    """Stripes with bins and the test by coordinates, over lists."""
    a, b = copies_of(40, 6, 13, "r")[1:], copies_of(40, 7, 14, "s")
    out = join.spatial_join(*(spark.createDataFrame(x, SCHEMA) for x in (a, b)), stripes("x", 4, Bounds(0.0, 0.0, 1.0, 1.0)), dedup="ref_point", dense=0.0)
    assert bag(out) == brute(a, b) and "Generate explode(r_id" in out._jdf.queryExecution().executedPlan().toString()


def test_intervals_that_coincide_are_joined_once(spark):
    """Equal on one axis, apart or null on the other one, against brute force."""
    a, b = ([(f"{p}{i}", *(x[1], None if i % 5 == 0 else float(i), x[3], float(i + 1))) for i, x in enumerate(copies_of(30, 8, seed, p)[1:])] for seed, p in ((6, "r"), (7, "s")))
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    want = sorted((x[0], y[0]) for x in a for y in b if x[1] <= y[3] and y[1] <= x[3])
    out = join.interval_join(r, s, "x", dense=0.0)
    assert bag(out) == bag(join.interval_join(r, s, "x", dense=float("inf"))) == want
    assert "Generate explode(r_id" in out._jdf.queryExecution().executedPlan().toString()


def test_multiway_takes_lists_apart_as_triples(spark):
    """Triples of many copies against brute force; what is shuffled for the second join is lists."""
    rows = [copies_of(25, 5, 8, "r")[1:], copies_of(20, 4, 9, "s"), copies_of(20, 3, 10, "t")]
    r, s, t = (spark.createDataFrame(x, SCHEMA) for x in rows)
    second = {}
    for i, j in brute(rows[1], rows[2]):
        second.setdefault(i, []).append(j)
    want = sorted((i, j, k) for i, j in brute(rows[0], rows[1]) for k in second.get(j, []))
    out = join.multiway(r, s, t, dense=0.0)
    triples = lambda df: sorted((x.r_id, x.s_id, x.t_id) for x in df.collect())
    assert triples(out) == triples(join.multiway(r, s, t, dense=float("inf"))) == want
    assert out._jdf.queryExecution().executedPlan().toString().count("Generate explode") >= 3


@pytest.mark.parametrize("hint", ["merge", "shuffle_hash"])
def test_hints_hold_for_lists(spark, hint):
    """A hint reaches the join of lists."""
    a, b = copies_of(40, 6, 15, "r")[1:], copies_of(40, 7, 16, "s")
    spec = stripes("x", 4, Bounds(0.0, 0.0, 1.0, 1.0)).binned(3)
    out = join.spatial_join(*(spark.createDataFrame(x, SCHEMA) for x in (a, b)), spec, hint=hint, dense=0.0)
    assert bag(out) == brute(a, b)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Generate explode(r_id" in plan and {"merge": "SortMergeJoin", "shuffle_hash": "ShuffledHashJoin"}[hint] in plan


@pytest.mark.parametrize("axis", ["y", "x"])
def test_stripes_with_bins_join_lists(spark, axis):
    a, b = copies_of(40, 6, 17, "r")[1:], copies_of(40, 7, 18, "s")
    out = join.spatial_join(*(spark.createDataFrame(x, SCHEMA) for x in (a, b)), stripes(axis, 4, Bounds(0.0, 0.0, 1.0, 1.0)).binned(5), dense=0.0)
    assert bag(out) == brute(a, b) and "Generate explode(r_id" in out._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["eq1_dedup_1d_w4", "hash_hint_w6", "merge_hint_w5", "stripe_bins_join_w5", "stripe_y_join_w5"])
def test_statistics_are_taken_once(spark, monkeypatch, name):
    """Each input is read once for the spec and the join by it."""
    from rectjoin.operators import stats
    from rectjoin.plans import queries, workloads

    taken, whole = [], stats.fused_stats
    for module in (coincide, join, stats, workloads):
        monkeypatch.setattr(module, "fused_stats", lambda df: taken.append(df) or whole(df))
    monkeypatch.setattr(coincide, "DENSE", float("inf"))
    queries.QUERIES[name](spark, "/root/testdata/sf0.001")
    assert len(taken) == 2


def dealt_by_homes(monkeypatch, about=16):
    from rectjoin.operators import homes

    monkeypatch.setattr(homes, "ROWS", 1)
    monkeypatch.setattr(homes, "ABOUT", about)


@pytest.mark.parametrize("dedup, hint", [("ref_cell", None), ("ref_cell", "merge"), ("ref_point", "shuffle_hash")])
def test_rectangles_are_shuffled_by_homes(spark, monkeypatch, dedup, hint):
    """Cells are cut in the tasks: the pairs of brute force, with two shuffles of fewer rows than there are copies."""
    from rectjoin.operators import homes, stats
    from rectjoin.operators.grid import assign

    dealt_by_homes(monkeypatch)
    a, b = copies_of(60, 2, 21, "r"), copies_of(70, 1, 22, "s") + [("s-none", None, None, None, None), ("s-far", 3.0, 0.2, 4.0, 0.3)]
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    want = brute(*([(str(i), *at) for i, *at in side if at[0] is not None] for side in (a, b)))
    for spec in (GridSpec("grid", Bounds(0.0, 0.0, 1.0, 1.0), 13, 9), stripes("y", 11, Bounds(0.1, 0.1, 0.9, 0.9))):
        out = join.spatial_join(r, s, spec, dedup=dedup, hint=hint, dense=float("inf"))
        assert text_bag(out) == want
        assert out._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0].count("Exchange shufflepartitionidpassthrough") == 2
        fine = tune.by_rows(stats.fused_stats(r), stats.fused_stats(s), spec)
        h = homes.homes(r, s, (stats.fused_stats(r), stats.fused_stats(s)), fine)
        assert homes.sent(s, h).count() < assign(s, fine).count() == homes.side(s, "s_", h).count()
    monkeypatch.setattr(homes, "HOT", 3)
    assert homes.homes(r, s, (stats.fused_stats(r), stats.fused_stats(s)), fine) is None


def test_kinds_of_rectangles_are_not_shuffled_in_vain(spark, monkeypatch):
    """Where hardly any rectangles are equal, that is found out without a shuffle of all of them."""
    t = spark.createDataFrame(copies_of(60, 1, 3, "t"), SCHEMA)
    whole = type(t).groupBy
    monkeypatch.setattr(type(t), "groupBy", lambda df, *by: pytest.fail("shuffled") if by else whole(df))
    assert coincide.lists(t, 60) is None


def test_methods_are_compared_without_shuffling_pairs(spark, monkeypatch):
    """Counts of pairs as by the set operations, also where the joins differ, are repeated or ids are null; the pairs stay in their tasks."""
    dealt_by_homes(monkeypatch)
    a, b = copies_of(60, 1, 24, "r"), copies_of(50, 2, 25, "s")
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    unit, n = Bounds(0.0, 0.0, 1.0, 1.0), lambda side: len(brute(*([(str(i), *at) for i, *at in x] for x in (side, b))))
    specs, inf = (stripes("x", 4, unit), GridSpec("grid", unit, 3, 5)), float("inf")
    out = join.same_pairs(r, s, *specs, dense=inf)
    assert out.first() == (0, 0, n(a))
    plan = out._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert "Exchange hashpartitioning" not in plan and "Exchange shufflepartitionidpassthrough" in plan
    whole = join.spatial_join
    monkeypatch.setattr(join, "spatial_join", lambda r, s, spec, **more: whole(r.where("xl < 0.5") if spec.kind == "grid" else r, s, spec, **more))
    both = n([x for x in a if x[1] < 0.5])
    assert join.same_pairs(r, s, *specs, dense=inf).first() == (n(a) - both, 0, both)
    monkeypatch.setattr(join, "spatial_join", lambda r, s, spec, **more: (one := whole(r, s, spec, **more)).unionAll(one) if spec.kind == "grid" else whole(r, s, spec, **more))
    assert join.same_pairs(r, s, *specs, dense=inf).first() == (0, n(a), n(a))


def test_paths_are_put_together_once(spark, monkeypatch):
    """Nothing is counted from the paths, which take a shuffle: statistics are those of the vertices."""
    from rectjoin.operators import refine, stats
    from rectjoin.plans import planner

    dealt_by_homes(monkeypatch)
    taken, whole = [], stats.fused_stats
    for module in (join, stats, planner):
        monkeypatch.setattr(module, "fused_stats", lambda df: taken.append(df) or whole(df))
    vertices = [(i % 20, *map(float, at)) for i, at in enumerate(np.random.default_rng(31).random((80, 2)))]
    boxes = copies_of(30, 1, 32, "s")
    monkeypatch.setattr(planner, "BROADCAST_ROWS", 0)
    out = refine.paths_in_boxes(spark.createDataFrame(vertices, "rid long, x double, y double"), spark.createDataFrame(boxes, SCHEMA))
    assert len(taken) == 2
    assert sorted((x.r_id, x.s_id) for x in out.collect()) == sorted({(i, b[0]) for i, x, y in vertices for b in boxes if b[1] <= x <= b[3] and b[2] <= y <= b[4]})


def test_sweep_shuffles_no_cells(spark):
    """What the kernel gets from coordinates and the tile is made after the shuffle."""
    a, b = copies_of(40, 1, 33, "r")[1:], copies_of(40, 1, 34, "s")
    r, s = (spark.createDataFrame(x, SCHEMA) for x in (a, b))
    from rectjoin.operators.sweep import sweep_kernel

    for spec in (stripes("x", 5, Bounds(0.0, 0.0, 1.0, 1.0)), GridSpec("grid", Bounds(0.1, 0.1, 0.9, 0.9), 4, 3)):
        out = sweep_kernel(r, s, spec, "y")
        plan = out._jdf.queryExecution().optimizedPlan().toString()
        dealt = plan[plan.index("RepartitionByExpression") :]
        assert "tile#" in dealt and " AS tx#" not in dealt.replace("explode", "") and " AS along#" not in dealt
        assert bag(out) == brute(a, b)
