"""Trees, costs and the dynamic program on hand cases and invariants."""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from kinetic.plans import domain, expansion, optimise, quad
from kinetic.plans.params import OptimizerParams, capacity_of


def mo(spark, rows):
    return spark.createDataFrame(rows, "oid long, x double, y double, vx double, vy double, speed double, t_ref double")


def grid(n: int, speed, start: int = 0):
    """n objects spread evenly over the domain."""
    side = math.ceil(math.sqrt(n))
    out = []
    for i in range(n):
        v = speed(i)
        out.append((start + i, (i % side + 0.5) * 10000 / side, (i // side + 0.5) * 10000 / side, v, 0.0, v, 0.0))
    return out


def test_capacity():
    assert [capacity_of(b) for b in (1024, 2048, 4096, 8192, 16384)] == [25, 51, 102, 204, 409]


def test_chi_square_by_hand(spark):
    counts = {0: [5, 5, 5, 5], 1: [8, 0, 0, 0], 2: [2, 0, 0, 0], 3: [3, 0, 0, 0]}
    cells = [(layer + 1, 1, k, n) for layer, c in counts.items() for k, n in enumerate(c) if n]
    df = spark.createDataFrame(cells, "layer int, level int, code long, n long")
    got = {r["layer"]: (r["stat"], r["uniform"]) for r in quad.uniformity(df, OptimizerParams()).collect()}
    assert got == {1: (0.0, 1), 2: (24.0, 0), 3: (6.0, 1), 4: (9.0, 0)}


def test_three_layer_tiling(spark):
    """Layer 1 is uniform, layer 2 splits the root, layer 3 the root and its last quarter."""
    splits = spark.createDataFrame([(2, 0, 0), (3, 0, 0), (3, 1, 3)], "layer int, level int, code long")
    layers = spark.createDataFrame([(1,), (2,), (3,)], "layer int")
    got = {}
    for r in quad.merged_tiling(splits, layers).collect():
        got.setdefault((r["s"], r["r"]), set()).add((r["level"], r["code"]))
    assert {k: len(v) for k, v in got.items()} == {(0, 1): 1, (0, 2): 4, (1, 2): 4, (2, 3): 7, (1, 3): 7, (0, 3): 7}
    trees = {2: {(0, 0)}, 3: {(0, 0), (1, 3)}}
    for (s, r), cells in got.items():
        assert cells == quad.merge_reference(trees, s, r)
        assert sum(4.0**-level for level, _ in cells) == 1


def test_tiling_equals_reference(spark, sf):
    from kinetic.sources.standins import mo_orders

    x = optimise.optimise(mo_orders(spark, sf), OptimizerParams(q=6))
    trees: dict[int, set] = {}
    for r in x.splits.collect():
        trees.setdefault(r["layer"], set()).add((r["level"], r["code"]))
    got: dict[tuple, set] = {}
    for r in quad.merged_tiling(x.splits, x.layers).collect():
        got.setdefault((r["s"], r["r"]), set()).add((r["level"], r["code"]))
    assert got == {(s, r): quad.merge_reference(trees, s, r) for s, r in got}
    leaves = quad.tree_leaves(x.splits, x.layers).groupBy("layer").agg(F.sum(F.pow(F.lit(0.25), F.col("level"))).alias("a")).collect()
    assert all(abs(r["a"] - 1) < 1e-12 for r in leaves)


def test_probabilities_are_binomial(spark):
    n, c = [4, 0, 7, 5], 3
    df = spark.createDataFrame([(0, i + 1, k) for i, k in enumerate(n) if k], "g int, layer int, n long")
    got = {r["layer"]: r["prob"] for r in expansion.node_max_prob(df, c, ["g"]).collect()}
    h = np.cumsum(n)
    want = {i + 1: (math.comb(h[i], c) - math.comb(h[i] - k, c)) / math.comb(h[-1], c) for i, k in enumerate(n) if k}
    assert all(abs(got[k] - v) < 1e-12 for k, v in want.items())
    assert abs(sum(got.values()) - 1) < 1e-12


def test_costs_of_a_range_by_enumeration():
    """The kernel against every subset of one cell's objects."""
    speeds, n, c, t = np.array([1.0, 5.0, 9.0]), [3, 2, 2], 3, 120.0
    p = OptimizerParams(q=3, capacity=c, node_rounding="exact")
    out = expansion.cell_costs(np.array([0]), np.array([[0, 0, 0, 0]]), np.array([[0, 1, 2, 3]]), np.array([[0, 3, 5, 7]]), speeds, p)
    for s, r in combinations(range(4), 2):
        members = [speeds[i] for i in range(s, r) for _ in range(n[i])]
        take = min(c, len(members))
        d = 10000 * math.sqrt(take / len(members))
        tops = [max(x) for x in combinations(members, take)]
        one = np.mean([d * d * t + 2 * d * v * t**2 + 4 / 3 * v * v * t**3 for v in tops]) * len(members) / c
        four = np.mean([4 * d * d * t + 2 * d * v * t**2 + v * v * t**3 / 3 for v in tops]) * len(members) / c
        assert out["one"][s, r] == pytest.approx(one, rel=1e-9)
        assert out["quad"][s, r] == pytest.approx(four, rel=1e-9)


def test_long_sums_equal_the_table(monkeypatch):
    b, u = np.array([150, 2000, 101, 4000]), np.array([300, 2500, 500, 4001])
    table = expansion.falling_ratio(b, u, 102)
    monkeypatch.setattr(expansion, "TABLE_COUNT", 0)
    assert np.allclose(table, expansion.falling_ratio(b, u, 102), rtol=1e-9)


def test_cells_cost_the_same_whatever_else_is_there():
    p, speeds = OptimizerParams(capacity=102), np.array([1.0, 3.0, 9.0])
    cum = np.array([[0, 1, 1, 2], [0, 0, 46, 90], [0, 400, 900, 4000], [0, 0, 0, 0], [0, 90_000, 140_000, 300_000]])
    level, own, par = np.zeros(5), np.zeros((5, 4), int), np.tile(np.arange(4), (5, 1))
    whole = expansion.cell_costs(level, own, par, cum, speeds, p)
    alone = [expansion.cell_costs(level[i : i + 1], own[i : i + 1], par[i : i + 1], cum[i : i + 1], speeds, p) for i in range(5)]
    for k, v in whole.items():
        assert np.allclose(v, sum(x[k] for x in alone), rtol=1e-13)


@pytest.mark.parametrize("tasks", [1, 8, 211])
def test_plan_does_not_depend_on_the_tasks(spark, tasks):
    from kinetic.sources.standins import mo_orders

    before = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    spark.conf.set("spark.sql.shuffle.partitions", str(tasks))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        plan = optimise.optimise(mo_orders(spark, "/root/testdata/sf0.01"), OptimizerParams(q=10)).plan.orderBy("part").collect()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert [r["hi_layer"] for r in plan] == [4, 10]


def test_node_costs_cross_where_they_should(spark):
    d, t = 100.0, 120.0
    v = math.sqrt(3) * d / t
    row = spark.range(1).select(expansion.node_cost(F.lit(d), F.lit(v), t).alias("a"), expansion.node_cost_quadrant(F.lit(d), F.lit(v), t).alias("b"), expansion.node_cost(F.lit(d), F.lit(0.0), t).alias("z")).first()
    assert row["a"] == pytest.approx(row["b"], rel=1e-12) and row["z"] == d * d * t


def costs(spark, values):
    return spark.createDataFrame([(s, r, 1, 1, v, v, v, 0) for (s, r), v in values.items()], "s int, r int, n long, regions long, v_one double, v_quad double, v double, quadrants int")


def layers(spark, q):
    return spark.createDataFrame([(i, i, i - 1.0, float(i), i - 0.5, 1) for i in range(1, q + 1)], "layer int, edge int, lo double, hi double, rep double, n long")


def test_program_by_hand(spark):
    v = {(0, 1): 4.0, (1, 2): 5.0, (2, 3): 9.0, (0, 2): 8.0, (1, 3): 16.0, (0, 3): 20.0}
    plan = optimise.optimal_plan(costs(spark, v), layers(spark, 3)).orderBy("part").collect()
    assert [(r["lo_layer"], r["hi_layer"]) for r in plan] == [(0, 2), (2, 3)]
    assert [(r["vstar"], r["tstar"]) for r in optimise.dp_table(costs(spark, v)).orderBy("r").collect()] == [(0.0, 0), (4.0, 0), (8.0, 0), (17.0, 2)]
    tie = costs(spark, v | {(0, 3): 17.0})
    assert optimise.optimal_plan(tie, layers(spark, 3)).count() == 1


def test_program_equals_enumeration(spark):
    rng = np.random.default_rng(3)
    q = 7
    v = {(s, r): float(rng.integers(1, 60) + 8 * (r - s)) for s in range(q) for r in range(s + 1, q + 1)}
    cost, lay = costs(spark, v), layers(spark, q)
    best = min(sum(v[p] for p in zip(b, b[1:], strict=False)) for k in range(q) for mid in combinations(range(1, q), k) for b in [(0, *mid, q)])
    assert sum(r["cost"] for r in optimise.optimal_plan(cost, lay).collect()) == best
    assert sum(r["cost"] for r in optimise.brute_force_plan(cost, lay).collect()) == best
    for k in (1, 3, 7):
        want = min(sum(v[p] for p in zip(b, b[1:], strict=False)) for mid in combinations(range(1, q), k - 1) for b in [(0, *mid, q)])
        got = optimise.plan_with_k(cost, lay, k).collect()
        assert len(got) == k and sum(r["cost"] for r in got) == want


def test_one_speed_is_one_part_and_two_speeds_are_two(spark):
    p = OptimizerParams(q=10, quadrant_grain="off")
    assert optimise.optimise(mo(spark, grid(2500, lambda i: 7.0)), p).plan.count() == 1
    plan = optimise.optimise(mo(spark, grid(5000, lambda i: 1.0) + grid(5000, lambda i: 50.0, 5000)), p).plan.collect()
    assert len(plan) == 2


def test_grains_are_ordered(spark, sf):
    from kinetic.sources.standins import mo_orders

    x = optimise.optimise(mo_orders(spark, sf), OptimizerParams(q=6))
    by = {g: {(r["s"], r["r"]): r["v"] for r in expansion.range_costs(x.cells, x.splits, x.layers, OptimizerParams(q=6, quadrant_grain=g)).collect()} for g in ("speed", "region", "part", "off", "on")}
    for k in by["part"]:
        assert by["speed"][k] <= by["region"][k] * (1 + 1e-12) and by["region"][k] <= by["part"][k] * (1 + 1e-12) and by["part"][k] <= min(by["off"][k], by["on"][k]) * (1 + 1e-12)


@pytest.mark.parametrize("change", [{}, {"bins": 4}, {"quadrant_grain": "speed"}, {"representative": "max", "node_rounding": "exact"}, {"layering": "equal_depth", "max_depth": 3}])
def test_arrays_and_tables_give_one_plan(spark, sf, change):
    from kinetic.sources.shared import kept
    from kinetic.sources.standins import mo_orders

    mo, p = mo_orders(spark, sf), OptimizerParams(**({"q": 8} | change))
    here, spread = optimise.optimise(mo, p), optimise.optimise(mo, p, kept)
    assert sorted(here.layers.collect()) == sorted(spread.layers.collect())
    assert set(map(tuple, here.splits.collect())) == set(map(tuple, spread.splits.select("layer", "level", "code").collect()))
    a, b = ({(r["s"], r["r"]): r for r in x.cost.collect()} for x in (here, spread))
    assert a.keys() == b.keys() and all(a[k]["v"] == pytest.approx(b[k]["v"], rel=1e-12) and a[k]["regions"] == b[k]["regions"] and a[k]["quadrants"] == b[k]["quadrants"] for k in a)
    assert [r["hi_layer"] for r in here.plan.orderBy("part").collect()] == [r["hi_layer"] for r in spread.plan.orderBy("part").collect()]


def test_odd_inputs(spark):
    p = OptimizerParams(q=10)
    empty = mo(spark, [])
    assert domain.speed_layers(empty, p).count() == 0
    assert optimise.optimise(empty, p).plan.count() == 0
    rows = [(1, 10000.0, 10000.0, 0.0, 0.0, 0.0, 0.0), (2, 0.0, 0.0, None, 0.0, None, 0.0), (3, -5.0, 20000.0, float("nan"), 0.0, float("nan"), 0.0)]
    x = optimise.optimise(mo(spark, rows), p)
    assert [(r["part"], r["lo_layer"], r["hi_layer"]) for r in x.plan.collect()] == [(1, 0, 1)]
