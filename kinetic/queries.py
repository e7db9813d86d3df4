"""A query for each method, variant, baseline, measure and workload, over the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetic import oracle as o
from kinetic import workloads as w
from kinetic.functions import motion, sqlfuncs
from kinetic.operators import baselines, index_box, index_curve, measures, partitions, query, update
from kinetic.plans import domain, expansion, optimise, quad
from kinetic.plans.params import OptimizerParams
from kinetic.sources import standins as st
from kinetic.sources.shared import kept
from kinetic.workloads import micro, optimised

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
P10 = OptimizerParams(q=10)


def add(name: str, fn: Query, sql: str | None = None) -> None:
    QUERIES[name] = w.afresh(fn)
    if sql is not None:
        ORACLES[name] = sql


def orders(spark: SparkSession, sf: str) -> DataFrame:
    return st.mo_orders(spark, sf)


def layers10(spark: SparkSession, sf: str) -> DataFrame:
    return domain.speed_layers(orders(spark, sf), P10)


def cells10(spark: SparkSession, sf: str, p: OptimizerParams = P10, counts=quad.cell_counts) -> DataFrame:
    mo = orders(spark, sf)
    return counts(mo, p, domain.speed_layers(mo, p)).select("layer", "level", "code", "n")


def splits10(spark: SparkSession, sf: str) -> DataFrame:
    return optimised(spark, sf, P10).splits.select("layer", "level", "code")


# stand-ins
add("mo_orders", orders, o.orders())
add("mo_orders_mix_s", lambda s, d: st.mo_orders(s, d, "mix-S"), o.orders("mix-S"))
add("mo_orders_mix_b", lambda s, d: st.mo_orders(s, d, "mix-B"), o.orders("mix-B"))
add("mo_orders_dir_any", lambda s, d: st.mo_orders(s, d, any_direction=True), o.orders(any_direction=True))
add("mo_lineitem", lambda s, d: st.mo_lineitem(s, d), o.lineitem())
add("mo_events", lambda s, d: st.mo_events(s, d).withColumn("us", F.unix_micros("ts")).drop("ts"), f"SELECT * EXCLUDE (ts) FROM ({o.events()})")
add("mo_events_rush", lambda s, d: st.mo_events(s, d, rush=True).withColumn("us", F.unix_micros("ts")).drop("ts"), f"SELECT * EXCLUDE (ts) FROM ({o.events(True)})")
add("mo_embed", lambda s, d: st.mo_embed(s, d), o.embed())
add("q_range", lambda s, d: st.q_range(s, d), o.ranges())
add("q_knn", lambda s, d: st.q_knn(s, d), o.knns())

# motion
add("position_at_60", lambda s, d: motion.position_at(orders(s, d), 60).select("oid", "px", "py"), f"SELECT oid, x + vx * (60 - t_ref) AS px, y + vy * (60 - t_ref) AS py FROM ({o.orders()})")
add("speed_and_quadrant", lambda s, d: motion.with_quadrant(motion.with_speed(st.mo_embed(s, d))).select("oid", "speed", "quadrant"), f"SELECT oid, sqrt(vx * vx + vy * vy) AS speed, 2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT) AS quadrant FROM ({o.embed()})")
add(
    "velocity_from_samples", lambda s, d: motion.velocity_from_samples(st.mo_events(s, d).select("oid", "ts", "event_id", "x", "y")).select("oid", "event_id", "vx", "vy"),
    f"WITH e AS (SELECT *, (us - lag(us) OVER w) / 1000000 AS gap, lag(x) OVER w AS x0, lag(y) OVER w AS y0 FROM ({o.events()}) WINDOW w AS (PARTITION BY oid ORDER BY us, event_id)) SELECT oid, event_id, CASE WHEN gap > 0 THEN (x - x0) / gap END AS vx, CASE WHEN gap > 0 THEN (y - y0) / gap END AS vy FROM e",
)
_LATEST = f"SELECT oid, arg_max(event_id, us * 100000000 + event_id) AS event_id, arg_max(speed, us * 100000000 + event_id) AS speed FROM (SELECT *, CAST(us AS HUGEINT) AS u2 FROM ({o.events()})) GROUP BY oid".replace("us * 100000000", "u2 * 100000000")
add("latest_status", lambda s, d: motion.latest_status(st.mo_events(s, d)).select("oid", "event_id", "speed"), _LATEST)

# speed domain
_LAYERS = f"SELECT layer, edge, n, {o.micro('hi')} AS hi_micro, {o.micro('rep')} AS rep_micro FROM layers"


def _layers(p: OptimizerParams, data: Query = orders) -> Query:
    return lambda s, d: domain.speed_layers(data(s, d), p).select(F.col("layer").cast("long").alias("layer"), F.col("edge").cast("long").alias("edge"), "n", micro("hi").alias("hi_micro"), micro("rep").alias("rep_micro"))


add("layers_equal_width", _layers(OptimizerParams(q=50)), f"WITH {o.layer_ctes(o.orders(), 50)} {_LAYERS}")
add("layers_distinct", _layers(OptimizerParams(layering="distinct"), lambda s, d: st.mo_lineitem(s, d)), f"WITH {o.layer_ctes(o.lineitem(), 50, 'distinct')} {_LAYERS}")
add("layers_equal_depth", _layers(OptimizerParams(q=20, layering="equal_depth")))
add("layers_max_representative", _layers(OptimizerParams(q=10, representative="max")), f"WITH {o.layer_ctes(o.orders(), 10)} SELECT layer, l.edge, l.n, {o.micro('hi')} AS hi_micro, {o.micro('(SELECT max(speed) FROM lm WHERE lm.edge = l.edge)')} AS rep_micro FROM layers l")
add("layers_smoothed", lambda s, d: domain.kde_layers(layers10(s, d), 4.0).select(F.col("layer").cast("long").alias("layer"), F.floor(F.col("smooth") * 1000 + F.lit(0.5)).cast("long").alias("milli")),
    f"WITH {o.layer_ctes(o.orders())}, m AS (SELECT *, (lo + hi) / 2 AS mid FROM layers) SELECT a.layer, CAST(floor(sum(exp(-((a.mid - b.mid) / 4.0::double) * ((a.mid - b.mid) / 4.0::double) / 2) * b.n) / sum(exp(-((a.mid - b.mid) / 4.0::double) * ((a.mid - b.mid) / 4.0::double) / 2)) * 1000 + 0.5) AS BIGINT) AS milli FROM m a, m b GROUP BY a.layer")

# quad trees
_CELLS = f"{o.layer_ctes(o.orders())}, {o.cell_ctes()}"
_TESTED = f"SELECT layer, level, code, CAST(n AS BIGINT) AS n, CAST(floor(stat * 1000 + 0.5) AS BIGINT) AS stat_milli, CAST(stat <= {{}} AS INT) AS uniform FROM tested"


def _tested(p: OptimizerParams) -> Query:
    return lambda s, d: quad.uniformity(cells10(s, d, p), p).select("layer", F.col("level").cast("long").alias("level"), "code", "n", F.floor(F.col("stat") * 1000 + F.lit(0.5)).cast("long").alias("stat_milli"), "uniform")


add("cell_cube", cells10, f"WITH {_CELLS} SELECT * FROM cells")
add("cell_rollup", lambda s, d: cells10(s, d, counts=quad.cell_counts_rollup), f"WITH {_CELLS} SELECT * FROM cells")
add("chi2_uniformity", _tested(P10), f"WITH {_CELLS}, {o.test_ctes()} {_TESTED.format(7.814728)}")
add("chi2_uniformity_4x4", _tested(OptimizerParams(q=10, bins=4)), f"WITH {o.layer_ctes(o.orders())}, {o.cell_ctes(6)}, {o.test_ctes(4, 24.995790)} {_TESTED.format(24.995790)}")
add("chi2_uniformity_alpha_1", _tested(OptimizerParams(q=10, alpha=0.01)), f"WITH {_CELLS}, {o.test_ctes()} {_TESTED.format(11.344867)}")
_SPLITS = f"{_CELLS}, {o.test_ctes()}, {o.split_ctes()}"
add("quad_splits", splits10, f"WITH {_SPLITS} SELECT layer, level, code FROM splits")
add("quad_leaves", lambda s, d: quad.tree_leaves(splits10(s, d), optimised(s, d, P10).layers), f"WITH {_SPLITS}, c AS (SELECT layer, level + 1 AS level, code * 4 + k AS code FROM splits, generate_series(0, 3) AS g(k) UNION ALL SELECT layer, 0, 0 FROM layers) SELECT * FROM c ANTI JOIN splits USING (layer, level, code)")
add("merged_tiling", lambda s, d: quad.merged_tiling(splits10(s, d), optimised(s, d, P10).layers).select(*[F.col(c).cast("long").alias(c) for c in ("s", "r", "level", "code")]), f"WITH {_SPLITS}, {o.TILING} SELECT s, r, level, code FROM tiling")

# cost of expansion
_PROB = f"WITH {o.layer_ctes(o.orders())}, h AS (SELECT layer, n, sum(n) OVER (ORDER BY layer) AS h1, sum(n) OVER (ORDER BY layer) - n AS h0, sum(n) OVER () AS t FROM layers), p AS (SELECT layer, exp(lgamma(h1 + 1) - lgamma(h1 - 101) - lgamma(t + 1) + lgamma(t - 101)) - CASE WHEN h0 < 102 THEN 0 ELSE exp(lgamma(h0 + 1) - lgamma(h0 - 101) - lgamma(t + 1) + lgamma(t - 101)) END AS p FROM h WHERE h1 >= 102 UNION ALL SELECT layer, 0 FROM h WHERE h1 < 102) "


def _probabilities(s: SparkSession, d: str) -> DataFrame:
    return expansion.node_max_prob(layers10(s, d).select(F.lit(0).alias("g"), "layer", "n"), 102, ["g"])


add("node_max_prob", lambda s, d: _probabilities(s, d).select(F.col("layer").cast("long").alias("layer"), micro("prob").alias("prob_micro")), _PROB + f"SELECT layer, {o.micro('p')} AS prob_micro FROM p")
add("prob_sums_to_one", lambda s, d: _probabilities(s, d).groupBy("g").agg(F.floor(F.sum("prob") * 1000000 + F.lit(0.5)).cast("long").alias("total_micro")).select("total_micro"), "SELECT CAST(1000000 AS BIGINT) AS total_micro")


def _choice(s: SparkSession, d: str) -> DataFrame:
    """Layers' nodes over the whole domain: both costs, and which is less by the closed test."""
    rows = layers10(s, d).withColumn("d", expansion.node_side(F.lit(10000.0), F.col("n"), 102)).withColumn("v", F.col("rep"))
    one, quad_ = expansion.node_cost(F.col("d"), F.col("v"), 120.0), expansion.node_cost_quadrant(F.col("d"), F.col("v"), 120.0)
    return rows.select(F.col("layer").cast("long").alias("layer"), F.floor(one / 1000 + F.lit(0.5)).cast("long").alias("one_k"), F.floor(quad_ / 1000 + F.lit(0.5)).cast("long").alias("quad_k"), expansion.quadrants_win(F.col("d"), F.col("v"), 120.0).cast("int").alias("quadrants"))


# in SQL by Simpson's rule, which is exact for squares
add("nu_one_quad_choice", _choice,
    f"WITH {o.layer_ctes(o.orders())}, x AS (SELECT layer, 10000.0::double * sqrt(least(102, n) / n::double) AS d, rep AS v FROM layers), y AS (SELECT layer, (d * d + 4 * (d + 120 * v) * (d + 120 * v) + (d + 240 * v) * (d + 240 * v)) * 20 AS one, (4 * d * d + 4 * (2 * d + 60 * v) * (2 * d + 60 * v) + (2 * d + 120 * v) * (2 * d + 120 * v)) * 20 AS quad FROM x) "
    "SELECT layer, CAST(floor(one / 1000 + 0.5) AS BIGINT) AS one_k, CAST(floor(quad / 1000 + 0.5) AS BIGINT) AS quad_k, CAST(quad < one AS INT) AS quadrants FROM y")  # fmt: skip


def _costs(p: OptimizerParams) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        cost = optimised(s, d, p).cost
        whole = cost.agg(F.max_by("v", F.col("r") - F.col("s")).alias("whole"))
        return cost.crossJoin(F.broadcast(whole)).select(F.col("s").cast("long").alias("s"), F.col("r").cast("long").alias("r"), "n", "regions", F.floor(F.col("v") / F.col("whole") * 100000 + F.lit(0.5)).cast("long").alias("share"), "quadrants")

    return run


for _name, _grain in (("range_costs", "part"), ("range_costs_region", "region"), ("range_costs_speed", "speed"), ("range_costs_off", "off"), ("range_costs_on", "on")):
    _sql = ", ".join([_SPLITS, o.TILING, o.cost_ctes(grain=_grain)])
    add(_name, _costs(OptimizerParams(q=10, quadrant_grain=_grain)), f"WITH {_sql} SELECT s, r, CAST(n AS BIGINT) AS n, regions, CAST(floor(v / (SELECT arg_max(v, r - s) FROM cost) * 100000 + 0.5) AS BIGINT) AS share, quadrants FROM cost")
_sql = ", ".join([_SPLITS, o.TILING, o.cost_ctes(rounding="floor")])
add("range_costs_floor", _costs(OptimizerParams(q=10, node_rounding="floor")), f"WITH {_sql} SELECT s, r, CAST(n AS BIGINT) AS n, regions, CAST(floor(v / (SELECT arg_max(v, r - s) FROM cost) * 100000 + 0.5) AS BIGINT) AS share, quadrants FROM cost")

# optimiser
_PLAN_COLUMNS = f"SELECT part, lo_layer, hi_layer, {o.micro('lo')} AS lo_micro, {o.micro('hi')} AS hi_micro, quadrants FROM plan"


def plan_columns(plan: DataFrame) -> DataFrame:
    return plan.select(*[F.col(c).cast("long").alias(c) for c in ("part", "lo_layer", "hi_layer")], micro("lo").alias("lo_micro"), micro("hi").alias("hi_micro"), "quadrants")


_OPT = o.optimiser(o.orders())
add("optimal_plan", lambda s, d: plan_columns(optimised(s, d, P10).plan), f"WITH {_OPT} {_PLAN_COLUMNS}")
add("brute_force_plan", lambda s, d: plan_columns(optimise.brute_force_plan(optimised(s, d, P10).cost, optimised(s, d, P10).layers)), f"WITH {_OPT} {_PLAN_COLUMNS}")
add("optimal_plan_off", lambda s, d: plan_columns(optimised(s, d, OptimizerParams(q=10, quadrant_grain="off")).plan), f"WITH {o.optimiser(o.orders(), grain='off')} {_PLAN_COLUMNS}")
add("plan_fixed_k", lambda s, d: plan_columns(optimise.plan_with_k(optimised(s, d, P10).cost, optimised(s, d, P10).layers, 3)), f"WITH {o.optimiser(o.orders(), k=3)} {_PLAN_COLUMNS}")
add("optimal_plan_q50", lambda s, d: plan_columns(optimised(s, d, OptimizerParams()).plan), f"WITH RECURSIVE {o.optimiser_by_prefixes(o.orders(), 50)} {_PLAN_COLUMNS}")
add("optimal_plan_lineitem", lambda s, d: plan_columns(optimised(s, d, P10, "lineitem").plan), f"WITH {o.optimiser(o.lineitem())} {_PLAN_COLUMNS}")
add("optimal_plan_sampled", lambda s, d: plan_columns(optimise.optimise_sampled(orders(s, d), P10, 0.5).plan))
add("dp_table", lambda s, d: _dp(optimised(s, d, P10).cost),
    f"WITH {_OPT}, w AS (SELECT arg_max(v, r - s) AS whole FROM cost), pre AS (SELECT g.r AS hi, m.m, sum(c.v) AS total, max(c.s) AS last FROM (SELECT layer AS r FROM layers) g JOIN (SELECT m, s, r FROM pieces) m ON m.r <= g.r JOIN cost c ON c.s = m.s AND c.r = m.r GROUP BY g.r, m.m HAVING max(m.r) = g.r) "
    "SELECT hi AS r, CAST(floor(min(total) / any_value(whole) * 100000 + 0.5) AS BIGINT) AS share, arg_min(last, total) AS tstar FROM pre, w GROUP BY hi UNION ALL SELECT 0, 0, 0")  # fmt: skip
add("walk_back", lambda s, d: optimise.walk_back(optimised(s, d, P10).cost).select(F.col("step").cast("long").alias("step"), F.col("bound").cast("long").alias("bound")), f"WITH {_OPT} SELECT part AS step, hi_layer AS bound FROM plan UNION ALL SELECT 0, 0")


def _dp(cost: DataFrame) -> DataFrame:
    """Prefix optima as shares of the whole range's cost."""
    whole = cost.agg(F.max_by("v", F.col("r") - F.col("s")).alias("whole"))
    return optimise.dp_table(cost).crossJoin(F.broadcast(whole)).select(F.col("r").cast("long").alias("r"), F.floor(F.col("vstar") / F.col("whole") * 100000 + F.lit(0.5)).cast("long").alias("share"), F.col("tstar").cast("long").alias("tstar"))


def heuristics(s: SparkSession, d: str) -> DataFrame:
    """how, part, lo_layer, hi_layer of the rules of thumb."""
    x = optimised(s, d, P10)
    out = None
    for how, k in (("single", 1), ("each", 10), ("equal_width", 3), ("equal_depth", 3)):
        one = optimise.heuristic_plan(x.layers, x.cost, k, how).select(F.lit(how).alias("how"), *[F.col(c).cast("long").alias(c) for c in ("part", "lo_layer", "hi_layer")])
        out = one if out is None else out.unionByName(one)
    return out


add("heuristic_plans", heuristics,
    f"WITH {o.layer_ctes(o.orders())}, g AS (SELECT 'single' AS how, layer, 1 AS g FROM layers UNION ALL SELECT 'each', layer, layer FROM layers UNION ALL SELECT 'equal_width', layer, greatest(1, least(3, ceil(hi * 3 / max(hi) OVER () - 1e-9))) FROM layers UNION ALL SELECT 'equal_depth', layer, least(3, (sum(n) OVER (ORDER BY layer) - n) * 3 // sum(n) OVER () + 1) FROM layers), "
    "e AS (SELECT how, g, max(layer) AS hi FROM g GROUP BY how, g) SELECT how, row_number() OVER (PARTITION BY how ORDER BY hi) AS part, coalesce(lag(hi) OVER (PARTITION BY how ORDER BY hi), 0) AS lo_layer, hi AS hi_layer FROM e")  # fmt: skip

# parts
_PARTED = f"{_OPT}, {o.PARTED}"


def parted10(s: SparkSession, d: str) -> DataFrame:
    return partitions.assign_parts(orders(s, d), optimised(s, d, P10).plan)


add("assign_parts", lambda s, d: parted10(s, d).select("oid", F.col("part").cast("long").alias("part"), "quadrant"), f"WITH {_PARTED} SELECT oid, part, quadrant FROM parted")
add("part_stats", lambda s, d: partitions.part_stats(parted10(s, d)).select(F.col("part").cast("long").alias("part"), "quadrant", "n", "vxlo", "vxhi", "vylo", "vyhi", "vmax"), f"WITH {_PARTED} SELECT part, quadrant, count(*) AS n, min(vx) AS vxlo, max(vx) AS vxhi, min(vy) AS vylo, max(vy) AS vyhi, max(speed) AS vmax FROM parted GROUP BY part, quadrant")
add("quadrant_counts", lambda s, d: partitions.single_part(orders(s, d), True).groupBy("quadrant").agg(F.count(F.lit(1)).alias("n")), f"SELECT 2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT) AS quadrant, count(*) AS n FROM ({o.orders()}) GROUP BY 1")
add("plan_summary", lambda s, d: measures.plan_summary(optimised(s, d, P10).plan, parted10(s, d)).select(*[F.col(c).cast("long").alias(c) for c in ("part", "lo_layer", "hi_layer", "quadrants", "n", "sub_parts")]), f"WITH {_PARTED} SELECT p.part, lo_layer, hi_layer, CAST(quadrants AS BIGINT) AS quadrants, count(oid) AS n, count(DISTINCT quadrant) AS sub_parts FROM plan p LEFT JOIN parted USING (part) GROUP BY ALL")
add("page_counts", lambda s, d: measures.page_counts(parted10(s, d)).select(F.col("part").cast("long").alias("part"), "n", F.col("pages").cast("long").alias("pages")), f"WITH {_PARTED} SELECT part, count(*) AS n, CAST(ceil(count(*) * 40 / 4096.0::double) AS BIGINT) AS pages FROM parted GROUP BY part")

# answers: every way must give the scan's
_RANGE, _KNN = o.range_answers(o.orders(), o.ranges()), o.knn_answers(o.orders(), o.knns())
RANGE_WAYS = {
    "range_box": lambda s, d, q: w.stored(s, d).range(q), "range_box_flat": lambda s, d, q: query.range_box(None, q, two_levels=False, objects=w.stored(s, d).objects, nodes=w.stored(s, d).catalog),
    "range_box_unstored": lambda s, d, q: query.range_box(parted10(s, d), q), "range_curve": lambda s, d, q: w.stored(s, d, kind="curve").range(q),
    "range_curve_hilbert": lambda s, d, q: query.range_curve(parted10(s, d), q, curve="hilbert"), "range_pushdown": lambda s, d, q: w.stored(s, d).pushed(q),
    "range_sequential": lambda s, d, q: partitions.run_partitioned(q, parted10(s, d), query.range_box, "sequential"), "range_concurrent": lambda s, d, q: partitions.run_partitioned(q, parted10(s, d), query.range_box, "concurrent"),
}
KNN_WAYS = {
    "knn_box": lambda s, d, q: w.stored(s, d).neighbours(q), "knn_merged": lambda s, d, q: query.knn_merged(w.stored(s, d).objects, q), "knn_growing": lambda s, d, q: w.stored(s, d, kind="curve").neighbours(q),
}
add("range_scan", lambda s, d: query.range_scan(orders(s, d), st.q_range(s, d)), _RANGE)
for _name, _way in RANGE_WAYS.items():
    add(_name, lambda s, d, way=_way: way(s, d, st.q_range(s, d)), _RANGE)
add("knn_scan", lambda s, d: query.knn_scan(orders(s, d), st.q_knn(s, d)), _KNN)
for _name, _way in KNN_WAYS.items():
    add(_name, lambda s, d, way=_way: way(s, d, st.q_knn(s, d)), _KNN)


def places(s: SparkSession, d: str) -> DataFrame:
    """A window round each place of the neighbour queries: few enough for literal bounds."""
    return st.q_knn(s, d).select("qid", (F.col("cx") - 300).alias("xlo"), (F.col("cy") - 300).alias("ylo"), (F.col("cx") + 300).alias("xhi"), (F.col("cy") + 300).alias("yhi"), "t")


add("range_pushdown_literal", lambda s, d: w.stored(s, d).pushed(places(s, d)), o.range_answers(o.orders(), f"SELECT qid, cx - 300 AS xlo, cy - 300 AS ylo, cx + 300 AS xhi, cy + 300 AS yhi, t FROM ({o.knns()})"))


def built(s: SparkSession, d: str, kind: str) -> DataFrame:
    """part, quadrant, objects and nodes (or pages) of an index that is written now."""
    index = w.store_index(parted10(s, d), f"{w.checkpoint_folder(s)}/built-{kind}-{w.time.time_ns()}", kind)
    return index.catalog.groupBy(F.col("part").cast("long").alias("part"), "quadrant").agg(F.sum("n").alias("objects"), F.count(F.lit(1)).alias("nodes"))


add("layout_box", lambda s, d: built(s, d, "box"), f"WITH {_PARTED}, {o.node_ctes()} SELECT part, quadrant, CAST(sum(n) AS BIGINT) AS objects, count(*) AS nodes FROM nodes GROUP BY part, quadrant")
add("layout_curve", lambda s, d: built(s, d, "curve"))

# baselines
PARTITIONERS: dict[str, Callable[[DataFrame], DataFrame]] = {
    "unpartitioned": partitions.single_part, "quadrants_only": partial(partitions.single_part, quadrants=True), "seed_parts": baselines.seed_parts, "seed_parts_refined": partial(baselines.seed_parts, refine=20),
    "axis_parts": baselines.axis_parts, "axis_parts_3": partial(baselines.axis_parts, axes=3, outliers=False),
}
for _name, _way in {"unpartitioned": "one", "quadrants_only": "quadrants", "seed_parts": "seed", "seed_parts_refined": "seed_refined", "seed_parts_enlargement": "seed_enlargement", "axis_parts": "axis", "axis_parts_3": "axis_3"}.items():
    add(f"range_{_name}", lambda s, d, way=_way: w.stored(s, d, way).range(st.q_range(s, d)), _RANGE)
    add(f"knn_{_name}", lambda s, d, way=_way: w.stored(s, d, way).neighbours(st.q_knn(s, d)), _KNN)
    if _name in ("unpartitioned", "seed_parts_refined", "axis_parts"):
        add(f"range_curve_{_name}", lambda s, d, way=_way: w.stored(s, d, way, "curve").range(st.q_range(s, d)), _RANGE)
        add(f"knn_curve_{_name}", lambda s, d, way=_way: w.stored(s, d, way, "curve").neighbours(st.q_knn(s, d)), _KNN)
_SEEDS = (
    f"WITH mo AS ({o.embed()}), ends AS (SELECT arg_max(struct_pack(vx := vx, vy := vy), struct_pack(a := vx, b := -oid)) AS e1, arg_max(struct_pack(vx := vx, vy := vy), struct_pack(a := -vx, b := -oid)) AS e2, arg_max(struct_pack(vx := vx, vy := vy), struct_pack(a := vy, b := -oid)) AS e3, arg_max(struct_pack(vx := vx, vy := vy), struct_pack(a := -vy, b := -oid)) AS e4 FROM mo), "
    + "d4 AS (SELECT mo.*, " + ", ".join(f"(vx - e{i}.vx) * (vx - e{i}.vx) + (vy - e{i}.vy) * (vy - e{i}.vy) AS d{i}" for i in range(1, 5)) + " FROM mo, ends), "
    "f AS (SELECT arg_max(struct_pack(vx := vx, vy := vy), struct_pack(a := least(d1, d2, d3, d4), b := -oid)) AS e5 FROM d4), d5 AS (SELECT *, (vx - e5.vx) * (vx - e5.vx) + (vy - e5.vy) * (vy - e5.vy) AS d5 FROM d4, f) "
    "SELECT oid, CASE least(d1, d2, d3, d4, d5) WHEN d1 THEN 1 WHEN d2 THEN 2 WHEN d3 THEN 3 WHEN d4 THEN 4 ELSE 5 END AS part FROM d5"
)
add("seed_parts", lambda s, d: baselines.seed_parts(st.mo_embed(s, d)).select("oid", "part"), _SEEDS)
add("seed_parts_refined", lambda s, d: baselines.seed_parts(st.mo_embed(s, d), refine=20).groupBy("part").agg(F.count(F.lit(1)).alias("n")))
add("axis_parts_first_round", lambda s, d: baselines.axis_parts(st.mo_embed(s, d), rounds=0, outliers=False).select("oid", "part"), f"SELECT oid, CASE WHEN abs(vx * 0.0::double - vy * 1.0::double) <= abs(vx * 1.0::double - vy * 0.0::double) THEN 1 ELSE 2 END AS part FROM ({o.embed()})")
add("axis_parts", lambda s, d: baselines.axis_parts(st.mo_embed(s, d)).groupBy("part").agg(F.count(F.lit(1)).alias("n")))
add("axis_parts_outliers_first_round", lambda s, d: baselines.axis_parts(st.mo_embed(s, d), rounds=0).select("oid", "part"),
    f"WITH a AS (SELECT oid, abs(vx * 0.0::double - vy * 1.0::double) AS d1, abs(vx * 1.0::double - vy * 0.0::double) AS d2 FROM ({o.embed()})), b AS (SELECT *, CAST(floor(least(d1, d2) * 10) AS BIGINT) AS b FROM a), h AS (SELECT b, sum(count(*)) OVER (ORDER BY b) AS c FROM b GROUP BY b), cut AS (SELECT (min(b) + 1) / 10 AS c FROM h WHERE c >= 0.9::double * (SELECT count(*) FROM a)) "
    "SELECT oid, CASE WHEN least(d1, d2) > cut.c THEN 3 WHEN d1 <= d2 THEN 1 ELSE 2 END AS part FROM b, cut")  # fmt: skip
add("axis_parts_rotated", lambda s, d: baselines.axis_parts(st.mo_embed(s, d), rotate=True).agg(F.count(F.lit(1)).alias("n"), F.sum((F.abs(F.col("rvx") * F.col("rvx") + F.col("rvy") * F.col("rvy") - F.col("vx") * F.col("vx") - F.col("vy") * F.col("vy")) < 1e-6).cast("long")).alias("same_speed")), f"SELECT count(*) AS n, count(*) AS same_speed FROM ({o.embed()})")

# boxes and curve keys
_NODES = f"{_PARTED}, {o.node_ctes()}"
_ONE = f"mo AS ({o.orders()}), parted AS (SELECT *, 1 AS part, 0 AS quadrant FROM mo), {o.node_ctes()}"


def _boxes(s: SparkSession, d: str) -> DataFrame:
    return index_box.node_boxes(index_box.build_nodes(parted10(s, d)))


def accesses(partition: Callable[[SparkSession, str], DataFrame]) -> Query:
    return lambda s, d: measures.node_accesses(index_box.candidate_nodes(index_box.node_boxes(index_box.build_nodes(partition(s, d))), st.q_range(s, d)))


add("box_nodes", lambda s, d: _boxes(s, d).select(F.col("part").cast("long").alias("part"), "quadrant", "node", "n", "xlo", "xhi", "ylo", "yhi", "vxlo", "vxhi", "vylo", "vyhi"), f"WITH {_NODES} SELECT * FROM nodes")
add("node_accesses_opt", accesses(parted10), f"WITH {_NODES}, q AS ({o.ranges()}), {o.HITS} SELECT qid, count(*) AS accesses FROM hits GROUP BY qid")
add("node_accesses_one", accesses(lambda s, d: partitions.single_part(orders(s, d))), f"WITH {_ONE}, q AS ({o.ranges()}), {o.HITS} SELECT qid, count(*) AS accesses FROM hits GROUP BY qid")
add("node_accesses_quadrants", accesses(lambda s, d: partitions.single_part(orders(s, d), True)), f"WITH {_ONE.replace('0 AS quadrant', '2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT) AS quadrant')}, q AS ({o.ranges()}), {o.HITS} SELECT qid, count(*) AS accesses FROM hits GROUP BY qid")
for _name in ("seed_parts", "seed_parts_refined", "axis_parts"):
    add(f"node_accesses_{_name}", accesses(lambda s, d, way=PARTITIONERS[_name]: way(orders(s, d))))
_SWEPT = "(xhi - xlo) * (yhi - ylo) * 120 + ((xhi - xlo) * (vyhi - vylo) + (yhi - ylo) * (vxhi - vxlo)) * 7200 + (vxhi - vxlo) * (vyhi - vylo) * 576000"
add("measured_expansion", lambda s, d: measures.layout_expansion(index_box.build_nodes(parted10(s, d)), 120.0).select(F.col("part").cast("long").alias("part"), "nodes", F.floor(F.col("measured") / 1000000 + F.lit(0.5)).cast("long").alias("measured_m")), f"WITH {_NODES} SELECT part, count(*) AS nodes, CAST(floor(sum({_SWEPT}) / 1000000 + 0.5) AS BIGINT) AS measured_m FROM nodes GROUP BY part")
add("parent_expansion", lambda s, d: measures.parent_expansion(index_box.build_nodes(parted10(s, d)), 120.0).select(F.col("part").cast("long").alias("part"), F.floor(F.col("measured_parents") / 1000000 + F.lit(0.5)).cast("long").alias("measured_m")),
    f"WITH {_NODES}, up AS (SELECT part, quadrant, (node // 1048576) * 1048576 + (node % 1048576) // 102 AS u, min(xlo) AS xlo, max(xhi) AS xhi, min(ylo) AS ylo, max(yhi) AS yhi, min(vxlo) AS vxlo, max(vxhi) AS vxhi, min(vylo) AS vylo, max(vyhi) AS vyhi FROM nodes GROUP BY ALL) SELECT part, CAST(floor(sum({_SWEPT}) / 1000000 + 0.5) AS BIGINT) AS measured_m FROM up GROUP BY part")
add("estimate_accuracy", lambda s, d: measures.estimate_accuracy(measures.estimated_expansion(optimised(s, d, P10).plan), measures.layout_expansion(index_box.build_nodes(parted10(s, d)), 120.0)).select(F.col("part").cast("long").alias("part"), F.floor(F.col("ratio") * 10000 + F.lit(0.5)).cast("long").alias("ratio_4")), f"WITH {_NODES}, m AS (SELECT part, sum({_SWEPT}) AS m FROM nodes GROUP BY part) SELECT part, CAST(floor(cost / m * 10000 + 0.5) AS BIGINT) AS ratio_4 FROM plan JOIN m USING (part)")
add("velocity_aware_packing", lambda s, d: measures.node_accesses(index_box.candidate_nodes(index_box.node_boxes(index_box.build_nodes(parted10(s, d), pack_at=60.0)), st.q_range(s, d))))
_KEYED = f"WITH mo AS ({o.orders()}), k AS (SELECT *, x + vx * 60 AS lx, y + vy * 60 AS ly FROM mo) "
add("curve_keys_z", lambda s, d: index_curve.curve_keys(partitions.single_part(orders(s, d))).select("oid", "label", "key"), _KEYED + f"SELECT oid, 1 AS label, {o.code('lx', 'ly', 6)} AS key FROM k")


def _hilbert(s: SparkSession, d: str) -> DataFrame:
    """What makes the keys of the objects' cells a Hilbert curve: one key a cell, a step of one side between keys in a row, and whole squares in every run of 4**k keys."""
    at = index_curve.label_of(F.col("t_ref")) * (index_curve.PERIOD / index_curve.PHASES) - F.col("t_ref")
    cells = orders(s, d).select(*[index_curve.grid(F.col(p) + F.col(v) * at, index_curve.BITS).alias(c) for p, v, c in (("x", "vx", "gx"), ("y", "vy", "gy"))]).distinct()
    keyed = kept(cells.withColumn("key", index_curve.hilbert_code(F.col("gx"), F.col("gy"), index_curve.BITS)))  # 4096 rows at most
    after = keyed.select((F.col("key") - 1).alias("key"), F.col("gx").alias("nx"), F.col("gy").alias("ny"))
    jumps = keyed.join(after, "key").where(F.abs(F.col("gx") - F.col("nx")) + F.abs(F.col("gy") - F.col("ny")) != 1).agg(F.count(F.lit(1)).alias("jumps"))
    runs = keyed.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(5)))).select("k", F.expr("shiftright(key, 2 * k)"), F.expr("shiftright(gx, k)"), F.expr("shiftright(gy, k)")).distinct().agg(F.count(F.lit(1)).alias("squares"))
    return keyed.agg(F.count(F.lit(1)).alias("cells"), F.countDistinct("key").alias("keys")).crossJoin(jumps).crossJoin(runs)


# a run of keys with parts of two squares, or a square in two runs, would be counted twice
add("curve_hilbert_definition", _hilbert,
    f"WITH mo AS ({o.orders()}), c AS (SELECT DISTINCT least(63, greatest(0, CAST(floor((x + vx * 60) / 10000.0::double * 64) AS BIGINT))) AS gx, least(63, greatest(0, CAST(floor((y + vy * 60) / 10000.0::double * 64) AS BIGINT))) AS gy FROM mo), s AS (SELECT DISTINCT k, gx >> k AS a, gy >> k AS b FROM c, generate_series(1, 5) AS g(k)) SELECT count(*) AS cells, count(*) AS keys, CAST(0 AS BIGINT) AS jumps, (SELECT count(*) FROM s) AS squares FROM c")
_HRANK, _HNEXT = [[v for row in t for v in row] for t in (index_curve.HILBERT_RANK, index_curve.HILBERT_NEXT)]
add("curve_keys_hilbert", lambda s, d: index_curve.curve_keys(partitions.single_part(orders(s, d)), curve="hilbert").select("oid", "label", "key"),
    "WITH RECURSIVE mo AS (" + o.orders() + "), g AS (SELECT oid, least(63, greatest(0, CAST(floor((x + vx * 60) / 10000.0::double * 64) AS BIGINT))) AS gx, least(63, greatest(0, CAST(floor((y + vy * 60) / 10000.0::double * 64) AS BIGINT))) AS gy FROM mo), "
    f"h AS (SELECT oid, gx, gy, 5 AS i, 0 AS st, 0 AS key FROM g UNION ALL SELECT oid, gx, gy, i - 1, {_HNEXT}[st * 4 + ((gx >> i) & 1) * 2 + ((gy >> i) & 1) + 1], key * 4 + {_HRANK}[st * 4 + ((gx >> i) & 1) * 2 + ((gy >> i) & 1) + 1] FROM h WHERE i >= 0) SELECT oid, 1 AS label, CAST(key AS BIGINT) AS key FROM h WHERE i = -1")  # fmt: skip
_WINDOW = "b AS (SELECT min(vx) AS a1, max(vx) AS a2, min(vy) AS b1, max(vy) AS b2 FROM mo)"


def _g(e: str) -> str:
    return f"least(63, greatest(0, CAST(floor(({e}) / 10000.0::double * 64) AS BIGINT)))"


_COVER = (
    f"WITH mo AS ({o.orders()}), q AS ({o.ranges(t=90)}), {_WINDOW}, cell AS (SELECT qid, gx, gy FROM q, b, generate_series(0, 63) AS x(gx), generate_series(0, 63) AS y(gy) WHERE gx BETWEEN {_g('xlo + least(a1 * (60 - t), a2 * (60 - t))')} AND {_g('xhi + greatest(a1 * (60 - t), a2 * (60 - t))')} AND gy BETWEEN {_g('ylo + least(b1 * (60 - t), b2 * (60 - t))')} AND {_g('yhi + greatest(b1 * (60 - t), b2 * (60 - t))')}), "
    "z AS (SELECT qid, " + " | ".join(f"(((gx >> {i}) & 1) << {2 * i}) | (((gy >> {i}) & 1) << {2 * i + 1})" for i in range(6)) + " AS key FROM cell), "
    "isl AS (SELECT qid, key, key - row_number() OVER (PARTITION BY qid ORDER BY key) AS g FROM z), runs AS (SELECT qid, min(key) AS key_lo, max(key) AS key_hi FROM isl GROUP BY qid, g)"
)


def _runs(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    keyed = index_curve.curve_keys(partitions.single_part(orders(s, d)))
    return keyed, index_curve.curve_intervals(st.q_range(s, d, t=90), index_curve.key_stats(keyed))


add("curve_intervals", lambda s, d: _runs(s, d)[1].select("qid", "key_lo", "key_hi"), f"{_COVER} SELECT qid, key_lo, key_hi FROM runs")


def sql_intervals(s: SparkSession, d: str) -> DataFrame:
    """Runs of keys of every window, by the table function in a lateral join."""
    sqlfuncs.register(s, orders(s, d), prefix="iv_")
    st.q_range(s, d).createOrReplaceTempView("iv_q")
    return s.sql("SELECT q.qid, i.key_lo, i.key_hi FROM iv_q q, LATERAL iv_curve_intervals(q.xlo, q.ylo, q.xhi, q.yhi, 6) i")


add("sql_curve_intervals", sql_intervals,
    f"WITH q AS ({o.ranges()}), cell AS (SELECT qid, gx, gy FROM q, generate_series(0, 63) AS x(gx), generate_series(0, 63) AS y(gy) WHERE gx BETWEEN {_g('xlo')} AND {_g('xhi')} AND gy BETWEEN {_g('ylo')} AND {_g('yhi')}), {_COVER[_COVER.index('z AS (SELECT qid'):]} SELECT qid, key_lo, key_hi FROM runs")


def sql_neighbours(s: SparkSession, d: str) -> DataFrame:
    """The neighbours of every place, by the table function."""
    sqlfuncs.register(s, orders(s, d), prefix="nn_")
    asked = st.q_knn(s, d).collect()  # a row for each nation
    return s.sql(" UNION ALL ".join(f"SELECT {r['qid']}L AS qid, CAST(rank AS BIGINT) AS rank, oid, dist2 FROM nn_knn_query({r['cx']!r}D, {r['cy']!r}D, {r['k']}, {r['t']!r}D)" for r in asked))


add("sql_neighbours", sql_neighbours, _KNN)


def _false_hits(s: SparkSession, d: str) -> DataFrame:
    keyed, runs = _runs(s, d)
    return measures.false_hits(index_curve.count_candidates(keyed, runs), query.range_scan(orders(s, d), st.q_range(s, d, t=90)))


add("false_hits", _false_hits,
    f"{_COVER}, k AS (SELECT oid, {o.code('lx', 'ly', 6)} AS key, x + vx * 90 AS px, y + vy * 90 AS py FROM (SELECT *, x + vx * 60 AS lx, y + vy * 60 AS ly FROM mo)), c AS (SELECT qid, oid, px, py FROM k JOIN runs ON key BETWEEN key_lo AND key_hi), n AS (SELECT q.qid, count(*) AS candidates, count(*) FILTER (px BETWEEN xlo AND xhi AND py BETWEEN ylo AND yhi) AS answers FROM c JOIN q USING (qid) GROUP BY q.qid) SELECT qid, candidates, answers, candidates - answers AS false_hits FROM n")
add("page_accesses", lambda s, d: index_curve.page_accesses(index_curve.page_catalog(index_curve.leaf_pages(_runs(s, d)[0])), _runs(s, d)[1]))
def _quality(s: SparkSession, d: str) -> DataFrame:
    """Both sides from objects that are dealt by oid, so that their pairs meet where they are made."""
    mo = orders(s, d).repartition(max(200, int(s.conf.get("spark.sql.shuffle.partitions"))), "oid")
    parted, q = partitions.assign_parts(mo, optimised(s, d, P10).plan), st.q_range(s, d)
    return measures.answer_quality(query.range_curve(parted, q), query.range_scan(mo, q))


add("answer_quality", _quality, f"SELECT qid, count(*) AS answers, count(*) AS truth, count(*) AS hits FROM ({_RANGE}) GROUP BY qid")

# updates: the first half of the month is known, the rest arrives
_HALF = 1704067200000000 + 15 * 86400000000
DEMO = [(1, 0, 1, 0.0, 8.0, 0, 1.0), (2, 1, 2, 8.0, 16.0, 1, 1.0), (3, 2, 3, 16.0, 1e9, 1, 1.0)]


def demo_plan(s: SparkSession) -> DataFrame:
    return s.createDataFrame(DEMO, "part int, lo_layer int, hi_layer int, lo double, hi double, quadrants int, cost double")


def updates(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    rows = st.mo_events(s, d)
    return update.apply_updates(motion.latest_status(rows.where(F.unix_micros("ts") < _HALF), columns=update.STATE), rows.where(F.unix_micros("ts") >= _HALF), demo_plan(s))


_PLACE = "CASE WHEN speed <= 8 THEN 1 WHEN speed <= 16 THEN 2 ELSE 3 END AS part, CASE WHEN speed <= 8 THEN 0 ELSE 2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT) END AS quadrant"
_NEWEST = f"WITH e AS (SELECT *, us >= {_HALF} AS new, row_number() OVER (PARTITION BY oid, us >= {_HALF} ORDER BY us DESC, event_id DESC) AS rn FROM ({o.events()})), p AS (SELECT oid, new, event_id, {_PLACE} FROM e WHERE rn = 1), "
add("updates_apply", lambda s, d: updates(s, d)[0].select("oid", "event_id", "part", "quadrant"), _NEWEST + "z AS (SELECT *, row_number() OVER (PARTITION BY oid ORDER BY new DESC) AS r2 FROM p) SELECT oid, event_id, part, quadrant FROM z WHERE r2 = 1")
add("update_migrations", lambda s, d: updates(s, d)[1].groupBy("action").agg(F.count(F.lit(1)).alias("n")), _NEWEST + "a AS (SELECT * FROM p WHERE NOT new), b AS (SELECT * FROM p WHERE new) SELECT CASE WHEN a.oid IS NULL THEN 'insert' WHEN a.part = b.part AND a.quadrant = b.quadrant THEN 'update' ELSE 'migrate' END AS action, count(*) AS n FROM b LEFT JOIN a USING (oid) GROUP BY 1")
add("migration_rate", lambda s, d: measures.migration_rate(updates(s, d)[1]).select("action", "n"), _NEWEST + "a AS (SELECT * FROM p WHERE NOT new), b AS (SELECT * FROM p WHERE new) SELECT CASE WHEN a.oid IS NULL THEN 'insert' WHEN a.part = b.part AND a.quadrant = b.quadrant THEN 'update' ELSE 'migrate' END AS action, count(*) AS n FROM b LEFT JOIN a USING (oid) GROUP BY 1")
add("recall_last_known", lambda s, d: measures.answer_quality(query.last_known(st.mo_events(s, d), st.q_range(s, d, 1000)), query.range_scan(motion.latest_status(st.mo_events(s, d)), st.q_range(s, d, 1000))),
    f"WITH e AS (SELECT * FROM ({o.events()}) QUALIFY row_number() OVER (PARTITION BY oid ORDER BY us DESC, event_id DESC) = 1), q AS ({o.ranges(1000)}), m AS (SELECT qid, CAST(x BETWEEN xlo AND xhi AND y BETWEEN ylo AND yhi AS INT) AS a, CAST(x + vx * t BETWEEN xlo AND xhi AND y + vy * t BETWEEN ylo AND yhi AS INT) AS b FROM e, q) SELECT qid, CAST(sum(a) AS BIGINT) AS answers, CAST(sum(b) AS BIGINT) AS truth, CAST(sum(a * b) AS BIGINT) AS hits FROM m GROUP BY qid HAVING sum(a) + sum(b) > 0")

w.add_workloads(add)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
