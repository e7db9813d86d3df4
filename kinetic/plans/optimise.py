"""The cheapest set of speed ranges, by dynamic programming inside one expression."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kinetic.plans import local, quad
from kinetic.plans.domain import layers_of
from kinetic.plans.expansion import range_costs
from kinetic.plans.params import OptimizerParams
from kinetic.sources.shared import kept

#: Cost of (s, r] inside the flattened costs, which are ordered by r, then s.
_COST = "costs[r * (r - 1) div 2 + s]"


def _matrix(cost: DataFrame) -> DataFrame:
    """One row: q and the costs of all ranges, ordered by (r, s); at most q (q + 1) / 2 entries."""
    return cost.agg(F.max("r").cast("long").alias("q"), F.transform(F.array_sort(F.collect_list(F.struct("r", "s", "v"))), lambda x: x["v"]).alias("costs")).where("q IS NOT NULL")


def _solved(cost: DataFrame) -> DataFrame:
    """q, costs, dp(best, last): least cost of the layers 1..r and where its last range begins; ties take the slowest."""
    step = f"""
    aggregate(sequence(1L, q), named_struct('best', array(0D), 'last', array(0L)), (a, r) ->
      aggregate(sequence(0L, r - 1), named_struct('v', CAST('Infinity' AS DOUBLE), 's', 0L),
        (b, s) -> IF(a.best[s] + {_COST} < b.v, named_struct('v', a.best[s] + {_COST}, 's', s), b),
        b -> named_struct('best', concat(a.best, array(b.v)), 'last', concat(a.last, array(b.s)))))
    """
    return _matrix(cost).withColumn("dp", F.expr(step))


def dp_table(cost: DataFrame) -> DataFrame:
    """r, vstar, tstar for r = 0..q."""
    return _solved(cost).select(F.posexplode(F.arrays_zip("dp.best", "dp.last")).alias("r", "_x")).select("r", F.col("_x.best").alias("vstar"), F.col("_x.last").alias("tstar"))


def _walk(df: DataFrame) -> DataFrame:
    """+bounds: 0 = first < ... < q, from the predecessors in dp.last."""
    return df.withColumn("bounds", F.expr("array_sort(array_distinct(aggregate(sequence(1L, q), array(q), (a, i) -> concat(a, array(dp.last[element_at(a, -1)])))))"))


def _ranges(bounds: DataFrame) -> DataFrame:
    """part, lo_layer, hi_layer from bounds."""
    return bounds.select(F.posexplode(F.expr("transform(sequence(1, size(bounds) - 1), i -> named_struct('lo', bounds[i - 1], 'hi', bounds[i]))")).alias("_p", "_x")).select((F.col("_p") + 1).alias("part"), F.col("_x.lo").cast("int").alias("lo_layer"), F.col("_x.hi").cast("int").alias("hi_layer"))


def _priced(ranges: DataFrame, cost: DataFrame, layers: DataFrame) -> DataFrame:
    """+lo, hi, quadrants, cost: the plan."""
    edges = layers.select(F.col("layer").alias("_l"), F.col("hi").alias("_h"))
    out = ranges.join(F.broadcast(cost.select(F.col("s").alias("lo_layer"), F.col("r").alias("hi_layer"), "quadrants", F.col("v").alias("cost"))), ["lo_layer", "hi_layer"])
    out = out.join(F.broadcast(edges.select(F.col("_l").alias("lo_layer"), F.col("_h").alias("lo"))), "lo_layer", "left").join(F.broadcast(edges.select(F.col("_l").alias("hi_layer"), F.col("_h").alias("hi"))), "hi_layer")
    return out.select("part", "lo_layer", "hi_layer", F.coalesce("lo", F.lit(0.0)).alias("lo"), "hi", "quadrants", "cost")


def optimal_plan(cost: DataFrame, layers: DataFrame) -> DataFrame:
    """part, lo_layer, hi_layer, lo, hi, quadrants, cost of the cheapest partitioning; the number of parts is an output."""
    return _priced(_ranges(_walk(_solved(cost))), cost, layers)


def walk_back(cost: DataFrame) -> DataFrame:
    """step, bound: the distinct boundaries in the order of layers."""
    return _walk(_solved(cost)).select(F.posexplode("bounds").alias("step", "bound"))


def plan_with_k(cost: DataFrame, layers: DataFrame, k: int) -> DataFrame:
    """The cheapest plan of exactly k parts (of as many as there are layers, if fewer)."""
    step = f"""
    aggregate(sequence(1L, least({k}L, q)), named_struct('v', transform(sequence(0L, q), r -> IF(r = 0, 0D, CAST('Infinity' AS DOUBLE))), 'b', transform(sequence(0L, q), r -> array(0L))), (a, i) ->
      aggregate(sequence(0L, q), named_struct('v', cast(array() as array<double>), 'b', cast(array() as array<array<bigint>>)), (o, r) ->
        IF(r = 0, named_struct('v', array(CAST('Infinity' AS DOUBLE)), 'b', array(array(0L))),
          aggregate(sequence(0L, greatest(r - 1, 0L)), named_struct('v', CAST('Infinity' AS DOUBLE), 's', 0L),
            (b, s) -> IF(r > 0 AND a.v[s] + costs[greatest(r * (r - 1) div 2 + s, 0L)] < b.v, named_struct('v', a.v[s] + costs[greatest(r * (r - 1) div 2 + s, 0L)], 's', s), b),
            b -> named_struct('v', concat(o.v, array(b.v)), 'b', concat(o.b, array(concat(a.b[b.s], array(r)))))))))
    """
    return _priced(_ranges(_matrix(cost).withColumn("_dp", F.expr(step)).select(F.expr("_dp.b[q]").alias("bounds"))), cost, layers)


def brute_force_plan(cost: DataFrame, layers: DataFrame) -> DataFrame:
    """The cheapest of all 2**(q-1) plans; for q up to 12."""
    q = cost.agg(F.max("r").cast("int").alias("q"))
    masks = q.select("q", F.explode(F.expr("sequence(0, cast(pow(2, q - 1) as int) - 1)")).alias("mask"))
    bounds = F.expr("concat(array(0), filter(sequence(1, q), i -> i = q OR (shiftright(mask, i - 1) & 1) = 1))")
    pairs = masks.withColumn("bounds", bounds).withColumn("_x", F.explode(F.expr("transform(sequence(1, size(bounds) - 1), i -> named_struct('s', bounds[i - 1], 'r', bounds[i]))")))
    priced = pairs.select("mask", "bounds", F.col("_x.s").alias("s"), F.col("_x.r").alias("r")).join(F.broadcast(cost.select("s", "r", "v")), ["s", "r"])
    best = priced.groupBy("mask", "bounds").agg(F.sum("v").alias("total")).orderBy("total", F.size("bounds"), "mask").limit(1)
    return _priced(_ranges(best), cost, layers)


def heuristic_plan(layers: DataFrame, cost: DataFrame, k: int, how: str) -> DataFrame:
    """Rule-of-thumb plans: equal_width and equal_depth with k parts, single, each (a part for each layer)."""
    if how == "single":
        k = 1
    n = layers.agg(F.count(F.lit(1)).alias("_q"), F.sum("n").alias("_all"), F.max("hi").alias("_top"))
    rows = layers.crossJoin(F.broadcast(n)).withColumn("_cum", F.sum("n").over(Window.orderBy("layer").rowsBetween(Window.unboundedPreceding, Window.currentRow)))  # q rows
    group = {
        "single": F.lit(1),
        "each": F.col("layer"),
        "equal_width": F.greatest(F.lit(1), F.least(F.lit(k), F.ceil(F.col("hi") * k / F.col("_top") - 1e-9))),
        "equal_depth": F.expr(f"least({k}L, (_cum - n) * {k} div _all + 1)"),
    }[how]
    ends = rows.withColumn("_g", group.cast("long")).groupBy("_g").agg(F.max("layer").alias("hi_layer"))
    bounds = ends.agg(F.concat(F.array(F.lit(0)), F.array_sort(F.collect_list("hi_layer"))).alias("bounds"))
    return _priced(_ranges(bounds), cost, layers)


@dataclass
class Optimised:
    """Every table on the way to the plan."""

    layers: DataFrame
    cells: DataFrame
    tested: DataFrame
    splits: DataFrame
    cost: DataFrame
    plan: DataFrame


def optimise(mo: DataFrame, p: OptimizerParams, keep=None) -> Optimised:
    """Layers, counts, trees, range costs and the cheapest plan.

    The objects are read for their greatest speed and for the counts by layer
    and finest cell. These are at most q * 4**depth rows: where that is few
    (``local.fits``), arrays in the driver do the rest. Else, or with ``keep``,
    DataFrames do, and ``keep`` is applied to the tables that are used more than
    once (they are written to the shared folder if it is None).
    """
    finest = quad.finest_counts(mo, p)
    if keep is None and local.fits(p):
        return _solved_here(mo.sparkSession, finest.toArrow(), p)
    return _from_counts((keep or kept)(finest), p, keep or kept)


def _solved_here(spark: SparkSession, table: pa.Table, p: OptimizerParams) -> Optimised:
    x = local.solve(table, p)
    layers, splits, cost, plan = (spark.createDataFrame(t) for t in (x.layers, x.splits, x.cost, x.plan))
    cells = quad.cells_of(spark.createDataFrame(table), p, layers)
    return Optimised(layers, cells, quad.uniformity(cells, p), splits, cost, plan)


def optimise_by(mo: DataFrame, p: OptimizerParams, by: str) -> dict[int, Optimised]:
    """A plan for each value of a column of few values, all from one count of the objects."""
    if not local.fits(p) or p.layering != "equal_width":
        return {r[0]: optimise(mo.where(F.col(by) == r[0]), p) for r in mo.select(by).distinct().orderBy(by).collect()}  # a row for each period
    table = quad.finest_counts(mo, p, by).toArrow()
    values = sorted(set(table.column(by).to_pylist()))
    return {v: _solved_here(mo.sparkSession, table.filter(pc.equal(table.column(by), v)).drop_columns([by]), p) for v in values}


def _from_counts(finest: DataFrame, p: OptimizerParams, keep, fraction: float = 1.0) -> Optimised:
    layers = keep(layers_of(finest, p))
    cells = keep(quad.cells_of(finest, p, layers))
    tested = quad.uniformity(cells, p)
    splits = keep(quad.split_cells(tested))
    scaled = cells if fraction == 1.0 else cells.withColumn("n", F.floor(F.col("n") / fraction + F.lit(0.5)).cast("long"))
    cost = keep(range_costs(scaled, splits, layers, p))
    return Optimised(layers, scaled, tested, splits, cost, optimal_plan(cost, layers))


def optimise_sampled(mo: DataFrame, p: OptimizerParams, fraction: float, seed: int = 7) -> Optimised:
    """The optimiser over a sample: the test sees raw sample counts, the costs counts that are scaled up."""
    return _from_counts(kept(quad.finest_counts(kept(mo.sample(False, fraction, seed)), p)), p, kept, fraction)
