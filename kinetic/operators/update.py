"""Object updates, migration between parts, and re-optimisation by the hour."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetic.functions.motion import latest_status
from kinetic.operators.partitions import assign_parts
from kinetic.plans.optimise import Optimised, optimise_by
from kinetic.plans.params import OptimizerParams

STATE = ["x", "y", "vx", "vy", "speed", "t_ref", "ts", "event_id"]


def apply_updates(state: DataFrame, updates: DataFrame, plan: DataFrame | Callable[[DataFrame], DataFrame]) -> tuple[DataFrame, DataFrame]:
    """(new state, moves): the newest status of each object wins; a move tells what happens to each updated object.

    ``plan``: speed ranges, or the rule of another partitioner. Actions: insert (unknown object), update (same part), migrate (delete and
    insert), late (older than what is known: dropped). Part and quadrant
    together name the place.
    """
    route = plan if callable(plan) else lambda rows: assign_parts(rows, plan)
    new = route(latest_status(updates, columns=STATE))
    old = route(state.select("oid", *STATE))
    o = old.select("oid", *[F.col(c).alias(f"o_{c}") for c in [*STATE, "part", "quadrant"]])
    both = o.join(new, "oid", "full_outer")
    newer = F.col("o_ts").isNull() | (F.struct("ts", "event_id") > F.struct("o_ts", "o_event_id"))
    take = F.col("ts").isNotNull() & newer
    action = (
        F.when(F.col("ts").isNull(), None).when(F.col("o_ts").isNull(), "insert").when(~newer, "late").when((F.col("part") == F.col("o_part")) & (F.col("quadrant") == F.col("o_quadrant")), "update").otherwise("migrate")
    )
    after = both.select("oid", *[F.when(take, F.col(c)).otherwise(F.col(f"o_{c}")).alias(c) for c in [*STATE, "part", "quadrant"]])
    moves = both.withColumn("action", action).where("action IS NOT NULL").select("oid", F.col("o_part").alias("old_part"), F.col("part").alias("new_part"), F.col("o_quadrant").alias("old_quadrant"), F.col("quadrant").alias("new_quadrant"), "action")
    return after, moves


def migrate(mo: DataFrame, old_plan: DataFrame, new_plan: DataFrame) -> DataFrame:
    """oid, old_part, new_part of the objects whose place changes with the plan."""
    a = assign_parts(mo, old_plan).withColumnRenamed("part", "old_part").withColumnRenamed("quadrant", "old_quadrant")
    rows = assign_parts(a, new_plan)
    return rows.where("old_part <> part OR old_quadrant <> quadrant").select("oid", "old_part", F.col("part").alias("new_part"), "old_quadrant", F.col("quadrant").alias("new_quadrant"))


def commit(parted: DataFrame, path: str, generation: int) -> None:
    """One more generation of a log-structured layout: only the rows that changed, by part."""
    parted.write.mode("append").partitionBy("part", "quadrant").parquet(f"{path}/gen={generation}")


def current(spark, path: str) -> DataFrame:
    """Newest row of each object over all generations."""
    rows = spark.read.option("basePath", path).parquet(path)
    rest = [c for c in rows.columns if c not in ("oid",)]
    return rows.groupBy("oid").agg(F.max_by(F.struct(*rest), F.struct("gen", "ts", "event_id")).alias("_s")).select("oid", "_s.*")


def compact(spark, path: str, out: str) -> None:
    """All generations as one."""
    commit(current(spark, path).drop("gen"), out, 0)


def refresh_plan(rows: DataFrame, p: OptimizerParams, period: str = "hr") -> dict[int, Optimised]:
    """An optimised plan for each value of the period column (the hours of a day), from one count of all rows."""
    return optimise_by(rows, p, period)


def plans_by(plans: dict[int, Optimised], period: str = "hr") -> DataFrame:
    """period, part, lo_layer, hi_layer, lo, hi, quadrants, cost: the plans of all periods as one table."""
    out = None
    for value, x in sorted(plans.items()):
        one = x.plan.withColumn(period, F.lit(value))
        out = one if out is None else out.unionByName(one)
    return out


def plan_cost(plan: DataFrame, cost: DataFrame, layers: DataFrame, new_layers: DataFrame) -> DataFrame:
    """Cost of an older plan's boundaries under the costs of a new histogram: boundaries go to the new layer that ends nearest below or at them."""
    edges = new_layers.agg(F.array_sort(F.collect_list("hi")).alias("_e"))
    at = F.size(F.filter("_e", lambda e: e <= F.col("hi") + 1e-9))
    bounds = plan.crossJoin(F.broadcast(edges)).agg(F.array_sort(F.array_distinct(F.collect_list(F.when(F.col("hi") >= F.array_max("_e"), F.size("_e")).otherwise(at)))).alias("_b"), F.max(F.size("_e")).alias("_q"))
    bounds = bounds.select(F.expr("array_sort(array_distinct(concat(array(0), _b, array(_q))))").alias("_b"))
    pairs = bounds.select(F.explode(F.expr("transform(sequence(1, size(_b) - 1), i -> named_struct('s', _b[i - 1], 'r', _b[i]))")).alias("_x")).select("_x.*")
    return pairs.join(F.broadcast(cost), ["s", "r"]).agg(F.sum("v").alias("cost"))


def needs_refresh(old: Optimised, new: Optimised, threshold: float = 0.1) -> DataFrame:
    """regret, refresh: how much dearer the old boundaries are under the new histogram than the new optimum."""
    kept = plan_cost(old.plan, new.cost, old.layers, new.layers).select(F.col("cost").alias("kept"))
    best = new.plan.agg(F.sum("cost").alias("best"))
    return kept.crossJoin(best).select("kept", "best", (F.col("kept") / F.col("best") - 1).alias("regret"), (F.col("kept") / F.col("best") - 1 > threshold).cast("int").alias("refresh"))
