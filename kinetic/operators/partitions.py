"""Routing of objects to parts, the layout of parts, their statistics, and the fan-out of queries."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.functions.motion import at_time, quadrant_of, valid
from kinetic.sources.shared import kept


def assign_parts(mo: DataFrame, plan: DataFrame) -> DataFrame:
    """+part, quadrant: the part whose (lo, hi] holds the speed; beyond the first and last edge the first and last part.

    The plan has at most as many rows as there are layers, and is broadcast;
    quadrant is 0 in parts that are not split by it. No shuffle.
    """
    ends = plan.agg(F.min("part").alias("_first"), F.max("part").alias("_last"))
    edges = plan.crossJoin(F.broadcast(ends)).select(
        "part", F.col("quadrants").alias("_split"), F.when(F.col("part") == F.col("_first"), F.lit(float("-inf"))).otherwise(F.col("lo")).alias("_lo"), F.when(F.col("part") == F.col("_last"), F.lit(float("inf"))).otherwise(F.col("hi")).alias("_hi")
    )
    rows = valid(mo.drop("part", "quadrant"))
    out = rows.join(F.broadcast(edges), (F.col("speed") > F.col("_lo")) & (F.col("speed") <= F.col("_hi")))
    return out.withColumn("quadrant", F.when(F.col("_split") == 1, quadrant_of()).otherwise(0)).drop("_split", "_lo", "_hi")


def single_part(mo: DataFrame, quadrants: bool = False) -> DataFrame:
    """No partitioning, with or without the split by quadrants."""
    return valid(mo).withColumn("part", F.lit(1)).withColumn("quadrant", quadrant_of() if quadrants else F.lit(0))


def part_stats(parted: DataFrame) -> DataFrame:
    """part, quadrant, n, vxlo, vxhi, vylo, vyhi, vmax, tlo, thi."""
    return parted.groupBy("part", "quadrant").agg(
        F.count(F.lit(1)).alias("n"), F.min("vx").alias("vxlo"), F.max("vx").alias("vxhi"), F.min("vy").alias("vylo"), F.max("vy").alias("vyhi"), F.max("speed").alias("vmax"), F.min("t_ref").alias("tlo"), F.max("t_ref").alias("thi")
    )


def fan_out(queries: DataFrame, stats: DataFrame) -> DataFrame:
    """Each range query once for each part, its window moved to the reference time by that part's own extreme velocities.

    A quadrant's velocities have one sign on each axis, so that its window
    grows on one side only.
    """
    q = queries.crossJoin(F.broadcast(stats))

    def low(edge: str, vmax: str) -> Column:
        return F.least(F.col(edge) - F.col(vmax) * (F.col("t") - F.col("tlo")), F.col(edge) - F.col(vmax) * (F.col("t") - F.col("thi")))

    def high(edge: str, vmin: str) -> Column:
        return F.greatest(F.col(edge) - F.col(vmin) * (F.col("t") - F.col("tlo")), F.col(edge) - F.col(vmin) * (F.col("t") - F.col("thi")))

    return q.select(
        "qid", "t", "xlo", "ylo", "xhi", "yhi", "part", "quadrant",
        low("xlo", "vxhi").alias("sxlo"), high("xhi", "vxlo").alias("sxhi"), low("ylo", "vyhi").alias("sylo"), high("yhi", "vylo").alias("syhi"),
    )


def inside() -> Column:
    """The object's place at the query's time lies in the query's window."""
    px, py = at_time(F.col("t")), at_time(F.col("t"), "y", "vy")
    return (px >= F.col("xlo")) & (px <= F.col("xhi")) & (py >= F.col("ylo")) & (py <= F.col("yhi"))


@dataclass
class LayoutInfo:
    path: str
    index: str
    stats: DataFrame


def write_layout(parted: DataFrame, path: str, index: str = "box", files: int = 8, mode: str = "overwrite") -> LayoutInfo:
    """Parquet by part and quadrant, clustered by the index's key inside, so that footers prune what a query reads."""
    from kinetic.operators.index_curve import curve_keys, z_code

    if index == "curve":
        rows, key = curve_keys(parted), ["label", "key"]
    else:
        rows = parted.withColumn("_key", z_code(F.least(F.lit(1023), F.greatest(F.lit(0), F.floor(F.col("x") / 10000 * 1024))).cast("long"), F.least(F.lit(1023), F.greatest(F.lit(0), F.floor(F.col("y") / 10000 * 1024))).cast("long"), 10))
        key = ["_key"]
    by = ["part", "quadrant", *key]
    rows.repartitionByRange(files, *by).sortWithinPartitions(*by).drop("_key").write.mode(mode).partitionBy("part", "quadrant").parquet(path)
    return LayoutInfo(path, index, part_stats(rows.sparkSession.read.parquet(path)))


def run_partitioned(queries: DataFrame, parted: DataFrame, fn: Callable[[DataFrame, DataFrame], DataFrame], mode: str = "single_plan") -> DataFrame:
    """Every query over every part, merged: one plan for all parts, or one for each part, concurrent (a union) or sequential (a table each)."""
    if mode == "single_plan":
        return fn(parted, queries)
    parts = [r["part"] for r in parted.select("part").distinct().orderBy("part").collect()]  # a row for each part
    out = None
    for part in parts:
        one = fn(parted.where(F.col("part") == part), queries)
        if mode == "sequential":
            one = kept(one)
        out = one if out is None else out.unionByName(one)
    return out if out is not None else fn(parted, queries)


def asof_plan(updates: DataFrame, plans: DataFrame) -> DataFrame:
    """updates (ts, ...) +plan_id: the newest plan valid at each update, from plans (valid_from, plan_id).

    The plans of one day are a row each; both streams of rows are merged by
    day, so that no window holds all updates. A plan of an earlier day is
    found through the newest plan at the start of each day.
    """
    day = F.date_trunc("day", F.col("ts"))
    days = updates.select(day.alias("_day")).distinct()
    starts = days.join(F.broadcast(plans), F.col("valid_from") <= F.col("_day")).groupBy("_day").agg(F.max_by("plan_id", "valid_from").alias("plan_id")).select("_day", F.col("_day").alias("ts"), "plan_id")
    changes = plans.select(F.date_trunc("day", "valid_from").alias("_day"), F.col("valid_from").alias("ts"), "plan_id")
    known = starts.unionByName(changes).withColumn("_new", F.lit(0))
    rows = updates.withColumn("_day", day).withColumn("_new", F.lit(1))
    w = Window.partitionBy("_day").orderBy("ts", "_new").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = rows.unionByName(known, allowMissingColumns=True).withColumn("plan_id", F.last("plan_id", ignorenulls=True).over(w))
    return both.where("_new = 1").drop("_day", "_new")
