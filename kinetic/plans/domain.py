"""Speed layers: the finite, ordered speed domain."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.functions.motion import valid
from kinetic.plans.params import OptimizerParams


def sums_of_speed() -> list[Column]:
    """What a layer needs of its objects: their number, the sum of their speeds in whole micro-units, and the greatest."""
    return [F.count(F.lit(1)).alias("n"), F.sum(F.floor(F.col("speed") * 1000000 + F.lit(0.5)).cast("long")).alias("sum"), F.max("speed").alias("most")]


def _summed(rows: DataFrame, representative: str) -> DataFrame:
    """edge, top (upper speed of the edge), width, n, sum, most -> layers without gaps: layer, edge, lo, hi, rep, n, width."""
    order = Window.orderBy("edge")  # at most q rows
    rep = F.col("most") if representative == "max" else F.col("sum") / 1000000 / F.col("n")
    return rows.select(
        F.row_number().over(order).alias("layer"), F.col("edge").cast("int").alias("edge"), F.coalesce(F.lag("top").over(order), F.lit(0.0)).alias("lo"), F.col("top").alias("hi"), rep.alias("rep"), "n", "width"
    )


def equal_width(mo: DataFrame, q: int, *by: str) -> DataFrame:
    """mo +edge 1..q, top, width: half-open layers (lo, hi] of one width up to the greatest speed (of each value of ``by``, which has few)."""
    top = mo.groupBy(*by).agg((F.max("speed") / q).alias("width"))
    rows = mo.join(F.broadcast(top), list(by)) if by else mo.crossJoin(F.broadcast(top))  # one row
    edge = F.when(F.col("width") > 0, F.least(F.lit(q), F.greatest(F.lit(1), F.ceil(F.col("speed") / F.when(F.col("width") > 0, F.col("width")))))).otherwise(1).cast("int")
    return rows.withColumn("edge", edge).withColumn("top", F.col("edge") * F.col("width"))


def equal_depth(mo: DataFrame, q: int, accuracy: int = 10000) -> DataFrame:
    """mo +edge, top: layers of about equal counts, from a quantile sketch."""
    shares = [i / q for i in range(1, q + 1)]
    cuts = mo.agg(F.array_sort(F.array_distinct(F.percentile_approx("speed", shares, accuracy))).alias("_cuts"))
    rows = mo.crossJoin(F.broadcast(cuts))
    edge = (F.size(F.filter("_cuts", lambda c: c < F.col("speed"))) + 1).cast("int")
    return rows.withColumn("edge", F.least(edge, F.size("_cuts"))).withColumn("top", F.element_at("_cuts", F.col("edge"))).withColumn("width", F.lit(0.0)).drop("_cuts")


def distinct_speeds(mo: DataFrame, q: int) -> DataFrame:
    """mo +edge, top: a layer for each speed that occurs (for sets with few speeds)."""
    speeds = mo.select("speed").distinct().withColumn("edge", F.dense_rank().over(Window.orderBy("speed"))).select(F.col("speed").alias("top"), "edge")
    return mo.join(F.broadcast(speeds), F.col("speed") == F.col("top")).withColumn("width", F.lit(0.0))


LAYERINGS = {"equal_width": equal_width, "equal_depth": equal_depth, "distinct": distinct_speeds}


def layered(mo: DataFrame, p: OptimizerParams, *by: str) -> DataFrame:
    return LAYERINGS[p.layering](valid(mo), p.q, *by)


def speed_layers(mo: DataFrame, p: OptimizerParams) -> DataFrame:
    """layer 1.., edge, lo, hi, rep, n, width; layers that no object is in are left out and the rest renumbered."""
    rows = layered(mo, p).groupBy("edge", "top", "width").agg(*sums_of_speed())
    return _summed(rows, p.representative)


def layers_of(finest: DataFrame, p: OptimizerParams) -> DataFrame:
    """The same layers from counts that are already there: edge, top, width, n, sum, most of every layer and cell."""
    return _summed(finest.groupBy("edge", "top", "width").agg(*[F.sum(c).alias(c) for c in ("n", "sum")], F.max("most").alias("most")), p.representative)


def kde_layers(layers: DataFrame, bandwidth: float) -> DataFrame:
    """+smooth: the histogram of the layers smoothed by a normal kernel over their middle speeds."""
    a = layers.withColumn("_m", (F.col("lo") + F.col("hi")) / 2)
    b = a.select(F.col("_m").alias("_o"), F.col("n").alias("_n"))
    z = (F.col("_m") - F.col("_o")) / bandwidth
    return a.crossJoin(F.broadcast(b)).withColumn("_w", F.exp(-z * z / 2)).groupBy("layer", "edge", "lo", "hi", "rep", "n").agg((F.sum(F.col("_w") * F.col("_n")) / F.sum("_w")).alias("smooth"))
