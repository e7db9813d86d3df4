"""Linear motion: position at a time, speed, quadrant, velocity from samples, latest status."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def valid(mo: DataFrame) -> DataFrame:
    """Without rows whose position or velocity is null or not a number."""
    cond = F.lit(True)
    for c in ("x", "y", "vx", "vy", "speed"):
        cond = cond & F.col(c).isNotNull() & ~F.isnan(c)
    return mo.where(cond)


def at_time(t: Column, p: str = "x", v: str = "vx", t_ref: str = "t_ref") -> Column:
    return F.col(p) + F.col(v) * (t - F.col(t_ref))


def position_at(mo: DataFrame, t: float) -> DataFrame:
    """+px, py: where each object is at time t."""
    return mo.withColumns({"px": at_time(F.lit(float(t))), "py": at_time(F.lit(float(t)), "y", "vy")})


def with_speed(mo: DataFrame) -> DataFrame:
    return mo.withColumn("speed", F.sqrt(F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy")))


def quadrant_of() -> Column:
    """0 to 3 by the signs of the velocity."""
    return F.when(F.col("vx") >= 0, 2).otherwise(0) + F.when(F.col("vy") >= 0, 1).otherwise(0)


def with_quadrant(mo: DataFrame) -> DataFrame:
    return mo.withColumn("quadrant", quadrant_of())


def velocity_from_samples(samples: DataFrame, longest_gap: float | None = None) -> DataFrame:
    """(oid, ts, event_id, x, y) -> +gap seconds, vx, vy against the sample before; null for the first, at no or too long a gap."""
    w = Window.partitionBy("oid").orderBy("ts", "event_id")
    gap = (F.unix_micros("ts") - F.lag(F.unix_micros("ts")).over(w)) / 1000000
    out = samples.withColumns({"gap": gap, "_x": F.lag("x").over(w), "_y": F.lag("y").over(w)})
    usable = (F.col("gap") > 0) if longest_gap is None else (F.col("gap") > 0) & (F.col("gap") <= longest_gap)
    return out.withColumns({"vx": F.when(usable, (F.col("x") - F.col("_x")) / F.col("gap")), "vy": F.when(usable, (F.col("y") - F.col("_y")) / F.col("gap"))}).drop("_x", "_y")


def latest_status(updates: DataFrame, key: str = "oid", columns: list[str] | None = None) -> DataFrame:
    """The newest row of each object (ties: the larger event id), by a partial aggregate."""
    columns = columns or [c for c in updates.columns if c != key]
    row = F.max_by(F.struct(*columns), F.struct("ts", "event_id")).alias("_s")
    return updates.groupBy(key).agg(row).select(key, *[F.col(f"_s.{c}").alias(c) for c in columns])
