"""Traffic on a road network: junctions, segments, and vehicles that drive leg by leg.

A vehicle starts anywhere on a segment, drives at a speed that is about normal
round the mean of the segment's class (deviation 10), may stop at the crossroads
with one chance in four, and turns into a segment picked by modular arithmetic;
legs are steps over arrays of vehicles, no driver loop.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetic.sources.standins import read

MEANS = {1: 30.0, 2: 18.0, 3: 9.0}


def junctions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, x, y of the 25 crossroads."""
    return read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("int").alias("id"), (1000 + 2000 * (F.col("n_nationkey") % 5)).cast("double").alias("x"), (1000 + 2000 * F.expr("n_nationkey div 5")).cast("double").alias("y"))


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, a, b, len, class, mu of the roads between neighbours on the grid."""
    a, b = junctions(spark, sf_dir).alias("a"), junctions(spark, sf_dir).alias("b")
    near = (F.abs(F.col("a.x") - F.col("b.x")) + F.abs(F.col("a.y") - F.col("b.y"))) == 2000
    rows = a.join(F.broadcast(b), near & (F.col("a.id") < F.col("b.id"))).select(F.col("a.id").alias("a"), F.col("b.id").alias("b"), F.lit(2000.0).alias("len"))
    m = (F.col("a") + F.col("b")) % 5
    rows = rows.withColumn("class", F.when(m == 0, 1).when(m <= 2, 2).otherwise(3))
    mu = F.when(F.col("class") == 1, MEANS[1]).when(F.col("class") == 2, MEANS[2]).otherwise(MEANS[3])
    return rows.withColumn("mu", mu).withColumn("id", F.col("a") * 25 + F.col("b")).select("id", "a", "b", "len", "class", "mu")


LEGS = "oid long, leg int, t0 double, t1 double, x double, y double, vx double, vy double, speed double, stopped int"


def driven(oid: np.ndarray, at: np.ndarray, known: np.ndarray, seconds: float, legs: int) -> Iterator[pa.RecordBatch]:
    """The legs of vehicles that start at the crossroads ``at``, of which some are not known: their places are null."""
    t, mod = np.zeros(len(oid)), np.fmod  # remainders have the sign of what is divided
    for i in range(1, legs + 1):
        way = mod(oid * 31 + i * 17 + at * 7, 4)
        rest = np.where(mod(oid * 13 + i * 29, 4) == 0, mod(oid * 7 + i * 3, 20), 0).astype(np.float64) if i > 1 else np.zeros(len(oid))
        noise = 10 * 1.7320508075688772 * (mod(oid * 37 + i * 101, 997) / 997 + mod(oid * 61 + i * 211, 991) / 991 + mod(oid * 13 + i * 307, 983) / 983 + mod(oid * 89 + i * 401, 977) / 977 - 2)
        done = mod(oid * 71 + 17, 1009) / 1009 if i == 1 else np.zeros(len(oid))
        col, row = mod(at, 5), (at - mod(at, 5)) // 5
        way = np.where(known, way, -1)
        to = np.select([way == 0, way == 1, way == 2], [np.where(col < 4, at + 1, at - 1), np.where(col > 0, at - 1, at + 1), np.where(at < 20, at + 5, at - 5)], np.where(at >= 5, at - 5, at + 5))
        road = np.where(known, mod(at + to, 5), -1)
        speed = np.maximum(0.5, np.select([road == 0, road == 1, road == 2], [MEANS[1], MEANS[2], MEANS[2]], MEANS[3]) + noise)
        east, south = mod(to, 5) - col, (to - mod(to, 5)) // 5 - row
        off = t + rest
        end = off + 2000.0 * (1 - done) / speed
        x, y, none = 1000.0 + 2000.0 * col, 1000.0 + 2000.0 * row, np.zeros(len(oid))
        for stopped, (t0, t1, *moving) in ((1, (t, off, x, y, none, none, none)), (0, (off, end, x + 2000.0 * done * east, y + 2000.0 * done * south, speed * east, speed * south, speed))):
            here = (t0 < seconds) & (t1 > t0)
            n, lost = int(here.sum()), ~known[here]
            places = [pa.array(c[here], mask=lost if k < (2 if stopped else 4) else None) for k, c in enumerate(moving)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(oid[here]), pa.array(np.full(n, 2 * i - stopped, np.int32)), pa.array(t0[here]), pa.array(np.minimum(t1[here], seconds)), *places, pa.array(np.full(n, stopped, np.int32))],
                names=["oid", "leg", "t0", "t1", "x", "y", "vx", "vy", "speed", "stopped"],
            )
        t = end
        go = t < seconds  # others have no leg any more
        oid, at, known, t = oid[go], np.where(known, to, at)[go], known[go], t[go]


def traffic(spark: SparkSession, sf_dir: str, seconds: float = 120.0, legs: int = 8) -> DataFrame:
    """oid, leg, t0, t1, x, y, vx, vy, speed, stopped: what each vehicle (an order) does until ``seconds`` are over.

    Speeds add four even draws, which have the deviation of a normal one; the
    first leg begins at a share of its segment.
    """
    start = read(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("oid"), F.expr("cast(o_custkey % 25 as long)").alias("at")).where("oid IS NOT NULL")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield from driven(b.column("oid").to_numpy(), b.column("at").fill_null(0).to_numpy(), b.column("at").is_valid().to_numpy(zero_copy_only=False), seconds, legs)

    return start.mapInArrow(run, LEGS)


def traffic_at(legs: DataFrame, t: float) -> DataFrame:
    """Moving objects as they are known at time t: place, velocity and reference time of the leg under way."""
    now = legs.where((F.col("t0") <= t) & (F.col("t1") > t))
    return now.select("oid", (F.col("x") + F.col("vx") * (F.lit(t) - F.col("t0"))).alias("x"), (F.col("y") + F.col("vy") * (F.lit(t) - F.col("t0"))).alias("y"), "vx", "vy", "speed", F.lit(float(t)).alias("t_ref"))
