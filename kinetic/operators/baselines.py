"""Rival partitioners: velocity seeds and dominant velocity axes. Each gives the same part and quadrant columns."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetic.functions.motion import valid


def _seed_distance(seed: tuple[float, float]) -> Column:
    dx, dy = F.col("vx") - F.lit(seed[0]), F.col("vy") - F.lit(seed[1])
    return dx * dx + dy * dy


def _nearest(distance: list[Column]) -> Column:
    """1-based number of the least of the distances, the first of equal ones."""
    out = F.lit(len(distance))
    least = F.least(*distance) if len(distance) > 1 else distance[0]
    for i in range(len(distance) - 1, 0, -1):
        out = F.when(distance[i - 1] == least, i).otherwise(out)
    return out


def spread_seeds(mo: DataFrame, k: int) -> list[tuple[float, float]]:
    """k velocities that span the velocity space: the extremes of both axes, then the farthest from all so far. k rows reach the driver."""
    rows = valid(mo)
    v = F.struct("vx", "vy")
    ends = rows.agg(*[F.max_by(v, F.struct(key, -F.col("oid"))).alias(f"e{i}") for i, key in enumerate((F.col("vx"), -F.col("vx"), F.col("vy"), -F.col("vy")))]).first()
    seeds = [tuple(e) for e in ends if e is not None][:k]
    while seeds and len(seeds) < k:
        far = F.least(*[_seed_distance(s) for s in seeds]) if len(seeds) > 1 else _seed_distance(seeds[0])
        seeds.append(tuple(rows.agg(F.max_by(v, F.struct(far, -F.col("oid"))).alias("e")).first()["e"]))
    return seeds


def refine_seeds(mo: DataFrame, seeds: list[tuple[float, float]], rounds: int) -> list[tuple[float, float]]:
    """Seeds moved to the mean velocity of their members; sums are of whole micro-units, so that no order of rows changes them."""
    rows = valid(mo)
    for _ in range(rounds):
        parts = rows.withColumn("part", _nearest([_seed_distance(s) for s in seeds])).groupBy("part").agg(*[F.sum(F.floor(F.col(c) * 1000000 + F.lit(0.5)).cast("long")).alias(c) for c in ("vx", "vy")], F.count(F.lit(1)).alias("n"))
        moved = {r["part"]: (r["vx"] / r["n"] / 1e6, r["vy"] / r["n"] / 1e6) for r in parts.collect()}
        new = [moved.get(i + 1, s) for i, s in enumerate(seeds)]
        if new == seeds:
            break
        seeds = new
    return seeds


def seed_router(mo: DataFrame, k: int = 5, refine: int = 0, how: str = "nearest") -> Callable[[DataFrame], DataFrame]:
    """A rule fitted to mo: +part, quadrant 0 of any objects.

    ``refine`` rounds move the seeds first. ``how``: nearest seed, or the part
    whose box of velocities (of its nearest members) grows least, the nearest of
    equal ones.
    """
    seeds = spread_seeds(mo, k)
    if not seeds:
        return lambda rows: valid(rows).withColumn("part", F.lit(1)).withColumn("quadrant", F.lit(0))
    seeds = refine_seeds(mo, seeds, refine)
    near = [_seed_distance(s) for s in seeds]
    rule = _nearest(near)
    if how == "enlargement":
        # boxes of the inner half of each seed's members: where objects in between go is what the rule decides
        rows = valid(mo).withColumn("part", rule).withColumn("d", F.least(*near) if len(near) > 1 else near[0])
        half = rows.groupBy("part").agg(F.percentile_approx("d", 0.5, 1000).alias("cut"))
        inner = rows.join(F.broadcast(half), "part").where("d <= cut").groupBy("part").agg(F.min("vx").alias("x0"), F.max("vx").alias("x1"), F.min("vy").alias("y0"), F.max("vy").alias("y1"))
        boxes = {r["part"]: (r["x0"], r["x1"], r["y0"], r["y1"]) for r in inner.collect()}  # k rows
        growth = []
        for i, (x, y) in enumerate(seeds, 1):
            x0, x1, y0, y1 = boxes.get(i, (x, x, y, y))
            wide = F.greatest(F.lit(x1), F.col("vx")) - F.least(F.lit(x0), F.col("vx"))
            high = F.greatest(F.lit(y1), F.col("vy")) - F.least(F.lit(y0), F.col("vy"))
            growth.append(F.struct((wide * high - F.lit((x1 - x0) * (y1 - y0))).alias("g"), near[i - 1].alias("d"), F.lit(i).alias("part")))
        rule = F.least(*growth)["part"] if len(growth) > 1 else F.lit(1)
    return lambda rows: valid(rows).withColumn("part", rule).withColumn("quadrant", F.lit(0))


def seed_parts(mo: DataFrame, k: int = 5, refine: int = 0, how: str = "nearest") -> DataFrame:
    """+part, quadrant 0: mo under the rule that is fitted to it."""
    return seed_router(mo, k, refine, how)(mo)


def _axis_distance(axis: tuple[float, float]) -> Column:
    return F.abs(F.col("vx") * F.lit(axis[1]) - F.col("vy") * F.lit(axis[0]))


def leading_axis(sxx: float, sxy: float, syy: float, before: tuple[float, float]) -> tuple[float, float]:
    """Unit eigenvector of the larger eigenvalue of [[sxx, sxy], [sxy, syy]]."""
    half = (sxx - syy) / 2
    top = (sxx + syy) / 2 + math.sqrt(half * half + sxy * sxy)
    a, b = (sxy, top - sxx) if sxx < syy else (top - syy, sxy)
    size = math.sqrt(a * a + b * b)
    return (a / size, b / size) if size > 0 else before


def dominant_axes(mo: DataFrame, axes: int = 2, rounds: int = 10) -> list[tuple[float, float]]:
    """Axes through the origin, each fitted to the velocities nearest to it; ``axes`` rows reach the driver in each round."""
    start = [(1.0, 0.0), (0.0, 1.0), (math.sqrt(0.5), math.sqrt(0.5)), (math.sqrt(0.5), -math.sqrt(0.5))][:axes]
    rows = valid(mo)

    def milli(c: Column) -> Column:
        return F.sum(F.floor(c * 1000 + F.lit(0.5)).cast("long"))

    for _ in range(rounds):
        sums = rows.withColumn("part", _nearest([_axis_distance(a) for a in start])).groupBy("part").agg(milli(F.col("vx") * F.col("vx")).alias("xx"), milli(F.col("vx") * F.col("vy")).alias("xy"), milli(F.col("vy") * F.col("vy")).alias("yy"))
        got = {r["part"]: r for r in sums.collect()}
        new = [leading_axis(got[i + 1]["xx"] / 1e3, got[i + 1]["xy"] / 1e3, got[i + 1]["yy"] / 1e3, a) if i + 1 in got else a for i, a in enumerate(start)]
        if all(abs(p - q) < 1e-12 for a, b in zip(start, new, strict=True) for p, q in zip(a, b, strict=True)):
            return new
        start = new
    return start


def axis_router(mo: DataFrame, axes: int = 2, outliers: bool = True, rounds: int = 10, share: float = 0.9, rotate: bool = False) -> Callable[[DataFrame], DataFrame]:
    """A rule fitted to mo: +part, quadrant 0 of any objects. Each goes to its nearest axis; those farther than nine tenths are from theirs form the last part.

    The distance that parts them comes from counts by tenths of a unit.
    ``rotate`` adds rx, ry, rvx, rvy: place and velocity along the part's axis.
    """
    fitted = dominant_axes(mo, axes, rounds)
    near = [_axis_distance(a) for a in fitted]
    rule, least = _nearest(near), F.least(*near) if len(near) > 1 else near[0]
    if outliers:
        hist = [(r["b"], r["n"]) for r in valid(mo).groupBy(F.floor(least * 10).cast("long").alias("b")).agg(F.count(F.lit(1)).alias("n")).orderBy("b").collect()]  # as many rows as the top speed has tenths
        total, seen, cut = sum(n for _, n in hist), 0, math.inf
        for b, n in hist:
            seen += n
            if seen >= share * total:
                cut = (b + 1) / 10
                break
        rule = F.when(least > cut, F.lit(axes + 1)).otherwise(rule)

    def route(rows: DataFrame) -> DataFrame:
        out = valid(rows).withColumn("part", rule).withColumn("quadrant", F.lit(0))
        if rotate:
            ax, ay = (F.element_at(F.array(*[F.lit(a[i]) for a in fitted], F.lit(1.0 - i)), F.least(F.col("part"), F.lit(len(fitted) + 1))) for i in (0, 1))
            for name, (p, q) in {"rx": ("x", "y"), "rvx": ("vx", "vy")}.items():
                out = out.withColumn(name, F.col(p) * ax + F.col(q) * ay).withColumn(name.replace("x", "y"), F.col(q) * ax - F.col(p) * ay)
        return out

    return route


def axis_parts(mo: DataFrame, axes: int = 2, outliers: bool = True, rounds: int = 10, share: float = 0.9, rotate: bool = False) -> DataFrame:
    """+part, quadrant 0: mo under the rule that is fitted to it."""
    return axis_router(mo, axes, outliers, rounds, share, rotate)(mo)
