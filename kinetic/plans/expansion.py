"""How much search space the nodes of an index sweep, estimated from counts.

A node of c objects in a region of N spread evenly has a side of
D sqrt(c / N); it grows at the speed of its fastest member, whose distribution
follows from the counts by speed. Integrals over the horizon need only the
first two moments of that speed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetic.plans.params import OptimizerParams
from kinetic.plans.quad import candidate_cells, layer_counts

#: Up to this count logarithms of factorials come from a table of fixed size; beyond it from sums over the node's capacity.
TABLE_COUNT = 1 << 17


def node_side(side: Column, count: Column, capacity: int) -> Column:
    return side * F.sqrt(F.least(F.lit(capacity), count) / count)


def node_cost(d: Column, v: Column, t: float) -> Column:
    """Integral of (d + 2 v t)^2 over 0..t: a node that grows on all sides."""
    return d * d * t + 2 * d * v * t * t + F.lit(4.0) / 3 * v * v * t * t * t


def node_cost_quadrant(d: Column, v: Column, t: float) -> Column:
    """Integral of (2 d + v t)^2 over 0..t: a node of one velocity quadrant grows on two sides only."""
    return 4 * d * d * t + 2 * d * v * t * t + F.lit(1.0) / 3 * v * v * t * t * t


def quadrants_win(d: Column, v: Column, t: float) -> Column:
    """Exactly where node_cost_quadrant < node_cost: v t > sqrt(3) d."""
    return v * t > F.sqrt(F.lit(3.0)) * d


def log_falling(h: Column, capacity: int) -> Column:
    """ln of h (h-1) ... (h-c+1) for h >= c, term by term."""
    return F.aggregate(F.sequence(F.lit(0), F.lit(capacity - 1)), F.lit(0.0), lambda a, i: a + F.ln((h - i).cast("double")))


def node_max_prob(counts: DataFrame, capacity: int, by: list[str]) -> DataFrame:
    """+total, before, cum, prob: probability that a node's fastest member is in each layer.

    ``counts``: by, layer, n. With fewer than ``capacity`` objects the node
    holds them all.
    """
    from kinetic.plans.quad import cumulative_window

    whole = counts.groupBy(*by).agg(F.sum("n").alias("total"))
    rows = counts.withColumn("cum", F.sum("n").over(cumulative_window(by, "layer"))).withColumn("before", F.col("cum") - F.col("n")).join(whole, by)

    def share(h: str) -> Column:
        c = F.least(F.lit(capacity), F.col("total")).cast("int")
        ratio = F.aggregate(F.sequence(F.lit(0), c - 1), F.lit(0.0), lambda a, i: a + F.ln((F.col(h) - i) / (F.col("total") - i)))
        return F.when(F.col(h) < c, 0.0).otherwise(F.exp(ratio))

    return rows.withColumn("prob", share("cum") - F.when(F.col("before") > 0, share("before")).otherwise(0.0))


_log_factorials: np.ndarray | None = None


def log_factorials() -> np.ndarray:
    """ln n! for n = 0..TABLE_COUNT, made once in a process."""
    global _log_factorials
    if _log_factorials is None:
        _log_factorials = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, TABLE_COUNT + 1, dtype=np.float64)))])
    return _log_factorials


def falling_ratio(below: np.ndarray, upto: np.ndarray, c: int) -> np.ndarray:
    """C(below, c) / C(upto, c) for upto > c; 0 where below < c.

    Each element is worked out by its own counts, whatever else is in the arrays.
    """
    out = np.zeros(len(below))
    few = (below >= c) & (upto <= TABLE_COUNT)
    many = (below >= c) & (upto > TABLE_COUNT)
    if few.any():
        t, b, u = log_factorials(), below[few], upto[few]
        out[few] = np.exp((t[b] - t[b - c]) - (t[u] - t[u - c]))
    if many.any():
        b, u, log = below[many], upto[many], np.zeros(int(many.sum()))
        for i in range(c):
            log += np.log1p((b - u) / (u - i))
        out[many] = np.exp(log)
    return out


def _nodes(n: np.ndarray, p: OptimizerParams) -> np.ndarray:
    x = n / p.capacity
    return {"ceil": np.ceil, "floor": np.floor, "round": lambda v: np.floor(v + 0.5), "exact": lambda v: v}[p.node_rounding](x)


def cell_costs(level: np.ndarray, own: np.ndarray, par: np.ndarray, cum: np.ndarray, speeds: np.ndarray, p: OptimizerParams) -> dict[str, np.ndarray]:
    """Costs of every range (s, r] summed over the given cells; arrays of (q+1) x (q+1).

    Follows the distribution of a node's fastest member as layers are added:
    what was there before keeps the share C(before, c) / C(now, c).
    """
    q, t, c = cum.shape[1] - 1, p.horizon, p.capacity
    out = {k: np.zeros((q + 1, q + 1)) for k in ("one", "quad", "region", "speed", "n", "regions")}
    side = p.side / 2.0**level
    for s in range(q):
        prob = np.zeros((len(cum), q))
        for r in range(s + 1, q + 1):
            n, before = cum[:, r] - cum[:, s], cum[:, r - 1] - cum[:, s]
            grown = n > before
            keep = np.where(n > c, falling_ratio(before, n, c), 0.0)
            keep = np.where(grown, keep, 1.0)
            prob *= keep[:, None]
            prob[:, r - 1] = np.where(grown, 1 - keep, 0.0)
            here = (own[:, r] == own[:, s]) & (par[:, r] > par[:, s])
            out["regions"][s, r] = here.sum()
            use = here & (n > 0)
            if not use.any():
                continue
            k, m, big, ps = _nodes(n[use], p), n[use], side[use], prob[use]
            d = big * np.sqrt(np.minimum(c, m) / m)
            d4 = np.minimum(2 * d, big) if p.clamp_quadrant else 2 * d
            e1, e2 = ps @ speeds, ps @ (speeds * speeds)
            one = k * (d * d * t + 2 * d * e1 * t * t + 4 / 3 * e2 * t**3)
            quad = k * (d4 * d4 * t + d4 * e1 * t * t + e2 * t**3 / 3)
            out["one"][s, r], out["quad"][s, r], out["n"][s, r] = one.sum(), quad.sum(), m.sum()
            out["region"][s, r] = np.minimum(one, quad).sum()
            if p.quadrant_grain == "speed":
                a = d[:, None] ** 2 * t + 2 * d[:, None] * speeds * t * t + 4 / 3 * speeds**2 * t**3
                b = d4[:, None] ** 2 * t + d4[:, None] * speeds * t * t + speeds**2 * t**3 / 3
                out["speed"][s, r] = (k * (ps * np.minimum(a, b)).sum(1)).sum()
    return out


def range_costs(cells: DataFrame, splits: DataFrame, layers: DataFrame, p: OptimizerParams) -> DataFrame:
    """s, r, n, regions, v_one, v_quad, v, quadrants for every contiguous range of layers.

    One row a cell goes through the kernel; what leaves it is a row for each
    range and task.
    """
    every = candidate_cells(splits, layers).join(layer_counts(cells, layers), ["level", "code"], "left")
    speeds = layers.agg(F.transform(F.array_sort(F.collect_list(F.struct("layer", "rep"))), lambda x: x["rep"]).alias("reps"))
    every = every.crossJoin(F.broadcast(speeds)).select("level", "own", "par", F.coalesce("cum", F.expr("transform(own, x -> 0L)")).alias("cum"), "reps")
    every = every.repartition(max(1, every.sparkSession.sparkContext.defaultParallelism), "level", "code")  # a few thousand cells, each worth q * q steps

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [b for b in batches if b.num_rows]
        if not tables:
            return
        t = pa.Table.from_batches(tables)
        grid = {c: np.array(t.column(c).to_pylist()) for c in ("level", "own", "par", "cum")}
        out = cell_costs(grid["level"], grid["own"], grid["par"], grid["cum"].astype(np.int64), np.array(t.column("reps")[0].as_py()), p)
        s, r = np.triu_indices(len(out["one"]), 1)
        names = ["s", "r", "n", "regions", "v_one", "v_quad", "v_region", "v_speed"]
        arrays = [s.astype(np.int32), r.astype(np.int32), out["n"][s, r].astype(np.int64), out["regions"][s, r].astype(np.int64), *(out[k][s, r] for k in ("one", "quad", "region", "speed"))]
        yield pa.RecordBatch.from_arrays([pa.array(a) for a in arrays], names=names)

    parts = every.mapInArrow(run, "s int, r int, n long, regions long, v_one double, v_quad double, v_region double, v_speed double")
    total = parts.groupBy("s", "r").agg(*[F.sum(c).alias(c) for c in ("n", "regions", "v_one", "v_quad", "v_region", "v_speed")])
    quad = F.col("v_quad") < F.col("v_one")
    v = {"off": F.col("v_one"), "on": F.col("v_quad"), "part": F.least("v_one", "v_quad"), "region": F.col("v_region"), "speed": F.col("v_speed")}[p.quadrant_grain]
    chosen = {"off": F.lit(0), "on": F.lit(1)}.get(p.quadrant_grain, quad.cast("int"))
    return total.select("s", "r", "n", "regions", "v_one", "v_quad", v.alias("v"), chosen.alias("quadrants"))


def measured_expansion(nodes: DataFrame, horizon: float) -> DataFrame:
    """+swept: integral over the horizon of the area of each real node box."""
    wx, wy, gx, gy = F.col("xhi") - F.col("xlo"), F.col("yhi") - F.col("ylo"), F.col("vxhi") - F.col("vxlo"), F.col("vyhi") - F.col("vylo")
    t = horizon
    return nodes.withColumn("swept", wx * wy * t + (wx * gy + wy * gx) * (t * t / 2) + gx * gy * (t**3 / 3))
