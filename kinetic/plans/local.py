"""What follows the count of objects, on arrays in the driver, for counts whose size is bounded by the parameters.

The same trees, tilings, costs and plan as the steps over DataFrames give; the
counts of q layers in 4**depth cells are all that it needs.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from kinetic.plans.expansion import cell_costs
from kinetic.plans.params import OptimizerParams

#: Counts up to so many rows may come to the driver (a few tens of MB).
MOST_CELLS = 1 << 20


def fits(p: OptimizerParams) -> bool:
    """The counts are bounded by the parameters and small; layers of distinct speeds have no bound."""
    return p.layering != "distinct" and p.q * 4**p.counted_depth <= MOST_CELLS


@dataclass
class Solved:
    """Tables of layers, splits, range costs and the cheapest plan."""

    layers: pa.Table
    splits: pa.Table
    cost: pa.Table
    plan: pa.Table


def _summed(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys and the sums of their values."""
    found, at = np.unique(keys, return_inverse=True)
    total = np.zeros(len(found), np.int64)
    np.add.at(total, at, values)
    return found, total


def _rough(cells: dict[int, tuple[np.ndarray, np.ndarray]], q: int, p: OptimizerParams) -> dict[int, np.ndarray]:
    """By level: keys (code * (q + 1) + layer) of the cells that a layer's tree splits."""
    down, bins, out = 1 if p.bins == 2 else 2, p.bins * p.bins, {}
    for level in range(p.max_depth):
        below, n = cells[level + down]
        code, layer = below // (q + 1) >> 2 * down, below % (q + 1)
        key, total = _summed(code * (q + 1) + layer, n)
        square = _summed(code * (q + 1) + layer, n * n)[1]
        stat = square * bins / total - total
        rough = key[(stat > p.critical) & (stat > total * p.effect)]
        if level:
            rough = rough[np.isin((rough // (q + 1) >> 2) * (q + 1) + rough % (q + 1), out[level - 1])]
        out[level] = rough
    return out


def _cuts(keys: np.ndarray, codes: np.ndarray, q: int) -> np.ndarray:
    """For each code how many of the layers 1..i split it, i = 0..q."""
    grid = np.zeros((len(codes), q + 1), np.int64)
    at = np.searchsorted(codes, keys // (q + 1))
    grid[at, keys % (q + 1)] = 1
    return grid.cumsum(1)


def solve(finest: pa.Table, p: OptimizerParams) -> Solved:
    """From the rows of ``finest_counts``."""
    got = {c: finest.column(c).to_numpy() for c in ("edge", "top", "width", "code", "n", "sum", "most")}
    edges, first, layer = np.unique(got["edge"], return_index=True, return_inverse=True)
    q, layer = len(edges), layer + 1
    n, total, most = np.zeros(q, np.int64), np.zeros(q, np.int64), np.full(q, -np.inf)
    np.add.at(n, layer - 1, got["n"])
    np.add.at(total, layer - 1, got["sum"])
    np.maximum.at(most, layer - 1, got["most"])
    hi = got["top"][first].astype(np.float64)
    lo = np.concatenate([[0.0], hi[:-1]])[:q]
    rep = most if p.representative == "max" else total / 1000000 / np.maximum(n, 1)
    ranks = np.arange(1, q + 1, dtype=np.int32)
    layers = pa.table({"layer": ranks, "edge": edges.astype(np.int32), "lo": lo, "hi": hi, "rep": rep, "n": n, "width": got["width"][first].astype(np.float64)})

    depth = p.counted_depth
    cells = {level: _summed((got["code"] >> 2 * (depth - level)) * (q + 1) + layer, got["n"]) for level in range(depth + 1)}
    splits = _rough(cells, q, p) if q else {}
    own, par, cum, level_of = [], [], [], []
    for level in range(p.max_depth + 1 if q else 0):
        above = splits.get(level - 1, np.zeros(0, np.int64))
        parents = np.unique(above // (q + 1))
        codes = (parents[:, None] * 4 + np.arange(4)).ravel() if level else np.zeros(1, np.int64)
        if not len(codes):
            break
        here = splits.get(level, np.zeros(0, np.int64))
        own.append(_cuts(here, codes, q))
        par.append(np.repeat(_cuts(above, parents, q), 4, axis=0) if level else np.arange(q + 1)[None, :])
        key, count = cells[level]
        inside = np.isin(key // (q + 1), codes)
        grid = np.zeros((len(codes), q + 1), np.int64)
        grid[np.searchsorted(codes, key[inside] // (q + 1)), key[inside] % (q + 1)] = count[inside]
        cum.append(grid.cumsum(1))
        level_of.append(np.full(len(codes), level))
    cut = [(int(k % (q + 1)), level, int(k // (q + 1))) for level, keys in splits.items() for k in keys]
    a, b, c = zip(*cut, strict=True) if cut else ((), (), ())
    split_table = pa.table({"layer": pa.array(a, pa.int32()), "level": pa.array(b, pa.int32()), "code": pa.array(c, pa.int64())})
    cost = _costs(np.concatenate(level_of), np.concatenate(own), np.concatenate(par), np.concatenate(cum), rep, p) if q else _costs(*[np.zeros((0, *s), np.int64) for s in ((), (1,), (1,), (1,))], rep, p)
    return Solved(layers, split_table, cost, _plan(cost, lo, hi, q))


def _costs(level: np.ndarray, own: np.ndarray, par: np.ndarray, cum: np.ndarray, rep: np.ndarray, p: OptimizerParams) -> pa.Table:
    out = cell_costs(level, own, par, cum, rep, p)
    s, r = np.triu_indices(len(out["one"]), 1)
    one, quad = out["one"][s, r], out["quad"][s, r]
    v = {"off": one, "on": quad, "part": np.minimum(one, quad), "region": out["region"][s, r], "speed": out["speed"][s, r]}[p.quadrant_grain]
    chosen = {"off": np.zeros(len(s)), "on": np.ones(len(s))}.get(p.quadrant_grain, quad < one)
    return pa.table({
        "s": s.astype(np.int32), "r": r.astype(np.int32), "n": out["n"][s, r].astype(np.int64), "regions": out["regions"][s, r].astype(np.int64), "v_one": one, "v_quad": quad, "v": v, "quadrants": chosen.astype(np.int32),
    })


def _plan(cost: pa.Table, lo: np.ndarray, hi: np.ndarray, q: int) -> pa.Table:
    """Least cost of the layers 1..r for each r; of equal ones the range that begins with the slowest layer."""
    v, quadrants = np.full((q + 1, q + 1), np.inf), np.zeros((q + 1, q + 1), np.int32)
    s, r = cost.column("s").to_numpy(), cost.column("r").to_numpy()
    v[s, r], quadrants[s, r] = cost.column("v").to_numpy(), cost.column("quadrants").to_numpy()
    best, last = np.zeros(q + 1), np.zeros(q + 1, np.int64)
    for k in range(1, q + 1):
        sums = best[:k] + v[:k, k]
        last[k] = sums.argmin()
        best[k] = sums[last[k]]
    bounds = [q] if q else []
    while bounds and bounds[0]:
        bounds.insert(0, int(last[bounds[0]]))
    a, b = np.array(bounds[:-1], np.int32), np.array(bounds[1:], np.int32)
    at = b - 1
    return pa.table({"part": np.arange(1, len(a) + 1, dtype=np.int32), "lo_layer": a, "hi_layer": b, "lo": lo[a] if q else lo, "hi": hi[at] if q else hi, "quadrants": quadrants[a, b], "cost": v[a, b]})
