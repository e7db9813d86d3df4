"""Curve-keyed index: objects projected to the next label time, gridded, keyed by a space-filling curve."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.sources.shared import kept

BITS, PHASES, PERIOD, SIDE = 6, 2, 120.0, 10000.0
#: Low bits of a key that do not count for the join's prefix.
PREFIX = 6
#: Turns of the Hilbert curve: by state and quadrant (x bit, y bit), the rank of the quadrant and the next state (fixed values).
HILBERT_RANK = ((0, 1, 3, 2), (0, 3, 1, 2), (2, 1, 3, 0), (2, 3, 1, 0))
HILBERT_NEXT = ((1, 0, 2, 0), (0, 3, 1, 1), (2, 2, 0, 3), (3, 1, 3, 2))


def z_code(gx: Column, gy: Column, bits: int) -> Column:
    """Morton code: the bits of both coordinates in turn, x lowest."""
    code = F.lit(0).cast("long")
    for i in range(bits):
        code = code.bitwiseOR(F.shiftleft(F.shiftright(gx, i).bitwiseAND(F.lit(1)), 2 * i)).bitwiseOR(F.shiftleft(F.shiftright(gy, i).bitwiseAND(F.lit(1)), 2 * i + 1))
    return code


def hilbert_code(gx: Column, gy: Column, bits: int) -> Column:
    """Hilbert code, from the highest bit down: four states, each with the ranks of its quadrants."""
    rank = F.array(*[F.lit(v) for row in HILBERT_RANK for v in row])
    turn = F.array(*[F.lit(v) for row in HILBERT_NEXT for v in row])

    def step(a: Column, i: Column) -> Column:
        # shifts by a column: halving by a power of two
        place = F.pow(F.lit(2.0), i).cast("long")
        at = (a["state"] * 4 + (F.floor(gx / place) % 2) * 2 + F.floor(gy / place) % 2 + 1).cast("int")
        return F.struct((a["code"] * 4 + F.element_at(rank, at)).cast("long").alias("code"), F.element_at(turn, at).cast("int").alias("state"))

    start = F.struct(F.lit(0).cast("long").alias("code"), F.lit(0).cast("int").alias("state"))
    return F.aggregate(F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1)), start, step, lambda a: a["code"])


CURVES = {"z": z_code, "hilbert": hilbert_code}


def grid(c: Column, bits: int) -> Column:
    cells = 1 << bits
    return F.least(F.lit(cells - 1), F.greatest(F.lit(0), F.floor(c / SIDE * cells))).cast("long")


def label_of(t_ref: Column, phases: int = PHASES, period: float = PERIOD) -> Column:
    """Number of the label time after the reference time; label l stands for l * period / phases."""
    return (F.floor(t_ref / (period / phases)) + 1).cast("int")


def curve_keys(parted: DataFrame, bits: int = BITS, curve: str = "z", phases: int = PHASES, period: float = PERIOD) -> DataFrame:
    """+label, key: the curve's code of the cell at the label time."""
    rows = parted.withColumn("label", label_of(F.col("t_ref"), phases, period))
    at = F.col("label") * (period / phases) - F.col("t_ref")
    return rows.withColumn("key", CURVES[curve](grid(F.col("x") + F.col("vx") * at, bits), grid(F.col("y") + F.col("vy") * at, bits), bits))


def covers(queries: DataFrame, stats: DataFrame, bits: int = BITS, phases: int = PHASES, period: float = PERIOD) -> DataFrame:
    """qid, part, quadrant, label, _rect: the cells that cover each query's window, moved to the label time by the part's own velocities.

    A rectangle of cells is one number, ``bits`` for each of its edges. ``stats``: part, quadrant, label and the extreme velocities.
    """
    q = queries.crossJoin(F.broadcast(stats))
    back = F.col("label") * (period / phases) - F.col("t")
    edges = [grid(F.col(f"{a}{e}") + pick(F.col(f"v{a}lo") * back, F.col(f"v{a}hi") * back), bits) for a in "xy" for e, pick in (("lo", F.least), ("hi", F.greatest))]
    rect = F.lit(0).cast("long")
    for e in edges:
        rect = rect * (1 << bits) + e
    return q.select("qid", *_STAT, rect.alias("_rect"))


_STAT = ["part", "quadrant", "label"]


def _sides(rect: int, bits: int) -> tuple[slice, slice]:
    x0, x1, y0, y1 = (rect >> bits * i & (1 << bits) - 1 for i in (3, 2, 1, 0))
    return slice(min(x0, x1), max(x0, x1) + 1), slice(min(y0, y1), max(y0, y1) + 1)


@cache
def _turns(bits: int) -> tuple[np.ndarray, np.ndarray]:
    """What a coordinate of a cell adds to its Morton code, for x and for y."""
    at = np.arange(1 << bits)
    x = sum(((at >> i & 1) << 2 * i for i in range(bits)), np.zeros_like(at))
    return x, x << 1


def _codes(rect: int, bits: int, curve: str) -> np.ndarray:
    """The keys of a rectangle's cells, in no order."""
    xs, ys = _sides(rect, bits)
    if curve == "z":
        x, y = _turns(bits)
        return (x[xs, None] | y[ys]).ravel()
    gx, gy = (a.ravel() for a in np.mgrid[xs, ys])
    code, state, rank, turn = np.zeros_like(gx), np.zeros_like(gx), np.array(HILBERT_RANK), np.array(HILBERT_NEXT)
    for i in reversed(range(bits)):
        at = (gx >> i & 1) * 2 + (gy >> i & 1)
        code, state = code * 4 + rank[state, at], turn[state, at]
    return code


def _runs(rect: int, bits: int, curve: str) -> tuple[np.ndarray, np.ndarray]:
    """First and last keys of the runs that a rectangle's cells form."""
    keys = _codes(rect, bits, curve)
    if len(keys) << 4 > 1 << 2 * bits:  # many of all keys: marked, which orders them
        here = np.zeros((1 << 2 * bits) + 2, bool)
        here[keys + 1] = True
        edges = np.flatnonzero(here[1:] != here[:-1])
        return edges[::2], edges[1::2] - 1
    keys.sort()
    ends = np.flatnonzero(np.diff(keys) > 1)
    return keys[np.concatenate([[0], ends + 1])], keys[np.concatenate([ends, [len(keys) - 1]])]


def curve_intervals(queries: DataFrame, stats: DataFrame, bits: int = BITS, curve: str = "z", phases: int = PHASES, period: float = PERIOD) -> DataFrame:
    """qid, part, quadrant, label, key_lo, key_hi: runs of keys that cover each query's window, moved to the label time by the part's own velocities.

    Windows that cover the same cells have the same runs, which are made once.
    ``stats``: part, quadrant, label and the extreme velocities.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            runs = [_runs(r, bits, curve) for r in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in runs], pa.list_(pa.int64())) for i in (0, 1))], names=["_rect", "key_lo", "key_hi"])

    covered = covers(queries, stats, bits, phases, period)
    runs = covered.select("_rect").distinct().mapInArrow(run, "_rect long, key_lo array<long>, key_hi array<long>")
    return covered.join(runs, "_rect").select("qid", *_STAT, F.inline(F.arrays_zip("key_lo", "key_hi")))


def visited_keys(queries: DataFrame, stats: DataFrame, bits: int = BITS, curve: str = "z") -> DataFrame:
    """part, quadrant, label, key: the keys in a run of any query. As many as there are cells by part at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[tuple, np.ndarray] = {}
        for b in batches:
            for *group, rect in zip(*(c.to_pylist() for c in b.columns), strict=True):
                seen.setdefault(tuple(group), np.zeros((1 << bits, 1 << bits), bool))[_sides(rect, bits)] = True
        every = _codes((1 << bits) - 1 << 2 * bits | (1 << bits) - 1, bits, curve)  # the rectangle of all cells
        for group, cells in seen.items():
            at = every[cells.ravel()]
            yield pa.RecordBatch.from_arrays([*(pa.array(np.full(len(at), v, np.int32)) for v in group), pa.array(at)], names=[*_STAT, "key"])

    rects = covers(queries.where("xlo <= xhi AND ylo <= yhi AND t IS NOT NULL"), stats, bits).select(*[F.col(c).cast("int") for c in _STAT], "_rect").distinct()
    return rects.mapInArrow(run, "part int, quadrant int, label int, key long").distinct()


@dataclass
class Cover:
    """Whether the key of an object lies in a query's runs, told from cells: the runs are the keys of all cells from the first to the last on both axes."""

    stats: DataFrame
    bits: int = BITS

    def placed(self, keyed: DataFrame, times: DataFrame) -> DataFrame:
        """keyed at each of the times (_t), beside what the edges of windows move by in their part."""
        back = F.col("label") * (PERIOD / PHASES) - F.col("_t")
        moves = [pick(F.col(f"v{a}lo") * back, F.col(f"v{a}hi") * back).alias(f"_m{a}{e}") for a in "xy" for e, pick in (("lo", F.least), ("hi", F.greatest))]
        return keyed.join(F.broadcast(self.stats.crossJoin(F.broadcast(times)).select(*_STAT, *times.columns, *moves)), _STAT)

    def columns(self) -> list[Column]:
        """Of keyed objects that are ``placed``: cells at the label time, what the windows' edges move by, and _sure.

        Where an object's own place, moved as an edge is, does not pass its
        cell, no edge of a window that holds the place does: sums and cells keep
        the order of what they are made from. Rounding alone makes others.
        """
        at = F.col("label") * (PERIOD / PHASES) - F.col("t_ref")
        out, sure = [], F.lit(True)
        for a in "xy":
            cell = grid(F.col(a) + F.col(f"v{a}") * at, self.bits)
            out += [cell.alias(f"_g{a}"), F.col(f"_m{a}lo"), F.col(f"_m{a}hi")]
            sure = sure & (grid(F.col(f"p{a}") + F.col(f"_m{a}lo"), self.bits) <= cell) & (grid(F.col(f"p{a}") + F.col(f"_m{a}hi"), self.bits) >= cell)
        return [*out, F.coalesce(sure, F.lit(False)).alias("_sure")]

    def holds(self) -> Column:
        """The check itself, of such a place beside a window."""
        met = F.lit(True)
        for a in "xy":
            met = met & (grid(F.col(f"{a}lo") + F.col(f"_m{a}lo"), self.bits) <= F.col(f"_g{a}")) & (grid(F.col(f"{a}hi") + F.col(f"_m{a}hi"), self.bits) >= F.col(f"_g{a}"))
        return F.col("_sure") | met


def key_stats(keyed: DataFrame) -> DataFrame:
    return keyed.groupBy("part", "quadrant", "label").agg(F.count(F.lit(1)).alias("n"), F.min("vx").alias("vxlo"), F.max("vx").alias("vxhi"), F.min("vy").alias("vylo"), F.max("vy").alias("vyhi"))


#: Low bits of a key by the two sizes of blocks that runs are cut into.
BLOCKS = (0, 4)
#: Queries in all lists of blocks up to which the lists are broadcast.
BROADCAST_LISTS = 16_000_000


def run_blocks(intervals: DataFrame) -> DataFrame:
    """intervals +_l, _p: the aligned blocks of 2**_l keys (key >> _l = _p) that each run consists of; every key of it is in one block."""
    small, large = BLOCKS
    step = 1 << (large - small)
    rows = intervals.where("key_lo <= key_hi").withColumn("_b", F.expr(f"(key_lo + {step - 1}) div {step}")).withColumn("_y", F.expr(f"(key_hi + 1) div {step}"))
    single = f"transform(filter(sequence(key_lo, key_hi), k -> _b >= _y OR k < _b * {step} OR k >= _y * {step}), k -> struct({small} AS _l, k AS _p))"
    whole = f"transform(filter(sequence(_b, greatest(_b, _y - 1)), k -> k < _y), k -> struct({large} AS _l, k AS _p))"
    return rows.withColumn("_b", F.explode(F.expr(f"concat({single}, {whole})"))).select(*intervals.columns, "_b._l", "_b._p")


def probe_intervals(keyed: DataFrame, intervals: DataFrame) -> DataFrame:
    """qid + the objects whose key lies in one of the query's runs: an equi-join on part, label and block of keys.

    Each block has the list of its queries. The lists are broadcast behind a
    check of their size; beyond it they meet the objects in a shuffle.
    """
    by = ["part", "quadrant", "label", "_l", "_p"]
    lists = kept(run_blocks(intervals).groupBy(*by).agg(F.collect_list("qid").alias("_q")))
    few = (lists.agg(F.sum(F.size("_q"))).first()[0] or 0) <= BROADCAST_LISTS
    rows = keyed.withColumn("_l", F.explode(F.array(*[F.lit(b) for b in BLOCKS])))
    rows = rows.withColumn("_p", F.when(F.col("_l") == BLOCKS[0], F.col("key")).otherwise(F.shiftright("key", BLOCKS[1])))
    met = rows.join(F.broadcast(lists) if few else lists, by)
    return met.select(F.explode("_q").alias("qid"), *keyed.columns)


def count_candidates(keyed: DataFrame, intervals: DataFrame) -> DataFrame:
    """qid, candidates: how many rows ``probe_intervals`` gives for each query that has any, from running counts by key."""
    by = ["part", "quadrant", "label"]
    counts = kept(keyed.groupBy(*by, "key").agg(F.count(F.lit(1)).alias("n")))
    every = counts.groupBy(*by).agg(F.max("key").alias("_last")).withColumn("key", F.explode(F.sequence(F.lit(0).cast("long"), "_last")))
    upto = F.sum(F.coalesce("n", F.lit(0))).over(Window.partitionBy(*by).orderBy("key"))
    # as many counts by part as there are keys
    parts = every.join(counts, [*by, "key"], "left").withColumn("upto", upto).groupBy(*by, "_last").agg(F.array_sort(F.collect_list(F.struct("key", "upto")))["upto"].alias("_upto"))
    n = F.expr("_upto[cast(least(key_hi, _last) as int)] - IF(key_lo > 0, _upto[cast(key_lo - 1 as int)], 0L)")
    rows = intervals.join(F.broadcast(parts), by).where("key_lo <= _last").select("qid", n.alias("n"))
    return rows.groupBy("qid").agg(F.sum("n").alias("candidates")).where("candidates > 0")


def leaf_pages(keyed: DataFrame, capacity: int = 102, dealt: bool = False) -> DataFrame:
    """+leaf: runs of about ``capacity`` objects in key order inside each part, label and key prefix.

    ``dealt``: tasks get ranges of prefixes, so that rows leave in the order of
    their keys by one shuffle.
    """
    keyed = keyed.withColumn("_prefix", F.shiftright("key", PREFIX))
    if dealt:
        keyed = keyed.repartitionByRange(*_STAT, "_prefix")
    w = Window.partitionBy(*_STAT, "_prefix").orderBy("key", "oid")
    return keyed.withColumn("_r", F.row_number().over(w)).withColumn("leaf", F.col("_prefix") * 1048576 + F.expr(f"(_r - 1) div {capacity}")).drop("_r", "_prefix")


def page_catalog(paged: DataFrame) -> DataFrame:
    """part, quadrant, label, leaf, key_lo, key_hi, n."""
    return paged.groupBy("part", "quadrant", "label", "leaf").agg(F.min("key").alias("key_lo"), F.max("key").alias("key_hi"), F.count(F.lit(1)).alias("n"))


def page_accesses(pages: DataFrame, intervals: DataFrame) -> DataFrame:
    """qid, accesses: leaf pages that meet one of the query's runs."""
    by = ["part", "quadrant", "label"]
    runs = intervals.withColumn("_p", F.explode(F.sequence(F.shiftright("key_lo", PREFIX), F.shiftright("key_hi", PREFIX)))).withColumnRenamed("key_lo", "ilo").withColumnRenamed("key_hi", "ihi")
    met = pages.withColumn("_p", F.shiftright("key_lo", PREFIX)).join(runs, [*by, "_p"]).where("key_lo <= ihi AND key_hi >= ilo")
    return met.select("qid", *by, "leaf").distinct().groupBy("qid").agg(F.count(F.lit(1)).alias("accesses"))


def count_pages(pages: DataFrame, queries: DataFrame, stats: DataFrame) -> DataFrame:
    """qid, accesses: what ``page_accesses`` gives for the runs of each query, without their pairs.

    The pages of a part, in the order of their keys, that meet a run begin
    after those that end before it and end with those that begin up to its
    last key; a page that the run before has met already does not count again.
    As many counts reach the driver by part as there are keys; windows that cover
    the same cells are counted once.
    """
    size, groups = 1 << 2 * BITS, {}
    for i, key in enumerate(("key_lo", "key_hi")):
        got = pages.groupBy(*_STAT, key).agg(F.count(F.lit(1)).alias("n")).toArrow()
        for *group, k, n in zip(*(c.to_pylist() for c in got.columns), strict=True):
            groups.setdefault(tuple(group), np.zeros((2, size + 1), np.int64))[i, k + i] = n
    # by key: pages that begin up to it, and pages that end before it
    counts = {g: np.cumsum(n, axis=1) for g, n in groups.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for *group, rect in zip(*(c.to_pylist() for c in b.columns), strict=True):
                begun, over = counts.get(tuple(group), (None, None))
                lo, hi = _runs(rect, BITS, "z")
                if begun is None:
                    out.append(0)
                    continue
                last = begun[hi]
                first = np.maximum(over[lo], np.concatenate([[0], last[:-1]]))
                out.append(int(np.maximum(last - first, 0).sum()))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.int64())], names=[*_STAT, "_rect", "accesses"])

    covered = covers(queries, stats).select("qid", *[F.col(c).cast("int") for c in _STAT], "_rect")
    counted = covered.select(*_STAT, "_rect").distinct().mapInArrow(run, "part int, quadrant int, label int, _rect long, accesses long")
    return covered.join(counted, [*_STAT, "_rect"]).groupBy("qid").agg(F.sum("accesses").alias("accesses")).where("accesses > 0")
