"""Numbers of places and boxes in windows, without going over pairs."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType


def below(rank: np.ndarray, lo: np.ndarray, hi: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """How many of rank[lo:hi] are less than each bound; ranks are below the length of ``rank``.

    They are counted bit by bit, the highest first, while the ranks are parted
    by that bit and each run shrinks to those that still agree with its bound.
    """
    order = np.argsort(lo, kind="stable")  # runs side by side read places side by side
    lo, hi, bound = (a[order].astype(np.int32) for a in (lo, hi, bound))
    n, zeros = np.zeros(len(bound), np.int64), np.zeros(len(rank) + 1, np.int32)
    for bit in reversed(range(len(rank).bit_length())):
        one = (rank >> bit & 1).astype(bool)
        np.cumsum(~one, out=zeros[1:])
        lo0, hi0, up = zeros[lo], zeros[hi], (bound >> bit & 1).astype(bool)
        n += (hi0 - lo0) * up
        lo, hi = np.where(up, zeros[-1] + lo - lo0, lo0), np.where(up, zeros[-1] + hi - hi0, hi0)
        rank = np.concatenate([rank[~one], rank[one]])
    out = np.empty_like(n)
    out[order] = n
    return out


def _ranked(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """x in order, y in order, and the ranks of y in the order of x."""
    by_x, by_y = np.argsort(x, kind="stable"), np.sort(y)
    return x[by_x], by_y, np.searchsorted(by_y, y[by_x], "left").astype(np.int32)


def held(px: np.ndarray, py: np.ndarray, xlo: np.ndarray, xhi: np.ndarray, ylo: np.ndarray, yhi: np.ndarray) -> np.ndarray:
    """The number of places in each window, edges included: a window is a run of the places by x."""
    xs, by_y, rank = _ranked(px, py)
    first, last = np.searchsorted(xs, xlo, "left"), np.searchsorted(xs, xhi, "right")
    # both bounds of y at once: those below the upper one less those below the lower one
    bound = np.concatenate([np.searchsorted(by_y, yhi, "right"), np.searchsorted(by_y, ylo, "left")])
    n, both = len(xlo), below(rank, np.concatenate([first, first]), np.concatenate([last, last]), bound)
    return both[:n] - both[n:]


def meeting(x0: np.ndarray, x1: np.ndarray, y0: np.ndarray, y1: np.ndarray, xlo: np.ndarray, xhi: np.ndarray, ylo: np.ndarray, yhi: np.ndarray) -> np.ndarray:
    """The number of boxes that meet each window (xlo <= xhi, ylo <= yhi), edges included.

    All boxes, less those beyond one of its four edges; those beyond two, which
    are in its corners, would be taken off twice.
    """
    n = np.full(len(xlo), len(x0), np.int64)
    for x, left in ((x1, True), (x0, False)):
        for y, under in ((y1, True), (y0, False)):
            xs, by_y, rank = _ranked(x, y)
            lo = np.zeros(len(xlo), np.int64) if left else np.searchsorted(xs, xhi, "right")
            hi = np.searchsorted(xs, xlo, "left") if left else np.full(len(xlo), len(xs))
            bound = np.searchsorted(by_y, ylo, "left") if under else np.searchsorted(by_y, yhi, "right")
            less = below(rank, lo, hi, bound)
            n += less if under else hi - lo - less
            if under:
                n -= hi - lo  # beyond the edge of x
            if left:
                n -= bound if under else len(xs) - bound  # beyond the edge of y
    return n


class Asked:
    """A given, small set of range queries as arrays, with the distinct times they ask for."""

    def __init__(self, queries: DataFrame):
        rows = queries.select("qid", "xlo", "xhi", "ylo", "yhi", "t").toArrow()
        self.qid, self.field = rows.column("qid").combine_chunks(), queries.schema["qid"]
        self.windows = [rows.column(c).to_numpy() for c in ("xlo", "xhi", "ylo", "yhi")]
        times, self.at = np.unique(rows.column("t").to_numpy(), return_inverse=True)
        self.times = [float(x) for x in times]

    def times_of(self, spark) -> DataFrame:
        """_i, _t: the times and their numbers."""
        return F.broadcast(spark.createDataFrame(list(enumerate(self.times)), "_i int, _t double"))

    def counts(self, rows: DataFrame, fn: Callable[..., np.ndarray], name: str, at_once: int) -> DataFrame:
        """qid, ``name``: the sum of fn(columns of rows, windows) over rows (_i and columns), for each query that has any.

        Each task takes ``at_once`` rows at a time, those of a time together
        with the queries of that time.
        """
        qids, windows, at = self.qid, self.windows, self.at

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            n, waiting, size = np.zeros(len(at), np.int64), [], 0

            def count() -> None:
                which, *cols = (np.concatenate([b.column(i).to_numpy() for b in waiting]) for i in range(waiting[0].num_columns))
                for i in np.unique(which):
                    of, here = np.flatnonzero(at == i), which == i
                    n[of] += fn(*[c[here] for c in cols], *[w[of] for w in windows])

            for b in batches:
                waiting.append(b)
                size += b.num_rows
                if size >= at_once:
                    count()
                    waiting, size = [], 0
            if size:
                count()
            some = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([qids.take(pa.array(some)), pa.array(n[some])], names=["qid", name])

        return rows.mapInArrow(run, StructType([self.field, StructField(name, LongType())])).groupBy("qid").agg(F.sum(name).alias(name))
