"""The methods from SQL: views, scalar functions and table functions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

SIDE = 10000.0


def _z(gx: int, gy: int, bits: int) -> int:
    return sum((gx >> i & 1) << 2 * i | (gy >> i & 1) << 2 * i + 1 for i in range(bits))


@udtf(returnType="key_lo: bigint, key_hi: bigint")
class CurveIntervals:
    """Runs of Z-curve keys that cover a window, for LATERAL joins."""

    def eval(self, xlo: float, ylo: float, xhi: float, yhi: float, bits: int) -> Iterator[tuple[int, int]]:
        def cell(v: float) -> int:
            return min((1 << bits) - 1, max(0, int(v / SIDE * (1 << bits) // 1)))

        low = high = None
        for key in sorted(_z(gx, gy, bits) for gx in range(cell(xlo), cell(xhi) + 1) for gy in range(cell(ylo), cell(yhi) + 1)):
            if high is not None and key > high + 1:
                yield low, high
                low = key
            low = key if low is None else low
            high = key
        if high is not None:
            yield low, high


def register(spark: SparkSession, mo: DataFrame, plan: DataFrame | None = None, prefix: str = "") -> None:
    """Views mo (and plan, parted), scalar functions position_at, nu_one and nu_quad, and the table functions range_query, knn_query and curve_intervals."""
    mo.createOrReplaceTempView(f"{prefix}mo")
    if plan is not None:
        from kinetic.operators.partitions import assign_parts

        plan.createOrReplaceTempView(f"{prefix}plan")
        assign_parts(mo, plan).createOrReplaceTempView(f"{prefix}parted")
    for text in (
        "position_at(p DOUBLE, v DOUBLE, t_ref DOUBLE, t DOUBLE) RETURNS DOUBLE RETURN p + v * (t - t_ref)",
        "nu_one(d DOUBLE, v DOUBLE, t DOUBLE) RETURNS DOUBLE RETURN d * d * t + 2 * d * v * t * t + 4D / 3 * v * v * t * t * t",
        "nu_quad(d DOUBLE, v DOUBLE, t DOUBLE) RETURNS DOUBLE RETURN 4 * d * d * t + 2 * d * v * t * t + 1D / 3 * v * v * t * t * t",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {prefix}{text}")
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION {prefix}range_query(qxlo DOUBLE, qylo DOUBLE, qxhi DOUBLE, qyhi DOUBLE, qt DOUBLE) RETURNS TABLE (oid BIGINT, px DOUBLE, py DOUBLE) "
        f"RETURN SELECT oid, x + vx * (qt - t_ref), y + vy * (qt - t_ref) FROM {prefix}mo WHERE x + vx * (qt - t_ref) BETWEEN qxlo AND qxhi AND y + vy * (qt - t_ref) BETWEEN qylo AND qyhi"
    )
    dx, dy = "(x + vx * (qt - t_ref) - qx)", "(y + vy * (qt - t_ref) - qy)"
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION {prefix}knn_query(qx DOUBLE, qy DOUBLE, qk INT, qt DOUBLE) RETURNS TABLE (rank INT, oid BIGINT, dist2 DOUBLE) "
        f"RETURN SELECT r, oid, d FROM (SELECT oid, d, row_number() OVER (ORDER BY d, oid) AS r FROM (SELECT oid, {dx} * {dx} + {dy} * {dy} AS d FROM {prefix}mo)) WHERE r <= qk"
    )
    spark.udtf.register(f"{prefix}curve_intervals", CurveIntervals)
