"""The layout's data source, and plans valid at the time of an update."""

from __future__ import annotations

from pyspark.sql import functions as F

from kinetic import queries as kq
from kinetic.operators import partitions
from kinetic.sources import box_source
from kinetic.sources import standins as st


def test_files_are_picked_by_footers(spark, sf, tmp_path):
    parted = partitions.assign_parts(st.mo_orders(spark, sf), kq.demo_plan(spark))
    path = str(tmp_path / "layout")
    partitions.write_layout(parted, path)
    box_source.register(spark)
    rows = spark.read.format("moving_objects").load(path)
    want = parted.where("x < 2000 AND y < 2000 AND part = 1")
    assert sorted(r["oid"] for r in rows.where("x < 2000 AND y < 2000 AND part = 1").select("oid").collect()) == sorted(r["oid"] for r in want.select("oid").collect())
    reader = box_source.LayoutReader(f"file://{path}")
    every = len(reader.partitions())
    list(reader.pushFilters([box_source.EqualTo(("part",), 1), box_source.LessThan(("x",), -1e9)]))
    assert every > 1 and [p.path for p in reader.partitions()] == [""]


def test_plan_at_the_time(spark, sf):
    updates = st.mo_events(spark, sf).select("event_id", "ts")
    plans = spark.createDataFrame([("2024-01-01 00:00:00", 1), ("2024-01-10 12:00:00", 2), ("2024-01-10 18:00:00", 3)], "v string, plan_id int").select(F.col("v").cast("timestamp").alias("valid_from"), "plan_id")
    got = {r["event_id"]: r["plan_id"] for r in partitions.asof_plan(updates, plans).collect()}
    for r in updates.collect():
        t = str(r["ts"])
        assert got[r["event_id"]] == (3 if t >= "2024-01-10 18:00:00" else 2 if t >= "2024-01-10 12:00:00" else 1)
